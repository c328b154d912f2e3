import base64
import hashlib
import random
import re
import zlib

import numpy as np
import pytest

pytest.importorskip("approxset.llm")
import public_tokenizers as P

from approxset.llm import bytebpe, dedup, html, licenses, neardup, packing, quality, sharding, textkit, tokenfiles, topk

VOCAB = P.path("word_bpe_49k.json")
SCHEMA = "doc_id long, text string, shard string, keep_id string, n int, k string, grade string"


def docs(spark, rows):
    """Documents with extra columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, "s", "k", 1, "x", "g") for i, t in rows], SCHEMA).repartition(3)


LONG = " ".join(f"w{i % 977}" for i in range(60_000))
ROWS = [(1, None), (2, ""), (3, "one"), (4, "Alpha beta gamma delta"), (5, "alpha beta gamma delta"), (6, "one"), (7, LONG), (7, LONG), (None, "one"), (8, " \n\t "), (9, "été 'll don't 日本 😀 x  y")]


def test_sharding(spark):
    out = sharding.balanced_shards(docs(spark, ROWS), 3).collect()
    assert len(out) == len(ROWS) and sum(r["size"] for r in out) == sum(len((t or "").encode()) + 16 for _, t in ROWS)
    for s in {r["shard"] for r in out}:
        assert sorted(r["slot"] for r in out if r["shard"] == s) == list(range(sum(r["shard"] == s for r in out)))
    assert sharding.balanced_shards(docs(spark, []), 3).count() == 0


def test_exact_dedup(spark):
    out = dedup.exact_duplicates(docs(spark, ROWS), hot_share=2, copies=3).collect()
    best = {}
    for i, t in ROWS:
        best.setdefault(t or "", []).append(i)
    for r in out:
        group = next(v for k, v in best.items() if hashlib.sha256(k.encode()).digest() == bytes(r["digest"]))
        assert r["n"] == len(group) and r["keep_id"] == max((i for i in group if i is not None), default=None)
    assert len(out) == len(ROWS) and dedup.exact_duplicates(docs(spark, [])).count() == 0
    assert dedup.keep_one_of_each(docs(spark, ROWS)).columns == docs(spark, ROWS).columns


def test_exact_dedup_against_other_history(spark):
    old = dedup.distinct_digests(docs(spark, [(100, "one"), (101, "zwei")]))
    out = {(r["doc_id"], r["keep_id"], r["n"]) for r in dedup.exact_duplicates(docs(spark, [(1, "one"), (2, "new"), (3, "new")]), old).collect()}
    assert out == {(1, 100, 1), (2, 3, 2), (3, 3, 2)}


def test_perfect_hash_is_minimal():
    keys = np.random.default_rng(1).integers(0, 1 << 63, (5000, 4)).astype(np.uint64)
    h = dedup.PerfectHash(keys)
    assert sorted(h.slots(keys).tolist()) == list(range(5000))


def near_brute(rows, width, percent):
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        sets[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} or ({tuple(w)} if w else set())
    comp = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                x = len(sets[a] & sets[b])
                if sets[a] and sets[b] and 100 * x >= percent * (len(sets[a]) + len(sets[b]) - x):
                    comp[a] = comp[b] = min(comp[a], comp[b])
    return {i: (len(sets[i]), comp[i]) for i in sets}


@pytest.mark.parametrize("width", [2, 5])
def test_near_dedup(spark, width):
    rng = random.Random(width)
    base = [[f"t{rng.randrange(500)}" for _ in range(60)] for _ in range(6)]
    rows = [(1, None), (2, ""), (3, "one"), (4, "One"), (5, LONG)]
    for i in range(60):
        w = list(rng.choice(base))
        for _ in range(rng.randrange(4)):
            w[rng.randrange(60)] = f"u{rng.randrange(500)}"
        rows.append((10 + i, " ".join(w)))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in neardup.near_duplicates(docs(spark, rows), width).collect()}
    assert got == near_brute(rows, width, 80)
    assert neardup.near_duplicates(docs(spark, []), width).count() == 0


def test_near_dedup_mixed_group(spark):
    """Texts that share a passage, among near copies below and above the limit: no link is lost, few pairs are proposed."""
    rng = random.Random(5)
    passage = [f"t{rng.randrange(500)}" for _ in range(60)]
    rows = []
    for i in range(70):
        w = list(passage)
        for k in range(28, 60) if i % 2 else rng.sample(range(60), 2 + i % 7):
            w[k] = f"u{rng.randrange(5000)}"
        rows.append((i, " ".join(w)))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in neardup.near_duplicates(docs(spark, rows), 2).collect()}
    assert got == near_brute(rows, 2, 80)
    sets = neardup.shingle_sets([t.encode() for _, t in rows], 2)
    frame = spark.createDataFrame([(i, x.view(np.int64).tolist()) for (i, _), x in zip(rows, sets, strict=True)], "id long, shingles array<long>")
    alone = spark.createDataFrame([(i, i) for i, _ in rows], "x long, comp long")
    pairs = {(r["x"], r["y"]) for r in neardup._sharing_rare(alone, frame, 80).collect()}
    links = set()
    for i in range(70):
        for j in range(i):
            both = len(np.intersect1d(sets[i], sets[j]))
            if 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                links.add((i, j))
    assert links and links <= pairs
    assert len(pairs) < 70 * 69 // 4


def test_near_dedup_null_and_repeated_ids(spark):
    out = neardup.near_duplicates(docs(spark, ROWS)).collect()
    assert len(out) == len(ROWS) and all(r["kept"] for r in out if r["doc_id"] in (None, 1, 2, 7))


def test_byte_bpe():
    import tiktoken

    path = P.path("byte_bpe_50k.tiktoken")
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    b, rng = bytebpe.ByteBPE(path), random.Random(3)
    texts = ["".join(rng.choice("a's'tlrevmd  \n\t!?9é½İΣ日\x1c\x85😀'") for _ in range(rng.randrange(50))) for _ in range(3000)] + ["", "a" * 4000, " " * 999 + "x"]
    got = b.encode(texts)
    assert got == [lib.encode_ordinary(t) for t in texts]
    assert [b.decode(g) for g in got] == [t.encode() for t in texts]


def test_byte_bpe_query_rows(spark):
    out = bytebpe.round_trip(docs(spark, ROWS), P.path("byte_bpe_50k.tiktoken")).collect()
    assert sorted(r["decoded_sha256"] for r in out) == sorted(hashlib.sha256((t or "").encode()).hexdigest() for _, t in ROWS)


def encoded(rows):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(VOCAB)
    return [(i, np.array(t.encode(x or "", add_special_tokens=False).ids + [1], "<u4")) for i, x in rows]


def test_token_files(spark, tmp_path):
    tokenfiles.write_tokens(docs(spark, ROWS), f"file://{tmp_path}/t", VOCAB)
    out = tokenfiles.read_tokens(spark, f"file://{tmp_path}/t").orderBy("start").collect()
    assert [r["doc_id"] for r in out] == sorted((i for i, _ in ROWS), key=lambda i: (i is not None, i or 0))
    assert sorted((r["n_tokens"], r["ids_crc32"]) for r in out) == sorted((len(x), zlib.crc32(x.tobytes())) for _, x in encoded(ROWS))
    assert [r["start"] for r in out] == np.cumsum([0] + [r["n_tokens"] for r in out])[:-1].tolist()
    tokenfiles.write_tokens(docs(spark, []), f"file://{tmp_path}/e", VOCAB)
    assert tokenfiles.read_tokens(spark, f"file://{tmp_path}/e").count() == 0


def test_packing(spark):
    rows = [(i, t) for i, t in ROWS if i != 7 and i is not None] + [(7, LONG)]
    want = dict(encoded(rows))
    out = packing.pack(docs(spark, rows), VOCAB, shard_tokens=50_000).collect()
    for i, ids in want.items():
        mine = sorted((r["start"], r["length"], r["ids_crc32"]) for r in out if r["doc_id"] == i)
        assert [s for s, _, _ in mine] == np.cumsum([0] + [n for _, n, _ in mine])[:-1].tolist() and sum(n for _, n, _ in mine) == len(ids)
        assert all(zlib.crc32(ids[s : s + n].tobytes()) == c for s, n, c in mine)
    for q in {r["sequence_id"] for r in out}:
        mine = sorted((r["offset"], r["length"]) for r in out if r["sequence_id"] == q)
        assert [o for o, _ in mine] == np.cumsum([0] + [n for _, n in mine])[:-1].tolist() and sum(n for _, n in mine) <= 2048
    assert packing.pack(docs(spark, ROWS), VOCAB).count() >= len(ROWS) and packing.pack(docs(spark, []), VOCAB).count() == 0


def test_top_k(spark):
    rng = np.random.default_rng(5)
    rows = [(int(i), [float(x) for x in rng.normal(size=8).round(1)]) for i in range(300)] + [(1000, None), (1001, [1.0, None]), (1002, [float("nan")] * 8), (1003, [float("inf")] * 8), (50, [0.5] * 8)]
    v = topk.integer_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>"))
    got = sorted(map(tuple, topk.top_k(v, v.filter("id % 50 = 0"), 5, pivots=4, block=64).collect()))
    f = [(i, np.floor(256 * np.array(x, np.float32).astype(float)).astype(int)) for i, x in rows[:300] + rows[-1:]]
    for q in (0, 100, 150):
        s = sorted(((-int(x @ f[q][1]), i) for i, x in f if i != q))[:5]
        assert [(r[2], r[3]) for r in got if r[0] == q] == [(i, -x) for x, i in s]
    assert topk.top_k(v.limit(0), v.limit(0)).count() == 0


def test_main_text(spark):
    side = "<nav><ul>" + "<li><a href='/x'>Link text here</a></li>" * 6 + "</ul></nav>"
    page = f"<html><body>{side}<div class='ad'>Buy this now please</div><article><h1>Title</h1><p>First &amp; <b>bold</b>\n words<p>Second one<div class='cookie-notice'>We use cookies</div><p>Third</article><div class='comments'><p>Nice post friend</p></div><footer>&copy; x</footer>"
    assert html.main_text(page, html.fit_weights([page] * 3)) == "Title\n\nFirst & bold words\n\nSecond one\n\nThird"
    rows = [(1, "u", page), (2, "u", None), (3, None, ""), (1, "u", page), (4, "u", "<p>" * 30_000), (5, "u", "<script>never closed")]
    out = {r["page_id"]: r["text"] for r in html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert out[2] == out[3] == out[5] == "" and out[1].startswith("Title")


def test_licenses(spark):
    lic = licenses.TEMPLATES["Apache-2.0-line"]
    rows = [(1, None), (2, ""), (3, "plain words only"), (4, f"code {lic} more {lic.upper()}"), (5, "é " * 5000 + licenses.TEMPLATES["MIT"].replace("without limitation", "with no limitation")), (4, f"code {lic} more {lic.upper()}")]
    out = licenses.scan_licenses(docs(spark, rows)).collect()
    assert sum(r["license"] == "Apache-2.0-line" and r["coverage"] == 1 for r in out if r["doc_id"] == 4) == 4
    mit = [r for r in out if r["doc_id"] == 5 and r["license"] == "MIT"]
    assert len(mit) == 1 and 0.95 < mit[0]["coverage"] < 1 and mit[0]["start_byte"] == 15_000
    assert {r["doc_id"] for r in out} == {4, 5} and licenses.scan_licenses(docs(spark, [])).count() == 0


def test_quality_held_out(spark):
    d = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    graded = quality.ratings_of(spark.read.parquet("/root/testdata/sf0.1/labels.parquet"))
    model = quality.train(d, graded, sample=2500)
    seen = graded.orderBy("doc_id").collect()
    rest = {r["doc_id"]: r["grade"] for r in seen}
    out = quality.score(d, model).filter("doc_id is not null").collect()
    kept = lambda g: np.mean([r["tail_probability"] >= 0.5 for r in out if rest.get(r["doc_id"]) == g])
    assert kept(2) > 0.97 and kept(0) < 0.1 and kept(1) < 0.5


def test_quality_edges(spark):
    empty = spark.createDataFrame([], "doc_id long, grade int")
    model = quality.train(docs(spark, ROWS), empty)
    assert quality.score(docs(spark, ROWS), model).count() == len(ROWS)
    labels = spark.createDataFrame([(1, None, 0), (4, 1, 0), (7, 0, 1)], "doc_id long, quality int, toxic int")
    assert quality.keep_good(docs(spark, ROWS), labels).columns == docs(spark, ROWS).columns


def test_encoder_equals_library():
    from tokenizers import Tokenizer

    lib, e = Tokenizer.from_file(VOCAB), textkit.WordEncoder(VOCAB)
    for t in ["a's 'RE İΣ Σaś", "é ́b", "", "\tab\rcd 12345 ½ ß", "ﬁ K Å̧", "x<|endoftext|>y", "日本語 テキスト", "a​b  c"]:
        assert np.frombuffer(e.ids(t), e.dtype).tolist() == lib.encode(t, add_special_tokens=False).ids


def test_pipeline(spark, sf):
    import corpus_pipeline

    out = corpus_pipeline.run(spark, sf)
    n = spark.read.parquet(f"{sf}/documents.parquet").count()
    assert 0 < out.select("doc_id").distinct().count() < n
