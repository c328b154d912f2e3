"""Operators against brute-force versions, and the cases that their docstrings define."""

import random
import re
import time
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

pytest.importorskip("approxset.llm")
import public_tokenizers as P

from approxset.llm import bytebpe, dedup, html, licenses, neardup, packing, quality, sharding, topk


def documents(spark, rows):
    """With extra columns named like the operators' own."""
    names = ("n", "k", "size", "shard", "digest", "tag", "keep_id", "ids", "grade")
    return spark.createDataFrame(rows, "doc_id long, text string").select("*", *[F.lit(i).alias(c) for i, c in enumerate(names)])


def test_sharding_query(spark, sf):
    """Checksums, law, gapless slots, and shards whose sizes differ by less than two rows from the target."""
    rows = sorted((r["doc_id"], (r["text"] or "").encode()) for r in spark.read.parquet(f"{sf}/documents.parquet").collect())
    got = {r["doc_id"]: r for r in sharding.op3_sharding(spark, sf).collect()}
    total = sum(len(t) + 16 for _, t in rows)
    start, slots, sizes = 0, {}, [0] * 40
    for i, t in rows:
        r, want = got[i], min(39, start * 40 // total)
        assert (r["size"], r["text_crc32"], r["law"], r["shard"], r["slot"], r["grown_shard"]) == (len(t) + 16, zlib.crc32(t), "bytes", want, slots.get(want, 0), None)
        slots[want] = slots.get(want, 0) + 1
        sizes[want] += len(t) + 16
        start += len(t) + 16
    most = max(len(t) + 16 for _, t in rows)
    assert max(abs(s - total / 40) for s in sizes) <= 2 * most


def test_one_of_equal_rows_stays(spark):
    rows = [(7, "A"), (9, "A"), (7, "B"), (5, "C"), (5, "C"), (3, None), (2, ""), (None, "D"), (None, "C")]
    out = dedup.keep_one_of_each(documents(spark, rows))
    assert out.columns == documents(spark, rows).columns
    assert sorted(((r["doc_id"], r["text"]) for r in out.collect()), key=str) == [(3, None), (5, "C"), (7, "B"), (9, "A"), (None, "D")]
    assert dedup.keep_one_of_each(documents(spark, [])).count() == 0


def test_ranks_of_the_perfect_hash():
    for n in (0, 1, 63, 64, 65, 3000):
        keys = np.random.default_rng(n).integers(0, 1 << 63, (n, 4)).astype(np.uint64)
        h = dedup.PerfectHash(keys)
        assert sorted(h.slots(keys).tolist()) == list(range(n))
        assert sum(r.nbytes for r in h.ranks) * 8 <= sum(len(x) for x in h.levels) * 8


def brute_components(rows, width):
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        sets[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} or ({tuple(w)} if w else set())
    links = []
    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b]:
                x = len(sets[a] & sets[b])
                if 100 * x >= 80 * (len(sets[a]) + len(sets[b]) - x):
                    links.append((a, b))
    comp, moved = {i: i for i in sets}, True
    while moved:
        moved = False
        for a, b in links:
            low = min(comp[a], comp[b])
            moved |= comp[a] != low or comp[b] != low
            comp[a] = comp[b] = low
    return comp


def test_near_dedup_ways_agree(spark, monkeypatch):
    """Hot sub-keys, pairs too many to broadcast and shingles spread over tasks give the same components."""
    rng = random.Random(9)
    base = [[f"t{rng.randrange(400)}" for _ in range(50)] for _ in range(3)]
    rows = []
    for i in range(60):
        w = list(base[i % 3])
        for _ in range(i % 6):
            w[rng.randrange(50)] = f"u{rng.randrange(900)}"
        rows.append((i, " ".join(w)))
    monkeypatch.setattr(neardup, "HOT", 2)
    monkeypatch.setattr(neardup, "SMALL", -1)
    monkeypatch.setattr(neardup, "MEETING", 2)
    out = {r["doc_id"]: r["component_id"] for r in neardup.near_duplicates(documents(spark, rows), 2).collect()}
    assert out == brute_components(rows, 2)


def test_near_dedup_equal_ids_of_different_texts(spark):
    a, b = " ".join(f"a{i}" for i in range(40)), " ".join(f"b{i}" for i in range(40))
    kept = neardup.keep_one_of_each_group(documents(spark, [(1, a), (7, a + " x"), (7, b), (9, None)]))
    # an id stands for all its texts: whatever one of them is linked with, the others go with
    assert sorted((r["doc_id"], r["text"]) for r in kept.filter("text is not null").collect()) == [(1, a)]
    kept = neardup.keep_one_of_each_group(documents(spark, [(1, a), (7, a + " x"), (5, b), (7, b), (9, None)]))
    assert sorted((r["doc_id"], r["text"]) for r in kept.filter("text is not null").collect()) == [(1, a)]


def plain_alignment(doc, template):
    """Words matched by the best local alignment, over the whole table."""
    n, m = len(doc), len(template)
    score, matched, best = [[0] * (n + 1) for _ in range(m + 1)], [[0] * (n + 1) for _ in range(m + 1)], (0, 0)
    for i in range(1, m + 1):
        for j in range(1, n + 1):
            same = doc[j - 1] == template[i - 1]
            score[i][j], matched[i][j] = max((score[i - 1][j - 1] + (2 if same else -1), matched[i - 1][j - 1] + same), (score[i - 1][j] - 1, matched[i - 1][j]), (score[i][j - 1] - 1, matched[i][j - 1]), (0, 0))
            best = max(best, (score[i][j], matched[i][j]))
    return best


def test_license_coverage_equals_full_alignment(spark):
    """Notices with words inserted, dropped and changed; whatever full alignment finds at the limit is reported."""
    rng = random.Random(4)
    words = licenses.TEMPLATES["MIT"].split()
    rows = []
    for i in range(24):
        w = []
        for j, x in enumerate(words):
            if i < 8 and j and j % (i + 4) == 0:
                w += [f"extra{rng.randrange(99)}"] * (1 + i % 3)
            if i < 8 or rng.random() > 0.02 * (i - 8):
                w.append(x if i < 16 or rng.random() > 0.01 * (i - 8) else f"other{j}")
        rows.append((i, " ".join(["before"] * 30 + w + ["after"] * 30)))
    template = re.findall(r"[0-9a-z]+", licenses.TEMPLATES["MIT"].lower())
    got = {}
    for r in licenses.scan_licenses(documents(spark, rows), {"MIT": licenses.TEMPLATES["MIT"]}).collect():
        got[r["doc_id"]] = max(got.get(r["doc_id"], 0), r["matched_words"])
    for i, t in rows:
        matched = plain_alignment(re.findall(r"[0-9a-z]+", t.lower()), template)[1]
        if matched / len(template) >= 0.7:
            assert abs(got.get(i, 0) - matched) <= 2, i
        else:
            assert got.get(i, 0) <= matched + 2


def test_quality_fit_is_a_minimum():
    """No change of a threshold or of the weights' scale lowers the penalised likelihood by more than a trace."""
    r = np.random.default_rng(2)
    rows, grades = [], r.integers(0, 3, 300)
    for g in grades:
        bins = np.unique(np.concatenate([[int(g) if r.random() < 0.7 else int(r.integers(0, 3))], r.integers(3, 40, 6)])).astype("<i4")
        rows.append((bins, np.ones(len(bins), "<f4")))
    w, cuts = quality.fit(list(rows), grades, 2)

    def loss(w, cuts):
        s = np.array([w[b] @ v for b, v in rows])
        edge = np.concatenate([[-np.inf], cuts, [np.inf]])
        p = 1 / (1 + np.exp(-(edge[grades + 1] - s))) - 1 / (1 + np.exp(-(edge[grades] - s)))
        return -np.log(np.maximum(p, 1e-12)).mean()

    assert cuts[0] < cuts[1]
    best = loss(w, cuts)
    assert best < 0.8 * loss(w * 0, np.array([np.log(1 / 2), np.log(2)]))
    for d in (-0.3, 0.3):
        assert loss(w, cuts + d) > best - 1e-3 and loss(w, cuts + np.array([0, d])) > best - 1e-3


def test_quality_empty(spark):
    graded = spark.createDataFrame([(1, 2), (2, 0)], "doc_id long, grade int")
    model = quality.train(documents(spark, [(1, "good words"), (2, "bad")]), graded)
    assert quality.score(documents(spark, []), model).count() == 0


def test_text_under_doubtful_names():
    prose = "prior work on this matter is long " * 8
    page = f"<body><article><p>{prose}</p><section class='related-work'><p>{prose}</p></section><div class='related-posts'><p>{prose}</p></div><div class='share-price-note'><a href=x>short links</a></div><div id='comments-by-readers'><p>{prose}</p></div></article></body>"
    assert html.main_text(page, html.fit_weights([page])).count("this matter") == 16
    assert html.main_text(page, dict(html.START)).count("this matter") == 16


def test_deep_nesting_takes_linear_time():
    for make in (lambda n: "<div>" * n + "</b></i>" * n, lambda n: "<p>" + "<span>" * n + "<hr>" * n, lambda n: "<div class='related-work'>" * n + "x"):
        took = []
        for n in (4000, 16000):
            t = time.time()
            html.main_text(make(n), dict(html.START))
            took.append(time.time() - t)
        assert took[1] < 10 * took[0] + 0.5


def test_pages_edges(spark):
    d = spark.createDataFrame([(1, "u", "<p>a b c</p>", 1, 2)], "page_id long, url string, html string, text int, n_chars int")
    assert html.extract(d.limit(0)).count() == 0
    assert html.extract(d).columns == ["page_id", "url", "text", "n_chars"]


def test_top_k_of_large_and_odd_vectors(spark):
    r = np.random.default_rng(3)
    rows = [(i, (r.normal(size=6) * 10.0 ** r.integers(0, 4)).tolist()) for i in range(400)] + [(1000, []), (1001, [1.0])]
    d = spark.createDataFrame(rows, "vec_id long, embedding array<double>").select("*", F.lit(1).alias("id"), F.lit(2).alias("v"), F.lit(3).alias("rank"))
    v = topk.integer_vectors(d)
    got = sorted(map(tuple, topk.top_k(v, v.filter("id % 50 = 0"), 5, pivots=8, sample=100, block=64).collect()))
    f = {i: np.concatenate([np.floor(256 * np.array(x)), np.zeros(6 - len(x))]).astype(int) for i, x in rows}
    for q in [i for i in f if i % 50 == 0]:
        s = sorted((-int(x @ f[q]), i) for i, x in f.items() if i != q)[:5]
        assert [(x[2], x[3]) for x in got if x[0] == q] == [(i, -x) for x, i in s]


def test_offsets_decode_any_range(spark):
    path = P.path("byte_bpe_50k.tiktoken")
    rows = [(1, "Hello wörld, it's 日本語 12345  x\n\n y" * 20), (2, None), (3, ""), (1, "twice")]
    coded = bytebpe.encode_documents(documents(spark, rows), path)
    for r in coded.collect():
        assert r["begins"][0] == 0 and r["firsts"][-1] == len(r["ids"]) and len(r["begins"]) == len(r["firsts"])
    for lo, hi in ((0, None), (3, 11), (7, 7), (100, 5000)):
        got = sorted(bytes(r["bytes"]) for r in bytebpe.decode_documents(coded, path, lo, hi).collect())
        assert got == sorted((t or "").encode()[lo:hi] for _, t in rows)
    with pytest.raises(ValueError):
        bytebpe.coder(path).decode([1, 2], [0, 9], [0, 2])
    assert bytebpe.round_trip(documents(spark, []), path).count() == 0


def test_packing_of_equal_ids_is_repeatable(spark):
    rows = [(1, f"word{i} " * (40 + i % 3)) for i in range(60)] + [(1, "same text"), (1, "same text")]
    run = lambda k: sorted(map(tuple, packing.pack(documents(spark, rows).repartition(k), P.path("word_bpe_49k.json")).collect()))
    assert run(1) == run(3)


def test_pipeline_stages(spark, sf):
    """What each of the dedup stages keeps of its input is what brute force keeps."""
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = corpus_pipeline.exact_dedup(spark, docs, sf)
    best = {}
    for r in docs.collect():
        best[r["text"] or ""] = max(best.get(r["text"] or "", -1), r["doc_id"])
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(best.values()) and kept.columns == docs.columns
    near = corpus_pipeline.near_dedup(spark, kept, sf)
    comp = brute_components([(r["doc_id"], r["text"]) for r in kept.filter("n_chars < 3000").collect()], 5)
    some = {r["doc_id"] for r in corpus_pipeline.near_dedup(spark, kept.filter("n_chars < 3000"), sf).collect()}
    assert some == {i for i, c in comp.items() if i == c} and near.columns == docs.columns
