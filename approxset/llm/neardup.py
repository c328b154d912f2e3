"""MinHash near-duplicates with tensored banding, links confirmed on full shingle sets, components over the links.

Two independent collections of `s` sub-keys (each of two minhashes) are computed per document; table (i, j) is keyed
by the pair of sub-key i of the first and sub-key j of the second collection. So s*s tables cost 4*s minhashes
instead of 4*s*s. A pair of similarity J shares a table unless one collection has no equal sub-key:
it is missed with probability below 2*(1 - J^2)^s, 7.4e-5 at J = 0.8 and s = 10, 2e-8 at 0.9.

Documents with the same shingle set are one class from the start (pre-aggregated by a 128-bit set hash), so groups of
copies cost one member. In each table's bucket all members are compared with the smallest one: first each with the
smallest one that it meets in most tables, then with the others that are not yet in its component. In buckets that
still hold several components, a pivot drawn by hash among the members outside the largest one meets all members of
other components (but for those that sizes or the triangle inequality rule out exactly). What is then still mixed is
settled exactly by its rarest shingles (`_sharing_rare`). A group of near copies is soon one component with a few
outliers; no pair list is quadratic in it, and none is cut off.

Defined results: words are separated by ASCII white space and A-Z lower-cased; with fewer words than the width the whole
sequence is one shingle; a null text or one without words has an empty set, is linked with nothing and is kept; rows with
equal ids are one document that stands for all its texts: what any of them is linked with, the others go with; null ids take part as
nothing: component null, kept; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import textkit
from .common import cut, documents, drop_cut, ship

#: Pairs that are broadcast at most (16 bytes each), nodes that a sub-key holds before it may count as hot, earlier shingles
#: compared to tell whether a pair has met, members of a shingle that meet in one task, and words of parity bits.
SMALL, HOT, BEFORE, MEETING, WORDS = 500_000, 4096, 8, 2048, 8


def shingle_sets(texts: list[bytes], width: int) -> list[np.ndarray]:
    """The distinct shingles of each text as sorted 64-bit hashes."""
    row, _, _, h = textkit.words(texts)
    at = textkit.bounds(row, len(texts))
    if not len(h):
        return [h] * len(texts)
    full = max(0, len(h) - width + 1)
    with np.errstate(over="ignore"):
        acc = np.zeros(full, np.uint64)
        for k in range(width):
            acc = acc * np.uint64(0xD6E8FEB86659FD93) + h[k : k + full]
        acc = textkit.mix(acc)
    out = []
    for i in range(len(texts)):
        a, b = at[i], at[i + 1]
        if b - a >= width:
            out.append(np.unique(acc[a : b - width + 1]))
        elif b > a:
            x = np.uint64(0x5851F42D4C957F2D)
            with np.errstate(over="ignore"):
                for v in h[a:b]:
                    x = x * np.uint64(0xD6E8FEB86659FD93) + v
            out.append(textkit.mix(np.array([x])))
        else:
            out.append(h[:0])
    return out


def _signer(width: int, s: int, seed: int):
    r = np.random.default_rng(seed)
    a = r.integers(1, 1 << 63, 4 * s, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    b = r.integers(0, 1 << 63, 4 * s, dtype=np.uint64)
    schema = pa.schema([("doc_id", pa.int64()), ("tag", pa.int64()), ("n", pa.int64()), ("h1", pa.int64()), ("h2", pa.int64()), ("a", pa.list_(pa.int64())), ("b", pa.list_(pa.int64()))])

    def sign(batches):
        textkit.release()
        for batch in batches:
            ids, tags = batch.column(0), batch.column(2)
            for lo, hi, texts in textkit.groups_of_rows(batch, "text"):
                sets = shingle_sets(texts, width)
                low = np.zeros((len(sets), 4 * s), np.uint64)
                h1, h2 = np.zeros(len(sets), np.uint64), np.zeros(len(sets), np.uint64)
                for i, x in enumerate(sets):
                    if len(x):
                        m = np.full(4 * s, np.iinfo(np.uint64).max)
                        for k in range(0, len(x), 8192):
                            m = np.minimum(m, (x[k : k + 8192, None] * a + b).min(axis=0))
                        low[i] = m
                        h1[i], h2[i] = x.sum(), np.bitwise_xor.reduce(x * np.uint64(0x9FB21C651E98DF25) ^ (x >> np.uint64(29)))
                sub = textkit.mix(low[:, 0::2] * np.uint64(0xD6E8FEB86659FD93) + textkit.mix(low[:, 1::2])).view(np.int64)
                n = np.array([len(x) for x in sets], np.int64)
                some = n > 0
                part = lambda v: pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(some * s)]).astype(np.int32)), pa.array(v[some].ravel()))  # noqa: E731, B023
                yield pa.RecordBatch.from_arrays([ids.slice(lo, hi - lo), tags.slice(lo, hi - lo), pa.array(n), pa.array(h1.view(np.int64)), pa.array(h2.view(np.int64)), part(sub[:, :s]), part(sub[:, s:])], schema=schema)

    return sign


def _setter(width: int):
    schema = pa.schema([("id", pa.int64()), ("shingles", pa.list_(pa.int64()))])

    def sets(batches):
        textkit.release()
        for batch in batches:
            for lo, hi, texts in textkit.groups_of_rows(batch, "text"):
                got = shingle_sets(texts, width)
                flat = np.concatenate(got).view(np.int64) if got else np.zeros(0, np.int64)
                offsets = np.concatenate([[0], np.cumsum([len(x) for x in got])]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], schema=schema)

    return sets


def components(links: DataFrame) -> DataFrame:
    """id, comp (smallest id reachable) of every node of the undirected links (x, y).

    Every node hooks to its smallest neighbour, the graph is contracted along the hooks, until no link is left."""
    edges = cut(links.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y")).filter("x != y").distinct(), "links")
    label, used = None, []
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("y").alias("x"), F.col("x").alias("y")))
        hook = both.groupBy(F.col("x").alias("id")).agg(F.min("y").alias("m")).select("id", F.least("id", "m").alias("comp"))
        hook = cut(hook, "hooks")
        used += [hook, edges]
        hx, hy = hook.toDF("x", "cx"), hook.toDF("y", "cy")
        edges = cut(edges.join(hy, "y").join(hx, "x").filter("cx != cy").select(F.greatest("cx", "cy").alias("x"), F.least("cx", "cy").alias("y")).distinct(), "links")
        if label is None:
            label = hook
        else:
            step = hook.toDF("comp", "next")
            label = label.join(step, "comp", "left").select("id", F.coalesce("next", "comp").alias("comp"))
    if label is None:
        return edges.select(F.col("x").alias("id"), F.col("y").alias("comp"))
    out = cut(label, "components")
    drop_cut(*used, edges)
    return out


def _measured(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """x, y, d (Jaccard distance of the full sets), linked (100 * intersection >= percent * union) of the pairs.

    Few pairs go to the sets, of which only the named ones move; many pairs and the sets meet by shuffles."""
    sy, sx = sets.toDF("y", "sy"), sets.toDF("x", "sx")
    if pairs.count() <= SMALL:
        sx = sx.join(F.broadcast(pairs.select("x").distinct()), "x", "left_semi")
        pairs = F.broadcast(pairs)
    both = F.size(F.array_intersect("sx", "sy"))
    found = pairs.select("x", "y").join(sy, "y").join(sx, "x").select("x", "y", both.alias("both"), (F.size("sx") + F.size("sy") - both).alias("union"))
    return found.select("x", "y", (1 - F.col("both") / F.col("union")).alias("d"), (F.col("both") * 100 >= F.col("union") * percent).alias("linked"))


def _sharing_tables(nodes: DataFrame, s: int) -> DataFrame:
    """bucket, x, n, y, ny: the members of the buckets of all s * s tables that hold several nodes, with the smallest node y.

    Rows move once, by their sub-key of the first collection, which every table key contains: `s` rows a node instead of
    `s * s`, and the tables' keys are formed where they land. Sub-keys that hold over a thousandth of all nodes (so fewer
    than 1000 * s of them) would make hot tasks: their table keys are aggregated first and joined with the minima."""
    sub = nodes.select(F.col("doc_id").alias("x"), "n", "b", F.posexplode("a").alias("i", "u")).select("x", "n", "b", F.xxhash64("i", "u").alias("g"))
    limit = max(HOT, nodes.count() // 1000)
    hot = cut(sub.groupBy("g").count().filter(F.col("count") > limit).select("g"), "hot-keys")
    keyed = lambda d: d.select("x", "n", "g", F.posexplode("b").alias("j", "v")).select("x", "n", "g", F.xxhash64("g", "j", "v").alias("bucket"))
    least, most = F.min(F.struct("x", "n")).alias("y"), F.max("x").alias("z")
    w = Window.partitionBy("g", "bucket")
    some = not hot.isEmpty()
    cold = sub.join(F.broadcast(hot), "g", "left_anti") if some else sub
    cold = keyed(cold.repartition("g")).withColumn("y", F.min(F.struct("x", "n")).over(w)).withColumn("z", F.max("x").over(w)).filter("y.x < z").select("bucket", "x", "n", "y")
    if some:
        keys = keyed(sub.join(F.broadcast(hot), "g", "left_semi"))
        cold = cold.unionByName(keys.join(keys.groupBy("bucket").agg(least, most).filter("y.x < z").select("bucket", "y"), "bucket").select("bucket", "x", "n", "y"))
    out = cut(cold.select("bucket", "x", F.col("n").cast("int").alias("n"), F.col("y.x").alias("y"), F.col("y.n").cast("int").alias("ny")), "buckets")
    drop_cut(hot)
    return out


def _open(rest: DataFrame, comp: DataFrame) -> DataFrame:
    """The members of buckets that hold several components, with their own and their bucket's largest one (main)."""
    now = rest.join(comp.toDF("x", "comp"), "x", "left").select("bucket", "x", "n", "d", F.coalesce("comp", "x").alias("comp"))
    main = now.groupBy("bucket", "comp").agg(F.count("*").alias("m")).groupBy("bucket").agg(F.max_by("comp", F.struct("m", "comp")).alias("main"), F.count("*").alias("comps")).filter("comps > 1").select("bucket", "main")
    return cut(now.join(main, "bucket"), "open")


def _merged(comp: DataFrame, links: DataFrame) -> DataFrame:
    """The components after further links."""
    if links.isEmpty():
        return comp
    cx, cy = (comp.toDF(c, f"c{c}") for c in "xy")
    between = components(links.join(cx, "x", "left").join(cy, "y", "left").select(F.coalesce("cx", "x").alias("x"), F.coalesce("cy", "y").alias("y")))
    known = comp.join(between.toDF("comp", "into"), "comp", "left").select("id", F.coalesce("into", "comp").alias("comp"))
    out = cut(known.unionByName(between.join(known.select("id"), "id", "left_anti")), "components")
    drop_cut(comp, between)
    return out


def _linked(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The confirmed links (x, y) among the pairs, which are used up."""
    pairs = cut(pairs, "pairs")
    out = cut(_measured(pairs, sets, percent).filter("linked").select("x", "y"), "confirmed")
    drop_cut(pairs)
    return out


def _parities(shingles: str) -> list:
    """64 * WORDS parity bits of a set as columns b0, b1, ...: how many of its shingles fall on each bit, odd or even."""
    word = lambda w: F.aggregate(F.filter(shingles, lambda t: F.pmod(F.shiftrightunsigned(t, 6), F.lit(WORDS)) == w), F.lit(0).cast("long"), lambda a, t: a.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(t, F.lit(64)).cast("int"))))
    return [word(w).alias(f"b{w}") for w in range(WORDS)]


def _sharing_rare(left: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (x, y) across the components of `left` (x, comp), among them every one that is linked.

    Only shingles of several components count. With each set's ordered by frequency, rarest first, behind all others of
    the set, a pair whose first common shingle stands so far back that what follows is less than the overlap a link takes
    can't be linked. So only the rare ends of the sets meet, and texts that share a passage but are otherwise different
    don't. A pair would meet again at each further common shingle: there it is skipped, if one of the `BEFORE` shingles
    before it is common as well (at the first of those it has met). Nor does it where the sets' parity bits differ in more
    places than linked sets have shingles apart: two parities differ only where the sets do. Members of a frequent
    shingle are dealt to several tasks. Exact, whatever the size of a group."""
    each = sets.join(left, F.col("id") == F.col("x")).select("x", F.xxhash64("shingles").alias("r"), "comp", F.size("shingles").alias("n"), "shingles").select("x", "r", "comp", "n", F.explode("shingles").alias("t"))
    crossing = each.groupBy("t").agg(F.count("*").alias("f"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo != hi").select("t", "f")
    whole = Window.partitionBy("x", "r")
    order = whole.orderBy("f", "t")
    place = each.join(crossing, "t").withColumn("k", F.count("*").over(whole)).withColumn("after", F.col("k") + 1 - F.row_number().over(order)).withColumn("before", F.collect_list("t").over(order.rowsBetween(-BEFORE, -1)))
    rare = cut(place.filter(f"after * 100 >= n * {percent}").select("t", "x", "r", "comp", "n", "after", "before"), "rare")
    parity = sets.join(rare.select("x").distinct(), F.col("id") == F.col("x"), "left_semi").select(F.col("id").alias("x"), F.xxhash64("shingles").alias("r"), *_parities("shingles"))
    spread = rare.groupBy("t", "comp").agg(F.count("*").alias("m")).groupBy("t").agg(F.max_by("comp", F.struct("m", "comp")).alias("main"), F.count("*").alias("comps"), F.ceil(F.sum("m") / MEETING).cast("int").alias("parts")).filter("comps > 1").select("t", "main", "parts")
    some = rare.join(spread, "t").join(parity, ["x", "r"])
    apart = " + ".join(f"bit_count(p.b{w} ^ q.b{w})" for w in range(WORDS))
    p = some.filter("comp != main").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).alias("p")
    q = some.withColumn("part", F.pmod(F.hash("x"), "parts")).alias("q")
    meet = F.expr(f"p.t = q.t and p.part = q.part and p.comp != q.comp and (q.comp = q.main or p.x > q.x) and least(p.after, q.after) * {100 + percent} >= (p.n + q.n) * {percent} and ({apart}) * {100 + percent} <= (p.n + q.n) * {100 - percent} and not arrays_overlap(p.before, q.before)")
    out = cut(p.join(q, meet).select(F.greatest("p.x", "q.x").alias("x"), F.least("p.x", "q.x").alias("y")).distinct(), "pairs")
    drop_cut(rare)
    return out


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, s: int = 10, seed: int = 7, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, n_shingles, component_id, kept, tag (hash of the text): one row per row of `docs`."""
    ship(docs.sparkSession)
    docs = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"), F.xxhash64(text).alias("tag"))
    signed = cut(docs.mapInArrow(_signer(width, s, seed), "doc_id long, tag long, n long, h1 long, h2 long, a array<long>, b array<long>"), "signatures")
    whole = signed.filter("n > 0 and doc_id is not null")
    classes = cut(whole.groupBy("h1", "h2", "n").agg(F.min("doc_id").alias("rep")), "classes")
    members = _sharing_tables(whole.join(classes.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi"), s)
    fits = f"least(n, ny) * 100L >= greatest(n, ny) * {percent}L"  # sizes further apart can't be linked
    pairs = cut(members.filter("x != y").filter(fits).groupBy("x", "y").agg(F.count("*").alias("c")), "pairs")
    # the bucket minimum that a member meets most often comes first, the others only where that left them apart
    best = cut(pairs.groupBy("x").agg(F.max_by("y", F.struct("c", -F.col("y"))).alias("y")), "pairs")
    involved = members.select(F.col("x").alias("doc_id")).distinct()
    sets = cut(docs.select("doc_id", "text").join(involved, "doc_id", "left_semi").mapInArrow(_setter(width), "id long, shingles array<long>"), "sets")
    first = cut(_measured(best, sets, percent), "measured")
    comp = components(first.filter("linked").select("x", "y"))
    cx, cy = (comp.toDF(c, f"c{c}") for c in "xy")
    others = pairs.join(best.select("x", F.col("y").alias("met")), "x").filter("y != met").join(cx, "x", "left").join(cy, "y", "left").filter(F.coalesce("cx", "x") != F.coalesce("cy", "y")).select("x", "y")
    others = cut(others, "pairs")
    second = cut(_measured(others, sets, percent), "measured")
    comp = _merged(comp, second.filter("linked").select("x", "y"))
    # each member with its distance to the bucket's smallest member, where it was measured
    measured = first.unionByName(second).select("x", "y", "d")
    rest = members.join(measured, ["x", "y"], "left").select("bucket", "x", "n", F.when(F.col("x") == F.col("y"), F.lit(0.0)).otherwise(F.col("d")).alias("d"))
    rest = _open(rest, comp)
    drop_cut(members, pairs, best, others, first, second)
    if not rest.isEmpty():
        # one pivot of each mixed bucket meets its members, so that large groups that the smallest member missed come together
        drawn = F.min_by(F.struct("x", "comp", "n", "d"), F.struct(F.xxhash64("x"), "x"))
        pivots = rest.filter("comp != main").groupBy("bucket").agg(drawn.alias("p")).select("bucket", F.col("p.x").alias("y"), F.col("p.comp").alias("cy"), F.col("p.n").alias("ny"), F.col("p.d").alias("dy"))
        # by the triangle inequality, members too far apart in their distance to the same third set can't be linked
        near = F.coalesce(F.abs(F.col("d") - F.col("dy")) <= 1 - percent / 100 + 1e-9, F.lit(True)) & F.expr(fits)
        crossing = rest.join(pivots, "bucket").filter((F.col("comp") != F.col("cy")) & near)
        confirmed = _linked(crossing.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y")).distinct(), sets, percent)
        comp = _merged(comp, confirmed)
        still = _open(rest.select("bucket", "x", "n", "d"), comp)
        left = cut(still.select("x", "comp").distinct(), "mixed")
        drop_cut(rest, still, confirmed)
        confirmed = _linked(_sharing_rare(left, sets, percent), sets, percent)
        comp = _merged(comp, confirmed)
        drop_cut(left, confirmed)
    drop_cut(sets)
    per_class = classes.join(comp.toDF("rep", "comp"), "rep", "left").select("h1", "h2", "n", F.coalesce("comp", "rep").alias("comp"))
    out = signed.select("doc_id", "tag", "n", "h1", "h2").join(per_class, ["h1", "h2", "n"], "left")
    component = F.when((F.col("n") == 0) | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.coalesce("comp", "doc_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), "tag").withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def keep_one_of_each_group(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The documents that stay, with all their columns: of each group those with the smallest id."""
    gone = near_duplicates(docs, width, percent).filter("not kept").select(F.col("doc_id").alias("__gone"), F.col("tag").alias("__tag")).distinct()
    return docs.join(gone, (F.col("doc_id") == F.col("__gone")) & (F.xxhash64("text") == F.col("__tag")), "left_anti")


def op9_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir), width=2, percent=80).drop("tag")
