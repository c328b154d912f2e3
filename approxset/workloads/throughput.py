"""Inserts and lookups a second at each twentieth of a filter's slots: clocks, so reported and never asserted."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..cluster import cleaned
from ..operators import bloom
from ..operators import quotient as qf
from ..schema import FilterSpec
from ..sources import tables as src
from .base import query

STRUCTURES = ("quotient", "classic", "page-local")


def run(spark, d, structures=STRUCTURES, steps=tuple(range(1, 19)), r: int = 9) -> list[tuple]:
    """(structure, step, operation, items, seconds, items a second): up to 18 steps fill 90 % of the slots.

    An insert step merges the step's keys into what is there; lookups are as many absent and as many present keys as the
    step has inserted."""
    keys = src.triple_keys(spark, d)
    n = keys.count()
    slots = -(-n * 10 // 9)
    spec = FilterSpec(p=(slots - 1).bit_length() + r, slots=slots, max_load=0.9)
    b, p = bloom.BloomFilter(slots * (r + 3), r), bloom.PageLocalBloom(-(-slots * (r + 3) // 4096), 4096, r)
    ends = [i * slots // 20 for i in range(1, 20)]
    arrived = src.arrived_by(keys, ends).withColumn("step", F.call_function("div", F.col("seq") * 20 + slots - 1, F.lit(slots).cast("long"))).cache()
    arrived.count()
    absent = arrived.select("step", F.concat(F.lit("absent "), "k").alias("k"))
    out = []
    for name in structures:
        build, merge, probe = {"quotient": (lambda x: qf.build_fp(x, spec), qf.merge, lambda x, f: qf.probe_join(x, f, spec)), "classic": (b.build, b.union, b.probe), "page-local": (p.build, b.union, p.probe)}[name]
        state, last = None, 0
        for step in steps:
            new = arrived.filter((F.col("step") > last) & (F.col("step") <= step))
            items = new.count()
            grown = build(new.select("k"))
            grown = grown if state is None else merge(state, grown)
            t = time.time()
            grown = grown.cache()
            grown.count()
            out.append((name, step, "insert", items, time.time() - t))
            if state is not None:
                state.unpersist()
            state = grown
            for kind, rows in (("absent", absent), ("present", arrived)):
                t = time.time()
                probe(rows.filter((F.col("step") > last) & (F.col("step") <= step)).select("k"), state).write.format("noop").mode("overwrite").save()
                out.append((name, step, kind, items, time.time() - t))
            last = step
        state.unpersist()
    arrived.unpersist()
    return [(*x, x[3] / max(x[4], 1e-9)) for x in out]


@query("throughput_by_phase")
def throughput_by_phase(spark, d) -> DataFrame:
    """Four of the phases, at a quarter, half, three quarters and nine tenths of the slots."""
    with cleaned(spark):
        rows = run(spark, d, steps=(5, 10, 15, 18))
    return spark.createDataFrame(rows, "structure string, step long, operation string, items long, seconds double, a_second double")
