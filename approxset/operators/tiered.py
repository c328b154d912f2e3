"""Storage-tiered filters: one buffer before one large filter, and a buffer before geometrically growing levels.

Contents live as Parquet in folders of their own, never changed once written; numbered catalogue files name those that make
up a version, so readers pin one and a crash before the commit leaves only orphan files. Deletes are negative counts that
wait in the buffer and are settled when merged."""

from __future__ import annotations

import dataclasses
import json
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions.fingerprint import fingerprint
from ..schema import FilterSpec, FilterSpecMismatch
from . import quotient


def capacities(buffer: int, fanout: int, factor: int, levels: int) -> list[int]:
    return [buffer] + [buffer * factor * fanout**i for i in range(levels)]


def choose_level(items: list[int], buffer: int, fanout: int, factor: int) -> int:
    """The smallest level that takes everything up to itself."""
    cap = capacities(buffer, fanout, factor, 64)
    i = 1
    while sum(items[: i + 1]) > cap[i]:
        i += 1
    return i


def merge_schedule(epochs: int, fanout: int = 2, factor: int = 1, buffer: int = 1) -> list[tuple[int, int, int, int]]:
    """(epoch, target level, units written, non-empty levels after it)."""
    items = [0] * 65
    out = []
    for e in range(1, epochs + 1):
        items[0] = buffer
        t = choose_level(items, buffer, fanout, factor)
        items[t] = sum(items[: t + 1])
        items[:t] = [0] * t
        out.append((e, t, items[t], sum(1 for x in items if x)))
    return out


class Catalogue:
    """The commit point: small JSON files numbered by version. A commit creates the next number and fails if that exists, so
    no version is ever lost or overwritten, and of two writers one has to start again. Readers take the newest whole file."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, f"{path.rstrip('/')}/catalogue"
        self.P = spark._jvm.org.apache.hadoop.fs.Path
        self.fs = self.P(self.path).getFileSystem(spark._jsc.hadoopConfiguration())

    def _name(self, version: int) -> str:
        return f"{self.path}/{version:012d}.json"

    def _versions(self) -> list[int]:
        if not self.fs.exists(self.P(self.path)):
            return []
        return sorted((int(f.getPath().getName()[:12]) for f in self.fs.listStatus(self.P(self.path)) if f.getPath().getName().endswith(".json")), reverse=True)

    def _text(self, version: int) -> str:
        stream = self.fs.open(self.P(self._name(version)))
        try:
            return bytes(stream.readAllBytes()).decode()
        finally:
            stream.close()

    def read(self) -> dict:
        for v in self._versions():
            try:
                return json.loads(self._text(v))
            except ValueError:  # a writer died inside its commit
                continue
        return {"version": 0, "number": 0, "buffer": [], "levels": {}, "batches": [], "tombstones": False, "history": []}

    def commit(self, state: dict) -> None:
        """The next version after the one that `state` was read from."""
        seen = self._versions()
        newest = self.read()["version"]
        if newest != state["version"]:
            raise RuntimeError(f"the catalogue has moved from version {state['version']} to {newest}")
        state["version"] += 1
        state["number"] = max(seen[0] if seen else 0, state["number"]) + 1
        out = self.fs.create(self.P(self._name(state["number"])), False)
        out.write(bytearray(json.dumps(state).encode()))
        out.close()


class LevelledFilter:
    """A buffer before levels of growing size. `fanout` and `factor` as in `capacities`; with `tiers` of 1 there is one level.

    The buffer holds what has arrived since the last flush, as small files of their own (level 0). When it holds `buffer`
    items it is merged into the level that takes it; a batch beyond the buffer's size counts as what it holds."""

    def __init__(self, spark: SparkSession, path: str, spec: FilterSpec, buffer: int, fanout: int = 2, factor: int = 1, tiers: int | None = None):
        self.spark, self.path, self.spec = spark, path.rstrip("/"), spec
        self.buffer, self.fanout, self.factor, self.tiers = buffer, fanout, factor, tiers
        self.shards = max(1, min(spec.slots, max(64, spec.slots >> 20)))
        self.cat = Catalogue(spark, path)

    def state(self) -> dict:
        state = self.cat.read()
        mine = dataclasses.asdict(self.spec)
        if state.setdefault("spec", mine) != mine:
            raise FilterSpecMismatch(f"{self.path} holds {state['spec']}, not {mine}")
        return state

    def _read(self, part: dict) -> DataFrame:
        return self.spark.read.schema("fp long, cnt long").parquet(part["path"])

    def _write(self, fps: DataFrame, folder: str) -> dict:
        """Files sorted by fingerprint inside ranges of them, and how many items they hold, deletes included."""
        path = f"{self.path}/{folder}/{uuid.uuid4().hex}"
        seen = Observation()
        fps.select("fp", "cnt").observe(seen, F.coalesce(F.sum(F.abs("cnt")), F.lit(0)).alias("items")).write.parquet(path)
        return {"path": path, "items": int(seen.get["items"])}

    def _shard(self) -> Column:
        return F.call_function("div", F.col("fp"), F.lit(-(-(1 << self.spec.p) // self.shards)).cast("long"))

    def _merged(self, parts: list[DataFrame]) -> DataFrame:
        """The parts' counts added up: one shuffle by range of fingerprints, which is the stored order as well."""
        d = parts[0]
        for p in parts[1:]:
            d = d.unionByName(p)
        return d.withColumn("shard", self._shard()).repartition("shard").groupBy("shard", "fp").agg(F.sum("cnt").alias("cnt")).sortWithinPartitions("shard", "fp")

    def ingest(self, keys: DataFrame, batch: str | None = None, sign: int = 1) -> None:
        """Keys into the buffer, which is flushed when full. A batch already committed is skipped."""
        self.ingest_fps(quotient.build_fp(keys, self.spec), batch, sign)

    def ingest_fps(self, fps: DataFrame, batch: str | None = None, sign: int = 1) -> None:
        """`ingest` of keys that are (fp, cnt) already."""
        state = self.state()
        if batch is not None and batch in state["batches"]:
            return
        delta = fps.withColumn("cnt", F.col("cnt") * sign)
        state["buffer"].append(self._write(delta, "buffer"))
        state["tombstones"] = state["tombstones"] or sign < 0
        if batch is not None:
            state["batches"].append(batch)
        if sum(b["items"] for b in state["buffer"]) >= self.buffer:
            self._flush(state)
        self.cat.commit(state)

    def delete(self, keys: DataFrame, batch: str | None = None) -> None:
        self.ingest(keys, batch, -1)

    def vacuum(self) -> None:
        """Delete the files that the newest version doesn't name: for the one writer, when no reader has an older one pinned."""
        named, fs, P = json.dumps(self.state()), self.cat.fs, self.cat.P
        for folder in fs.listStatus(P(self.path)):
            if folder.isDirectory() and folder.getPath().getName() != "catalogue":
                for run in fs.listStatus(folder.getPath()):
                    if run.getPath().getName() not in named:
                        fs.delete(run.getPath(), True)

    def flush(self) -> None:
        """The buffer into the levels, full or not."""
        state = self.state()
        if state["buffer"]:
            self._flush(state)
            self.cat.commit(state)

    def _flush(self, state: dict) -> None:
        items = [0] * 65
        for i, lv in state["levels"].items():
            items[int(i)] = lv["items"]
        items[0] = sum(b["items"] for b in state["buffer"])
        t = 1 if self.tiers == 1 else choose_level(items, self.buffer, self.fanout, self.factor)
        below = [i for i in state["levels"] if int(i) <= t]
        last = len(below) == len(state["levels"])
        whole = self._merged([self._read(p) for p in [*state["buffer"], *(state["levels"][i] for i in below)]])
        written = self._write(whole.filter("cnt > 0" if last else "cnt != 0"), f"level={t}")
        for i in below:
            del state["levels"][i]
        state["levels"][str(t)] = written
        state["buffer"] = []
        state["tombstones"] = state["tombstones"] and not last
        state["history"].append({"epoch": len(state["history"]) + 1, "target": t, "flushed": items[0], "written": written["items"], "levels": len(state["levels"])})

    def history(self) -> DataFrame:
        """epoch, target level, items flushed from the buffer, items written, non-empty levels after it: one row a flush."""
        rows = [(h["epoch"], h["target"], h["flushed"], h["written"], h["levels"]) for h in self.state()["history"]]
        return self.spark.createDataFrame(rows, "epoch long, target int, flushed long, written long, levels int")

    def _parts(self, state: dict) -> list[tuple[int, DataFrame]]:
        """(level, its fingerprints): the buffer is level 0."""
        return [(0, self._read(b)) for b in state["buffer"]] + [(int(i), self._read(lv)) for i, lv in sorted(state["levels"].items(), key=lambda x: int(x[0]))]

    def levels(self) -> dict[int, DataFrame]:
        return {i: d for i, d in self._parts(self.state()) if i}

    def contents(self) -> DataFrame:
        """(fp, cnt) settled over the buffer and all levels."""
        parts = [d for _, d in self._parts(self.state())]
        return quotient.merge(*parts).filter("cnt > 0") if parts else self.spark.createDataFrame([], "fp long, cnt long")

    def probe(self, df: DataFrame, precheck: bool = False) -> DataFrame:
        """df with `maybe`, `level` of the newest hit (0 is the buffer; null if none) and `levels_read`.

        The buffer first, which costs no read, then the newest level, stopping at the first hit unless a tombstone may hide
        it. With `precheck`, a level whose bucket bitmap is clear isn't read."""
        state = self.state()
        parts = self._parts(state)
        if not parts:
            return df.select("*", F.lit(False).alias("maybe"), F.lit(None).cast("int").alias("level"), F.lit(0).cast("long").alias("levels_read"))
        union = None
        for i, d in parts:
            d = d.withColumn("lv", F.lit(i))
            union = d if union is None else union.unionByName(d)
        stored = F.array(*[F.lit(i) for i in sorted({i for i, _ in parts if i})]).cast("array<int>")
        hits = union.groupBy(F.col("fp").alias("__fp")).agg(F.sum("cnt").alias("__net"), F.min("lv").alias("__lv")).filter("__net > 0")
        out = df.withColumn("__fp", fingerprint(F.col("k"), self.spec)).join(hits, "__fp", "left")
        # where lookups may stop: a tombstone in a newer level may hide a copy, so they go on
        stop = F.lit(None).cast("int") if state["tombstones"] else F.col("__lv")
        at = stored
        if precheck:
            bucket = F.call_function("div", F.col("__fp"), F.lit(self.spec.width).cast("long"))
            occupied = union.filter("lv > 0").select(F.call_function("div", F.col("fp"), F.lit(self.spec.width).cast("long")).alias("__bucket"), "lv").groupBy("__bucket").agg(F.collect_set("lv").alias("__at"))
            out = out.withColumn("__bucket", bucket).join(occupied, "__bucket", "left")
            at = F.coalesce("__at", F.array().cast("array<int>"))
        read = F.when(F.col("__fp").isNull(), 0).otherwise(F.size(F.filter(at, lambda x: stop.isNull() | (x <= stop))))
        return out.select(*df.columns, F.col("__net").isNotNull().alias("maybe"), F.col("__lv").alias("level"), read.cast("long").alias("levels_read"))

    def compact(self) -> None:
        """All levels into the highest that takes them, as a separate job; the commit fails if the version has moved."""
        state = self.state()
        if not state["levels"]:
            return
        whole = self._merged([d for i, d in self._parts(state) if i]).filter("cnt > 0")
        written = self._write(whole, "compacted")
        cap = capacities(self.buffer, self.fanout, self.factor, 64)
        t = next(i for i in range(1, 65) if cap[i] >= written["items"])
        state |= {"levels": {str(t): written}, "tombstones": state["tombstones"] and bool(state["buffer"])}
        self.cat.commit(state)


class TwoTierFilter(LevelledFilter):
    """A buffer before one large filter: every flush merges into the one stored level."""

    def __init__(self, spark, path, spec, buffer):
        super().__init__(spark, path, spec, buffer, tiers=1)


class DeamortisedFilter(LevelledFilter):
    """Levels whose merges are cut into `shards` tasks, of which a flush does `per_flush` at most.

    A flush writes its buffer as a run and, where the schedule merges levels, queues a merge. A merge's output holds the
    shards done so far and its sources answer for the rest, so lookups are right at any time: counts only add up."""

    def __init__(self, spark, path, spec, buffer, per_flush: int, fanout: int = 2, factor: int = 1, shards: int = 16):
        super().__init__(spark, path, spec, buffer, fanout, factor)
        self.per_flush, self.shards = per_flush, shards

    def _range(self, run: dict, lo: int, hi: int) -> DataFrame:
        return self.spark.read.schema("fp long, cnt long, shard long").parquet(run["path"]).filter((F.col("shard") >= lo) & (F.col("shard") < hi))

    def _run(self, fps: DataFrame, path: str) -> int:
        seen = Observation()
        fps.select("fp", "cnt", "shard").observe(seen, F.coalesce(F.sum(F.abs("cnt")), F.lit(0)).alias("items")).write.mode("append").partitionBy("shard").parquet(path)
        return int(seen.get["items"])

    def _flush(self, state: dict) -> None:
        runs, queue = state.setdefault("runs", {}), state.setdefault("queue", [])
        items = [0] * 65
        for i, lv in state["levels"].items():
            items[int(i)] = lv["items"]
        items[0] = sum(b["items"] for b in state["buffer"])
        t = choose_level(items, self.buffer, self.fanout, self.factor)
        name, path = uuid.uuid4().hex, f"{self.path}/run/{uuid.uuid4().hex}"
        written = self._run(self._merged([self._read(b) for b in state["buffer"]]), path)
        runs[name] = {"path": path, "from": 0}
        below = [i for i in state["levels"] if int(i) <= t]
        if below:
            out = uuid.uuid4().hex
            queue.append({"sources": [name, *(state["levels"][i]["run"] for i in below)], "out": out, "next": 0, "last": len(below) == len(state["levels"])})
            runs[out] = {"path": f"{self.path}/run/{uuid.uuid4().hex}", "to": 0}
            name = out
        for i in below:
            del state["levels"][i]
        state["levels"][str(t)] = {"run": name, "items": sum(items[: t + 1])}
        state["buffer"] = []
        left = self.per_flush
        while left and queue:
            m = queue[0]
            lo, hi = m["next"], min(m["next"] + left, self.shards)
            d = self._merged([self._range(runs[s], lo, hi).select("fp", "cnt") for s in m["sources"]])
            # each step of a merge has files of its own: a step repeated after a crash leaves no row twice
            path = f"{runs[m['out']]['path']}/step={lo}-{uuid.uuid4().hex}"
            written += self._run(d.filter("cnt > 0" if m["last"] else "cnt != 0"), path)
            runs[m["out"]].setdefault("steps", []).append([path, lo, hi])
            left -= hi - lo
            m["next"] = hi
            runs[m["out"]]["to"] = hi
            for s in m["sources"]:
                runs[s]["from"] = hi
            if hi == self.shards:
                for s in m["sources"]:
                    del runs[s]
                queue.pop(0)
        state["history"].append({"epoch": len(state["history"]) + 1, "target": t, "flushed": items[0], "written": written, "levels": len(state["levels"]), "done": self.per_flush - left, "waiting": sum(self.shards - m["next"] for m in queue)})

    def _range_of(self, run: dict) -> list[DataFrame]:
        lo = run.get("from", 0)
        if "to" not in run:
            return [self._range(run, lo, self.shards).select("fp", "cnt")]
        return [self._range({"path": p}, max(lo, a), b).select("fp", "cnt") for p, a, b in run.get("steps", []) if b > lo]

    def _parts(self, state: dict) -> list[tuple[int, DataFrame]]:
        level = {lv["run"]: int(i) for i, lv in state["levels"].items()}
        for m in reversed(state.get("queue", [])):
            for s in m["sources"]:
                level.setdefault(s, level.get(m["out"], 64))
        return [(0, self._read(b)) for b in state["buffer"]] + [(level[n], d) for n, r in state.get("runs", {}).items() for d in self._range_of(r)]

    def progress(self) -> DataFrame:
        """epoch, shards of merge work done, shards waiting: one row a flush."""
        return self.spark.createDataFrame([(h["epoch"], h["done"], h["waiting"]) for h in self.state()["history"]], "epoch long, done long, waiting long")

    def compact(self) -> None:
        raise NotImplementedError("merges are queued here")
