"""Token ids in flat binary files with 64-bit document offsets, memory-mapped on reading.

Rows are range-partitioned by document id; each partition is encoded straight into its own files:
`<part>.ids` (unsigned little-endian integers, 16 bits where the vocabulary fits, else 32), `<part>.offsets` (64-bit:
where each document begins in the part, and the end) and `<part>.docs` (64-bit ids; the smallest integer for null).
A part's files carry the number of the task attempt that wrote them. The driver sees one row per part, from the attempt
that succeeded; prefix sums over their totals give the parts' bases, kept in `manifest.json`, which names the files
and is the one commit: files of failed or repeated attempts are in no manifest and are removed.

Defined results: a null text is empty and has only the end id; order is ascending id, null ids first, equal ids by their
texts' hashes, then texts;
an empty table gives a manifest without parts and no rows.
"""

from __future__ import annotations

import json
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyarrow.fs import FileSelector
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textkit
from .common import documents, partitions, shared_folder, ship

NULL_ID = -(1 << 63)
READ = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])


def _store(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder)


def _writer(folder: str, vocabulary: str, end_id: int):
    def write(batches):
        store, base = _store(folder)
        task = TaskContext.get()
        name = f"part-{task.partitionId():06d}-{task.taskAttemptId()}"
        enc = textkit.word_encoder(vocabulary)
        end = np.array([end_id], enc.dtype).tobytes()
        at, docs = [0], []
        with store.open_output_stream(f"{base}/{name}.ids") as out:
            for batch in batches:
                docs.append(batch.column(0).fill_null(NULL_ID).to_numpy().astype("<i8"))
                for t in batch.column(1).to_pylist():
                    ids = enc.ids(t or "") + end
                    out.write(ids)
                    at.append(at[-1] + len(ids) // enc.dtype.itemsize)
        for ext, values in (("offsets", np.array(at, "<i8")), ("docs", np.concatenate(docs) if docs else np.zeros(0, "<i8"))):
            with store.open_output_stream(f"{base}/{name}.{ext}") as out:
                out.write(values.tobytes())
        yield pa.RecordBatch.from_pydict({"part": [name], "docs": [len(at) - 1], "tokens": [at[-1]], "width": [enc.dtype.itemsize]})

    return write


def write_tokens(docs: DataFrame, folder: str, vocabulary: str, end_id: int = 1, text: str = "text", key: str = "doc_id") -> list[dict]:
    """Write the files of all documents; returns the manifest's parts, in order, each with its base."""
    spark = docs.sparkSession
    ship(spark)
    store, base = _store(folder)
    store.create_dir(base)
    ordered = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).repartitionByRange(partitions(spark) * 2, "doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text"), "text")
    parts = [r.asDict() for r in ordered.mapInArrow(_writer(folder, vocabulary, end_id), "part string, docs long, tokens long, width long").collect()]  # one row per part
    parts.sort(key=lambda p: p["part"])
    bases = np.cumsum([0] + [p["tokens"] for p in parts])
    rows = np.cumsum([0] + [p["docs"] for p in parts])
    for p, b, r in zip(parts, bases, rows, strict=False):
        p["base"], p["row_base"] = int(b), int(r)
    with store.open_output_stream(f"{base}/manifest.json") as out:
        out.write(json.dumps({"end_id": end_id, "tokens": int(bases[-1]), "documents": int(rows[-1]), "parts": parts}).encode())
    named = {p["part"] for p in parts}
    for f in store.get_file_info(FileSelector(base)):
        if f.base_name.startswith("part-") and f.base_name.split(".")[0] not in named:
            store.delete_file(f.path)
    return parts


def open_part(folder: str, part: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, offsets, document ids) of a part; memory-mapped where the store has local paths."""
    store, base = _store(folder)

    def array(ext: str, kind: str) -> np.ndarray:
        path = f"{base}/{part['part']}.{ext}"
        if store.type_name == "local":
            source = pa.memory_map(path)
        else:
            source = store.open_input_file(path)
        return np.frombuffer(source.read_buffer(), kind)

    return array("ids", f"<u{part['width']}"), array("offsets", "<i8"), array("docs", "<i8")


def _reader(folder: str):
    def read(batches):
        for batch in batches:
            for part in batch.to_pylist():
                ids, at, docs = open_part(folder, part)
                for lo in range(0, len(docs), 4096):
                    hi = min(lo + 4096, len(docs))
                    crc = [zlib.crc32(ids[at[i] : at[i + 1]].astype("<u4")) for i in range(lo, hi)]
                    d = docs[lo:hi]
                    yield pa.RecordBatch.from_arrays([pa.array(d, mask=d == NULL_ID), pa.array(at[lo:hi] + part["base"]), pa.array(np.diff(at[lo : hi + 1])), pa.array(crc, pa.int64())], schema=READ)

    return read


def read_tokens(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start (ids of all documents before), n_tokens, ids_crc32 (of the ids as 32-bit integers), from the files."""
    store, base = _store(folder)
    parts = json.loads(store.open_input_file(f"{base}/manifest.json").read())["parts"]
    files = spark.createDataFrame([tuple(p[k] for k in ("part", "docs", "tokens", "width", "base")) for p in parts], "part string, docs long, tokens long, width long, base long")
    return files.repartition(max(1, len(parts))).mapInArrow(_reader(folder), "doc_id long, start long, n_tokens long, ids_crc32 long")


def op10_token_files(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    folder = f"{shared_folder(spark)}/tokens-{uuid.uuid4().hex}"
    write_tokens(documents(spark, sf_dir), folder, public_tokenizers.path("word_bpe_49k.json"))
    return read_tokens(spark, folder)
