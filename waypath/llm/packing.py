"""Packing by concatenate and cut: global offsets from two passes, then fixed windows."""

from __future__ import annotations

import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written
from .tokens import WORD_FILE, loaded

WINDOW, END_ID = 4096, 2


def tokenised(docs: DataFrame, path: str | None = None, end_id: int = END_ID) -> DataFrame:
    """First pass: ids of each document with the end id, and where they start in their partition."""
    path = path or public_tokenizers.path(WORD_FILE)

    def encode(batches):
        bpe = loaded(path)
        end = np.array([end_id], bpe.dtype).tobytes()
        width, part, at = len(end), TaskContext.get().partitionId(), 0
        for b in batches:
            ids = [bpe.encode(t) + end for t in b.column(1).to_pylist()]
            n = np.array([len(x) // width for x in ids], "int64")
            start = at + np.cumsum(n) - n
            at += int(n.sum())
            yield pa.RecordBatch.from_arrays([
                b.column(0), pa.array(np.full(len(n), part, "int32")), pa.array(start), pa.array(n), pa.array(ids, pa.binary()),
            ], ["doc_id", "part", "local_start", "n", "ids"])

    return docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(
        encode, "doc_id long, part int, local_start long, n long, ids binary")


def partition_bases(table: DataFrame) -> dict[int, int]:
    """Ids before each partition.  One row per partition of the written table reaches the driver."""
    totals = table.groupBy("part").agg(F.sum("n").alias("n")).collect()
    at, out = 0, {}
    for part, n in sorted(map(tuple, totals)):
        out[part] = at
        at += n
    return out


def pack(docs: DataFrame, window: int = WINDOW, path: str | None = None, end_id: int = END_ID) -> DataFrame:
    """Pieces of all documents laid end to end and cut every ``window`` ids.

    Pass one tokenises and writes ids with their start inside the partition; the prefix sum
    of the partition totals turns these into global offsets; pass two cuts.  A document that
    crosses a boundary gives one record per window.  Every sequence but the last is full.
    A null or empty text is the end id alone; repeated rows are packed each; an empty table
    gives no pieces; other columns are ignored.
    """
    table = written(tokenised(docs, path, end_id), "ids")
    bases = docs.sparkSession.sparkContext.broadcast(partition_bases(table))
    width = loaded(path).dtype

    def cut(batches):
        base = bases.value
        for b in batches:
            rows = []
            for doc, part, local, n, raw in zip(*(b.column(k).to_pylist() for k in range(5))):
                ids = np.frombuffer(raw, width).astype("<u4")
                at, g = 0, base[part] + local
                while at < n:
                    seq, off = divmod(g + at, window)
                    size = min(window - off, n - at)
                    rows.append((doc, at, size, zlib.crc32(ids[at:at + size].tobytes()), n, seq, off))
                    at += size
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)] if rows else [pa.array([], pa.int64())] * len(names), names)

    return table.mapInArrow(cut, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
