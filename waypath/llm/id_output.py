"""Token-id files: documents in id order, in checksummed blocks of the range coder, and back."""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shared_dir, to_drop, written
from .id_coder import BLOCK_IDS, block_bytes, crc_joined, decode_lanes, encode_lanes, read_block
from .packing import tokenised
from .tokens import loaded

#: Blocks coded side by side: a step costs its calls, so more lanes make an id cheaper; a lane takes some 150 KB of a worker.
LANES = 1024


def write_ids(docs: DataFrame, path: str, tokenizer: str | None = None, block_ids: int = BLOCK_IDS, lanes: int = LANES) -> None:
    """Write the ids of all documents (each with the end id) to ``path`` in ascending doc_id order.

    Ids are written once, then sorted by range; each task lays its documents end to end, cuts
    every ``block_ids`` ids and codes ``lanes`` blocks at a time.  A document of any length
    spans as many blocks as it needs.  The files are Parquet with one block a row, which any
    file system Spark can write to will hold.
    """
    bpe = loaded(tokenizer)
    width, top = bpe.dtype, bpe.lib.get_vocab_size() - 1
    ids = written(tokenised(docs, tokenizer).select("doc_id", "ids"), "ids")

    def encode(batches):
        part, place, number = TaskContext.get().partitionId(), 0, 0
        ready: list[tuple] = []  # (place, fragments, ids)
        parts: list[np.ndarray] = []
        frags: list[tuple] = []
        fill = 0

        def coded():
            nonlocal ready
            words = encode_lanes([x for _, _, x in ready], top)
            out = [block_bytes(part, at, fr, x, w) for (at, fr, x), w in zip(ready, words)]
            places = [at for at, _, _ in ready]
            ready = []
            return pa.RecordBatch.from_arrays([pa.array([part] * len(out), pa.int32()), pa.array(places, pa.int64()), pa.array(out, pa.binary())], ["part", "place", "block"])

        def close():
            nonlocal parts, frags, fill, place
            ready.append((place, frags, np.concatenate(parts)))
            place += fill
            parts, frags, fill = [], [], 0

        for b in batches:
            for doc, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                x = np.frombuffer(raw, width)
                at = frag = 0
                while at < len(x):
                    size = min(block_ids - fill, len(x) - at)
                    parts.append(x[at:at + size])
                    frags.append((doc, number, frag, size))
                    fill += size
                    at += size
                    frag += 1
                    if fill == block_ids or len(frags) == 65535:
                        close()
                        if len(ready) == lanes:
                            yield coded()
                number += 1
        if fill:
            close()
        if ready:
            yield coded()

    ids.orderBy(F.col("doc_id").asc_nulls_last(), "ids").mapInArrow(encode, "part int, place long, block binary").write.parquet(path)


def read_ids(spark, path: str, top: int | None = None, lanes: int = LANES) -> DataFrame:
    """(part, number, doc_id, frag, place, n, crc) of every fragment in the files, decoded and checked."""
    if top is None:
        top = loaded().lib.get_vocab_size() - 1

    def decode(batches):
        todo: list[tuple] = []

        def run():
            nonlocal todo
            found = decode_lanes([t[5] for t in todo], [t[3] for t in todo], top)
            rows = []
            for (part, place, frags, _, crc, _), ids in zip(todo, found):
                raw = ids.astype("<u4").tobytes()
                if zlib.crc32(raw) != crc:
                    raise ValueError("ids differ from their checksum")
                at = 0
                for doc, number, frag, n in frags:
                    rows.append((part, number, doc, frag, place + at, n, zlib.crc32(raw[4 * at:4 * (at + n)])))
                    at += n
            todo = []
            cols = list(zip(*rows))
            kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["part", "number", "doc_id", "frag", "place", "n", "crc"])

        for b in batches:
            for blob in b.column(0).to_pylist():
                todo.append(read_block(blob))
                if len(todo) == lanes:
                    yield run()
        if todo:
            yield run()

    return spark.read.schema("part int, place long, block binary").parquet(path).select("block").mapInArrow(
        decode, "part int, number long, doc_id long, frag int, place long, n long, crc long")


def id_report(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, read back from files written for it.

    A null or empty text is the end id alone; null ids come last; equal ids are ordered by
    their token ids; an empty table writes no blocks and gives no rows; other columns are
    ignored.
    """
    spark = docs.sparkSession
    path = f"{shared_dir(spark)}/waypath-idfile-{uuid.uuid4().hex}"
    write_ids(docs, path, tokenizer)
    to_drop(spark, path)
    frags = written(read_ids(spark, path, loaded(tokenizer).lib.get_vocab_size() - 1), "fragments")
    totals = frags.groupBy("part").agg(F.sum("n").alias("n")).collect()  # a row per partition of the sort
    at, rows = 0, []
    for part, n in sorted(map(tuple, totals)):
        rows.append((part, at))
        at += n
    bases = spark.createDataFrame(rows, "part int, base long")
    one = frags.groupBy("part", "number").agg(
        F.first("doc_id").alias("doc_id"), F.min("place").alias("place"), F.sum("n").alias("n_tokens"),
        F.sort_array(F.collect_list(F.struct("frag", "n", "crc"))).alias("f"))

    @F.pandas_udf("long")
    def joined(parts):
        out = []
        for fs in parts:
            crc = 0
            for f in fs:
                crc = crc_joined(crc, f["crc"], 4 * f["n"]) if f["frag"] else f["crc"]
            out.append(crc)
        return pd.Series(out, dtype="int64")

    crc = F.when(F.size("f") == 1, F.col("f")[0]["crc"]).otherwise(joined("f"))
    return one.join(F.broadcast(bases), "part").select("doc_id", (F.col("base") + F.col("place")).alias("start"), "n_tokens", crc.alias("ids_crc32"))
