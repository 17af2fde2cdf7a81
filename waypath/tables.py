"""Reading the given tables with explicit schemas, and tables written to the shared folder."""

from __future__ import annotations

import atexit
import os
import re
import tempfile
import threading
import uuid
import zipfile
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

SCHEMAS = {
    "lineitem": "l_orderkey BIGINT, l_partkey BIGINT, l_suppkey BIGINT, l_linenumber INT, l_quantity DOUBLE, l_extendedprice DOUBLE, l_discount DOUBLE, l_tax DOUBLE, l_returnflag STRING, l_linestatus STRING, l_shipdate TIMESTAMP",
    "orders": "o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate TIMESTAMP, o_orderpriority STRING",
    "customer": "c_custkey BIGINT, c_name STRING, c_nationkey INT, c_acctbal DOUBLE, c_mktsegment STRING",
    "supplier": "s_suppkey BIGINT, s_name STRING, s_nationkey INT, s_acctbal DOUBLE",
    "part": "p_partkey BIGINT, p_name STRING, p_brand STRING, p_type STRING, p_size INT, p_retailprice DOUBLE",
    "nation": "n_nationkey INT, n_name STRING, n_regionkey INT",
    "region": "r_regionkey INT, r_name STRING",
    "events": "event_id BIGINT, ts TIMESTAMP, user_id BIGINT, event_type STRING, value DOUBLE, props STRING",
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "labels": "doc_id BIGINT, quality INT, toxic INT",
    "pages": "page_id BIGINT, url STRING, html STRING",
    "conversations": "conv_id BIGINT, turn BIGINT, role STRING, text STRING",
    "embeddings": "vec_id BIGINT, embedding ARRAY<FLOAT>, label INT",
}
class _Written(threading.local):
    """The tables a thread wrote: one that drops its own leaves those of others."""

    everyone: list[list[tuple[SparkSession, str]]] = []

    def __init__(self):
        self.tables: list[tuple[SparkSession, str]] = []
        self.everyone.append(self.tables)


_WRITTEN = _Written()
_SHIPPED: set[str] = set()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, so no shared code folder is assumed."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    top = os.path.dirname(os.path.abspath(__file__))
    out = os.path.join(tempfile.mkdtemp(prefix="waypath-"), "waypath_pkg.zip")
    with zipfile.ZipFile(out, "w") as z:
        for folder, _, names in os.walk(top):
            for n in sorted(names):
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.join("waypath", os.path.relpath(full, top)))
    spark.sparkContext.addPyFile(out)
    _SHIPPED.add(app)


@contextmanager
def small_batches(spark: SparkSession, rows: int):
    """Python gets at most so many rows at a time from what is run inside."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


@contextmanager
def unpacked_sizes(spark: SparkSession):
    """Plans made inside count a file as twenty times its size, as its rows need in memory: a relation of a few MB is then not broadcast."""
    key = "spark.sql.sources.fileCompressionFactor"
    before = spark.conf.get(key)
    spark.conf.set(key, "20.0")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir.

    Where the session names none, a temporary folder serves a local master (tests) and the
    warehouse, which all executors share, any other.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        one_machine = re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master)
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="waypath-") if one_machine else f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/waypath-shared")
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def written(df: DataFrame, what: str = "table") -> DataFrame:
    """df as a Parquet table in the shared folder: cuts lineage and outlives executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/waypath-{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    to_drop(spark, path)
    return spark.read.schema(df.schema).parquet(path)


def to_drop(spark: SparkSession, path: str) -> None:
    """Have a folder removed at exit."""
    _WRITTEN.tables.append((spark, path))


def _file_system(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def drop(spark: SparkSession, path: str) -> None:
    p, fs = _file_system(spark, path)
    fs.delete(p, True)


def alive(df: DataFrame) -> bool:
    """Whether the files that df reads are still there."""
    for f in df.inputFiles()[:1]:
        p, fs = _file_system(df.sparkSession, f)
        if not fs.exists(p):
            return False
    return True


def tidy(spark: SparkSession) -> None:
    """Have the JVM drop what nothing refers to any more: shuffle files of finished steps stay on disk until then."""
    spark.sparkContext._jvm.System.gc()


def mark() -> int:
    """A place in this thread's list of written tables; see ``drop_since``."""
    return len(_WRITTEN.tables)


def drop_since(place: int, but: list[DataFrame] = ()) -> None:
    """Remove the tables written since ``place`` that none of the given frames reads."""
    needed = "\n".join(f for df in but for f in df.inputFiles())
    rest = []
    for spark, path in _WRITTEN.tables[place:]:
        if path.rsplit("/", 1)[-1] in needed:
            rest.append((spark, path))
        else:
            drop(spark, path)
    _WRITTEN.tables[place:] = rest


@atexit.register
def _clean() -> None:
    for spark, path in [x for own in _WRITTEN.everyone for x in own]:
        try:
            drop(spark, path)
        except Exception:  # noqa: BLE001  the session may be gone
            continue
