"""Where results go: Parquet, bucketed tables, and flat text exports of paths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def export_paths(paths: DataFrame, folder: str, fmt: str = "json") -> None:
    """JSON lines keep arrays; CSV joins nodes with '>'."""
    if fmt == "csv":
        flat = paths.select(*[c for c in paths.columns if c not in ("nodes", "steps", "cliques")], F.array_join(F.col("nodes").cast("array<string>"), ">").alias("nodes"))
        flat.write.mode("overwrite").option("header", True).csv(folder)
    else:
        paths.write.mode("overwrite").format(fmt).save(folder)


def save_bucketed(rel: DataFrame, name: str, buckets: int = 64) -> None:
    """The relation as a table bucketed by feature, so pair joins on features need no exchange."""
    rel.write.mode("overwrite").bucketBy(buckets, "feat").sortBy("feat").format("parquet").saveAsTable(name)
