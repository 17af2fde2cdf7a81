"""Associations that grow: event streams, windows, late rows, running profiles, arrivals against saved profiles."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.columns import hammock_width
from ..sources.carriers import event_features
from ..tables import SCHEMAS


def event_stream(spark: SparkSession, folder: str, files_per_batch: int = 1, pattern: str | None = None) -> DataFrame:
    """Event files as they appear in a folder, those whose names match the pattern."""
    reader = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_batch)
    return (reader.option("pathGlobFilter", pattern) if pattern else reader).parquet(folder)


def windowed_rel(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(start, obj, feat, val) per window; repeated event ids count once, rows behind the watermark drop out."""
    e = event_features(events)
    if e.isStreaming:
        e = e.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    else:
        e = e.dropDuplicates(["event_id"])
    g = e.groupBy(F.window("ts", width).alias("w"), F.col("user_id").alias("obj"), "feat").agg(F.count(F.lit(1)).alias("val"))
    return g.select(F.col("w.start").alias("start"), "obj", "feat", "val")


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    g = events.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return g.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "1 day", step: str = "6 hours") -> DataFrame:
    g = events.groupBy(F.window("ts", width, step).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    g = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.col("w.start").alias("start"), "n")


def running_profiles(events: DataFrame) -> DataFrame:
    """(obj, n_feat, total) updated as rows arrive; the state of an object is its feature counts."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        have = dict(zip(*state.get)) if state.exists else {}
        for f in frames:
            for feat, n in f["feat"].value_counts().items():
                have[int(feat)] = have.get(int(feat), 0) + int(n)
        state.update((list(have), list(have.values())))
        yield pd.DataFrame({"obj": [key[0]], "n_feat": [len(have)], "total": [sum(have.values())]})

    e = event_features(events).select("user_id", "feat")
    return e.groupBy("user_id").applyInPandasWithState(update, "obj long, n_feat long, total long", "feats array<long>, counts array<long>", "update", GroupStateTimeout.NoTimeout)


def arrivals_near(arrivals: DataFrame, profiles: DataFrame, width: int) -> DataFrame:
    """(obj, nbr, common) of arriving feature sets arrivals(obj, feats) against saved profiles, met through a feature in common."""
    inv = profiles.select(F.col("obj").alias("nbr"), F.col("feats").alias("nf"), F.explode("feats").alias("feat"))
    j = arrivals.select("obj", "feats", F.explode("feats").alias("feat")).join(inv, "feat").where("obj <> nbr")
    return j.select("obj", "nbr", hammock_width("feats", "nf").alias("common")).where(F.col("common") >= width).dropDuplicates(["obj", "nbr"])


def on_touched(stream: DataFrame, rebuild: Callable[[DataFrame, int], None], checkpoint: str):
    """Starts a query that hands each batch's touched objects to ``rebuild``, which renews the lattice."""
    return stream.writeStream.foreachBatch(lambda df, i: rebuild(event_features(df).select(F.col("user_id").alias("obj")).distinct(), i)).option("checkpointLocation", checkpoint).start()
