"""Mixing sources to target weights by systematic sampling, in DataFrame operators only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..tables import written

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS, TOTAL_SHARE, MOST_TIMES = (5, 2, 1), 1.5, 2
#: Rows a group of the numbering has about; more rows make more groups.
GROUP = 2048


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = TOTAL_SHARE, most: int = MOST_TIMES) -> DataFrame:
    """(source, source_size, docs, target) from (source, source_size, docs), one row per source.

    Sources in code-point order (null last) take the weights in turn.  Sorted by how soon a
    rising level would reach their cap, a prefix of sources is capped and the others share
    what is left by weight; the right prefix is found in one pass over running sums.
    The table has a row per source, so its windows stay small.
    """
    by_name = Window.orderBy(F.col("source").isNull().cast("int"), F.encode("source", "UTF-8"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.row_number().over(by_name) - 1) % len(weights) + 1)
    ranked = sizes.withColumn("__w", w).withColumn("__cap", F.col("source_size") * F.lit(float(most)))
    order = Window.orderBy(F.col("__cap") / F.col("__w"), F.col("source").isNull().cast("int"), F.encode("source", "UTF-8"))
    all_rows = Window.partitionBy()
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    ranked = (
        ranked.withColumn("__rank", F.row_number().over(order))
        .withColumn("__capped", F.coalesce(F.sum("__cap").over(before), F.lit(0.0)))
        .withColumn("__left", F.sum("__w").over(all_rows) - F.coalesce(F.sum("__w").over(before), F.lit(0.0)))
        .withColumn("__total", F.sum("source_size").over(all_rows) * F.lit(float(share)))
        .withColumn("__level", (F.col("__total") - F.col("__capped")) / F.col("__left"))
        .withColumn("__free", F.col("__level") * F.col("__w") <= F.col("__cap"))
        .withColumn("__first", F.min(F.when(F.col("__free"), F.col("__rank"))).over(all_rows))
        .withColumn("__final", F.max(F.when(F.col("__rank") == F.col("__first"), F.col("__level"))).over(all_rows))
    )
    target = F.when(F.col("__first").isNull() | (F.col("__rank") < F.col("__first")), F.col("__cap")).otherwise(F.col("__final") * F.col("__w"))
    return ranked.select("source", "source_size", "docs", target.alias("target"))


def offset_of(source: Column, seed: int) -> Column:
    """One offset in [0, 1) per source, from its name and the seed."""
    text = F.concat(F.lit(f"{seed}:"), F.coalesce(F.concat(F.lit("s"), source), F.lit("null")))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def id_hash(doc_id: Column) -> Column:
    """32 bits of a digest of the id, as a long; null ids share one."""
    return F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("long").cast("string"), F.lit("null")).cast("binary")), 1, 8), 16, 10).cast("long")


def sampled(docs: DataFrame, size: Column, seed: int = 7, weights: tuple[int, ...] = WEIGHTS, share: float = TOTAL_SHARE, most: int = MOST_TIMES) -> DataFrame:
    """docs with __size, __source_size, __target and __copies.

    Within a source every document expects target / source_size copies.  In an order by
    size class, then hash of the id, document number r gets a copy for each integer that
    r x copies + offset crosses on its way to (r + 1) x copies + offset; ordering by size
    class keeps the words taken close to the target.  The number r is a prefix sum over two
    levels of groups.  The groups of a size class are ranges of the hash, as many as keep
    each near ``GROUP`` rows, so no source is one task at any size and the order does not
    depend on how many there are.  Sizes are counted once and written; the columns that are
    added begin with two underscores, so no column of docs clashes.
    """
    cols = docs.columns
    placed = docs.withColumn("__size", size).withColumn("__src", F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("null")))
    placed = placed.withColumn("__class", F.floor(F.log2(F.col("__size") + 1.0) * 4).cast("int")).withColumn("__hash", id_hash(F.col("doc_id")))
    slim = written(placed.select("__src", "__class", "__hash", "__size"), "sizes")
    groups = max(1, -(-slim.count() // GROUP))
    group = ["__src", "__class", "__g"]
    g = F.floor(F.col("__hash") * F.lit(groups) / F.lit(1 << 32)).cast("int").alias("__g")
    small = slim.groupBy("__src", "__class", g).agg(F.count(F.lit(1)).alias("__n"), F.sum("__size").alias("__s"))
    mid = small.groupBy("__src", "__class").agg(F.sum("__n").alias("__n"), F.sum("__s").alias("__s"))
    top = mid.groupBy("__src").agg(F.sum("__n").alias("docs"), F.sum("__s").alias("source_size"))
    named = top.withColumn("source", F.expr("CASE WHEN __src = 'null' THEN NULL ELSE substr(__src, 2) END"))
    goal = targets(named.select("source", "source_size", "docs"), weights, share, most)
    goal = goal.select(F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("null")).alias("__src"), F.col("source_size").alias("__source_size"), F.col("target").alias("__target"), offset_of(F.col("source"), seed).alias("__u"))
    up = lambda part, by: Window.partitionBy(*part).orderBy(by).rowsBetween(Window.unboundedPreceding, -1)
    mid = mid.withColumn("__m", F.coalesce(F.sum("__n").over(up(["__src"], "__class")), F.lit(0))).select("__src", "__class", "__m").join(goal, "__src")
    small = small.withColumn("__l", F.coalesce(F.sum("__n").over(up(["__src", "__class"], "__g")), F.lit(0))).select(*group, "__l")
    starts = small.join(mid, ["__src", "__class"]).withColumn("__before", F.col("__l") + F.col("__m")).drop("__l", "__m")
    inside = Window.partitionBy(*group).orderBy("__hash", F.col("doc_id").asc_nulls_last(), "__size")
    numbered = placed.withColumn("__g", g).withColumn("__r", F.row_number().over(inside) - 1).join(starts, group)
    rate = F.when(F.col("__source_size") > 0, F.col("__target") / F.col("__source_size")).otherwise(F.lit(0.0))
    r = (F.col("__before") + F.col("__r")).cast("double")
    copies = F.floor((r + 1.0) * F.col("__rate") + F.col("__u")) - F.floor(r * F.col("__rate") + F.col("__u"))
    return numbered.withColumn("__rate", rate).withColumn("__copies", copies.cast("long")).select(*cols, "__size", "__source_size", "__target", "__copies")


def mix_report(docs: DataFrame, seed: int = 7) -> DataFrame:
    """doc_id, size, source_size, target, taken.

    Null texts have size 0; a null source is a source of its own and the last; repeated
    rows are counted and drawn each; sources of no words have target 0; other columns are
    ignored; an empty table gives no rows.
    """
    slim = written(docs.select("doc_id", "source", word_count(F.col("text")).alias("__words")), "words")
    out = sampled(slim, F.col("__words"), seed)
    return out.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("__size").alias("size"), F.col("__source_size").alias("source_size"), F.col("__target").alias("target"), (F.col("__copies") * F.col("__size")).alias("taken"))


def mix(docs: DataFrame, seed: int = 7) -> DataFrame:
    """The mixed documents themselves: each row as often as it is taken, columns unchanged.

    Null texts and texts without words count no words and are drawn at their source's rate
    like any row; a source without words gives none; repeated rows are drawn each; columns
    of any other name travel along; an empty table gives no rows.
    """
    cols = docs.columns
    out = sampled(docs, word_count(F.col("text")), seed).where("__copies > 0")
    return out.select(*cols, F.explode(F.sequence(F.lit(1), F.col("__copies").cast("int"))).alias("__copy")).drop("__copy")
