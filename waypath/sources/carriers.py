"""Association datasets over the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import drop_sequences, drop_stopwords, light_stem, stop_words, strip_html, tf, tokenize
from ..operators.dataset import AssocDataset
from ..tables import table


def _orders_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"])


def _terms(counts: DataFrame, name: str) -> AssocDataset:
    """Terms become 64-bit hashes: no dictionary has to be built or shared."""
    return AssocDataset(counts.select("obj", F.xxhash64("term").alias("feat"), "val"), name)


def parts_by_customers(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return AssocDataset.from_weights(_orders_lines(spark, sf_dir), "l_partkey", "o_custkey", "l_quantity", name="parts_by_customers", together=True)


def suppliers_by_customers(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return AssocDataset.from_weights(_orders_lines(spark, sf_dir), "l_suppkey", "o_custkey", "l_quantity", name="suppliers_by_customers")


def parts_by_suppliers(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return AssocDataset.from_weights(table(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey", "l_quantity", name="parts_by_suppliers", together=True)


def documents_by_terms(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return _terms(tf(table(spark, sf_dir, "documents"), "doc_id", tokenize(F.col("text"))), "documents_by_terms")


def cleaned(words) -> Column:
    """Terms without stop words and letter sequences, stemmed; numerals and signs are no terms to begin with."""
    return F.filter(F.transform(drop_sequences(drop_stopwords(words, stop_words())), light_stem), lambda t: F.length(t) >= 3)


def clean_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(obj, term, val) of the documents."""
    return tf(table(spark, sf_dir, "documents"), "doc_id", cleaned(tokenize(F.col("text"))))


def documents_by_stems(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return _terms(clean_terms(spark, sf_dir), "documents_by_stems")


def pages_by_stems(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return _terms(tf(table(spark, sf_dir, "pages"), "page_id", cleaned(tokenize(strip_html(F.col("html"))))), "pages_by_stems")


def pages_by_terms(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return _terms(tf(table(spark, sf_dir, "pages"), "page_id", tokenize(strip_html(F.col("html")))), "pages_by_terms")


def conversations_by_terms(spark: SparkSession, sf_dir: str) -> AssocDataset:
    return _terms(tf(table(spark, sf_dir, "conversations"), "conv_id", tokenize(F.col("text"))), "conversations_by_terms")


def embeddings_by_dims(spark: SparkSession, sf_dir: str) -> AssocDataset:
    """Each dimension is two features, one for either sign, so weights stay positive."""
    d = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("dim", "x")).where("x <> 0 AND NOT isnan(x)")
    d = d.select("vec_id", (2 * F.col("dim") + (F.col("x") < 0).cast("int")).alias("feat"), F.abs(F.col("x").cast("double")).alias("val"))
    return AssocDataset.from_weights(d, "vec_id", "feat", "val", name="embeddings_by_dims")


def users_by_events(spark: SparkSession, sf_dir: str) -> AssocDataset:
    """A feature is an event type with the number in its JSON properties."""
    e = event_features(table(spark, sf_dir, "events"))
    return AssocDataset(e.groupBy(F.col("user_id").alias("obj"), "feat").agg(F.count(F.lit(1)).cast("double").alias("val")), "users_by_events")


def event_features(events: DataFrame) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("long")
    return events.withColumn("k", k).where("user_id IS NOT NULL AND event_type IS NOT NULL AND k IS NOT NULL").withColumn("feat", F.xxhash64("event_type", "k"))


def sampled_parts(spark: SparkSession, sf_dir: str, n: int = 1000, seed: int = 42) -> AssocDataset:
    """The relation of n parts in the order of a seeded hash."""
    ds = parts_by_customers(spark, sf_dir)
    take = ds.rel.select("obj").distinct().orderBy(F.xxhash64(F.lit(seed), "obj"), "obj").limit(n)
    return AssocDataset(ds.rel.join(take, "obj", "left_semi").select("obj", "feat", "val"), "sampled_parts")


CARRIERS = {f.__name__: f for f in (parts_by_customers, suppliers_by_customers, parts_by_suppliers, documents_by_terms, documents_by_stems, pages_by_terms, pages_by_stems, conversations_by_terms, embeddings_by_dims, users_by_events, sampled_parts)}
