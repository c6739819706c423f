"""Workloads: set collections built from the given tables, each as long rows ``(sid BIGINT, tok STRING)``.

Rows are distinct and without nulls; a set without tokens has no rows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from setsim.functions.tokens import distinct_qgrams, json_entries, positive_dimensions, qgrams, shingles, words


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def long_sets(df: DataFrame, sid: str | Column, token: str | Column) -> DataFrame:
    """Distinct ``(sid, tok)`` of one token per row."""
    s, t = (F.col(c) if isinstance(c, str) else c for c in (sid, token))
    slim = df.select(s.cast("long").alias("sid"), t.alias("tok"))
    if not isinstance(slim.schema["tok"].dataType, IntegralType):  # numbers are as distinct as their texts, and shorter
        slim = slim.withColumn("tok", F.col("tok").cast("string"))
    return slim.filter("sid IS NOT NULL AND tok IS NOT NULL").distinct().withColumn("tok", F.col("tok").cast("string"))


def from_arrays(df: DataFrame, sid: str, tokens: Column) -> DataFrame:
    """Distinct ``(sid, tok)`` of an array of tokens per row; where no id has two rows they are so without a shuffle, else only the rows are shuffled."""
    id_ = F.col(sid).cast("long")
    if not df.isStreaming and df.filter(id_.isNotNull()).groupBy(id_.alias("sid")).count().filter("count > 1").isEmpty():
        return df.select(id_.alias("sid"), F.explode(F.array_distinct(tokens.cast("array<string>"))).alias("tok")).filter("sid IS NOT NULL AND tok IS NOT NULL")
    if not df.isStreaming:  # rows of an id meet before their tokens are made
        df = df.filter(id_.isNotNull()).repartition(id_)
    return long_sets(df.select(id_.alias("sid"), F.explode(F.array_distinct(tokens)).alias("tok")), "sid", "tok")


def order_parts(spark, d):
    """Parts of an order."""
    return long_sets(table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def part_name_q2(spark, d):
    """Character pairs of a part's name."""
    return from_arrays(table(spark, d, "part"), "p_partkey", qgrams("p_name", 2))


def cust_brands(spark, d):
    """Brands that a customer bought."""
    bought = table(spark, d, "orders").select("o_orderkey", "o_custkey").join(table(spark, d, "lineitem").select("l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    return long_sets(bought.join(table(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")), "o_custkey", "p_brand")


def user_evt_dow(spark, d):
    """Event types of a user by day of week (0 is Sunday)."""
    return long_sets(table(spark, d, "events"), "user_id", F.concat("event_type", F.lit("@"), (F.dayofweek("ts") - 1).cast("string")))


def doc_words(spark, d):
    """Lower-cased words of a document."""
    return from_arrays(table(spark, d, "documents"), "doc_id", words("text"))


def doc_q3(spark, d):
    """Character triples of a document."""
    return from_arrays(table(spark, d, "documents"), "doc_id", distinct_qgrams("text", 3))


def page_words(spark, d):
    """Letter and digit runs of a page's markup."""
    return from_arrays(table(spark, d, "pages"), "page_id", words("html", "[a-z0-9]+"))


def emb_pos(spark, d):
    """Dimensions in which an embedding is positive."""
    return from_arrays(table(spark, d, "embeddings"), "vec_id", positive_dimensions("embedding"))


def doc_shingles(spark, d):
    """Runs of three words of a document."""
    return from_arrays(table(spark, d, "documents"), "doc_id", shingles(words("text"), 3))


def bench_shingles(spark, d):
    """Runs of three words of a benchmark item."""
    return from_arrays(table(spark, d, "benchmark"), "item_id", shingles(words("text"), 3))


def cust_parts(spark, d):
    """Parts that a customer bought (no similar pairs)."""
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    return long_sets(o.join(table(spark, d, "lineitem").select("l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey")), "o_custkey", "l_partkey")


def supp_parts(spark, d):
    """Parts that a supplier delivers (no similar pairs)."""
    return long_sets(table(spark, d, "lineitem"), "l_suppkey", "l_partkey")


def conv_words(spark, d):
    """Words of a conversation (no similar pairs)."""
    return from_arrays(table(spark, d, "conversations"), "conv_id", words("text"))


def turn_words(spark, d):
    """Words of one turn (no similar pairs)."""
    return from_arrays(table(spark, d, "conversations").withColumn("tid", F.col("conv_id") * 1000 + F.col("turn")), "tid", words("text"))


def user_evt_hour(spark, d):
    """Event types of a user by day and hour (no similar pairs)."""
    return long_sets(table(spark, d, "events"), "user_id", F.concat("event_type", F.lit("@"), F.date_format("ts", "yyyy-MM-dd HH")))


def event_props(spark, d):
    """Property entries of a user's events."""
    return from_arrays(table(spark, d, "events"), "user_id", json_entries("props"))


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (order_parts, part_name_q2, cust_brands, user_evt_dow, doc_words, doc_q3, page_words, emb_pos, doc_shingles, bench_shingles, cust_parts, supp_parts, conv_words, turn_words, user_evt_hour, event_props)
}


def synth(spark: SparkSession, kind: str = "uniform", n: int = 100_000, seed: int = 1) -> DataFrame:
    """Generated collections: ``uniform`` (about 10 of 220 tokens), ``zipf`` (about 50 of 101,584 tokens, skewed)."""
    mean, universe = (10, 220) if kind == "uniform" else (50, 101_584)
    u = lambda *parts: (F.pmod(F.xxhash64(*parts, F.lit(seed)), F.lit(1 << 40)) + 0.5) / float(1 << 40)
    # a sum of coin flips with the Poisson's mean and nearly its variance
    size = F.greatest(F.lit(1), F.aggregate(F.sequence(F.lit(1), F.lit(20 * mean)), F.lit(0), lambda acc, i: acc + (u(F.col("id"), i, F.lit("size")) < 0.05).cast("int")))
    rows = spark.range(n).select(F.col("id").alias("sid"), F.explode(F.sequence(F.lit(1), size)).alias("i"))
    x = u(F.col("sid"), F.col("i"), F.lit("token"))
    token = F.floor(x * universe) if kind == "uniform" else F.floor(F.pow(F.lit(float(universe)), x)) - 1
    return long_sets(rows, "sid", token.cast("long"))


def drawn(spark: SparkSession, d: str, kind: str = "uniform") -> DataFrame:
    """The same kinds of collections drawn from the events: neighbouring events form a set, and the hash of an event's id is its draw."""
    mean, universe = (10, 220) if kind == "uniform" else (50, 101_584)
    x = F.expr("CAST(conv(substring(md5(CAST(event_id AS STRING)), 1, 8), 16, 10) AS BIGINT)") / float(1 << 32)
    token = F.floor(x * universe) if kind == "uniform" else F.floor(F.pow(F.lit(float(universe)), x)) - 1
    return long_sets(table(spark, d, "events"), F.floor(F.col("event_id") / mean), token.cast("long"))
