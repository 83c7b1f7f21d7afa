"""The experiments' streams on the given tables: (stream, x, w[, order columns])."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import element_key, uniform
from .tables import table
from .weights import law, tfidf

#: an arrival order of lineitem; rows that tie in it are one element
ARRIVAL = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as they are sold, weighed by their price: one stream, with ``ARRIVAL``."""
    return table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_partkey").cast("string").alias("x"), F.col("p_retailprice").alias("w"), *ARRIVAL)


def edges(spark: SparkSession, sf_dir: str, kind: str = "portable") -> DataFrame:
    """Who bought from whom, weighed by a number drawn for the pair: a follow graph's stand-in."""
    pair = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    x = element_key("o_custkey", "l_suppkey")
    return pair.select(x.alias("x"), uniform(x, F.lit(0), 17, kind).alias("w"), *ARRIVAL)


def ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers' largest quantity of each part: many streams, ``stream`` customer, whose rows are in one task each."""
    sold = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    dealt = sold.select(F.col("o_custkey").alias("stream"), F.col("l_partkey").cast("string").alias("x"), "l_quantity").repartition("stream")
    return dealt.groupBy("stream", "x").agg(F.max("l_quantity").alias("w"))


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("string").alias("x"), F.col("o_totalprice").alias("w"))


def documents(spark: SparkSession, sf_dir: str, english: bool | None = None) -> DataFrame:
    """Words of documents by tf-idf: in English, in other languages, or all; ``stream`` document."""
    d = table(spark, sf_dir, "documents")
    if english is not None:
        d = d.where((F.col("lang") == "en") == english)
    return tfidf(d, "doc_id", "text").withColumnRenamed("doc_id", "stream")


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.concat_ws(" ", F.array_sort(F.collect_list("text"))).alias("text"))
    return tfidf(said, "conv_id", "text").withColumnRenamed("conv_id", "stream")


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tfidf(table(spark, sf_dir, "pages").select("page_id", F.regexp_replace("html", "<[^>]*>", " ").alias("text")), "page_id", "text").withColumnRenamed("page_id", "stream")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positive entries of the embeddings, ``stream`` vector."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("stream"), F.posexplode("embedding").alias("i", "v"))
    return e.where("v > 0").select("stream", F.col("i").cast("string").alias("x"), F.col("v").cast("double").alias("w"))


def synthetic(spark: SparkSession, sf_dir: str, kind: str = "uniform", scale: float = 1.0, size: int | None = None) -> DataFrame:
    """Events as elements with weights of a law; ``size``: only the first events, as the size sweep has it."""
    e = table(spark, sf_dir, "events")
    if size is not None:
        e = e.where(F.col("event_id") < size)
    x = F.col("event_id").cast("string")
    return e.select(x.alias("x"), law(kind, x, scale).alias("w"), "ts", "event_id")


def generated(spark: SparkSession, n: int, kind: str = "uniform", scale: float = 1.0, hash: str = "fast", partitions: int | None = None) -> DataFrame:
    """A synthetic stream of any size."""
    x = F.col("id").cast("string")
    return spark.range(0, n, 1, partitions).select(x.alias("x"), law(kind, x, scale, hash=hash).alias("w"), F.col("id").alias("event_id"))


def texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole texts with their lengths: the size of a DISTINCT result."""
    return table(spark, sf_dir, "documents").select(F.col("text").alias("x"), F.col("n_chars").cast("double").alias("w"))


def votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers vote for order priorities with their balance, if positive; ``stream`` priority."""
    cast = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return cast.where("c_acctbal > 0").select(F.col("o_orderpriority").alias("stream"), F.col("o_custkey").cast("string").alias("x"), F.col("c_acctbal").alias("w"))


def daily_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users seen on each day, weighed by their balance, if positive; ``stream`` day."""
    seen = table(spark, sf_dir, "events").join(table(spark, sf_dir, "customer"), F.col("user_id") == F.col("c_custkey"))
    return seen.where("c_acctbal > 0").select(F.date_format("ts", "yyyy-MM-dd").alias("stream"), F.col("user_id").cast("string").alias("x"), F.col("c_acctbal").alias("w"), "ts", "event_id")


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of nations that trade, each of weight 1."""
    o, l, c, s = (table(spark, sf_dir, n) for n in ("orders", "lineitem", "customer", "supplier"))
    trade = o.join(l, F.col("o_orderkey") == F.col("l_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return trade.select(element_key("c_nationkey", "s_nationkey").alias("x"), F.lit(1.0).alias("w"))


def monitoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by type, weighed by their value, in order of arrival."""
    return table(spark, sf_dir, "events").select(F.col("event_type").alias("stream"), F.col("event_id").cast("string").alias("x"), F.col("value").alias("w"), "ts", "event_id")
