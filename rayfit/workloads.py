"""The experiment workloads over the given tables."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import features as X
from .instances import Instances
from .losses import LeastSquares, Logistic, Loss


@dataclass
class Workload:
    data: Instances
    loss: Loss
    lam: float
    theta: float
    degree: int = 5


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def w1(spark, sf_dir, label="lt5", lam=1e-8) -> Workload:
    """Dense, balanced, few parameters."""
    y = F.col("label") < 5 if label == "lt5" else F.col("label") % 2 == 1
    return Workload(Instances(X.dense(table(spark, sf_dir, "embeddings"), "embedding", y), 65, kind="dense", name="w1"), Logistic(), lam, 1e-6)


def w2(spark, sf_dir, m=1024) -> Workload:
    """Sparse text, fewer parameters than rows."""
    df = X.hashed(table(spark, sf_dir, "documents"), "doc_id", X.tokens(F.col("text")), m, F.col("lang") == "en", stable=True)
    return Workload(Instances(df, m + 1, kind="sparse", name="w2"), Logistic(), 1e-7, 1e-4)


def slots(spark, sf_dir, name: str, m: int, stable=False) -> DataFrame:
    """Words of w3 and w4 as sorted buckets, before they are counted; see features.slots."""
    if name == "w3":
        words = F.concat(F.transform(X.tokens(F.regexp_extract("url", r"://(.*)", 1)), lambda t: F.concat(F.lit("u:"), t)), X.tokens(F.regexp_replace("html", r"<[^>]*>", " ")))
        return X.slots(table(spark, sf_dir, "pages"), "page_id", words, m, F.col("url").startswith("http://"), stable)
    docs = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id").repartition("doc_id").withColumn("w", X.tokens(F.col("text")))
    pairs = F.when(F.size("w") > 1, X.bigrams(F.col("w"))).otherwise(F.array().cast("array<string>"))
    words = F.concat("w", pairs, F.array(F.concat(F.lit("source:"), "source"), F.concat(F.lit("lang:"), "lang")))
    return X.slots(docs, "doc_id", words, m, F.col("quality") == 1, stable, dealt=True)


def w3(spark, sf_dir, m=1 << 20, stable=False, held=None) -> Workload:
    """Sparse, more parameters than rows: tokens of url without its scheme, and of the page. held: its slots, if there are some."""
    df = X.weighed(held or slots(spark, sf_dir, "w3", m, stable), m)
    return Workload(Instances(df, m + 1, kind="sparse", name="w3"), Logistic(), 1e-8, 1e-4)


def w4(spark, sf_dir, m=1 << 20, stable=False, held=None) -> Workload:
    """Sparse and ill-posed: words, pairs of words, source and language of the labelled documents."""
    df = X.weighed(held or slots(spark, sf_dir, "w4", m, stable), m)
    return Workload(Instances(df, m + 1, kind="sparse", name="w4"), Logistic(), 1e-9, 1e-6)


def w5(spark, sf_dir, m=1 << 20, stable=False) -> Workload:
    """The largest number of rows: one-hot keys and attributes of order lines, without quantity and price.

    Order lines meet the other tables in hash joins, whose other side has its key once, so that they are not sorted; the narrowest rows
    travel first, and customers go to orders. The joins also deal out a file of one row group, which one task reads."""
    t = lambda name: table(spark, sf_dir, name)
    df = t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity", "l_returnflag", "l_linestatus", "l_shipdate")
    orders = t("orders").select("o_orderkey", "o_custkey", "o_orderpriority").join(t("customer").select("c_custkey", "c_nationkey", "c_mktsegment").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey"))
    df = df.join(t("supplier").select("s_suppkey", "s_nationkey").hint("shuffle_hash"), F.col("l_suppkey") == F.col("s_suppkey"))
    df = df.join(orders.hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey"))
    df = df.join(t("part").select("p_partkey", "p_brand", "p_type").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey"))
    month = F.month("l_shipdate")
    parts = [("part", ["l_partkey"]), ("supp", ["l_suppkey"]), ("cust", ["o_custkey"]), ("brand", ["p_brand"]), ("type", ["p_type"]), ("flag", ["l_returnflag"]), ("status", ["l_linestatus"]), ("month", [month]), ("nation", ["c_nationkey"]), ("home", ["s_nationkey"]), ("priority", ["o_orderpriority"]), ("segment", ["c_mktsegment"]), ("brand-month", ["p_brand", month]), ("nations", ["c_nationkey", "s_nationkey"]), ("part-supp", ["l_partkey", "l_suppkey"])]
    return Workload(Instances(X.one_hot(df, parts, m, F.col("l_quantity") > 7, stable=stable), m + 1, kind="sparse", name="w5", ones=True), Logistic(), 1e-9, 1e-4)


def w6(spark, sf_dir) -> Workload:
    """Least squares of the price."""
    df = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part").select("p_partkey", "p_size", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey"))
    df = df.select(((F.col("l_quantity") - 25.5) / 14.43).alias("x1"), ((F.col("l_discount") - 0.05) / 0.0316 + 0.0).alias("x2"), ((F.col("l_tax") - 0.04) / 0.0258).alias("x3"), ((F.col("p_size") - 25.5) / 14.4).alias("x4"), ((F.col("p_retailprice") - 1400) / 300).alias("x5"), F.lit(1.0).alias("x6"), (F.col("l_extendedprice") / 1e5).alias("y"))
    return Workload(Instances(df, 6, [f"x{i}" for i in range(1, 7)], name="w6"), LeastSquares(), 1e-6, 1e-4, 2)


def w7a(spark, sf_dir) -> DataFrame:
    """Ratings (i, j, value) of users and event keys."""
    df = table(spark, sf_dir, "events").select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("j"), (F.col("value") / 100).alias("v"))
    return df.groupBy("i", "j").agg(F.avg("v").alias("value"))


def w7b(spark, sf_dir) -> DataFrame:
    """Ratings (i, j, value) of customers and parts."""
    df = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return df.groupBy(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j")).agg((F.sum("l_quantity") / 50).alias("value"))


def planted(spark, sf_dir) -> DataFrame:
    """Order lines with scaled columns and labels drawn from a known logistic model; see FIXTURES.md."""
    t = table(spark, sf_dir, "lineitem")
    word = F.concat_ws("|", *(F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")))
    u = (F.conv(F.substring(F.md5(word.cast("binary")), 1, 8), 16, 10).cast("double") + 0.5) / 4294967296.0
    t = t.select(((F.col("l_quantity") - 25.5) / 14.43).alias("x1"), ((F.col("l_extendedprice") - 52500) / 30000).alias("x2"), ((F.col("l_discount") - 0.05) / 0.0316).alias("x3"), ((F.col("l_tax") - 0.04) / 0.0258).alias("x4"), F.lit(1.0).alias("x5"), u.alias("u"), "l_orderkey")
    h = F.col("x1") - 0.8 * F.col("x2") + 0.5 * F.col("x3") + 0.3 * F.col("x4") + 0.2 + F.log(F.col("u") / (1 - F.col("u")))
    return t.select("x1", "x2", "x3", "x4", "x5", F.when(h > 0, 1.0).otherwise(0.0).alias("y"), "l_orderkey")


def w9(spark, sf_dir) -> Workload:
    return Workload(Instances(planted(spark, sf_dir), 5, [f"x{i}" for i in range(1, 6)], name="w9"), Logistic(), 1e-3, 1e-6)


def example(spark, sf_dir, alpha=1.0, orders=range(8)) -> DataFrame:
    """The worked function of one number, its rising part weighed by the mean quantity of the order lines and its falling part by
    their mean price, both about 1: its derivatives at alpha, one row for each order, from one pass."""
    rise, fall = F.avg("l_quantity") / 25.5, F.avg("l_extendedprice") / 52500
    terms = [F.struct(F.lit(k).alias("k"), (rise * ((alpha + k) * math.exp(alpha)) + fall * ((-1) ** k * math.exp(4 - alpha))).alias("d")) for k in orders]
    return table(spark, sf_dir, "lineitem").agg(F.array(*terms).alias("x")).select(F.inline("x"))


def w15(events: DataFrame) -> Workload:
    """Purchases among events, for batches of a stream: hour, key, size of the value."""
    k = F.get_json_object("props", "$.k").cast("int")
    df = events.select("event_id", F.to_date("ts").alias("day"), F.array(F.hour("ts"), F.lit(24) + k, F.lit(124), F.lit(125)).alias("idx"), F.array(F.lit(1.0), F.lit(1.0), F.log1p("value"), F.lit(1.0)).alias("val"), (F.col("event_type") == "purchase").cast("double").alias("y"))
    return Workload(Instances(df, 126, kind="sparse", name="w15"), Logistic(), 1e-4, 1e-4)
