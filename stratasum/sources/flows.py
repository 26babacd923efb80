"""Inputs of the methods, built from the given tables: sets, pairs, arcs and points."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stratasum.operators.markov import repair, transition
from stratasum.plans.materialize import keep

from .catalog import table


def supplier_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item, cents: account balances of suppliers."""
    return table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("item"), F.round(F.col("s_acctbal") * 100).cast("bigint").alias("cents"))


def part_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item, cents: retail prices, where many parts share a price."""
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("item"), F.round(F.col("p_retailprice") * 100).cast("bigint").alias("cents"))


def order_pairs(spark: SparkSession, sf_dir: str, by: str = "o_orderpriority") -> DataFrame:
    """grp, item, cents: order totals in groups."""
    return table(spark, sf_dir, "orders").select(F.col(by).alias("grp"), F.col("o_orderkey").alias("item"), F.round(F.col("o_totalprice") * 100).cast("bigint").alias("cents"))


def nation_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, weight: quantity that flows from customers' nations to suppliers' nations."""
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey"))
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    suppliers = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    joined = items.join(orders, "l_orderkey").join(customers, "c_custkey").join(suppliers, "l_suppkey")
    return joined.groupBy(F.col("c_nationkey").alias("src"), F.col("s_nationkey").alias("dst")).agg(F.sum("l_quantity").alias("weight"))


def nation_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return transition(repair(nation_weights(spark, sf_dir)))


def event_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, share: which type of event a user has after which."""
    after = F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    pairs = table(spark, sf_dir, "events").select(F.col("event_type").alias("src"), after.alias("dst")).filter("dst is not null")
    return transition(repair(pairs.withColumn("weight", F.lit(1.0))))


def _succession(spark: SparkSession, sf_dir: str, column: str) -> DataFrame:
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return items.select(F.col(column).alias("src"), F.lead(column).over(w).alias("dst")).filter("dst is not null").withColumn("weight", F.lit(1.0))


def part_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _succession(spark, sf_dir, "l_partkey")


def part_flow(spark: SparkSession, sf_dir: str, repaired: bool = True) -> DataFrame:
    """src, dst, share: which part follows which in an order."""
    weights = part_weights(spark, sf_dir)
    return transition(repair(weights) if repaired else weights)


def supplier_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return transition(repair(_succession(spark, sf_dir, "l_suppkey")))


def host_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, weight: hosts and the paths that their pages link to."""
    pages = table(spark, sf_dir, "pages").select(F.expr("parse_url(url, 'HOST')").alias("src"), F.explode(F.expr("regexp_extract_all(html, 'href=\"/([^\"]+)\"', 1)")).alias("dst"))
    return pages.groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("weight"))


def part_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """point_id, v: parts in the plane, with whole-number coordinates, so that sums are exact."""
    x = (F.col("p_size") * 20).cast("double")
    y = F.round((F.col("p_retailprice") - 900) * 10).cast("double")
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("point_id"), F.array(x, y).alias("v"))


def tall(wide: DataFrame) -> DataFrame:
    return wide.select("point_id", F.posexplode("v").alias("dim", "val"))


def embedding_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("point_id"), F.col("embedding").cast("array<double>").alias("v"))


def order_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """point_id, v: sum of quantities, mean discount in percent, number of lines of each order."""
    per = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("q"), (F.avg("l_discount") * 100).alias("d"), F.count(F.lit(1)).cast("double").alias("n"))
    return per.select(F.col("l_orderkey").alias("point_id"), F.array("q", "d", "n").alias("v"))


def order_chains(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Arcs (src, dst) from each order to the next of its customer, and the nodes that begin a chain."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("src"), F.lead("o_orderkey").over(w).alias("dst"), F.row_number().over(w).alias("n"))
    placed = keep(orders)
    return placed.filter("dst is not null").select("src", "dst"), placed.filter("n = 1").select(F.col("src").alias("node"))


def event_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """point_id, v: value and hour of day of each event."""
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("point_id"), F.array("value", F.hour("ts").cast("double")).alias("v"))
