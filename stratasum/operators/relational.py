"""Joins and selections that Spark has no operator for, as compositions of those it has."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: list[str], on: str, take: list[str], tolerance_s: float | None = None) -> DataFrame:
    """left with, for each row, the columns `take` of the latest right row of its key at or before `on`.

    One shuffle of both sides together and one ordered pass, instead of a join of all pairs. A right
    row at the same time counts as before; of right rows at one time the one with the largest `take`.
    """
    columns = left.columns
    a = left.select(*[F.col(c) for c in columns], F.lit(1).alias("__side"), F.lit(None).cast(right.select(F.struct(on, *take)).schema[0].dataType).alias("__hit"))
    keys = [*by, on]
    b = right.select(*[F.col(c) if c in keys else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in columns], F.lit(0).alias("__side"), F.struct(on, *take).alias("__hit"))
    w = Window.partitionBy(*by).orderBy(on, "__side", F.col("__hit").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = a.unionByName(b).withColumn("__hit", F.last("__hit", ignorenulls=True).over(w)).filter("__side = 1")
    hit: Column = F.col("__hit")
    if tolerance_s is not None:
        hit = F.when(F.col(on).cast("timestamp").cast("double") - F.col("__hit")[on].cast("timestamp").cast("double") <= tolerance_s, F.col("__hit"))
    return out.withColumn("__hit", hit).select(*columns, *[F.col("__hit")[c].alias(c) for c in take])


def interval_join(left: DataFrame, right: DataFrame, by: list[str], left_on: str, right_on: str, low_s: int, high_s: int) -> DataFrame:
    """Pairs of a key with right_on - left_on from low_s to high_s seconds.

    Times are cut into buckets as long as the interval, so a pair meets in one of two buckets and
    hot keys are spread over theirs.
    """
    width = max(1, high_s - low_s)

    def seconds(c: str) -> Column:
        return F.col(c).cast("timestamp").cast("double")

    a = left.withColumn("__b", F.floor((seconds(left_on) + low_s) / width)).withColumn("__b", F.explode(F.array("__b", F.col("__b") + 1)))
    b = right.withColumn("__b", F.floor(seconds(right_on) / width))
    gap = seconds(right_on) - seconds(left_on)
    return a.join(b, [*by, "__b"]).filter((gap >= low_s) & (gap <= high_s)).drop("__b")


def range_join(left: DataFrame, right: DataFrame, value: str, lo: str, hi: str, bucket: float) -> DataFrame:
    """Pairs where lo <= value < hi: a right row is listed in each bucket that its range touches."""
    a = left.withColumn("__b", F.floor(F.col(value) / bucket))
    b = right.filter(F.col(lo) < F.col(hi)).withColumn("__b", F.explode(F.sequence(F.floor(F.col(lo) / bucket), F.floor(F.col(hi) / bucket))))
    return a.join(b, "__b").filter((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("__b")


def topk(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; Spark cuts groups before the shuffle."""
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("__r", F.row_number().over(w)).filter(F.col("__r") <= k).drop("__r")


def hash_sample(df: DataFrame, keys: list[str], share: float, seed: int = 0) -> DataFrame:
    """About that share of the rows, chosen by a hash of their keys: the same rows in every run."""
    return df.filter(F.pmod(F.xxhash64(*keys, F.lit(seed)), F.lit(1 << 30)) < F.lit(int(share * (1 << 30))))
