"""Continuous and final aggregates of a set, with every way to know that the set has ended.

Continuous forms give a fact (counter, value) for each item. Final forms pick one of them:
`negation` takes the fact whose counter has no successor, `max_running` the one with the largest
counter, `precount` the one whose counter is a size known beforehand, and `complete` lets Spark's
blocking aggregate notice the end of its input, which is the form to use at scale.

Continuous forms in `prefix` mode never pass a whole set through one task: the items are
range-partitioned by their order, each part is accumulated alone, and the totals of the parts before
it (one row a part, broadcast) are added.

Null values are refused in strict mode; else they count as items and add nothing.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from stratasum.functions.aggspec import SPECS
from stratasum.plans.materialize import keep, observed

#: Parts of a prefix sum are no more than this, so the broadcast of their totals is bounded.
MOST_PARTS = 20_000


def as_set(df: DataFrame, items: list[str], value: str | None = None, distinct_values: bool = False, strict: bool = False) -> DataFrame:
    """The items as a set: of keyed bindings (all columns of `items` and the value), or of bare values."""
    columns = [value] if distinct_values else [*items, *([value] if value and value not in items else [])]
    out = df.select(*columns).dropDuplicates()
    if strict and value:
        out = out.withColumn(value, F.when(F.col(value).isNull(), F.raise_error(F.lit("null value in a strict set"))).otherwise(F.col(value)))
    return out


def running(df: DataFrame, kind: str, value: str | None, order_by: list[str], mode: str = "window", parts: int | None = None) -> DataFrame:
    """Columns of df with `counter` and `running`: the continuous aggregate in the given order.

    mode="window" is one ordered pass in a single task, for small sets; mode="prefix" is distributed.
    """
    spec, v = SPECS[kind], F.col(value) if value else F.lit(1)
    if mode == "window":
        w = Window.orderBy(*order_by)
        return df.withColumn("counter", F.row_number().over(w).cast("bigint")).withColumn("running", spec.running(v, w))
    parts = min(parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), MOST_PARTS)
    dealt = keep(df.repartitionByRange(parts, *order_by).withColumn("__part", F.spark_partition_id()))
    totals = dealt.groupBy("__part").agg(F.count(F.lit(1)).alias("__n"), spec.over(v).alias("__acc"))
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)  # a row a part: MOST_PARTS at most
    combine = {"max": F.max, "min": F.min}.get(kind, F.sum)
    offsets = totals.select("__part", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__n0"), combine("__acc").over(before).alias("__acc0"))
    inside = Window.partitionBy("__part").orderBy(*order_by)
    frame = inside.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    own = dealt.join(F.broadcast(offsets), "__part")
    acc = spec.over(v).over(frame)
    acc = F.when(F.col("__acc0").isNull(), acc).otherwise(spec.merge(F.col("__acc0"), acc))
    n = F.col("__n0") + F.row_number().over(inside)
    return own.withColumn("counter", n.cast("bigint")).withColumn("running", spec.finish(acc, n)).drop("__part", "__n0", "__acc0")


def facts(df: DataFrame, kind: str, value: str | None, order_by: list[str], mode: str = "window") -> DataFrame:
    """counter, running: the facts of the accumulating phase."""
    return running(df, kind, value, order_by, mode).select("counter", "running")


def final(df: DataFrame, kind: str, value: str | None, order_by: list[str], strategy: str = "complete", cardinality: int | DataFrame | None = None, mode: str = "window") -> DataFrame:
    """One row `value`: the final aggregate.

    precount: cardinality is a number, a one-row frame with column n, or None to count in a stratum
    below. A size that is too small raises, as a successor exists; one that is too large gives no row.
    """
    v = F.col(value) if value else F.lit(1)
    if strategy == "complete":
        return df.agg(SPECS[kind].total(v).alias("value"))
    own = facts(df, kind, value, order_by, mode)
    if strategy == "max_running":
        return own.agg(F.max_by("running", "counter").alias("value"))
    if strategy == "negation":
        after = own.select((F.col("counter") - 1).alias("counter"))
        return own.join(after, "counter", "left_anti").select(F.col("running").alias("value"))
    if strategy != "precount":
        raise ValueError(f"no such strategy: {strategy}")
    if cardinality is None:
        cardinality = df.agg(F.count(F.lit(1)).alias("n"))
    if isinstance(cardinality, int):
        n = cardinality
        late = own.agg(F.max("counter").alias("last"), F.max(F.when(F.col("counter") == n, F.struct("running"))).alias("hit"))
        checked = F.when(F.col("last") > n, F.raise_error(F.lit(f"the set has more than {n} items"))).otherwise(F.col("hit.running"))
        return late.filter(F.col("hit").isNotNull()).select(checked.alias("value"))
    return own.join(F.broadcast(cardinality.select(F.col("n").alias("counter"))), "counter").select(F.col("running").alias("value"))


def final_counted(df: DataFrame, kind: str, value: str | None) -> tuple[object, int]:
    """The final aggregate by completion, and the number of items, which the same job counts on the way."""
    seen = Observation()
    watched = df.observe(seen, F.count(F.lit(1)).alias("n"))
    out = watched.agg(SPECS[kind].total(F.col(value) if value else F.lit(1)).alias("value")).first()["value"]
    return out, int(observed(seen).get("n", 0))


def permutation_facts(df: DataFrame, item: str, max_n: int = 7) -> DataFrame:
    """counter, visited: the count by its definition, which visits the items in all orders.

    Its size is the sum of n!/(n-k)!, so more than max_n items are refused.
    """
    items = df.select(F.col(item).alias("item")).dropDuplicates()
    n = items.limit(max_n + 1).count()
    if n > max_n:
        raise ValueError(f"more than {max_n} items")
    levels = [items.select(F.lit(1).cast("bigint").alias("counter"), F.array("item").alias("visited"))]
    for _ in range(1, n):
        last = levels[-1]
        step = last.join(items, ~F.array_contains("visited", F.col("item")))
        levels.append(step.select((F.col("counter") + 1).alias("counter"), F.concat("visited", F.array("item")).alias("visited")))
    return reduce(DataFrame.unionByName, levels)


def grouped_running(df: DataFrame, by: list[str], value: str, item: list[str], kind: str = "sum", counter: str = "group", mode: str = "window") -> DataFrame:
    """Continuous aggregate of groups.

    counter="group": one fact an item, counted in its group. counter="global": every group has a fact
    for each counter from 0 on, as each item moves the counter of all groups but the value of its own
    only; that is groups x (items + 1) facts. mode="prefix" makes them by prefix sums of range-partitioned
    parts, so neither the items nor a group pass through one task; a row for each part and group is broadcast.
    """
    spec = SPECS[kind]
    if counter == "group":
        w = Window.partitionBy(*by).orderBy(*item)
        return df.select(*by, F.row_number().over(w).cast("bigint").alias("counter"), spec.running(F.col(value), w).alias("running"))
    if kind != "sum":
        raise ValueError("the global counter starts every group at zero: sums only")
    if mode == "prefix":
        return _global_prefix(df, by, value, item)
    order = Window.orderBy(*item)
    steps = df.select(F.row_number().over(order).cast("bigint").alias("counter"), *[F.col(b).alias(f"__{b}") for b in by], F.col(value).alias("__v"))
    groups = df.select(*by).dropDuplicates()
    start = groups.select(*by, F.lit(0).cast("bigint").alias("counter"), F.lit(0).cast("bigint").alias("__own"))
    mine = reduce(lambda a, b: a & b, [F.col(b).eqNullSafe(F.col(f"__{b}")) for b in by])
    rows = groups.hint("broadcast").join(steps, F.lit(True)).select(*by, "counter", F.when(mine, F.col("__v")).otherwise(F.lit(0)).alias("__own"))
    w = Window.partitionBy(*by).orderBy("counter").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return start.unionByName(rows).select(*by, "counter", F.sum("__own").over(w).alias("running"))


def _global_prefix(df: DataFrame, by: list[str], value: str, item: list[str]) -> DataFrame:
    """by, counter, running for every group and counter from 0 on."""
    parts = min(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), MOST_PARTS)
    own = [f"__{b}" for b in by]
    items = df.select(*item, *[F.col(b).alias(o) for b, o in zip(by, own, strict=True)], F.col(value).alias("__v"))
    dealt = keep(items.repartitionByRange(parts, *item).withColumn("__part", F.spark_partition_id()))
    inside = Window.partitionBy("__part").orderBy(*item)
    sizes = dealt.groupBy("__part").agg(F.count(F.lit(1)).alias("__n"))
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)  # a row a part: MOST_PARTS at most
    sizes = sizes.select("__part", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__n0"))
    groups = df.select(*by).dropDuplicates()
    mine = reduce(lambda a, b: a & b, [F.col(b).eqNullSafe(F.col(o)) for b, o in zip(by, own, strict=True)])
    sums = dealt.groupBy("__part", *own).agg(F.sum("__v").alias("__sum")).withColumnRenamed("__part", "__of")
    every = groups.hint("broadcast").join(sizes, F.lit(True))
    at = every.join(F.broadcast(sums), mine & (F.col("__of") == F.col("__part")), "left")
    offsets = at.select(*by, "__part", "__n0", F.coalesce("__sum", F.lit(0)).alias("__sum"))
    earlier = Window.partitionBy(*by).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = offsets.select(*by, "__part", "__n0", F.coalesce(F.sum("__sum").over(earlier), F.lit(0)).alias("__acc0"))
    numbered = dealt.withColumn("__k", F.row_number().over(inside).cast("bigint"))
    facts = numbered.join(F.broadcast(offsets), "__part").withColumn("__own", F.when(mine, F.col("__v")).otherwise(F.lit(0)))
    run = Window.partitionBy("__part", *by).orderBy("__k").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = facts.select(*by, (F.col("__n0") + F.col("__k")).alias("counter"), (F.col("__acc0") + F.coalesce(F.sum("__own").over(run), F.lit(0))).alias("running"))
    zero = F.lit(0).cast("bigint")
    return groups.select(*by, zero.alias("counter"), zero.alias("running")).unionByName(rows)


def grouped_final(df: DataFrame, by: list[str], value: str, item: list[str], kind: str = "sum", strategy: str = "complete", count_scope: str = "group", mode: str = "window") -> DataFrame:
    """by, value: the final aggregate of each group, by any strategy."""
    if strategy == "complete":
        return df.groupBy(*by).agg(SPECS[kind].total(F.col(value)).alias("value"))
    own = grouped_running(df, by, value, item, kind, "global" if count_scope == "global" else "group", mode)
    if strategy == "max_running":
        return own.groupBy(*by).agg(F.max_by("running", "counter").alias("value"))
    if strategy == "negation":
        after = own.select(*by, (F.col("counter") - 1).alias("counter"))
        return own.join(after, [*by, "counter"], "left_anti").select(*by, F.col("running").alias("value"))
    if strategy != "precount":
        raise ValueError(f"no such strategy: {strategy}")
    if count_scope == "global":
        size = df.agg(F.count(F.lit(1)).alias("counter"))
        return own.join(F.broadcast(size), "counter").select(*by, F.col("running").alias("value"))
    size = df.groupBy(*by).agg(F.count(F.lit(1)).alias("counter"))
    return own.join(size, [*by, "counter"]).select(*by, F.col("running").alias("value"))


def compare_strategies(df: DataFrame, by: list[str], value: str, item: list[str], kind: str = "sum") -> DataFrame:
    """by, strategy, value for all strategies; they agree if each group has one distinct value."""
    found = [grouped_final(df, by, value, item, kind, s).select(*by, F.lit(s).alias("strategy"), "value") for s in ("complete", "negation", "max_running", "precount")]
    return reduce(DataFrame.unionByName, found)


def money(column: str) -> Column:
    """An amount as whole cents, exact in sums."""
    return F.round(F.col(column) * 100).cast("bigint")
