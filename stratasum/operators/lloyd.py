"""Lloyd's clustering with aggregates in the recursion.

Points are tall, (point_id, dim, val), or wide, (point_id, v array). Three strategies give the same
centres. `tall` is relational and runs as a staged fixpoint: distances are sums over dimensions, the
nearest centre is a packed minimum, new centres are means, and no step passes through the driver. `array`
and `arrow` keep a point's coordinates in a row, send the centres (k x D numbers, of checked size) to
the points, and shuffle only partial sums of each task.

A centre that no point is nearest to is dropped, kept where it was (so the number of products stays
constant), or put on the point farthest from its centre. Ties go to the smallest centre id.

Defined results, alike in all strategies: a point without coordinates (a null vector, or no rows) is no
point; a null coordinate, a vector of another length than the centres', and a tall point that lacks a
dimension of the centres (with certify="verify" or "goal") raise; dims of tall points may be any numbers;
wide rows that repeat a point_id are points of their own, while a repeated (point_id, dim) of tall points
breaks its certificate; without points all centres are empty; NaN coordinates make NaN distances, which
sort last.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stratasum.functions.aggspec import pack_pair, unpack_pair
from stratasum.operators.markov import sums_at_count
from stratasum.plans.fixpoint import Certificate, FixpointResult, StagedFixpoint, StopRule, TraceRow, Watch, converged, max_steps
from stratasum.plans.materialize import keep

#: Numbers of a centre table that may be sent to every task.
CENTRE_NUMBERS = 10_000_000


def to_tall(df: DataFrame, id_column: str, columns: list[str]) -> DataFrame:
    """point_id, dim, val from numeric columns."""
    pairs = F.array(*[F.struct(F.lit(i).alias("dim"), F.col(c).cast("double").alias("val")) for i, c in enumerate(columns)])
    return df.select(F.col(id_column).alias("point_id"), F.explode(pairs).alias("p")).select("point_id", "p.dim", "p.val")


def to_wide(points: DataFrame) -> DataFrame:
    """point_id, v from tall points."""
    packed = F.transform(F.sort_array(F.collect_list(F.struct("dim", "val"))), lambda p: p["val"])
    return points.groupBy("point_id").agg(packed.alias("v"))


def tall_vectors(df: DataFrame, id_column: str, vector: str) -> DataFrame:
    return df.select(F.col(id_column).alias("point_id"), F.posexplode(vector).alias("dim", "val")).withColumn("val", F.col("val").cast("double"))


def _few(centres: DataFrame) -> bool:
    """Whether a tall centre table may be sent to every task."""
    return centres.limit(CENTRE_NUMBERS + 1).count() <= CENTRE_NUMBERS


def _coordinate(value: Column) -> Column:
    return F.when(value.isNull(), F.raise_error(F.lit("null coordinate"))).otherwise(value)


def gaps(points: DataFrame, centres: DataFrame, broadcast: bool | None = None) -> DataFrame:
    """point_id, centre_id, dim, sq: P x C x D products. Centres are sent to the points where their number was checked, else both sides are dealt by dim."""
    c = centres.select("centre_id", "dim", F.col("val").alias("cval"))
    c = F.broadcast(c) if (_few(centres) if broadcast is None else broadcast) else c
    gap = _coordinate(F.col("val")) - F.col("cval")
    return points.join(c, "dim").select("point_id", "centre_id", "dim", (gap * gap).alias("sq"))


def squared_distances(points: DataFrame, centres: DataFrame, broadcast: bool | None = None) -> DataFrame:
    """point_id, centre_id, d: P x C sums over D products."""
    return gaps(points, centres, broadcast).groupBy("point_id", "centre_id").agg(F.sum("sq").alias("d"))


def nearest(distances: DataFrame, pack: str = "struct") -> DataFrame:
    """point_id, centre_id, d: the least (distance, centre) pair of each point.

    pack: struct; bits, where the distance must be a whole number below 2^31 (others raise); min_by,
    which leaves ties to Spark unless distances differ.
    """
    by = distances.groupBy("point_id")
    if pack == "struct":
        return by.agg(F.min(F.struct("d", "centre_id")).alias("m")).select("point_id", "m.centre_id", "m.d")
    if pack == "bits":
        fits = (F.col("d") >= 0) & (F.col("d") < 2**31) & (F.col("d") == F.floor("d"))
        whole = F.when(fits, F.col("d").cast("bigint")).otherwise(F.raise_error(F.concat(F.lit("no whole distance below 2^31: "), F.col("d").cast("string"))))
        d, centre = unpack_pair(F.col("m"))
        return by.agg(F.min(pack_pair(whole, F.col("centre_id"))).alias("m")).select("point_id", centre.cast("int").alias("centre_id"), d.cast("double").alias("d"))
    if pack != "min_by":
        raise ValueError(f"no such packing: {pack}")
    return by.agg(F.min_by("centre_id", "d").alias("centre_id"), F.min("d").alias("d"))


def recentre(assigned: DataFrame, points: DataFrame, weight: str | None = None) -> DataFrame:
    """centre_id, dim, val: the (weighted) mean of the points of each centre, as sum over count."""
    w = F.col(weight) if weight else F.lit(1.0)
    own = points.join(assigned.select("point_id", "centre_id"), "point_id")
    return own.groupBy("centre_id", "dim").agg((F.sum(w * F.col("val")) / F.sum(w)).alias("val"))


def cardinalities(points: DataFrame, centres: DataFrame) -> DataFrame:
    """distance_items, nearest_items, mean_items: P C D, P C and P D, counted once before the recursion."""
    p = points.agg(F.count_distinct("point_id").alias("p"), F.count_distinct("dim").alias("d"))
    c = centres.agg(F.count_distinct("centre_id").alias("c"))
    return p.crossJoin(F.broadcast(c)).select((F.col("p") * F.col("c") * F.col("d")).alias("distance_items"), (F.col("p") * F.col("c")).alias("nearest_items"), (F.col("p") * F.col("d")).alias("mean_items"))


def _centre_array(centres: DataFrame) -> tuple[list[int], list[int], np.ndarray]:
    """Ids, dims and values of a centre table, on the driver; its size is checked first."""
    if not _few(centres):
        raise ValueError("too many centres to send to every task: use the tall strategy")
    rows = centres.select("centre_id", "dim", "val").collect()  # k x D rows, of checked number
    ids = sorted({r["centre_id"] for r in rows})
    dims = sorted({r["dim"] for r in rows})
    if len(rows) != len(ids) * len(dims):
        raise ValueError("each centre needs one value for each dimension")
    out = np.zeros((len(ids), len(dims)))
    place, column = {c: i for i, c in enumerate(ids)}, {d: j for j, d in enumerate(dims)}
    for r in rows:
        out[place[r["centre_id"]], column[r["dim"]]] = r["val"]
    return ids, dims, out


def _centre_rows(spark, ids: list[int], values: np.ndarray, dims: list[int] | None = None) -> DataFrame:
    dims = list(range(values.shape[1])) if dims is None else dims
    rows = [(int(c), int(d), float(x)) for c, row in zip(ids, values, strict=True) for d, x in zip(dims, row, strict=True)]
    return spark.createDataFrame(rows, "centre_id int, dim int, val double")


def _points(wide: DataFrame, width: int) -> DataFrame:
    """point_id, v of the rows that have coordinates; a null one or another number of them raises."""
    odd = (F.size("v") != width) | F.exists("v", lambda x: x.isNull())
    message = F.concat(F.lit(f"not {width} coordinates at point "), F.coalesce(F.col("point_id").cast("string"), F.lit("null")))
    return wide.filter("v is not null").select("point_id", F.when(odd, F.raise_error(message)).otherwise(F.col("v").cast("array<double>")).alias("v"))


def nearest_in_row(v: Column, ids: list[int], centres: np.ndarray) -> Column:
    """struct(d, centre_id) of the nearest centre of a wide point, without a join."""
    table = F.array(*[F.struct(F.lit(int(c)).alias("centre_id"), F.array(*[F.lit(float(x)) for x in row]).alias("c")) for c, row in zip(ids, centres, strict=True)])
    scored = F.transform(table, lambda c: F.struct(F.aggregate(F.zip_with(v, c["c"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x).alias("d"), c["centre_id"].alias("centre_id")))
    return F.array_min(scored)


def assign_array(wide: DataFrame, ids: list[int], centres: np.ndarray) -> DataFrame:
    own = _points(wide, centres.shape[1])
    return own.withColumn("m", nearest_in_row(F.col("v"), ids, centres)).select("point_id", "v", F.col("m.centre_id").alias("centre_id"), F.col("m.d").alias("d"))


def _sums(got: list, width: int) -> tuple[dict, float, int]:
    return {r["centre_id"]: (np.array([r[f"s{j}"] for j in range(width)]), r["n"]) for r in got}, sum(r["cost"] for r in got), int(sum(r["n"] for r in got))


def _step_array(wide: DataFrame, ids: list[int], centres: np.ndarray) -> tuple[dict, float, int]:
    own = assign_array(wide, ids, centres)
    width = centres.shape[1]
    got = own.groupBy("centre_id").agg(F.count(F.lit(1)).alias("n"), F.sum("d").alias("cost"), *[F.sum(F.col("v")[j]).alias(f"s{j}") for j in range(width)]).collect()  # a row a centre
    return _sums(got, width)


def _step_arrow(wide: DataFrame, ids: list[int], centres: np.ndarray) -> tuple[dict, float, int]:
    shared = wide.sparkSession.sparkContext.broadcast((np.array(ids), centres))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, c = shared.value
        sums, count, cost = np.zeros_like(c), np.zeros(len(c)), np.zeros(len(c))
        for batch in batches:
            x = batch.column("v").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(batch.num_rows, c.shape[1])
            d = np.zeros((len(x), len(c)))
            for j in range(c.shape[1]):  # in the order of dimensions, as a sum in SQL would be
                d += (x[:, j, None] - c[None, :, j]) ** 2
            at = d.argmin(1)
            np.add.at(sums, at, x)
            count += np.bincount(at, minlength=len(c))
            cost += np.bincount(at, d[np.arange(len(x)), at], len(c))
        held = np.flatnonzero(count)
        if len(held):
            yield pa.RecordBatch.from_pydict({"centre_id": pa.array(names[held].astype(np.int32)), "n": pa.array(count[held]), "cost": pa.array(cost[held]), "s": pa.array(list(sums[held]), pa.list_(pa.float64()))})

    width = centres.shape[1]
    partial = _points(wide, width).select("v").mapInArrow(run, "centre_id int, n double, cost double, s array<double>")
    got = partial.groupBy("centre_id").agg(F.sum("n").alias("n"), F.sum("cost").alias("cost"), *[F.sum(F.col("s")[j]).alias(f"s{j}") for j in range(width)]).collect()
    return _sums(got, width)


def reassigned(wide: DataFrame, before: DataFrame, after: DataFrame) -> DataFrame:
    """n: points whose nearest centre is another one after than before."""
    (ids, _, old), (new_ids, _, new) = _centre_array(before), _centre_array(after)
    own = _points(wide, old.shape[1])
    moved = nearest_in_row(F.col("v"), ids, old)["centre_id"] != nearest_in_row(F.col("v"), new_ids, new)["centre_id"]
    return own.agg(F.count_if(moved).alias("n"))


def lloyd(points: DataFrame, centres: DataFrame, steps: int = 1000, eps: float | None = 0.0, empty: str = "keep", strategy: str = "array", pack: str = "struct", weight: str | None = None, stop: StopRule | None = None, retain: str = "last", certify: str = "complete") -> FixpointResult:
    """Centres (centre_id, dim, val) after each step, from `centres`; stops when they move by at most eps (sum of squares).

    points: tall for strategy tall, wide (point_id, v) for array and arrow. The trace has the
    objective (before the step's means), the number of empty centres and how far the centres moved.
    certify: verify and goal, of strategy tall, hold the three bodies of a step against their sizes.
    In array and arrow a step's state is k x D numbers, which go through the driver.
    """
    if empty not in ("keep", "drop", "farthest"):
        raise ValueError(f"no such rule for empty centres: {empty}")
    if strategy == "tall":
        return _lloyd_tall(points, centres, steps, eps, empty, pack, weight, stop, retain, certify)
    if strategy not in ("array", "arrow"):
        raise ValueError(f"no such strategy: {strategy}")
    if weight or certify != "complete":
        raise ValueError("weights and certificates need the tall strategy")
    spark = points.sparkSession
    ids, dims, at = _centre_array(centres)
    rule = max_steps(steps) if stop is None else stop | max_steps(steps)
    trace, history, reason = [TraceRow(0, None, at.size, None, None, 0.0, at.size)], [(0, list(ids), at.copy())], "cap"
    while not (found := rule.test(trace)):
        began = time.time()
        sums, cost, n = (_step_array if strategy == "array" else _step_arrow)(points, ids, at)
        new_ids, rows, moved, empties = [], [], 0.0, 0
        spare = iter(_farthest(points, ids, at, len(ids) - len(sums))) if empty == "farthest" and len(sums) < len(ids) else iter(())
        for c, old in zip(ids, at, strict=True):
            if c in sums:
                s, k = sums[c]
                new = s / k
            else:
                empties += 1
                if empty == "drop":
                    moved += float("inf")
                    continue
                new = next(spare, old) if empty == "farthest" else old
            moved += float(((new - old) ** 2).sum())
            new_ids.append(c)
            rows.append(new)
        body = int(n * at.size)
        ids, at = new_ids, np.array(rows).reshape(len(rows), len(dims))
        step = trace[-1].step + 1
        trace.append(TraceRow(step, body, at.size, moved, None, time.time() - began, at.size, more={"objective": float(cost), "empty": empties}))
        history.append((step, list(ids), at.copy()))
        if eps is not None and moved <= eps:
            found = "converged"
            break
        if retain == "last":
            history = history[-1:]
    reason = found
    if retain != "last":
        trace[-1].retained_rows = sum(c.size for _, _, c in history)
    frames = [_centre_rows(spark, i, c, dims).withColumn("step", F.lit(k)) for k, i, c in (history if retain == "all" else history[-1:])]
    every = frames[0]
    for more in frames[1:]:
        every = every.unionByName(more)
    every = every.select("step", "centre_id", "dim", "val")
    return FixpointResult(every.filter(F.col("step") == trace[-1].step), every if retain == "all" else None, trace, reason)


def certificates(points: DataFrame, centres: DataFrame) -> dict[str, Certificate]:
    """The sizes of the three bodies, counted once, before the recursion."""
    row = cardinalities(points, centres).first()
    names = (("distance", "distance_items"), ("nearest", "nearest_items"), ("mean", "mean_items"))
    return {name: Certificate(name, int(row[column]), "P, C and D counted") for name, column in names}


def _lloyd_tall(points: DataFrame, centres: DataFrame, steps: int, eps: float | None, empty: str, pack: str, weight: str | None, stop: StopRule | None, retain: str, certify: str) -> FixpointResult:
    """The relational form: centre(J) -> distances -> nearest centres -> centre(J + 1), in a staged fixpoint."""
    if certify not in ("complete", "verify", "goal"):
        raise ValueError(f"no such certification: {certify}")
    if certify != "complete" and empty == "drop":
        raise ValueError("sizes are constant only if empty centres are not dropped")
    if certify == "goal" and weight:
        raise ValueError("the goal form has no weights")
    points = keep(points.select("point_id", "dim", "val", *([weight] if weight else [])))
    few = _few(centres)
    width, number = centres.agg(F.count_distinct("dim"), F.count_distinct("centre_id")).first()
    sizes = certificates(points, centres) if certify != "complete" else {}
    w = F.col(weight) if weight else F.lit(1.0)

    def advance(state: DataFrame, watch: Watch) -> DataFrame:
        body = watch("distance", gaps(points, state, few))
        if certify == "goal":
            summed = watch("nearest", _at_counter(body, ["point_id", "centre_id"], "dim", F.sum("sq"), width, "d"))
            pairs = summed.select("point_id", "centre_id", F.struct("d", "centre_id").alias("pair"))
            own = _at_counter(pairs, ["point_id"], "centre_id", F.min("pair"), number, "m").select("point_id", "m.centre_id", "m.d")
        else:
            own = nearest(watch("nearest", body.groupBy("point_id", "centre_id").agg(F.sum("sq").alias("d"))), pack)
        joined = watch("mean", points.join(watch("assigned", own, objective=F.sum("d")), "point_id"))
        if certify == "goal":
            items = joined.select(F.struct("centre_id", "dim").alias("slot"), "val", F.lit(1.0).alias("one"))
            both = sums_at_count(items, "slot", ["val", "one"], sizes["mean"])
            means = both.select("slot.centre_id", "slot.dim", (F.col("val") / F.col("one")).alias("new"))
        else:
            means = joined.groupBy("centre_id", "dim").agg((F.sum(w * F.col("val")) / F.sum(w)).alias("new"))
        means = watch("means", means)
        if empty == "drop":
            return means.withColumnRenamed("new", "val")
        merged = state.join(means, ["centre_id", "dim"], "left")
        if empty == "keep":
            return merged.select("centre_id", "dim", F.coalesce("new", "val").alias("val"))
        return _spread(points, state, merged, nearest(squared_distances(points, state, few), pack))

    rule = max_steps(steps)
    if eps is not None:
        rule = converged(eps) | rule
    if stop is not None:
        rule = stop | rule
    out = StagedFixpoint(centres, advance, ["centre_id", "dim"], ["val"], rule, "l2", retain, certify, sizes, "distance").run()
    for row in out.trace[1:]:
        held = row.bodies["means"] // max(1, width)
        row.more = {"objective": float(row.more.get("objective") or 0.0), "empty": number - held}
        number = held if empty == "drop" else number
    return out


def _at_counter(body: DataFrame, by: list[str], order: str, value: Column, size: int, name: str) -> DataFrame:
    """The goal form of an aggregate whose groups have a known size: its running value at that counter; a group that ends elsewhere raises."""
    w = Window.partitionBy(*by).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    counted = body.select(*by, value.over(w).alias(name), F.row_number().over(w).alias("__n"))
    broken = F.raise_error(F.lit(f"a group of {', '.join(by)} does not have {size} items"))
    last = counted.groupBy(*by).agg(F.max("__n").alias("__last"), F.max_by(name, F.when(F.col("__n") == size, F.col("__n"))).alias(name))
    return last.select(*by, F.when(F.col("__last") == size, F.col(name)).otherwise(broken).alias(name))


def _spread(points: DataFrame, state: DataFrame, merged: DataFrame, own: DataFrame) -> DataFrame:
    """New centres where each empty one, by its id, takes the coordinates of the farthest point left."""
    number = Window.orderBy("centre_id")  # a row a centre
    empties = merged.filter("new is null").select("centre_id").distinct().withColumn("rank", F.row_number().over(number))
    k = state.select("centre_id").distinct().count()
    far = own.orderBy(F.col("d").desc(), "point_id").limit(k).withColumn("rank", F.row_number().over(Window.orderBy(F.col("d").desc(), "point_id")))
    moved = empties.join(far.select("rank", "point_id"), "rank").join(points.select("point_id", "dim", F.col("val").alias("far")), "point_id").select("centre_id", "dim", "far")
    return merged.join(moved, ["centre_id", "dim"], "left").select("centre_id", "dim", F.coalesce("new", "far", "val").alias("val"))


def _farthest(wide: DataFrame, ids: list[int], centres: np.ndarray, n: int) -> list[np.ndarray]:
    rows = assign_array(wide, ids, centres).orderBy(F.col("d").desc(), "point_id").limit(n).collect()  # as many as empty centres
    return [np.array(r["v"], float) for r in rows]


def predict(wide: DataFrame, centres: DataFrame) -> DataFrame:
    """point_id, centre_id, d: each point's nearest centre."""
    ids, _, at = _centre_array(centres)
    return assign_array(wide, ids, at).select("point_id", "centre_id", "d")


def objective(wide: DataFrame, centres: DataFrame) -> DataFrame:
    """objective: sum of squared distances to the nearest centres."""
    return predict(wide, centres).agg(F.sum("d").alias("objective"))


def _as_centres(rows: list, spark) -> DataFrame:
    return _centre_rows(spark, list(range(len(rows))), np.array([list(r) for r in rows], float).reshape(len(rows), -1))


def seeds(wide: DataFrame, k: int, how: str = "first", seed: int = 0, rounds: int = 4, oversample: float = 2.0) -> DataFrame:
    """centre_id, dim, val: k points as first centres.

    first: smallest ids. random: smallest hashes. farthest: each next one farthest from those before.
    plusplus: each next one drawn with chances in proportion to squared distances. parallel: a few
    rounds that draw many at once, then weighted drawing among those. Fewer points than k raise.
    """
    spark = wide.sparkSession

    def exact(rows: list) -> DataFrame:
        if len(rows) < k:
            raise ValueError(f"fewer than {k} points")
        return _as_centres(rows, spark)

    wide = wide.filter("v is not null")
    if how == "first":
        return exact([r["v"] for r in wide.orderBy("point_id").limit(k).collect()])
    if how == "random":
        return exact([r["v"] for r in wide.orderBy(F.xxhash64("point_id", F.lit(seed)), "point_id").limit(k).collect()])
    u = (F.pmod(F.xxhash64("point_id", F.lit(seed)), F.lit(1 << 40)) + 1) / F.lit(float(1 << 40))
    if how in ("farthest", "plusplus"):
        first = wide.orderBy("point_id") if how == "farthest" else wide.orderBy(u, "point_id")
        chosen = [r["v"] for r in first.limit(1).collect()]
        while chosen and len(chosen) < k:
            d = nearest_in_row(F.col("v"), list(range(len(chosen))), np.array(chosen, float))["d"]
            if how == "farthest":
                row = wide.select("v", d.alias("d"), "point_id").orderBy(F.col("d").desc(), "point_id").first()
            else:  # the largest u^(1/d) is drawn with a chance in proportion to d
                draw = (F.pmod(F.xxhash64("point_id", F.lit(seed + len(chosen))), F.lit(1 << 40)) + 1) / F.lit(float(1 << 40))
                row = wide.select("v", d.alias("d"), "point_id").filter("d > 0").orderBy((F.log(draw) / F.col("d")).desc(), "point_id").first()
            if row is None:
                break
            chosen.append(row["v"])
        return exact(chosen)
    if how != "parallel":
        raise ValueError(f"no such seeding: {how}")
    pool = [r["v"] for r in wide.orderBy(u, "point_id").limit(1).collect()]
    for i in range(rounds):
        if not pool:
            break
        ids, at = list(range(len(pool))), np.array(pool, float)
        scored = wide.select("point_id", "v", nearest_in_row(F.col("v"), ids, at)["d"].alias("d"))
        total = scored.agg(F.sum("d")).first()[0] or 0.0
        if total == 0:
            break
        draw = (F.pmod(F.xxhash64("point_id", F.lit(seed + 1000 + i)), F.lit(1 << 40)) + 1) / F.lit(float(1 << 40))
        pool += [r["v"] for r in scored.filter(draw < F.lit(oversample * k / total) * F.col("d")).collect()]  # oversample x k, about
    weights = {r["centre_id"]: r["n"] for r in assign_array(wide, list(range(len(pool))), np.array(pool, float)).groupBy("centre_id").agg(F.count(F.lit(1)).alias("n")).collect()} if pool else {}
    rng, x = np.random.default_rng(seed), np.array(pool, float)
    w = np.array([weights.get(i, 0) for i in range(len(pool))], float)
    picked: list[int] = []
    while len(picked) < min(k, len(pool)):
        d = ((x[:, None] - x[picked][None]) ** 2).sum(2).min(1) if picked else np.ones(len(x))
        p = w * d
        picked.append(int(rng.choice(len(x), p=p / p.sum())) if p.sum() > 0 else next(i for i in range(len(x)) if i not in picked))
    return exact([pool[i] for i in picked])
