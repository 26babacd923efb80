"""Continuous and final aggregates over streams.

A continuous aggregate never waits: it gives a new value whenever items come. A final one must know
that its items have ended: by the watermark closing a window, or, when the number of items is known
beforehand, by its counter reaching that number, with no mark of the end and no delay.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from stratasum.plans.materialize import shared_folder


def replay(events: DataFrame, chunks: int, chunk: Column | None = None) -> DataFrame:
    """The rows as a stream of files, in the order of event_id, a chunk a micro-batch. chunk: the number of each row's chunk, to replay in another order."""
    spark, path = events.sparkSession, shared_folder(events.sparkSession)
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if chunk is None:
        least, most = rows.agg(F.min("event_id"), F.max("event_id")).first()
        chunk = F.floor((F.col("event_id") - (least or 0)) / max(1, ((most or 0) - (least or 0)) // chunks + 1))
    for k in range(chunks):
        rows.filter(chunk == k).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def rates(spark: SparkSession, rows_per_batch: int, parts: int = 2) -> DataFrame:
    """timestamp, value: a source that makes rows itself, so many a micro-batch, the same in every run."""
    return spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows_per_batch).option("numPartitions", parts).load()


def to_memory(stream: DataFrame, name: str, mode: str = "append", **trigger) -> StreamingQuery:
    """Starts a stream into a table in the driver's memory, for small results; the caller stops it. trigger: as in writeStream.trigger."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode)
    return (writer.trigger(**trigger) if trigger else writer).start()


def run_batches(stream: DataFrame, save: Callable[[DataFrame, int], None], log: str, mode: str = "append") -> None:
    """Runs a stream over all that is there, a call of save for each micro-batch. With the log of an earlier run it goes on where that ended."""
    stream.writeStream.outputMode(mode).option("checkpointLocation", log).foreachBatch(save).trigger(availableNow=True).start().awaitTermination()


def run_to_table(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all that is there and gives its output with the number of the micro-batch. A batch that runs again replaces itself."""
    spark, path = stream.sparkSession, shared_folder(stream.sparkSession)

    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    run_batches(stream, save, f"{path}/log", mode)
    return spark.read.option("basePath", f"{path}/out").parquet(f"{path}/out")


def split_late(stream: DataFrame, delay: str, path: str | None = None) -> tuple[DataFrame, DataFrame]:
    """The rows in time and the late ones, which final aggregates would drop: late is what lies before the largest time of earlier batches, less the delay.

    Each batch writes its marks beside its rows, so a run that starts again from its log goes on with the same policy.
    """
    spark, path = stream.sparkSession, path or shared_folder(stream.sparkSession)
    marks = f"{path}/marks"

    def save(batch: DataFrame, number: int) -> None:
        batch.agg(F.max("ts").alias("top")).write.mode("overwrite").parquet(f"{marks}/batch={number}")
        known = spark.read.schema("top timestamp, batch int").option("basePath", marks).parquet(marks).filter(F.col("batch") < number)
        mark = known.agg((F.max("top") - F.expr(f"interval {delay}")).alias("mark"))
        late = F.coalesce(F.col("ts") < F.col("mark"), F.lit(False))
        batch.crossJoin(F.broadcast(mark)).withColumn("late", late).drop("mark").write.mode("overwrite").parquet(f"{path}/out/batch={number}")  # one row

    run_batches(stream, save, f"{path}/log")
    out = spark.read.option("basePath", f"{path}/out").parquet(f"{path}/out")
    return out.filter("not late").drop("late"), out.filter("late").drop("late")


def running(stream: DataFrame, by: list[str]) -> DataFrame:
    """Continuous count, sum, min and max of each group, in update mode."""
    return stream.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"), F.min("value").alias("least"), F.max("value").alias("most"))


def final_windows(stream: DataFrame, length: str, delay: str, slide: str | None = None, by: list[str] | None = None) -> DataFrame:
    """Final aggregates of windows that the watermark has closed, in append mode."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.withWatermark("ts", delay).groupBy(w, *(by or [])).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sessions(stream: DataFrame, gap: str, delay: str, by: list[str]) -> DataFrame:
    return stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), *by).agg(F.count(F.lit(1)).alias("n"))


def deduplicated(stream: DataFrame, key: str, delay: str) -> DataFrame:
    """Each item once, though it may be replayed within the delay."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def precount_final(stream: DataFrame, by: str, sizes: DataFrame, timeout_s: int | None = None) -> DataFrame:
    """grp, n, total, given as soon as a group has as many items as `sizes` (grp, size) says.

    sizes is a static table joined to the stream; it certifies the sizes, so a group that gets more items
    than that, in the same batch or later, fails the stream. A full group leaves its count as a mark.
    Groups that never fill have no result. Their state stays, as marks do, or goes after `timeout_s`.
    Leave that out of runs that end by themselves: with a processing-time timeout Spark adds batches without
    data for ever.
    """
    joined = stream.join(sizes, stream[by] == sizes["grp"]).select("grp", "size", "cents")

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, total = state.get if state.exists else (0, 0)
        before, size = n, None
        for frame in frames:
            n, total, size = n + len(frame), total + int(frame["cents"].sum()), int(frame["size"].iloc[0])
        if size is not None and n > size:
            raise ValueError(f"{key[0]} has {n} items or more, not {size}")
        state.update((n, total))
        if timeout_s is not None:
            state.setTimeoutDuration(1000 * timeout_s)
        if size is not None and n == size and before < size:
            yield pd.DataFrame({"grp": [key[0]], "n": [n], "total": [total]})

    return joined.groupBy("grp").applyInPandasWithState(step, "grp string, n bigint, total bigint", "n bigint, total bigint", "append", GroupStateTimeout.NoTimeout if timeout_s is None else GroupStateTimeout.ProcessingTimeTimeout)


def near_pairs(left: DataFrame, right: DataFrame, delay: str, within: str) -> DataFrame:
    """Stream-stream join: right items of a user within a time after left ones."""
    a = left.withWatermark("ts", delay).select(F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_id"))
    b = right.withWatermark("ts", delay).select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_id"))
    return a.join(b, F.expr(f"a_user = b_user AND b_ts > a_ts AND b_ts <= a_ts + interval {within}")).select("a_id", "b_id")


def stream_lloyd(stream: DataFrame, centres: list[list[float]], columns: list[str], path: str | None = None) -> DataFrame:
    """batch, centre_id, n, v: centres that follow a stream. Each micro-batch is assigned to the nearest ones, and means are carried as sum and count.

    The state after each batch is a table at path, k rows; the next batch starts from the last one
    before it, so a run that starts again from its log goes on with the centres that it had.
    """
    spark, path = stream.sparkSession, path or shared_folder(stream.sparkSession)
    schema = "centre_id int, n bigint, sums array<double>, v array<double>"
    state = f"{path}/state"
    spark.createDataFrame([(k, 0, [0.0] * len(c), [float(x) for x in c]) for k, c in enumerate(centres)], schema).coalesce(1).write.mode("overwrite").parquet(f"{state}/batch=-1")

    def update(batch: DataFrame, number: int) -> None:
        every = spark.read.schema(schema + ", batch int").option("basePath", state).parquet(state)
        last = every.filter(F.col("batch") < number).agg(F.max("batch")).first()[0]
        now = every.filter(F.col("batch") == last).select("centre_id", "n", "sums", "v")
        rows = now.orderBy("centre_id").collect()  # a row a centre
        gap = lambda v: reduce(lambda a, b: a + b, [(F.col(c) - F.lit(x)) * (F.col(c) - F.lit(x)) for c, x in zip(columns, v, strict=True)])
        scored = F.array(*[F.struct(gap(r["v"]).alias("d"), F.lit(r["centre_id"]).alias("centre_id")) for r in rows])
        own = batch.withColumn("centre_id", F.array_min(scored)["centre_id"]).groupBy("centre_id").agg(F.count(F.lit(1)).alias("more"), F.array(*[F.sum(c) for c in columns]).alias("added"))
        both = now.join(own, "centre_id", "left").withColumn("n", F.col("n") + F.coalesce("more", F.lit(0)))
        both = both.withColumn("sums", F.when(F.col("more").isNull(), F.col("sums")).otherwise(F.zip_with("sums", "added", lambda a, b: a + b)))
        moved = both.withColumn("v", F.when(F.col("n") == 0, F.col("v")).otherwise(F.transform("sums", lambda x: x / F.col("n"))))
        moved.select("centre_id", "n", "sums", "v").coalesce(1).write.mode("overwrite").parquet(f"{state}/batch={number}")

    run_batches(stream, update, f"{path}/log")
    return spark.read.schema(schema + ", batch int").option("basePath", state).parquet(state).filter("batch >= 0").select("batch", "centre_id", "n", "v")
