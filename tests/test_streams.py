import time

import pytest
from pyspark.sql import functions as F

from stratasum.sources.catalog import write_bucketed
from stratasum.streaming import aggregates as S


def items(spark, rows):
    return spark.createDataFrame(rows, "event_id bigint, grp_name string, cents bigint").withColumn("ts", F.timestamp_seconds(F.col("event_id")))


def stream_of(spark, frames, path):
    """Each frame a micro-batch."""
    for k, frame in enumerate(frames):
        frame.coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.01 * (k + 1))
    return spark.readStream.schema(frames[0].schema).option("maxFilesPerTrigger", 1).parquet(path)


def sizes(spark, **n):
    return spark.createDataFrame(list(n.items()), "grp string, size bigint")


def test_known_sizes_end_groups(spark, tmp_path):
    frames = [items(spark, [(1, "a", 5), (2, "b", 7)]), items(spark, [(3, "a", 6)])]
    out = S.run_to_table(S.precount_final(stream_of(spark, frames, f"{tmp_path}/in"), "grp_name", sizes(spark, a=2, b=3)), "append")
    assert [(r["grp"], r["n"], r["total"]) for r in out.collect()] == [("a", 2, 11)]


@pytest.mark.parametrize("late", [False, True])
def test_more_items_than_certified_fail_the_stream(spark, tmp_path, late):
    batches = [[(1, "a", 5), (2, "a", 6)], [(3, "a", 7)]] if late else [[(1, "a", 5), (2, "a", 6), (3, "a", 7)]]
    stream = stream_of(spark, [items(spark, b) for b in batches], f"{tmp_path}/in")
    with pytest.raises(Exception, match="items or more"):
        S.run_to_table(S.precount_final(stream, "grp_name", sizes(spark, a=2)), "append")


def test_late_rows_are_set_aside(spark, tmp_path):
    frames = [items(spark, [(100, "a", 1), (200, "a", 1)]), items(spark, [(150, "a", 1), (195, "a", 1)]), items(spark, [(10, "a", 1), (300, "a", 1)])]
    in_time, late = S.split_late(stream_of(spark, frames, f"{tmp_path}/in"), "10 seconds")
    assert sorted(r["event_id"] for r in late.collect()) == [10, 150]
    assert sorted(r["event_id"] for r in in_time.collect()) == [100, 195, 200, 300]


def test_centres_go_on_after_a_restart(spark, tmp_path):
    rows = [[(k, "a", 10 * j + k % 3) for k in range(6)] for j in range(4)]
    start = [[0.0], [30.0]]

    def run(name, parts):
        place = f"file://{tmp_path}/{name}"
        for part in parts:  # each run finds the files of all runs before it
            stream = stream_of(spark, [items(spark, r) for r in part], f"{tmp_path}/in-{name}")
            out = S.stream_lloyd(stream, start, ["cents"], place)
        return sorted((r["batch"], r["centre_id"], r["n"], [round(x, 9) for x in r["v"]]) for r in out.collect())

    assert run("once", [rows]) == run("twice", [rows[:2], rows[2:]])


def test_rows_from_a_rate_into_memory(spark):
    started = S.to_memory(S.rates(spark, 5), "rated", processingTime="0 seconds")
    try:
        for _ in range(300):
            if spark.table("rated").count() >= 10:
                break
            time.sleep(0.1)
    finally:
        started.stop()
    got = [r["value"] for r in spark.table("rated").orderBy("value").collect()]
    assert len(got) >= 10 and got == list(range(len(got)))


def test_bucketed_tables_join_without_a_shuffle(spark):
    table = write_bucketed(spark.range(1000).withColumn("v", F.col("id") % 7), "bucketed_by_id", 4, "id")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        joined = table.join(spark.table("bucketed_by_id").withColumnRenamed("v", "w"), "id")
        assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString() and joined.count() == 1000
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE bucketed_by_id")
