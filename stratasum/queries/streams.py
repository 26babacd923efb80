"""Queries over the event stream, each run to the end of a replay, with batch SQL for comparison."""

from __future__ import annotations

from pyspark.sql import functions as F

from stratasum.sources.catalog import table
from stratasum.streaming import aggregates as S

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
CHUNKS = 4


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _stream(spark, sf_dir):
    return S.replay(table(spark, sf_dir, "events"), CHUNKS)


@query("SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, min(value) AS least, max(value) AS most FROM events GROUP BY event_type")
def stream_running_sum(spark, sf_dir):
    """The last update of each group."""
    out = S.run_to_table(S.running(_stream(spark, sf_dir), ["event_type"]), "update")
    return out.groupBy("event_type").agg(F.max("n").alias("n"), F.round(F.max_by("total", "batch"), 4).alias("total"), F.max_by("least", "batch").alias("least"), F.max_by("most", "batch").alias("most"))


# a window is final when the largest time seen, less the delay, has passed its end
@query("""WITH w AS (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start_ts, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1)
SELECT start_ts, n, total FROM w WHERE start_ts + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 10 MINUTE""")
def stream_tumbling_final(spark, sf_dir):
    out = S.run_to_table(S.final_windows(_stream(spark, sf_dir), "1 hour", "10 minutes"), "append")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("start_ts"), "n", F.round("total", 4).alias("total"))


@query("""WITH s AS (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS b, value FROM events),
w AS (SELECT b - k * INTERVAL 30 MINUTE AS start_ts, count(*) AS n FROM s, (VALUES (0), (1)) AS t(k) GROUP BY 1)
SELECT start_ts, n FROM w WHERE start_ts + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 10 MINUTE""")
def stream_sliding(spark, sf_dir):
    out = S.run_to_table(S.final_windows(_stream(spark, sf_dir), "1 hour", "10 minutes", "30 minutes"), "append")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("start_ts"), "n")


# a session ends its gap after its last event; it is final when the watermark has passed that
@query("""WITH marked AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
numbered AS (SELECT user_id, ts, sum(first) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM marked)
SELECT user_id, min(ts) AS start_ts, count(*) AS n FROM numbered GROUP BY user_id, session
HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) FROM events) - INTERVAL 10 MINUTE""")
def stream_session(spark, sf_dir):
    out = S.run_to_table(S.sessions(_stream(spark, sf_dir), "30 minutes", "10 minutes", ["user_id"]), "append")
    return out.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start_ts"), "n")


@query("SELECT event_type AS grp, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY event_type")
def stream_precount_final(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    sizes = events.groupBy(F.col("event_type").alias("grp")).agg(F.count(F.lit(1)).alias("size"))
    items = _stream(spark, sf_dir).withColumn("cents", F.round(F.col("value") * 100).cast("bigint"))
    return S.run_to_table(S.precount_final(items, "event_type", sizes), "append").select("grp", "n", "total")


@query("SELECT count(*) AS n FROM events")
def stream_dedup(spark, sf_dir):
    """Every event comes twice; each is taken once."""
    twice = table(spark, sf_dir, "events")
    stream = S.replay(twice.unionByName(twice), CHUNKS)
    return S.run_to_table(S.deduplicated(stream, "event_id", "365 days").select("event_id"), "append").agg(F.count(F.lit(1)).alias("n"))


@query("""SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id
AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 20 MINUTE""")
def stream_join(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    pairs = S.near_pairs(S.replay(events, CHUNKS), S.replay(events, CHUNKS), "2 hours", "20 minutes")
    return S.run_to_table(pairs, "append").select("a_id", "b_id")


@query("""WITH chunks AS (SELECT *, event_id % 4 AS chunk FROM events),
marks AS (SELECT c.chunk, (SELECT max(ts) FROM chunks e WHERE e.chunk < c.chunk) - INTERVAL 2 HOUR AS mark FROM (SELECT DISTINCT chunk FROM chunks) c)
SELECT event_type, CAST(count(*) FILTER (WHERE mark IS NULL OR ts >= mark) AS BIGINT) AS in_time, CAST(count(*) FILTER (WHERE ts < mark) AS BIGINT) AS late FROM chunks JOIN marks USING (chunk) GROUP BY event_type""")
def stream_late(spark, sf_dir):
    """Events replayed out of order: late ones are set aside instead of dropped."""
    events = table(spark, sf_dir, "events")
    in_time, late = S.split_late(S.replay(events, CHUNKS, F.col("event_id") % CHUNKS), "2 hours")
    both = in_time.select("event_type", F.lit(1).alias("a"), F.lit(0).alias("b")).unionByName(late.select("event_type", F.lit(0).alias("a"), F.lit(1).alias("b")))
    return both.groupBy("event_type").agg(F.sum("a").alias("in_time"), F.sum("b").alias("late"))


def _stream_lloyd_sql(chunks: int) -> str:
    levels = ["""WITH chunks AS (SELECT value AS x, CAST(hour(ts) AS DOUBLE) AS y, (event_id - (SELECT min(event_id) FROM events)) // greatest(1, (SELECT (max(event_id) - min(event_id)) // 4 + 1 FROM events)) AS chunk FROM events),
c0 AS (SELECT * FROM (VALUES (0, 10e0, 6e0), (1, 50e0, 12e0), (2, 90e0, 18e0)) AS t(c, x, y)), s0 AS (SELECT c, 0 AS n, 0e0 AS sx, 0e0 AS sy FROM c0)"""]
    for k in range(1, chunks + 1):
        levels.append(f"n{k} AS MATERIALIZED (SELECT p.x, p.y, (SELECT min(struct_pack(d := (p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y), c := q.c)) FROM c{k - 1} q) AS m FROM chunks p WHERE chunk = {k - 1})")
        levels.append(f"s{k} AS MATERIALIZED (SELECT o.c, o.n + coalesce(a.n, 0) AS n, o.sx + coalesce(a.sx, 0) AS sx, o.sy + coalesce(a.sy, 0) AS sy FROM s{k - 1} o LEFT JOIN (SELECT m.c AS c, count(*) AS n, sum(x) AS sx, sum(y) AS sy FROM n{k} GROUP BY m.c) a USING (c))")
        levels.append(f"c{k} AS MATERIALIZED (SELECT c, CASE WHEN n = 0 THEN o.x ELSE sx / n END AS x, CASE WHEN n = 0 THEN o.y ELSE sy / n END AS y FROM s{k} JOIN c{k - 1} o USING (c))")
    tail = " UNION ALL ".join(f"SELECT {k - 1} AS batch, c AS centre_id, CAST(n AS BIGINT) AS n, round(c{k}.x, 5) AS x, round(c{k}.y, 5) AS y FROM s{k} JOIN c{k} USING (c)" for k in range(1, chunks + 1))
    return ", ".join(levels) + " " + tail


@query(_stream_lloyd_sql(CHUNKS))
def stream_centres(spark, sf_dir):
    """Centres of (value, hour) that follow the stream."""
    stream = _stream(spark, sf_dir).withColumn("hour", F.hour("ts").cast("double"))
    out = S.stream_lloyd(stream, [[10.0, 6.0], [50.0, 12.0], [90.0, 18.0]], ["value", "hour"])
    return out.select("batch", "centre_id", "n", F.round(F.col("v")[0], 5).alias("x"), F.round(F.col("v")[1], 5).alias("y"))
