"""Queries of the relational operators around the methods, with the same SQL for comparison."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stratasum.functions.aggspec import grouped_udaf
from stratasum.operators import relational as R
from stratasum.sources.catalog import scan, table, views, write
from stratasum.sources.flows import part_points
from stratasum.plans.materialize import keep, shared_folder

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def shared(name: str, sql: str, *tables: str) -> None:
    """A query whose SQL is the same in both engines."""

    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        views(spark, sf_dir, *tables)
        return spark.sql(sql)

    f.__name__ = name
    query(sql)(f)


@query("SELECT r_regionkey, r_name FROM region")
def scan_parquet(spark, sf_dir):
    return table(spark, sf_dir, "region", check=True)


@query("SELECT n_nationkey, n_name, 3 AS formats FROM nation")
def scan_roundtrip_csv_json_orc(spark, sf_dir):
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    back = []
    for fmt in ("csv", "json", "orc"):
        path = shared_folder(spark)
        write(nation, path, fmt)
        back.append(scan(spark, path, fmt, "n_nationkey int, n_name string"))
    return back[0].unionByName(back[1]).unionByName(back[2]).groupBy("n_nationkey", "n_name").agg(F.count(F.lit(1)).cast("int").alias("formats"))


@query("SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount), 2) AS net FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'")
def op_project_filter(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").filter("l_quantity >= 45 and l_returnflag = 'R'").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 2).alias("net"))


shared("op_predicates", """SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'large' WHEN o_totalprice > 50000 THEN 'middle' ELSE 'small' END AS size
FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '%U%' AND o_totalprice BETWEEN 1000 AND 300000 AND o_custkey IS NOT DISTINCT FROM o_custkey""", "orders")
JOINED = "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_acctbal > 5000"


def _joined(hint: str):
    def f(spark, sf_dir):
        o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer").filter("c_acctbal > 5000")
        return o.join(c.hint(hint), o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "c_name")

    return f


for _name, _hint in (("join_hash", "shuffle_hash"), ("join_merge", "merge"), ("join_broadcast", "broadcast")):
    _f = _joined(_hint)
    _f.__name__ = _name
    query(JOINED)(_f)
shared("join_outer", "SELECT n_nationkey, s_suppkey FROM nation FULL JOIN supplier ON n_nationkey = s_nationkey", "nation", "supplier")
shared("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)", "customer", "orders")
shared("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')", "customer", "orders")
shared("join_cross_scalar", "SELECT s_suppkey, round(s_acctbal - a, 2) AS over FROM supplier CROSS JOIN (SELECT avg(s_acctbal) AS a FROM supplier)", "supplier")


@query("SELECT event_id, CAST(b AS INT) AS band FROM events JOIN range(0, 10) AS t(b) ON value >= b * 12.5 AND value < b * 12.5 + 20")
def join_theta_range(spark, sf_dir):
    bands = spark.range(10).select(F.col("id").cast("int").alias("band"), (F.col("id") * 12.5).alias("lo"), (F.col("id") * 12.5 + 20).alias("hi"))
    return R.range_join(table(spark, sf_dir, "events"), bands, "value", "lo", "hi", 10.0).select("event_id", "band")


@query("""SELECT e.event_id, max(p.event_id) AS before_id FROM events e LEFT JOIN events p
ON p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts WHERE e.event_type <> 'purchase' GROUP BY e.event_id""")
def join_asof(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    right = e.filter("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("before_id"))
    return R.asof_join(e.filter("event_type <> 'purchase'"), right, ["user_id"], "ts", ["before_id"]).select("event_id", "before_id")


@query("""SELECT a.event_id, b.event_id AS near_id FROM events a JOIN events b ON a.user_id = b.user_id
AND a.event_id < b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR""")
def join_interval(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    near = e.select(F.col("event_id").alias("near_id"), "user_id", F.col("ts").alias("near_ts"))
    return R.interval_join(e, near, ["user_id"], "ts", "near_ts", 0, 3600).filter("event_id < near_id").select("event_id", "near_id")


shared("agg_group", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_extendedprice), 4) AS price FROM lineitem GROUP BY l_returnflag, l_linestatus", "lineitem")
shared("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderstatus", "orders")
shared("agg_filter_clause", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, count(*) AS n FROM orders GROUP BY o_orderpriority", "orders")
shared("agg_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)", "orders")
shared("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)", "orders")
shared("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())", "orders")
shared("agg_min_max_by", "SELECT s_nationkey, max_by(s_suppkey, s_acctbal) AS richest, min_by(s_suppkey, s_acctbal) AS poorest FROM supplier GROUP BY s_nationkey", "supplier")
shared("agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY l_returnflag", "lineitem")


@query()
def agg_approx_distinct(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.approx_count_distinct("o_custkey", 0.02).alias("customers"))


shared("win_rank", "SELECT s_suppkey, rank() OVER w AS r, dense_rank() OVER w AS d, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS n FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal DESC)", "supplier")
shared("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before_id, lead(event_id, 2) OVER w AS later_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events")
shared("win_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS total FROM events", "events")
shared("win_sliding_rows", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) AS around FROM events", "events")
shared("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_custkey RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS n FROM orders", "orders")
shared("win_ntile", "SELECT s_suppkey, ntile(4) OVER (PARTITION BY s_nationkey % 3 ORDER BY s_acctbal, s_suppkey) AS q, round(percent_rank() OVER (PARTITION BY s_nationkey % 3 ORDER BY s_acctbal), 6) AS p FROM supplier", "supplier")
shared("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", "orders")


@query("SELECT o_orderstatus, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 5")
def topk_group(spark, sf_dir):
    return R.topk(table(spark, sf_dir, "orders"), ["o_orderstatus"], [F.desc("o_totalprice"), F.asc("o_orderkey")], 5).select("o_orderstatus", "o_orderkey")


shared("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier", "customer", "supplier")
shared("set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier WHERE s_acctbal > 0", "customer", "supplier")
shared("set_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders", "customer", "orders")
shared("set_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier", "customer", "supplier")
shared("sub_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.9 FROM orders)", "orders")
shared("sub_exists", "SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT c_nationkey FROM customer WHERE c_acctbal > 9900)", "supplier", "customer")
shared("sub_lateral", "SELECT n_nationkey, t.best FROM nation, LATERAL (SELECT max(s_acctbal) AS best FROM supplier WHERE s_nationkey = n_nationkey) t", "nation", "supplier")
shared("sub_recursive_cte", """WITH RECURSIVE sizes AS (SELECT CAST(row_number() OVER (ORDER BY p_size) AS INT) AS k, parts FROM (SELECT p_size, count(*) AS parts FROM part GROUP BY p_size)),
t(n, f, parts) AS (SELECT k, CAST(1 AS BIGINT), parts FROM sizes WHERE k = 1 UNION ALL SELECT k, f * k, t.parts + sizes.parts FROM t JOIN sizes ON k = n + 1 WHERE n < 15)
SELECT n, f, parts FROM t""", "part")
shared("fn_string", "SELECT p_partkey, upper(p_name) AS u, length(p_type) AS n, substr(p_brand, 1, 3) AS b, replace(p_name, 'a', 'A') AS r, levenshtein(p_name, p_type) AS d, concat(p_brand, '-', p_size) AS c FROM part", "part")
shared("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(o_orderdate + INTERVAL 3 DAY AS DATE) AS d FROM orders", "orders")
shared("fn_math", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(sqrt(l_extendedprice), 6) AS s, abs(l_quantity - 25) AS a, greatest(l_quantity, 10.0) AS g, l_partkey % 7 AS m, round(ln(l_extendedprice), 6) AS l FROM lineitem", "lineitem")


@query("SELECT vec_id, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def fn_array(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.array_max("embedding").cast("double"), 6).alias("top"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"))


@query("SELECT vec_id, CAST(generate_subscripts(embedding, 1) - 1 AS INT) AS dim, round(CAST(unnest(embedding) AS DOUBLE), 6) + 0.0 AS val FROM embeddings")
def fn_explode(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("dim", "x")).select("vec_id", "dim", (F.round(F.col("x").cast("double"), 6) + 0.0).alias("val"))


@query("SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (WHERE event_type = 'click') AS clicks FROM events GROUP BY user_id")
def fn_map(spark, sf_dir):
    per = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    maps = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.size(F.map_keys("m")).cast("bigint").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def fn_json(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


shared("fn_decimal", "SELECT o_orderstatus, sum(CAST(o_totalprice AS DECIMAL(18, 2))) AS total FROM orders GROUP BY o_orderstatus", "orders")
shared("fn_interval", "SELECT event_id FROM events WHERE ts < (SELECT min(ts) FROM events) + INTERVAL 2 HOUR", "events")


@query("SELECT s_suppkey, s_nationkey AS nation, TRY_CAST(s_name AS BIGINT) AS number FROM supplier")
def fn_struct(spark, sf_dir):
    packed = table(spark, sf_dir, "supplier").select("s_suppkey", F.struct(F.col("s_nationkey").alias("nation"), F.col("s_name").try_cast("bigint").alias("number")).alias("s"))
    return packed.select("s_suppkey", "s.nation", "s.number")


@query("SELECT p_partkey, CASE WHEN p_size % 2 = 0 THEN 'even' ELSE 'odd' END AS parity FROM part")
def udf_scalar(spark, sf_dir):
    @F.pandas_udf("string")
    def parity(size: pd.Series) -> pd.Series:
        return (size % 2 == 0).map({True: "even", False: "odd"})

    return table(spark, sf_dir, "part").select("p_partkey", parity("p_size").alias("parity"))


@query("SELECT s_nationkey, round(sqrt(sum(s_acctbal * s_acctbal) / count(*)), 4) AS rms FROM supplier GROUP BY s_nationkey")
def udaf_grouped(spark, sf_dir):
    rms = grouped_udaf(lambda a, x: a + x * x, 0.0, lambda a, n: (a / n) ** 0.5)
    return table(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.round(rms("s_acctbal"), 4).alias("rms"))


@query("SELECT row_number() OVER (ORDER BY s_suppkey) AS counter, CAST(sum(CAST(round(s_acctbal * 100) AS BIGINT)) OVER (ORDER BY s_suppkey) AS BIGINT) AS running FROM supplier")
def udtf_running(spark, sf_dir):
    """The continuous sum by a table function, which gets a part of the order at a time and goes on from the parts before it."""

    @F.udtf(returnType="counter bigint, running bigint")
    class Facts:
        def __init__(self):
            self.n = None

        def eval(self, row):
            if self.n is None:
                self.n, self.total = row["n0"], row["c0"]
            self.n += 1
            self.total += row["c"] or 0
            yield self.n, self.total

    spark.udtf.register("continuous_sum_of_parts", Facts)
    items = table(spark, sf_dir, "supplier").select("s_suppkey", F.round(F.col("s_acctbal") * 100).cast("bigint").alias("c"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = keep(items.repartitionByRange(parts, "s_suppkey").withColumn("part", F.spark_partition_id()))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row a part
    sizes = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("cs"))
    offsets = sizes.select("part", *[F.coalesce(F.sum(x).over(before), F.lit(0)).alias(y) for x, y in (("n", "n0"), ("cs", "c0"))])
    dealt.join(F.broadcast(offsets), "part").createOrReplaceTempView("supplier_parts")
    return spark.sql("SELECT counter, running FROM continuous_sum_of_parts(TABLE(supplier_parts) PARTITION BY part ORDER BY s_suppkey)")


@query()
def op_sample(spark, sf_dir):
    """A tenth of the rows by a hash, the same rows each time."""
    return R.hash_sample(table(spark, sf_dir, "orders"), ["o_orderkey"], 0.1).select("o_orderkey")


@query("SELECT p_partkey AS point_id, CAST(p_size * 20 AS DOUBLE) AS x, CAST(round((p_retailprice - 900) * 10) AS DOUBLE) AS y FROM part")
def op_tall_wide(spark, sf_dir):
    tall = part_points(spark, sf_dir).select("point_id", F.posexplode("v").alias("dim", "val"))
    wide = tall.groupBy("point_id").pivot("dim", [0, 1]).agg(F.first("val"))
    back = wide.unpivot("point_id", ["0", "1"], "dim", "val").withColumn("dim", F.col("dim").cast("int"))
    return back.groupBy("point_id").pivot("dim", [0, 1]).agg(F.first("val")).select("point_id", F.col("0").alias("x"), F.col("1").alias("y"))


@query("SELECT n_name FROM nation")
def scan_text(spark, sf_dir):
    path = shared_folder(spark)
    write(table(spark, sf_dir, "nation").select(F.col("n_name").alias("value")), path, "text")
    return scan(spark, path, "text").select(F.col("value").alias("n_name"))


@query("SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderstatus <> 'F' GROUP BY o_orderstatus")
def scan_partitioned(spark, sf_dir):
    """Folders by status are found when read, and the filter prunes them."""
    path = shared_folder(spark)
    write(table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus"), path, partition_by=("o_orderstatus",))
    return scan(spark, path).filter("o_orderstatus <> 'F'").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS middle, round(quantile_cont(o_totalprice, 0.9), 4) AS high FROM orders GROUP BY o_orderpriority")
def agg_percentile(spark, sf_dir):
    got = table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.percentile("o_totalprice", [0.5, 0.9]).alias("p"))
    return got.select("o_orderpriority", F.round(F.col("p")[0], 4).alias("middle"), F.round(F.col("p")[1], 4).alias("high"))


@query("SELECT c_nationkey, array_to_string(list_sort(list(DISTINCT c_mktsegment)), ',') AS segments FROM customer GROUP BY c_nationkey")
def agg_collect_set(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.array_join(F.sort_array(F.collect_set("c_mktsegment")), ",").alias("segments"))


shared("set_intersect_all", "SELECT c_nationkey AS nation FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier", "customer", "supplier")


@query("SELECT user_id, CAST(len(list(DISTINCT event_type) FILTER (WHERE event_type <> 'click')) AS INT) AS others FROM events GROUP BY user_id")
def fn_map_filter(spark, sf_dir):
    kinds = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return kinds.select("user_id", F.size(F.map_filter("m", lambda k, v: k != "click")).alias("others"))


@query("""SELECT event_id, '{"id":' || event_id || ',"type":"' || event_type || '"}' AS json FROM events""")
def fn_to_json(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.to_json(F.struct(F.col("event_id").alias("id"), F.col("event_type").alias("type"))).alias("json"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def fn_variant(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.try_variant_get(F.try_parse_json("props"), "$.k", "int").alias("k"))


@query("SELECT n_nationkey, reverse(n_name) AS name, n_regionkey * 2 AS twice FROM nation")
def udf_row_and_arrow(spark, sf_dir):
    """A function called row by row, and one called with Arrow arrays."""

    @F.udf("string")
    def backwards(x: str) -> str:
        return x[::-1]

    @F.arrow_udf("int")
    def doubled(x: pa.Array) -> pa.Array:
        return pa.compute.multiply(x, 2)

    return table(spark, sf_dir, "nation").select("n_nationkey", backwards("n_name").alias("name"), doubled("n_regionkey").alias("twice"))


@query()
def op_sample_by(spark, sf_dir):
    """About a tenth of the open orders and a hundredth of the others."""
    return table(spark, sf_dir, "orders").sampleBy("o_orderstatus", {"O": 0.1, "F": 0.01, "P": 0.01}, seed=7).select("o_orderkey", "o_orderstatus")
