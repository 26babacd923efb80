import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as entry_module
from stratasum.operators import relational as R
from stratasum.queries import methods, relational, streams

REPO = Path(__file__).resolve().parents[1]
CHOSEN = [
    "markov_kernel", "markov_converged", "markov_salted", "fix_sql_program", "base_stratified_markov", "lloyd_array_part", "lloyd_assign_bits", "grp_running_sum_global",
    "premap_shortest_stratified", "join_asof", "join_interval", "join_theta_range", "topk_group", "op_tall_wide", "stream_tumbling_final", "stream_precount_final",
]


def canon(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(f"{r[i]:.9g}" if isinstance(r[i], float) else str(r[i]) for i in order) for r in rows)


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for name in "region nation customer supplier part orders lineitem events embeddings pages".split():
        con.execute(f"create view {name} as select * from '{small}/{name}.parquet'")
    return con


@pytest.mark.parametrize("name", CHOSEN)
def test_against_sql(spark, small, duck, name):
    queries, oracles = {**methods.QUERIES, **relational.QUERIES, **streams.QUERIES}, {**methods.ORACLES, **relational.ORACLES, **streams.ORACLES}
    got = queries[name](spark, small)
    want = duck.sql(oracles[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert canon([tuple(r) for r in got.collect()], got.columns) == canon(want.fetchall(), want.columns)


def test_library_loop_equals_lloyd(spark, small):
    a, b = (methods.QUERIES[q](spark, small) for q in ("base_library_lloyd", "lloyd_array_part"))
    assert canon([tuple(r) for r in a.collect()], a.columns) == canon([tuple(r) for r in b.collect()], b.columns)


def test_asof_tolerance(spark):
    left = spark.createDataFrame([(1, 100), (1, 300)], "k int, t int").selectExpr("k", "timestamp_seconds(t) AS ts")
    right = spark.createDataFrame([(1, 90, "a")], "k int, t int, x string").selectExpr("k", "timestamp_seconds(t) AS ts", "x")
    got = R.asof_join(left, right, ["k"], "ts", ["x"], tolerance_s=60)
    assert sorted((r["ts"].minute, r["x"]) for r in got.collect()) == [(1, "a"), (5, None)]


def test_every_oracle_has_a_query():
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())


def test_entry(spark):
    assert entry_module.entry(spark).count() > 0


def test_imports_without_the_pipeline_part():
    code = """
import sys, importlib.abc
class Gone(importlib.abc.MetaPathFinder):
    def find_spec(self, name, path=None, target=None):
        if name.startswith("stratasum.llm") or name == "corpus_pipeline":
            raise ModuleNotFoundError(name)
sys.meta_path.insert(0, Gone())
import __spark_entry__ as e
names = e.queries()
assert "markov_kernel" in names and not any(n.startswith("op1_") or n == "pipeline" for n in names)
e.oracle_sql()
"""
    subprocess.run([sys.executable, "-c", code], cwd=REPO, check=True)


def test_table_function_over_all_suppliers(spark, tmp_path):
    cents = [(k * 7919) % 1000 - 300 for k in range(1, 301)]
    spark.createDataFrame([(k, c / 100) for k, c in enumerate(cents, 1)], "s_suppkey bigint, s_acctbal double").repartition(3).write.parquet(f"{tmp_path}/supplier.parquet")
    got = relational.QUERIES["udtf_running"](spark, str(tmp_path)).collect()
    assert sorted((r["counter"], r["running"]) for r in got) == [(n, sum(cents[:n])) for n in range(1, 301)]


def test_lloyd_past_the_steps_of_its_sql(spark, duck, tmp_path):
    """Points on a line with all seeds at one end: 57 steps, while the SQL has 40; the fixed point is another query."""
    spark.createDataFrame([(k, k, 900.0) for k in range(1, 101)], "p_partkey bigint, p_size int, p_retailprice double").coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    con = duckdb.connect()
    con.execute(f"create view part as select * from '{tmp_path}/part.parquet/*.parquet'")

    def rows(name):
        got = methods.QUERIES[name](spark, str(tmp_path))
        return canon([tuple(r) for r in got.collect()], got.columns)

    want = lambda n: con.sql(methods._lloyd_sql(n, f"SELECT c AS centre_id, 0 AS dim, round(x, 6) AS val FROM c{n} UNION ALL SELECT c, 1, round(y, 6) FROM c{n}"))
    at_40, at_end = (canon(w.fetchall(), w.columns) for w in (con.sql(methods.ORACLES["lloyd_converged_part"]), want(60)))
    assert at_40 != at_end
    assert rows("lloyd_converged_part") == at_40
    assert rows("lloyd_fixed_point_part") == at_end


@pytest.mark.parametrize("name,tables", [("measure_strata", "part lineitem orders customer supplier"), ("sub_recursive_cte", "part")])
def test_results_come_from_the_given_tables(spark, small, tmp_path, name, tables):
    """Fewer rows of the tables give another result, the same as SQL over them."""
    queries, oracles = {**methods.QUERIES, **relational.QUERIES}, {**methods.ORACLES, **relational.ORACLES}
    con, seen = duckdb.connect(), []
    for table in tables.split():
        whole = spark.read.parquet(f"{small}/{table}.parquet")
        few = {"part": "p_partkey <= 12", "supplier": "s_nationkey < 5", "customer": "c_nationkey < 5"}.get(table, "true")
        whole.filter(few).coalesce(1).write.parquet(f"{tmp_path}/{table}.parquet")
    for folder, files in ((small, ""), (str(tmp_path), "/*.parquet")):
        for table in tables.split():
            con.execute(f"create or replace view {table} as select * from '{folder}/{table}.parquet{files}'")
        got, want = queries[name](spark, folder), con.sql(oracles[name])
        assert sorted(got.columns) == sorted(want.columns)
        seen.append(canon([tuple(r) for r in got.collect()], got.columns))
        assert seen[-1] == canon(want.fetchall(), want.columns)
    assert seen[0] != seen[1]
