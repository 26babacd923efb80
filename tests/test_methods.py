import math

import pytest
from pyspark.sql import functions as F

from stratasum.operators import lloyd as L
from stratasum.operators import markov as M
from stratasum.operators import set_aggregates as A
from stratasum.plans import datalog as D
from stratasum.plans import fixpoint as X
from stratasum.plans import materialize as mat
from stratasum.plans.program import Literal, NotStratifiable, Program, Rule, drop_count_stratum, last_delta, negation_to_lookup
from stratasum.queries import methods
from stratasum.sources import flows


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame([(k, v) for k, v in enumerate((5, -3, 8, 8, 0))], "item bigint, cents bigint")


@pytest.mark.parametrize("n", [1, 2, 4, 5])
def test_definitional_count_has_all_orders(spark, n):
    got = A.permutation_facts(spark.range(n).withColumnRenamed("id", "item"), "item")
    assert got.count() == sum(math.factorial(n) // math.factorial(n - k) for k in range(1, n + 1))
    assert sorted({r["counter"] for r in got.collect()}) == list(range(1, n + 1))


def test_definitional_count_refuses_large_sets(spark):
    with pytest.raises(ValueError):
        A.permutation_facts(spark.range(8).withColumnRenamed("id", "item"), "item")


@pytest.mark.parametrize("kind,wanted", [("count", 5), ("sum", 18), ("avg", 3.6), ("max", 8), ("min", -3), ("sum_squares", 162)])
def test_strategies_agree(items, kind, wanted):
    for strategy in ("complete", "negation", "max_running", "precount"):
        for mode in ("window", "prefix"):
            rows = A.final(items, kind, "cents", ["item"], strategy, mode=mode).collect()
            assert [float(r["value"]) for r in rows] == [wanted], (strategy, mode)


def test_declared_sizes(items):
    assert A.final(items, "sum", "cents", ["item"], "precount", 5).first()["value"] == 18
    assert A.final(items, "sum", "cents", ["item"], "precount", 9).count() == 0
    with pytest.raises(Exception, match="more than 3"):
        A.final(items, "sum", "cents", ["item"], "precount", 3).collect()


def test_values_and_bindings(items):
    assert A.as_set(items, ["item"], "cents").count() == 5
    assert A.as_set(items, ["item"], "cents", distinct_values=True).count() == 4


def test_continuous_facts_only_grow(items):
    less = {tuple(r) for r in A.facts(items.filter("item < 3"), "sum", "cents", ["item"]).collect()}
    more = {tuple(r) for r in A.facts(items, "sum", "cents", ["item"]).collect()}
    assert less < more


def test_empty_set(spark):
    none = spark.createDataFrame([], "item bigint, cents bigint")
    assert A.final(none, "count", "cents", ["item"]).first()["value"] == 0
    assert A.final(none, "sum", "cents", ["item"], "negation").count() == 0


def test_grouped_global_counter(spark):
    pairs = spark.createDataFrame([("a", 1, 10), ("b", 2, 20), ("a", 3, 5)], "grp string, item bigint, cents bigint")
    got = {(r["grp"], r["counter"]): r["running"] for r in A.grouped_running(pairs, ["grp"], "cents", ["item"], counter="global").collect()}
    assert got == {("a", 0): 0, ("a", 1): 10, ("a", 2): 10, ("a", 3): 15, ("b", 0): 0, ("b", 1): 0, ("b", 2): 20, ("b", 3): 20}
    values = A.compare_strategies(pairs, ["grp"], "cents", ["item"]).groupBy("grp").agg(F.count_distinct("value").alias("n"))
    assert {r["n"] for r in values.collect()} == {1}


ARCS = "src bigint, dst bigint, share double"


def test_two_nodes(spark):
    arcs = spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5), (2, 1, 1.0)], ARCS)
    start = spark.createDataFrame([(1, 1e5), (2, 1e5)], "node bigint, mass double")
    rows = {(r["step"], r["node"]): r["mass"] for r in M.markov(arcs, start, steps=5, retain="all").history.collect()}
    assert [rows[k, 1] for k in range(1, 6)] == [150000, 125000, 137500, 131250, 134375]
    assert rows[5, 2] == 65625
    assert {tuple(r) for r in M.validate(arcs).collect()} == {(2, "no_self_arc")}
    assert [r["node"] for r in M.seed_from_self_arcs(arcs).collect()] == [1]


def test_equal_flows_count_each(spark):
    arcs = spark.createDataFrame([(1, 1, 0.5), (1, 3, 0.5), (2, 2, 0.5), (2, 3, 0.5), (3, 3, 1.0)], ARCS)
    got = {r["node"]: r["mass"] for r in M.markov(arcs, steps=1).final.collect()}
    assert got == {1: 50000, 2: 50000, 3: 200000}


def test_identity_stops_at_once(spark):
    arcs = spark.createDataFrame([(1, 1, 1.0), (2, 2, 1.0)], ARCS)
    out = M.markov(arcs, eps=0.0)
    assert (out.steps, out.stopped_by) == (1, "converged")
    assert M.markov(arcs, steps=0).final.count() == 2


def test_certificates(spark):
    arcs = spark.createDataFrame([(1, 2, 1.0), (2, 2, 1.0), (3, 1, 1.0)], ARCS)
    start = spark.createDataFrame([(1, 1.0), (2, 1.0), (3, 1.0)], "node bigint, mass double")
    with pytest.raises(X.CertificateBroken):
        M.markov(arcs, start, steps=3, certify="verify")
    closed = spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5), (2, 1, 0.5), (2, 2, 0.5)], ARCS)
    out = M.markov(closed, steps=3, certify="verify", retain="all")
    assert [t.body_rows for t in out.trace[1:]] == [4, 4, 4]
    goal = M.markov(closed, steps=3, certify="goal", retain="all")
    assert {tuple(r) for r in goal.history.collect()} == {tuple(r) for r in out.history.collect()}
    assert {tuple(r) for r in X.last_step(out.history).collect()} == {tuple(r) for r in out.final.select("step", "node", "mass").collect()}


def test_repair(spark):
    weights = spark.createDataFrame([(1, 2, 3.0), (1, 3, 1.0)], "src bigint, dst bigint, weight double")
    arcs = M.transition(M.repair(weights))
    assert M.validate(arcs).count() == 0
    assert {(r["src"], r["dst"]): r["share"] for r in arcs.collect()} == {(1, 1): 0.5, (1, 2): 0.375, (1, 3): 0.125, (2, 2): 1.0, (3, 3): 1.0}


def test_stratification():
    staged = Rule("mass", (Literal("mass", shift=1), Literal("arc")), "sum")
    Program((staged, Rule("last", (Literal("mass"),), "max"))).strata()
    lloyd = (Rule("dist", (Literal("point"), Literal("centre")), "sum"), Rule("near", (Literal("dist"),), "min"), Rule("centre", (Literal("near", shift=1), Literal("point")), "avg"))
    Program(lloyd).strata()
    with pytest.raises(NotStratifiable):
        Program((Rule("p", (Literal("p"), Literal("arc")), "sum"),)).strata()
    with pytest.raises(NotStratifiable):
        Program((Rule("p", (Literal("q", negated=True),)), Rule("q", (Literal("p"),)))).strata()
    Program((Rule("p", (Literal("p", certified=True),), "sum"),)).strata()


def test_rewrites():
    p = Program((Rule("size_of_p", (Literal("p"),), "count"), Rule("total", (Literal("p"), Literal("size_of_p")), "sum", "negation"), Rule("end", (Literal("mass"),), None, "max_stage")))
    q = drop_count_stratum(negation_to_lookup(p))
    assert [r.head for r in q.rules] == ["total", "end"] and q.rules[0].finish == "complete"
    assert last_delta(p, "mass").rules[2].finish == "last_delta"


def test_paths(spark):
    arcs = spark.createDataFrame([(1, 2, 1.0), (2, 3, 1.0), (1, 3, 5.0), (3, 1, 1.0), (4, 1, 1.0)], "src bigint, dst bigint, cost_of double")
    got = {r["node"]: r["cost"] for r in X.min_in_recursion(arcs, 1).collect()}
    assert got == {1: 0.0, 2: 1.0, 3: 2.0}
    assert {r["node"]: r["cost"] for r in X.stratified_min(arcs, 1, 3).collect()} == got
    facts = spark.createDataFrame([(1, 0.0), (1, 4.0), (2, 1.0)], "node bigint, cost double")
    assert X.check_premappable(arcs, facts)
    want = {1, 2, 3}
    assert {r["node"] for r in X.reachable_from(arcs, 1).collect()} == {r["node"] for r in X.reachable_from(arcs, 1, "naive").collect()} == want
    assert {r["dst"] for r in X.closure(arcs).filter("src = 1").collect()} == want
    seed = spark.createDataFrame([(1,), (2,)], "node bigint")
    assert {r["node"] for r in X.monotone_threshold(arcs, seed, 2).collect()} == {1, 2, 3}


def _wide(spark, rows):
    return spark.createDataFrame([(k, [float(x) for x in v]) for k, v in enumerate(rows)], "point_id bigint, v array<double>")


def _tall(wide):
    return wide.select("point_id", F.posexplode("v").alias("dim", "val"))


@pytest.mark.parametrize("strategy", ["tall", "array", "arrow"])
def test_four_points(spark, strategy):
    wide = _wide(spark, [[0], [1], [10], [11]])
    centres = L._centre_rows(spark, [0, 1], __import__("numpy").array([[0.0], [10.0]]))
    out = L.lloyd(_tall(wide) if strategy == "tall" else wide, centres, strategy=strategy)
    assert sorted(r["val"] for r in out.final.collect()) == [0.5, 10.5]
    assert out.trace[-1].more["objective"] == 1.0
    objective = [t.more["objective"] for t in out.trace[1:]]
    assert objective == sorted(objective, reverse=True)


def test_ties_empty_and_equal_coordinates(spark):
    import numpy as np

    tie = L.predict(_wide(spark, [[5]]), L._centre_rows(spark, [0, 1], np.array([[0.0], [10.0]])))
    assert tie.first()["centre_id"] == 0
    wide, centres = _wide(spark, [[0], [1]]), L._centre_rows(spark, [0, 1, 2], np.array([[0.0], [1.0], [100.0]]))
    assert L.lloyd(wide, centres, steps=1, eps=None, empty="drop").final.count() == 2
    assert {r["val"] for r in L.lloyd(wide, centres, steps=1, eps=None, empty="keep").final.collect()} == {0.0, 1.0, 100.0}
    assert {r["val"] for r in L.lloyd(wide, centres, steps=1, eps=None, empty="farthest").final.collect()} <= {0.0, 1.0}
    one = L.lloyd(_wide(spark, [[0], [0], [3]]), L._centre_rows(spark, [0], np.array([[9.0]])))
    assert one.final.first()["val"] == 1.0
    with pytest.raises(ValueError):
        L.seeds(wide, 5)


@pytest.mark.parametrize("how", ["first", "random", "farthest", "plusplus", "parallel"])
def test_seeds_are_points(spark, how):
    wide = _wide(spark, [[k, k * k] for k in range(30)])
    got = L.seeds(wide, 4, how, seed=3).filter("dim = 0").collect()
    assert len(got) == 4 and len({r["val"] for r in got}) == 4


def test_packed_minimum(spark):
    d = spark.createDataFrame([(1, 0, 4.0), (1, 1, 4.0), (1, 2, 9.0), (2, 1, 3.0)], "point_id bigint, centre_id int, d double")
    for pack in ("struct", "bits"):
        assert {(r["point_id"], r["centre_id"]) for r in L.nearest(d, pack).collect()} == {(1, 0), (2, 1)}


def test_plans(spark, small):
    from stratasum.sources import flows

    def plan(df):
        return df._jdf.queryExecution().executedPlan().toString()

    total = plan(A.final(flows.supplier_items(spark, small), "sum", "cents", ["item"]))
    assert total.count("Exchange") == 1 and "ReadSchema: struct<s_acctbal:double>" in total
    running = plan(A.running(flows.part_items(spark, small), "sum", "cents", ["item"], "prefix"))
    assert "CartesianProduct" not in running
    pruned = plan(flows.nation_weights(spark, small))
    assert "l_extendedprice" not in pruned


def test_global_counter_over_all_orders(spark, small):
    pairs = flows.order_pairs(spark, small).orderBy("item").collect()
    groups = sorted({r["grp"] for r in pairs})
    sums, want = dict.fromkeys(groups, 0), [(g, 0, 0) for g in groups]
    for n, r in enumerate(pairs, 1):
        sums[r["grp"]] += r["cents"]
        want += [(g, n, sums[g]) for g in groups]
    got = methods.QUERIES["grp_running_sum_global"](spark, small).collect()
    assert sorted((r["grp"], r["counter"], r["running"]) for r in got) == sorted(want)
    final = methods.QUERIES["grp_final_sum_precount"](spark, small).collect()
    assert sorted((r["grp"], r["value"]) for r in final) == sorted(sums.items())


@pytest.mark.parametrize("name", ["fix_reachability", "fix_reachability_naive"])
def test_reachability_over_all_parts(spark, name, tmp_path):
    parts = [1, 250, 900, 7, 5000, 1, 12, 13]  # one order after the other: paths through large numbers
    rows = [(1, k, p) for k, p in enumerate(parts[:5])] + [(2, k, p) for k, p in enumerate(parts[5:7])] + [(3, 0, 13), (3, 1, 12)]
    spark.createDataFrame([(o, k, p, 1) for o, k, p in rows], "l_orderkey bigint, l_linenumber int, l_partkey bigint, l_suppkey bigint").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = methods.QUERIES[name](spark, str(tmp_path))
    assert sorted(r["node"] for r in got.collect()) == [1, 7, 12, 250, 900, 5000]


@pytest.mark.parametrize("name", ["premap_shortest", "premap_shortest_stratified"])
def test_shortest_over_all_suppliers(spark, name, tmp_path):
    orders = [[1, 50, 70, 2], [1, 3], [1, 3], [3, 50], [3, 90], [70, 4], [50, 50]]
    rows = [(o, k, 1, s) for o, own in enumerate(orders) for k, s in enumerate(own)]
    spark.createDataFrame(rows, "l_orderkey bigint, l_linenumber int, l_partkey bigint, l_suppkey bigint").write.parquet(f"{tmp_path}/lineitem.parquet")
    arcs = [(a, b) for own in orders for a, b in zip(own, own[1:], strict=False)]
    cost = {(a, b): 1 - arcs.count((a, b)) / sum(x == a for x, _ in arcs) for a, b in arcs}
    best = {1: 0.0}
    for _ in range(3):  # no least path has more arcs
        for (a, b), c in cost.items():
            if a in best:
                best[b] = min(best.get(b, math.inf), best[a] + c)
    got = {r["node"]: r["cost"] for r in methods.QUERIES[name](spark, str(tmp_path)).collect()}
    assert set(got) == {1, 2, 3, 4, 50, 70, 90} and got == pytest.approx(best, abs=1e-6)


# ---- loops that must not end in silence


def chain_of(spark, n):
    return spark.createDataFrame([(k, k + 1, 1.0) for k in range(n)], "src bigint, dst bigint, cost_of double")


@pytest.mark.parametrize("strategy", ["semi_naive", "naive"])
def test_bounded_rounds_raise(spark, strategy):
    arcs = chain_of(spark, 11)
    with pytest.raises(X.RoundsExceeded):
        X.reachable_from(arcs, 0, strategy, rounds=3)
    assert X.reachable_from(arcs, 0, strategy, rounds=20).count() == 12
    assert X.reachable_from(arcs, 0, strategy).count() == 12


def test_bounds_of_other_loops_raise(spark):
    arcs = chain_of(spark, 6)
    with pytest.raises(X.RoundsExceeded):
        X.min_in_recursion(arcs, 0, rounds=2)
    assert X.min_in_recursion(arcs, 0).count() == 7
    seed = spark.createDataFrame([(0,)], "node bigint")
    with pytest.raises(X.RoundsExceeded):
        X.monotone_threshold(arcs, seed, 1, rounds=2)
    assert X.monotone_threshold(arcs, seed, 1).count() == 7
    with pytest.raises(X.RoundsExceeded):
        X.closure(arcs, rounds=1)


def test_threshold_counts_each_arc_once(spark):
    arcs = spark.createDataFrame([(1, 3), (1, 3), (2, 3), (3, 4), (1, 4), (4, 5), (9, 5)], "src bigint, dst bigint")
    seed = spark.createDataFrame([(1,), (2,), (1,)], "node bigint")
    assert {r["node"] for r in X.monotone_threshold(arcs, seed, 2).collect()} == {1, 2, 3, 4}


def test_facts_with_more_columns(spark):
    base = spark.createDataFrame([(0, "a")], "node bigint, why string")
    arcs = chain_of(spark, 4)
    out, sizes = X.semi_naive(base, lambda d: d.join(arcs, d["node"] == arcs["src"]).select(arcs["dst"].alias("node"), F.concat("why", F.lit("b")).alias("why")), ["node"])
    assert {r["node"]: r["why"] for r in out.collect()} == {k: "a" + "b" * k for k in range(5)} and sizes == [1, 1, 1, 1, 1, 0]


def test_end_of_chain(spark):
    assert [r["step"] for r in X.end_of_chain(spark.range(8).select(F.col("id").cast("int").alias("step"))).collect()] == [7]


# ---- the chain


def closed_arcs(spark):
    return spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5), (2, 1, 0.5), (2, 2, 0.5)], ARCS)


def test_a_wrong_size_raises_in_the_goal_form(spark):
    body = spark.createDataFrame([(k % 3, k, float(k)) for k in range(30)], "dst int, src int, flow double")
    for n in (29, 31):
        with pytest.raises(Exception, match="has 30 rows"):
            M.sums_at_count(body, "dst", ["flow"], X.Certificate("flow", n))


def test_goal_sums_of_a_hub(spark):
    """One group takes most of the rows, and goes over all parts."""
    rows = [(7 if k % 10 else k, k, float(k), 1.0) for k in range(1000)]
    body = spark.createDataFrame(rows, "dst int, src int, flow double, one double")
    got = {r["dst"]: (r["flow"], r["one"]) for r in M.sums_at_count(body.repartition(7), "dst", ["flow", "one"], X.Certificate("flow", 1000)).collect()}
    want = {}
    for d, _, f, o in rows:
        a, b = want.get(d, (0.0, 0.0))
        want[d] = (a + f, b + o)
    assert got == want


@pytest.mark.parametrize("strategy", ["auto", "broadcast", "shuffle", "salted"])
def test_steps_read_placed_arcs(spark, small, strategy):
    chain = M.Chain(flows.nation_flow(spark, small), strategy)
    state = spark.createDataFrame([(k, 1.0) for k in range(25)], "node int, mass double")
    plan = M.Chain.gather(chain.body(state))._jdf.queryExecution().executedPlan().toString()
    assert "lineitem" not in plan
    assert plan.count("Scan parquet") == 1


def test_bucketed_arcs_are_not_shuffled(spark):
    arcs = spark.range(2000).select(F.col("id").alias("src"), ((F.col("id") * 7) % 2000).alias("dst"), F.lit(1.0).alias("share"))
    chain = M.Chain(arcs, "shuffle")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        body = chain.body(spark.range(2000).select(F.col("id").alias("node"), F.lit(1.0).alias("mass")))
        plan = body._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert plan.count("Exchange hashpartitioning") == 1 and body.count() == 2000  # the state's


def test_validate_bad_shares(spark):
    arcs = spark.createDataFrame([(1, 1, 1.5), (1, 2, -0.5), (2, 2, None)], ARCS)
    found = {tuple(r) for r in M.validate(arcs).collect()}
    assert {(1, "bad_share"), (2, "bad_share"), (2, "no_self_arc")} <= found


def test_limit_of_a_chain(spark):
    arcs = spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5), (2, 1, 1.0)], ARCS)
    start = spark.createDataFrame([(1, 1e5), (2, 1e5)], "node bigint, mass double")
    got = {r["node"]: r["mass"] for r in M.limit_of(arcs, start).collect()}
    assert abs(got[1] - 4e5 / 3) < 1e-4 and abs(got[2] - 2e5 / 3) < 1e-4
    with pytest.raises(ValueError):
        M.limit_of(arcs, start, most=1)


def test_what_is_retained(spark):
    for retain, want in (("last", 2), ("window:2", 4), ("all", 8), ("chain_max", 8)):
        out = M.markov(closed_arcs(spark), steps=3, retain=retain)
        assert out.trace[-1].retained_rows == want
        assert {r["step"] for r in out.final.collect()} == {3}
    assert all(t.jobs > 0 for t in out.trace[1:])


def test_link_rank_keeps_mass_at_dangling_nodes(spark):
    arcs = spark.createDataFrame([(1, 2, 1.0)], ARCS)
    for rule in ("uniform", "self"):
        got = {r["node"]: r["mass"] for r in M.link_rank(arcs, steps=30, dangling=rule).final.collect()}
        if rule == "uniform":
            assert abs(sum(got.values()) - 1) < 1e-9
        else:
            assert abs(got[1] - 0.075) < 1e-9 and abs(got[2] - (0.075 + 0.85 * 0.075) / 0.15) < 0.02
    with pytest.raises(ValueError):
        M.link_rank(arcs, dangling="no")


# ---- clustering


def wide_points(spark, rows):
    return spark.createDataFrame(rows, "point_id bigint, v array<double>")


def centre_table(spark, rows):
    return spark.createDataFrame(rows, "centre_id int, dim int, val double")


def final_centres(out):
    return {(r["centre_id"], r["dim"]): r["val"] for r in out.final.collect()}


def test_null_points_are_no_points(spark):
    wide = wide_points(spark, [(1, [0.0]), (2, None), (3, [3.0])])
    start = centre_table(spark, [(0, 0, 1.0)])
    for strategy in ("array", "arrow", "tall"):
        points = L.tall_vectors(wide, "point_id", "v") if strategy == "tall" else wide
        out = L.lloyd(points, start, steps=1, eps=None, strategy=strategy)
        assert final_centres(out) == {(0, 0): 1.5}
        assert out.trace[-1].more["objective"] == 5.0


@pytest.mark.parametrize("odd", [[1.0], [1.0, None], [1.0, 2.0, 3.0]])
def test_odd_points_raise(spark, odd):
    wide = wide_points(spark, [(1, [0.0, 0.0]), (2, odd)])
    start = centre_table(spark, [(0, 0, 1.0), (0, 1, 1.0)])
    for strategy in ("array", "arrow"):
        with pytest.raises(Exception, match="coordinate"):
            L.lloyd(wide, start, steps=1, strategy=strategy)
    tall = wide.select("point_id", F.posexplode("v").alias("dim", "val"))
    with pytest.raises(Exception, match="coordinate|rows, not"):
        L.lloyd(tall, start, steps=1, strategy="tall", certify="verify")


@pytest.mark.parametrize("certify", ["complete", "verify", "goal"])
def test_dims_may_be_any_numbers(spark, certify):
    rows = [(p, d, float(v)) for p, xy in enumerate([(0, 0), (1, 0), (10, 4), (11, 4)]) for d, v in zip((5, 9), xy, strict=True)]
    points = spark.createDataFrame(rows, "point_id bigint, dim int, val double")
    start = centre_table(spark, [(0, 5, 0.0), (0, 9, 0.0), (1, 5, 10.0), (1, 9, 0.0)])
    out = L.lloyd(points, start, steps=4, strategy="tall", certify=certify)
    assert final_centres(out) == {(0, 5): 0.5, (0, 9): 0.0, (1, 5): 10.5, (1, 9): 4.0}
    assert out.stopped_by == "converged" and [t.more["empty"] for t in out.trace[1:]] == [0, 0]
    if certify != "goal":
        assert out.trace[1].bodies["distance"] == 16 and out.trace[1].bodies["mean"] == 8


def test_a_repeated_coordinate_breaks_its_certificate(spark):
    points = spark.createDataFrame([(1, 0, 1.0), (1, 0, 1.0), (2, 0, 4.0)], "point_id bigint, dim int, val double")
    start = centre_table(spark, [(0, 0, 0.0)])
    with pytest.raises(X.CertificateBroken):
        L.lloyd(points, start, steps=1, strategy="tall", certify="verify")
    with pytest.raises(Exception, match="does not have|rows, not"):
        L.lloyd(points, start, steps=1, strategy="tall", certify="goal")


@pytest.mark.parametrize("rule,want", [("keep", {0: 0.0, 1: 1.0, 2: 100.0}), ("drop", {0: 0.0, 1: 1.0}), ("farthest", {0: 0.0, 1: 1.05, 2: 1.5})])
def test_empty_centres_alike_in_all_strategies(spark, rule, want):
    wide = wide_points(spark, [(1, [0.0]), (2, [1.0])] if rule != "farthest" else [(1, [0.0]), (2, [0.6]), (3, [1.5])])
    start = centre_table(spark, [(0, 0, 0.0), (1, 0, 1.0), (2, 0, 100.0)])
    for strategy in ("array", "arrow", "tall"):
        points = L.tall_vectors(wide, "point_id", "v") if strategy == "tall" else wide
        out = L.lloyd(points, start, steps=1, eps=None, strategy=strategy, empty=rule)
        assert {c: round(v, 6) for (c, _), v in final_centres(out).items()} == want, strategy
        assert out.trace[1].more["empty"] == 1


def test_no_points(spark):
    start = centre_table(spark, [(0, 0, 2.0)])
    for strategy in ("array", "arrow", "tall"):
        points = spark.createDataFrame([], "point_id bigint, dim int, val double") if strategy == "tall" else wide_points(spark, [])
        assert final_centres(L.lloyd(points, start, steps=3, strategy=strategy)) == {(0, 0): 2.0}


def test_bits_refuse_fractions(spark):
    far = spark.createDataFrame([(1, 0, 0.4), (1, 1, 0.1)], "point_id bigint, centre_id int, d double")
    with pytest.raises(Exception, match="no whole distance"):
        L.nearest(far, "bits").collect()
    assert L.nearest(far).first()["centre_id"] == 1
    assert L.nearest(far.withColumn("d", F.col("d") * 10), "bits").first()["centre_id"] == 1


def test_many_centres_are_refused_before_they_are_collected(spark, monkeypatch):
    monkeypatch.setattr(L, "CENTRE_NUMBERS", 3)
    start = centre_table(spark, [(k, 0, float(k)) for k in range(4)])
    wide = wide_points(spark, [(1, [0.0]), (2, [3.0])])
    with pytest.raises(ValueError, match="too many centres"):
        L.lloyd(wide, start, steps=1)
    out = L.lloyd(L.tall_vectors(wide, "point_id", "v"), start, steps=1, eps=None, strategy="tall")  # dealt by dim instead
    assert final_centres(out) == {(k, 0): float(k) for k in range(4)}


def test_reassigned(spark):
    wide = wide_points(spark, [(k, [float(k)]) for k in range(5)])
    assert L.reassigned(wide, centre_table(spark, [(0, 0, 0.0), (1, 0, 4.0)]), centre_table(spark, [(0, 0, 0.0), (1, 0, 2.0)])).first()["n"] == 1


# ---- programs


def test_rewrites_change_what_the_loop_keeps(spark):
    arcs = closed_arcs(spark)
    program = methods.markov_program(finish="negation", top="max_stage")
    stop = X.max_steps(3)
    kept = program.run({"arc": arcs}, stop)
    fewer = last_delta(drop_count_stratum(negation_to_lookup(program)), "mass").run({"arc": arcs}, stop)
    rows = lambda e: {(r["step"], r["node"], r["mass"]) for r in e.frames["final"].select("step", "node", "mass").collect()}
    assert rows(kept) == rows(fewer) == {(3, 1, 1e5), (3, 2, 1e5)}
    assert kept.loops["mass"].trace[-1].retained_rows == 8 and fewer.loops["mass"].trace[-1].retained_rows == 2
    assert fewer.loops["mass"].trace[-1].jobs < kept.loops["mass"].trace[-1].jobs or fewer.loops["mass"].trace[-1].jobs <= 6


def test_precounted_groups_must_keep_their_size(spark):
    arcs = spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5), (2, 3, 1.0), (3, 3, 1.0)], ARCS)  # node 2 starts without mass
    with pytest.raises(Exception, match="certified size"):
        methods.markov_program(finish="precount").run({"arc": arcs}, X.max_steps(3))


def test_recursion_needs_a_stop_rule(spark):
    with pytest.raises(ValueError, match="stop rule"):
        methods.markov_program().run({"arc": closed_arcs(spark)})


def test_strata_of_a_program_that_counts(spark):
    items = spark.createDataFrame([("a", 1, 5), ("a", 2, 6), ("b", 3, 7)], "grp string, item int, cents bigint")
    for finish in ("complete", "precount", "negation", "max_running"):
        rule = Rule("total", (Literal("items"),), "sum", finish, lambda f: f["items"], ("grp",), "cents", ("item",), "total")
        got = Program((rule,)).run({"items": items}).frames["total"]
        assert {tuple(r) for r in got.collect()} == {("a", 11), ("b", 7)}


# ---- bindings pushed into recursion


def brute_paths(arcs):
    found = set(arcs)
    while True:
        more = found | {(a, d) for a, b in found for c, d in arcs if b == c}
        if more == found:
            return found
        found = more


@pytest.mark.parametrize("seed", [1, 2])
def test_pushed_bindings(spark, seed):
    import random

    rng = random.Random(seed)
    arcs = {(rng.randrange(12), rng.randrange(12)) for _ in range(14)}
    frame = spark.createDataFrame(sorted(arcs), "c0 bigint, c1 bigint")
    want = {z for x, z in brute_paths(arcs) if x == 3}
    plain = None
    for rules in (methods.LEFT_LINEAR, methods.RIGHT_LINEAR):
        for push in (False, True):
            out, found = D.ask(rules, {"arc": frame}, D.Atom("path", (3, "z")), push)
            assert {r["z"] for r in out.collect()} == want
            n = sum(v for k, v in found.facts.items() if k.startswith("path"))
            if not push:
                plain = n
            assert n <= plain


def test_constants_and_repeated_variables(spark):
    frame = spark.createDataFrame([(1, 1), (1, 2), (2, 2), (3, 1)], "c0 bigint, c1 bigint")
    rules = [D.Clause(D.Atom("own", ("x",)), (D.Atom("arc", ("x", "x")),)), D.Clause(D.Atom("one", ("x",)), (D.Atom("arc", ("x", 1)), D.Atom("own", ("x",))))]
    out = D.evaluate(rules, {"arc": frame})
    assert {r["c0"] for r in out.frames["own"].collect()} == {1, 2} and [r["c0"] for r in out.frames["one"].collect()] == [1]
    with pytest.raises(ValueError):
        D.evaluate([D.Clause(D.Atom("all", ("x", "y")), (D.Atom("arc", ("x", 1)), D.Atom("arc", ("y", 2))))], {"arc": frame})


def test_mutual_recursion(spark):
    frame = spark.createDataFrame([(k, k + 1) for k in range(6)], "c0 bigint, c1 bigint")
    zero = spark.createDataFrame([(0,)], "c0 bigint")
    rules = [
        D.Clause(D.Atom("even", ("x",)), (D.Atom("zero", ("x",)),)),
        D.Clause(D.Atom("odd", ("y",)), (D.Atom("even", ("x",)), D.Atom("arc", ("x", "y")))),
        D.Clause(D.Atom("even", ("y",)), (D.Atom("odd", ("x",)), D.Atom("arc", ("x", "y")))),
    ]
    out = D.evaluate(rules, {"arc": frame, "zero": zero})
    assert {r["c0"] for r in out.frames["even"].collect()} == {0, 2, 4, 6} and {r["c0"] for r in out.frames["odd"].collect()} == {1, 3, 5}


# ---- written tables


def test_kept_tables_can_go(spark):
    df, n = mat.keep_counted(spark.range(5))
    assert n == 5 and df.count() == 5
    folder = mat.shared_folder(spark).rpartition("/")[0]
    assert folder.endswith(f"steps/{spark.sparkContext.applicationId}")
    mat.discard(df)
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        spark.read.parquet(df._kept_at).count()
    placed = mat.place_by(spark.range(5), "id")
    mat.discard(placed)
    assert not spark.catalog.tableExists(placed._kept_as)


def test_a_cluster_needs_a_shared_folder():
    class Context:
        master, applicationId = "spark://host:7077", "app"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()

        class conf:
            @staticmethod
            def get(name, default=None):
                return default

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        mat.shared_folder(Session())
