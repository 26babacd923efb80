"""Runs the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one line of JSON."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from stratasum.operators import lloyd as L
from stratasum.operators import markov as M
from stratasum.operators import set_aggregates as A
from stratasum.plans import fixpoint as X
from stratasum.queries import methods
from stratasum.sources import flows

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def _parts(strategy: str, **options):
    def run(spark: SparkSession) -> dict:
        wide = flows.part_points(spark, SF_DIR)
        return _facts(L.lloyd(flows.tall(wide) if strategy == "tall" else wide, L.seeds(wide, 10), steps=5, eps=None, strategy=strategy, **options))

    return run


def _facts(out: X.FixpointResult) -> dict:
    body = sum(t.body_rows or 0 for t in out.trace)
    seconds = sum(t.seconds for t in out.trace)
    last = out.trace[-1]
    return {"steps": out.steps, "body_rows": body, "rows_per_s": round(body / seconds) if seconds else None, "seconds_a_step": round(seconds / max(1, out.steps), 3), "retained_rows": last.retained_rows, "jobs_a_step": round(sum(t.jobs for t in out.trace) / max(1, out.steps), 1), **last.more}


def _nation(**options):
    return lambda spark: _facts(M.markov(flows.nation_flow(spark, SF_DIR), eps=1e-6, **options))


def _succession(**options):
    return lambda spark: _facts(M.markov(flows.part_flow(spark, SF_DIR), steps=5, **options))


def _reloading(spark: SparkSession) -> dict:
    """The same five steps, each a job that reads and derives the arcs anew."""
    read = lambda: flows.part_flow(spark, SF_DIR)
    return {"rows": M.reloading_steps(read, M.seed_from_self_arcs(read()), 5).count()}


def _ranks(spark: SparkSession) -> dict:
    return _facts(M.link_rank(flows.part_flow(spark, SF_DIR, repaired=False), steps=5))


def _programs(finish: str, top: str):
    def run(spark: SparkSession) -> dict:
        arcs = X.keep(flows.nation_flow(spark, SF_DIR))
        return _facts(methods.markov_program(finish, top).run({"arc": arcs}, X.converged(1e-6) | X.max_steps(M.STEPS)).loops["mass"])

    return run


def _embeddings(spark: SparkSession) -> dict:
    wide = flows.embedding_points(spark, SF_DIR)
    return _facts(L.lloyd(wide, L.seeds(wide, 10), steps=5, eps=None, strategy="arrow"))


def _orders(spark: SparkSession) -> dict:
    wide = flows.order_points(spark, SF_DIR)
    return _facts(L.lloyd(wide, L.seeds(wide, 10), steps=3, eps=None, strategy="arrow"))


#: Arcs that two ways of evaluation are timed on, made before.
PREPARED: dict = {}


def _reach(how: str):
    def run(spark: SparkSession) -> dict:
        return {"rows": X.reachable_from(PREPARED["part_arcs"], 1, how).count()}

    return run


def _chains(how: str):
    """All pairs of an order and a later one of its customer: many rounds, each with fewer new facts."""

    def run(spark: SparkSession) -> dict:
        return {"rows": X.closure(PREPARED["chains"], strategy=how).count()}

    return run


def _listed_paths(spark: SparkSession) -> dict:
    flows.event_flow(spark, SF_DIR).createOrReplaceTempView("listed_arcs")
    return {"rows": M.stratified_masses(spark, "listed_arcs", 6).count(), "facts": sum(5 ** (k + 1) for k in range(7))}


def _staged_paths(spark: SparkSession) -> dict:
    return _facts(M.markov(flows.event_flow(spark, SF_DIR), steps=6, retain="all"))


def _orderings(spark: SparkSession) -> dict:
    return {"facts": A.permutation_facts(flows.supplier_items(spark, SF_DIR).orderBy("item").limit(7), "item").count()}


def _one_order(spark: SparkSession) -> dict:
    return {"facts": A.facts(flows.supplier_items(spark, SF_DIR).orderBy("item").limit(7), "count", None, ["item"]).count()}


RUNS = {
    "markov_nations_converged": _nation(),
    "markov_nations_verify": _nation(certify="verify"),
    "markov_nations_goal": _nation(certify="goal"),
    "program_nations_last_delta": _programs("complete", "last_delta"),
    "markov_parts_auto": _succession(),
    "markov_parts_shuffle": _succession(strategy="shuffle"),
    "markov_parts_salted": _succession(strategy="salted"),
    "markov_parts_keep_all": _succession(retain="all"),
    "markov_parts_reloading": _reloading,
    "link_rank_parts": _ranks,
    "lloyd_parts_tall": _parts("tall"),
    "lloyd_parts_tall_verify": _parts("tall", certify="verify"),
    "lloyd_parts_array": _parts("array"),
    "lloyd_parts_arrow": _parts("arrow"),
    "lloyd_embeddings_arrow": _embeddings,
    "lloyd_orders_arrow": _orders,
    "reach_semi_naive": _reach("semi_naive"),
    "reach_naive": _reach("naive"),
    "chains_semi_naive": _chains("semi_naive"),
    "chains_naive": _chains("naive"),
    "paths_listed": _listed_paths,
    "paths_staged": _staged_paths,
    "count_all_orderings": _orderings,
    "count_one_order": _one_order,
}
FRAMES = ["agg_final_sum_precount", "agg_running_sum_prefix", "grp_final_sum_eof", "grp_strategy_agreement"]


def _shuffled(spark: SparkSession) -> int:
    """Bytes that shuffles have written so far."""
    found = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    return sum(found.apply(i).totalShuffleWrite() for i in range(found.size()))


def _warm(spark: SparkSession) -> None:
    """Small runs of both kinds of loops, so that no query pays for code that others use as well, and the prepared arcs."""
    arcs = X.keep(spark.range(8).selectExpr("id AS src", "id + 1 AS dst", "1D AS share"))
    for how in ("semi_naive", "naive"):
        X.reachable_from(arcs, 0, how).count()
    PREPARED["part_arcs"] = X.keep(flows.part_weights(spark, SF_DIR).select("src", "dst").distinct())
    PREPARED["chains"] = flows.order_chains(spark, SF_DIR)[0]
    M.markov(spark.range(4).selectExpr("id AS src", "id AS dst", "1D AS share"), steps=2)


def main() -> None:
    conf = {"spark.sql.shuffle.partitions": CPUS, "spark.driver.memory": "8g", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC"}
    spark = SparkSession.builder.master(f"local[{CPUS}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    _warm(spark)
    frames = {name: (lambda s, q=methods.QUERIES[name]: q(s, SF_DIR).write.format("noop").mode("overwrite").save()) for name in FRAMES}
    took, facts = {}, {}
    for name, run in (RUNS | frames).items():
        began, before = time.time(), _shuffled(spark)
        found = run(spark) or {}
        took[name] = round(time.time() - began, 3)
        facts[name] = found | {"shuffle_mb": round((_shuffled(spark) - before) / 1e6, 2)}
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "facts": facts, "sf": SF_DIR.rstrip("/").rpartition("sf")[2]}))


if __name__ == "__main__":
    main()
