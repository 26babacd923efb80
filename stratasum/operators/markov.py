"""Population flow in a Markov chain: each step sums, for every node, what flows in along its arcs.

Arcs are (src, dst, share), where the shares that leave a node add up to 1. All strategies give the
same states; they differ in what is shuffled. Arcs are computed and placed once, before the first step,
for all of them: `shuffle` deals them by source into buckets, so that steps shuffle states only; `auto`
lets Spark choose over the placed arcs; `broadcast` sends the state to the arcs and falls back beyond a
checked size; `salted` deals the arcs of hub sources over several buckets and copies the state for each.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from stratasum.plans.fixpoint import Certificate, CertificateBroken, FixpointResult, StagedFixpoint, StopRule, Watch, converged, max_steps, shared_count
from stratasum.plans.materialize import keep, keep_counted, observed, place_by

START, STEPS, SALTS = 100_000.0, 1000, 8
#: Rows of a state that may be broadcast.
BROADCAST_ROWS = 5_000_000
#: Nodes of a chain whose limit is solved for on the driver.
SOLVED_NODES = 2000


def transition(weights: DataFrame) -> DataFrame:
    """src, dst, share from src, dst, weight: each weight over the sum of those with its source."""
    summed = weights.groupBy("src", "dst").agg(F.sum("weight").alias("weight"))
    whole = summed.groupBy("src").agg(F.sum("weight").alias("whole"))  # a join, which Spark can split at a hub, not a window
    return summed.join(whole, "src").select("src", "dst", (F.col("weight") / F.col("whole")).alias("share"))


def validate(arcs: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """node, violation: broken preconditions. Shares sum to 1, none is null or negative, arcs are unique, self-arcs exist, no node is a sink."""
    sums = arcs.groupBy("src").agg(F.sum("share").alias("s")).filter(F.abs(F.col("s") - 1) > tolerance).select(F.col("src").alias("node"), F.lit("share_sum").alias("violation"))
    odd = arcs.filter("share is null or share < 0").select(F.col("src").alias("node"), F.lit("bad_share").alias("violation")).distinct()
    twice = arcs.groupBy("src", "dst").count().filter("count > 1").select(F.col("src").alias("node"), F.lit("repeated_arc").alias("violation")).distinct()
    ends = _ends(arcs.withColumn("weight", F.when(F.col("share") > 0, F.lit(1))))
    lonely = ends.filter("selfish = 0").select("node", F.lit("no_self_arc").alias("violation"))
    sinks = ends.filter("leaving = 0").select("node", F.lit("sink").alias("violation"))
    return sums.unionByName(odd).unionByName(twice).unionByName(lonely).unionByName(sinks)


def _ends(arcs: DataFrame) -> DataFrame:
    """node, selfish (has a self-arc of some weight), leaving (arcs that leave it), out (their weight): one aggregate of both ends of each arc."""
    weight = F.col("weight")
    own = F.struct(F.col("src").alias("node"), ((F.col("src") == F.col("dst")) & weight.isNotNull()).cast("int").alias("selfish"), F.lit(1).alias("leaving"), weight.alias("out"))
    other = F.struct(F.col("dst").alias("node"), F.lit(0).alias("selfish"), F.lit(0).alias("leaving"), F.lit(None).cast(arcs.schema["weight"].dataType).alias("out"))
    both = arcs.select(F.explode(F.array(own, other)).alias("e")).select("e.*")
    return both.groupBy("node").agg(F.max("selfish").alias("selfish"), F.sum("leaving").alias("leaving"), F.sum("out").alias("out"))


def repair(weights: DataFrame) -> DataFrame:
    """Weights where every node has a self-arc: one that lacks it gets as much as flows out of it; a pure sink keeps what it gets."""
    summed = keep(weights.groupBy("src", "dst").agg(F.sum("weight").alias("weight")))
    kind = summed.schema["weight"].dataType
    missing = _ends(summed).filter("selfish = 0")
    return summed.unionByName(missing.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.coalesce(F.col("out").cast(kind), F.lit(1).cast(kind)).alias("weight")))


def seed_from_self_arcs(arcs: DataFrame, start: float = START) -> DataFrame:
    """node, mass: the start mass for every node that has an arc to itself."""
    return arcs.filter("src = dst").groupBy(F.col("src").alias("node")).agg(F.sum(F.lit(float(start))).alias("mass"))


class Chain:
    """Arcs placed for a strategy, once, with the body and the sum of a step."""

    def __init__(self, arcs: DataFrame, strategy: str = "auto", salts: int = SALTS):
        if strategy not in ("auto", "broadcast", "shuffle", "salted"):
            raise ValueError(f"no such strategy: {strategy}")
        self.strategy, self.salts = strategy, salts
        arcs = arcs.select("src", "dst", "share")
        if strategy == "salted":
            self.arcs = place_by(arcs.withColumn("salt", F.pmod(F.xxhash64("dst"), F.lit(salts)).cast("int")), "src", "salt")
        elif strategy == "shuffle":
            self.arcs = place_by(arcs, "src")
        else:
            self.arcs = keep(arcs)

    def body(self, state: DataFrame) -> DataFrame:
        """dst, flow: a row for each arc whose source has mass."""
        s = state.select(F.col("node").alias("src"), "mass")
        if self.strategy == "salted":
            s = s.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(self.salts - 1))))
            joined = self.arcs.join(s, ["src", "salt"])
        else:
            if self.strategy == "broadcast" and s.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
                s = F.broadcast(s)
            joined = self.arcs.join(s, "src")
        return joined.select("src", "dst", (F.col("mass") * F.col("share")).alias("flow"))

    @staticmethod
    def gather(body: DataFrame) -> DataFrame:
        return body.groupBy(F.col("dst").alias("node")).agg(F.sum("flow").alias("mass"))


def sums_at_count(body: DataFrame, by: str, values: list[str], certificate: Certificate, watch: Watch | None = None) -> DataFrame:
    """by and the sum of each value: the goal form of grouped sums, with one counter for the whole body.

    The counter runs through the parts of the body, one after the other. Each part makes its running sums
    and counts on its own (Spark's partial aggregate); of its facts only the last of each group are
    needed, since sums and counters go on from part to part. So a hub is no single task's, and where the
    counter ends is known when the sums are written. They are given if it ends at the certified size.
    """
    if watch is not None:
        body = watch(certificate.name, body)
    seen = Observation()
    last = body.groupBy(by).agg(*[F.sum(v).alias(v) for v in values], F.count(F.lit(1)).alias("__n"))
    kept = keep(last.observe(seen, F.sum("__n").alias("size")))
    size = int(observed(seen).get("size") or 0)
    if size != certificate.n:
        raise CertificateBroken(f"{certificate.name} has {size} rows, not {certificate.n}")
    return kept.drop("__n")


def markov(
    arcs: DataFrame,
    start: float | DataFrame = START,
    steps: int = STEPS,
    stop: StopRule | None = None,
    eps: float | None = None,
    retain: str = "last",
    certify: str = "complete",
    strategy: str = "auto",
    measure: str = "drop",
) -> FixpointResult:
    """States of the chain, until no node's mass falls by more than eps, or a cap of steps.

    start: the same mass for each node with a self-arc, or (node, mass) rows. steps=0 reports the start.
    """
    chain = Chain(arcs, strategy)
    seed = start.select("node", F.col("mass").cast("double").alias("mass")) if isinstance(start, DataFrame) else seed_from_self_arcs(chain.arcs, start)
    rule = max_steps(steps)
    if eps is not None:
        rule = converged(eps) | rule
    if stop is not None:
        rule = stop | rule
    certificates = {}
    if certify not in ("complete", "verify", "goal"):
        raise ValueError(f"no such certification: {certify}")
    if certify != "complete":
        seed = keep(seed)
        certificates["flow"] = shared_count(chain.arcs.join(seed.select(F.col("node").alias("src")), "src").select("src", "dst"), "flow")

    def advance(state: DataFrame, watch: Watch) -> DataFrame:
        if certify == "goal":
            return sums_at_count(chain.body(state), "dst", ["flow"], certificates["flow"], watch).select(F.col("dst").alias("node"), F.col("flow").alias("mass"))
        return Chain.gather(watch("flow", chain.body(state)))

    return StagedFixpoint(seed, advance, ["node"], ["mass"], rule, measure, retain, certify, certificates).run()


def limit_of(arcs: DataFrame, start: DataFrame, most: int = SOLVED_NODES) -> DataFrame:
    """node, mass: what an ergodic chain converges to, solved for as a linear system, to measure steps against.

    The system is dense and solved on the driver: chains of more than `most` nodes are refused.
    """
    nodes = arcs.select(F.col("src").alias("node")).union(arcs.select("dst")).union(start.select("node")).distinct()
    names = [r["node"] for r in nodes.orderBy("node").limit(most + 1).collect()]
    if len(names) > most:
        raise ValueError(f"more than {most} nodes")
    place = {n: i for i, n in enumerate(names)}
    share = np.zeros((len(names), len(names)))
    for r in arcs.select("src", "dst", "share").collect():  # at most `most` squared
        share[place[r["dst"]], place[r["src"]]] += r["share"]
    total = start.agg(F.sum("mass")).first()[0] or 0.0
    system = np.vstack([share - np.eye(len(names)), np.ones(len(names))])
    mass = np.linalg.lstsq(system, np.append(np.zeros(len(names)), total), rcond=None)[0]
    return arcs.sparkSession.createDataFrame([(n, float(m)) for n, m in zip(names, mass, strict=True)], f"node {nodes.schema['node'].dataType.simpleString()}, mass double")


def link_rank(arcs: DataFrame, damping: float = 0.85, steps: int = 20, eps: float | None = None, dangling: str = "uniform", retain: str = "last") -> FixpointResult:
    """node, mass: damped ranks of the nodes of arcs (src, dst, share). Mass at nodes without arcs is spread evenly, or stays (`dangling="self"`)."""
    if dangling not in ("uniform", "self"):
        raise ValueError(f"no such rule for dangling nodes: {dangling}")
    arcs = place_by(arcs.select("src", "dst", "share"), "src")
    nodes, n = keep_counted(arcs.select(F.col("src").alias("node")).union(arcs.select("dst")).distinct())
    ends = keep(nodes.join(arcs.select(F.col("src").alias("node")).distinct(), "node", "left_anti"))

    def advance(state: DataFrame, watch: Watch) -> DataFrame:
        body = watch("flow", state.join(arcs, state["node"] == arcs["src"]).select("dst", (F.col("mass") * F.col("share")).alias("flow")))
        lost = state.join(ends, "node", "left_semi").agg(F.coalesce(F.sum("mass"), F.lit(0.0)).alias("lost"))
        own = state.join(ends, "node", "left_semi").select(F.col("node").alias("dst"), F.col("mass").alias("flow"))
        got = (body.unionByName(own) if dangling == "self" else body).groupBy(F.col("dst").alias("node")).agg(F.sum("flow").alias("got"))
        even = F.lit(0.0) if dangling == "self" else F.col("lost") / n
        rank = (1 - damping) / n + damping * (F.coalesce("got", F.lit(0.0)) + even)
        return nodes.join(got, "node", "left").crossJoin(F.broadcast(lost)).select("node", rank.alias("mass"))  # one row

    rule = max_steps(steps) if eps is None else converged(eps) | max_steps(steps)
    return StagedFixpoint(nodes.select("node", F.lit(1.0 / max(1, n)).alias("mass")), advance, ["node"], ["mass"], rule, "abs", retain).run()


def reloading_steps(read_arcs, state: DataFrame, steps: int) -> DataFrame:
    """node, mass after some steps, where each step is a job of its own that reads and derives the arcs anew: the way of systems without recursion, to compare with.

    read_arcs: a function that gives the arcs from their source.
    """
    for _ in range(steps):
        arcs = read_arcs()
        flows = arcs.join(state, arcs["src"] == state["node"]).select("dst", (F.col("mass") * F.col("share")).alias("flow"))
        state = keep(flows.groupBy(F.col("dst").alias("node")).agg(F.sum("flow").alias("mass")))
    return state


def stratified_masses(spark: SparkSession, arcs_view: str, steps: int, start: float = START) -> DataFrame:
    """step, node, mass by plain SQL recursion: paths are listed first and summed after it. Rows grow as degree to the power of steps."""
    return spark.sql(f"""
        WITH RECURSIVE path(step, node, mass) AS (
          SELECT 0, src, CAST({start} AS DOUBLE) FROM {arcs_view} WHERE src = dst
          UNION ALL
          SELECT step + 1, a.dst, mass * a.share FROM path JOIN {arcs_view} a ON a.src = path.node WHERE step < {steps})
        SELECT step, node, sum(mass) AS mass FROM path GROUP BY step, node""")
