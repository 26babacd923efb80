"""Fixpoints: staged (all facts of a step before those of the next), semi-naive and naive.

In a staged fixpoint an aggregate over the body of a step is final when the step ends. Why that is
sound can be shown in three ways: `goal` computes the sizes of the bodies beforehand and picks, from the
running aggregates, the facts at these counters; `complete` relies on the blocking aggregate to see the
end of the body; `verify` does that and compares the counted bodies with the certificates.

No loop ends in silence before its fixpoint: where a bound on rounds is given and met, RoundsExceeded
is raised. (The step cap of a staged fixpoint is a rule of its program; it is reported as `stopped_by`.)
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from .materialize import discard, keep, keep_counted, observed, shared_folder, write_counted

#: Rows of a delta that are sent to every task instead of shuffling what they join.
DELTA_ROWS = 1_000_000


@dataclass(frozen=True)
class Certificate:
    """Size of a body, known before recursion."""

    name: str
    n: int
    how: str = "counted"


class CertificateBroken(RuntimeError):
    """A step's body did not have the certified size."""


class RoundsExceeded(RuntimeError):
    """A bound on rounds was met before the fixpoint."""


def shared_count(body: DataFrame, name: str = "body") -> Certificate:
    """Counts a body once, on its keys only."""
    return Certificate(name, body.count())


@dataclass
class TraceRow:
    step: int
    body_rows: int | None = None
    state_rows: int = 0
    change: float | None = None
    changed: int | None = None
    seconds: float = 0.0
    retained_rows: int = 0
    jobs: int = 0
    bodies: dict = field(default_factory=dict)
    more: dict = field(default_factory=dict)


@dataclass(frozen=True)
class StopRule:
    """test(trace) -> reason or None; trace is the list of rows so far."""

    test: Callable[[list[TraceRow]], str | None]

    def __or__(self, other: StopRule) -> StopRule:
        return StopRule(lambda t: self.test(t) or other.test(t))

    def __and__(self, other: StopRule) -> StopRule:
        return StopRule(lambda t: (self.test(t) and other.test(t)) or None)


def max_steps(n: int) -> StopRule:
    return StopRule(lambda t: "cap" if t[-1].step >= n else None)


def converged(eps: float, measure: str = "change") -> StopRule:
    """Stops after a step whose change is at most eps."""

    def test(trace: list[TraceRow]) -> str | None:
        row = trace[-1]
        value = row.changed if measure == "count_changed" else row.change
        return "converged" if row.step > 0 and value is not None and value <= eps else None

    return StopRule(test)


@dataclass
class FixpointResult:
    final: DataFrame
    history: DataFrame | None
    trace: list[TraceRow]
    stopped_by: str

    @property
    def steps(self) -> int:
        return self.trace[-1].step

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(t.step, t.body_rows, t.state_rows, t.change, t.changed, t.seconds, t.retained_rows, t.jobs) for t in self.trace]
        return spark.createDataFrame(rows, "step int, body_rows bigint, state_rows bigint, change double, changed bigint, seconds double, retained_rows bigint, jobs int")


class Watch:
    """Counts the bodies of one step while the step is computed, and what else a step wants to know of its rows."""

    def __init__(self) -> None:
        self.seen: dict[str, tuple[DataFrame, Observation]] = {}

    def __call__(self, name: str, body: DataFrame, **measures: Column) -> DataFrame:
        watched = Observation()
        self.seen[name] = (body, watched)
        return body.observe(watched, F.count(F.lit(1)).alias("n"), *[c.alias(m) for m, c in measures.items()])

    def counts(self) -> dict[str, int]:
        return {name: int(observed(o).get("n", 0)) for name, (_, o) in self.seen.items()}

    def measures(self) -> dict[str, float]:
        return {m: v for _, o in self.seen.values() for m, v in observed(o).items() if m != "n"}

    def check(self, certificates: dict[str, Certificate], step: int) -> None:
        """Raises where a body does not have its certified size. A retried task may have been observed twice, so a difference is counted anew."""
        for name, n in self.counts().items():
            c = certificates.get(name)
            if c is not None and n != c.n and (n := self.seen[name][0].count()) != c.n:
                raise CertificateBroken(f"step {step}: {name} has {n} rows, not {c.n}")


@dataclass
class StagedFixpoint:
    """seed: state 0. advance(state, watch) -> the next state, lazily; bodies go through watch(name, body).

    keys: what names a state row; values: its numbers. measure: drop (largest fall), abs, l1 or l2 between
    steps. retain: last, all, window:k, or chain_max (all, and the last step by a chain of maxima).
    certificates: by body; with certify="verify" each step is checked against them. A goal form takes
    its certificates itself, in `advance`, and raises inside the plan.
    """

    seed: DataFrame
    advance: Callable[[DataFrame, Watch], DataFrame]
    keys: list[str]
    values: list[str]
    stop: StopRule
    measure: str = "drop"
    retain: str = "last"
    certify: str = "complete"
    certificates: dict[str, Certificate] = field(default_factory=dict)
    main_body: str | None = None

    def _difference(self) -> tuple[Column, Column]:
        gaps = [(F.coalesce(F.col(f"prev_{v}"), F.lit(0.0)) - F.coalesce(F.col(v), F.lit(0.0))) for v in self.values]
        one = {
            "drop": reduce(F.greatest, gaps) if len(gaps) > 1 else gaps[0],
            "abs": reduce(F.greatest, [F.abs(g) for g in gaps]) if len(gaps) > 1 else F.abs(gaps[0]),
            "l1": reduce(lambda a, b: a + b, [F.abs(g) for g in gaps]),
            "l2": reduce(lambda a, b: a + b, [g * g for g in gaps]),
        }[self.measure]
        total = F.sum(one) if self.measure in ("l1", "l2") else F.max(one)
        moved = reduce(lambda a, b: a | b, [g != 0 for g in gaps])
        return total, F.sum(F.when(moved, 1).otherwise(0))

    def run(self) -> FixpointResult:
        spark = self.seed.sparkSession
        state, n = keep_counted(self.seed.select(*self.keys, *self.values))
        trace = [TraceRow(0, None, n, None, None, 0.0, n)]
        kept, reason = [(0, state)], "cap"
        most = {"last": 1, "all": None, "chain_max": None}.get(self.retain, int(self.retain.split(":")[1]) if ":" in self.retain else 1)
        chain = spark.createDataFrame([(0,)], "step int") if self.retain == "chain_max" else None
        while not (found := self.stop.test(trace)):
            began, step = time.time(), trace[-1].step + 1
            with _jobs_of(spark) as jobs:
                watch, seen = Watch(), Observation()
                new = self.advance(state, watch)
                total, moved = self._difference()
                old = state.select(*self.keys, *[F.col(v).alias(f"prev_{v}") for v in self.values])
                # a row that is gone counts as one whose values became nothing
                both = new.select(*self.keys, *self.values, F.lit(True).alias("__here")).join(old, self.keys, "full")
                both = both.observe(seen, total.alias("change"), moved.alias("changed"), F.sum(F.when(F.col("__here"), 1).otherwise(0)).alias("rows"))
                state = keep(both.filter("__here").select(*self.keys, *self.values))
                if self.certify == "verify":
                    watch.check(self.certificates, step)
            got, bodies = {"rows": 0, "change": None, "changed": 0} | observed(seen), watch.counts()
            main = self.main_body or next(iter(bodies), None)
            row = TraceRow(step, bodies.get(main), int(got["rows"] or 0), None if got["change"] is None else float(got["change"]), int(got["changed"] or 0), time.time() - began, 0, jobs(), bodies, watch.measures())
            kept.append((step, state))
            if chain is not None:  # a fact that is larger than all before: the chain only grows
                chain = chain.unionByName(spark.createDataFrame([(step,)], "step int"))
            while most is not None and len(kept) > most:
                discard(kept.pop(0)[1])
            trace.append(row)
            row.retained_rows = sum(t.state_rows for t in trace[-len(kept) :])
        reason = found
        history = None
        if self.retain != "last":
            history = reduce(DataFrame.unionByName, [s.select(F.lit(k).alias("step"), *self.keys, *self.values) for k, s in kept])
        final = state.select(F.lit(trace[-1].step).alias("step"), *self.keys, *self.values)
        if chain is not None:
            final = history.join(F.broadcast(end_of_chain(chain)), "step")
        return FixpointResult(final, history, trace, reason)


class _jobs_of:
    """Counts the Spark jobs that run inside the block."""

    def __init__(self, spark: SparkSession):
        self.context = spark.sparkContext

    def __enter__(self) -> Callable[[], int]:
        self.tag = f"step-{uuid.uuid4().hex}"
        self.context.addJobTag(self.tag)
        return lambda: self.n

    def __exit__(self, *_: object) -> None:
        self.context.removeJobTag(self.tag)
        self.n = len(self.context._jsc.sc().statusTracker().getJobIdsForTag(self.tag))


def end_of_chain(chain: DataFrame) -> DataFrame:
    """step: the fact of a chain that has no successor, which is its maximum. One row."""
    return chain.join(chain.select((F.col("step") - 1).alias("step")), "step", "left_anti")


def last_step(history: DataFrame) -> DataFrame:
    """The rows of the largest step, selected in a stratum above the recursion."""
    top = history.agg(F.max("step").alias("step"))
    return history.join(F.broadcast(top), "step")


def _bounded(rounds: int | None, done: int) -> None:
    if rounds is not None and done >= rounds:
        raise RoundsExceeded(f"no fixpoint after {rounds} rounds")


def small(df: DataFrame, n: int) -> DataFrame:
    """df with a broadcast hint if it has few rows; n is their known number."""
    return F.broadcast(df) if n <= DELTA_ROWS else df


def semi_naive(base: DataFrame, step: Callable[[DataFrame], DataFrame], keys: list[str], rounds: int | None = None) -> tuple[DataFrame, list[int]]:
    """All facts and the number of new ones in each round; only new facts feed the next round.

    A round is one job, which counts its own output. Facts are written once, into the folder of their
    round; all rounds together are one table. Offers and known facts meet in one aggregate, so a round
    shuffles keys once and joins the new facts only.
    """
    spark, folder = base.sparkSession, shared_folder(base.sparkSession)
    first = base.dropDuplicates(keys)
    columns, schema = first.columns, first.schema
    sizes = [write_counted(first, f"{folder}/0")]
    others = [c for c in columns if c not in keys]
    while sizes[-1]:
        _bounded(rounds, len(sizes) - 1)
        known = spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(folder)
        delta = spark.read.schema(schema).parquet(f"{folder}/{len(sizes) - 1}")
        offers = step(small(delta, sizes[-1])).select(*columns, F.lit(False).alias("__known"))
        both = offers.unionByName(known.select(*columns, F.lit(True).alias("__known")))
        new = both.groupBy(*keys).agg(F.max("__known").alias("__known"), *[F.first(c).alias(c) for c in others]).filter("not __known").select(*columns)
        sizes.append(write_counted(new, f"{folder}/{len(sizes)}"))
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(folder), sizes


def naive(base: DataFrame, step: Callable[[DataFrame], DataFrame], keys: list[str], rounds: int | None = None) -> tuple[DataFrame, list[int]]:
    """The same, where all facts feed every round."""
    known, n = keep_counted(base.dropDuplicates(keys))
    sizes = [n]
    while True:
        _bounded(rounds, len(sizes) - 1)
        old = known
        known, more = keep_counted(known.unionByName(step(small(known, n))).dropDuplicates(keys))
        discard(old)
        if more == n:
            return known, [*sizes, 0]
        sizes.append(more - n)
        n = more


def recursive_view(spark: SparkSession, seed_sql: str, step_sql: str, name: str, keys: list[str], values: list[str], stop: StopRule, retain: str = "last") -> FixpointResult:
    """The user writes seed and step as queries over the view `name`; aggregates are allowed, as steps are staged."""

    def advance(state: DataFrame, watch: Watch) -> DataFrame:
        state.createOrReplaceTempView(name)
        return watch("body", spark.sql(step_sql))

    return StagedFixpoint(spark.sql(seed_sql), advance, keys, values, stop, retain=retain).run()


def _least(costs: DataFrame) -> DataFrame:
    return costs.groupBy("node").agg(F.min("cost").alias("cost"))


def min_in_recursion(arcs: DataFrame, source: int, rounds: int | None = None) -> DataFrame:
    """node, cost: least path cost from source, where the minimum is taken in every round. Costs must not be negative."""
    spark = arcs.sparkSession
    best, n = keep_counted(spark.createDataFrame([(source, 0.0)], "node bigint, cost double"))
    delta, done = best, 0
    while n:
        _bounded(rounds, done)
        d = small(delta, n)
        offers = _least(d.join(arcs, d["node"] == arcs["src"]).select(arcs["dst"].alias("node"), (F.col("cost") + arcs["cost_of"]).alias("cost")))
        delta, n = keep_counted(offers.join(best.withColumnRenamed("cost", "old"), "node", "left").filter("old is null or cost < old").select("node", "cost"))
        if n:
            best = keep(_least(best.unionByName(delta)))
        done += 1
    return best


def stratified_min(arcs: DataFrame, source: int, bound: int) -> DataFrame:
    """The same for paths of at most `bound` arcs, where all paths are listed first and the minimum comes last."""
    spark = arcs.sparkSession
    level = spark.createDataFrame([(source, 0.0)], "node bigint, cost double")
    levels = [level]
    ends = arcs.select(F.col("src").alias("node"), "dst", "cost_of")
    for _ in range(bound):
        level = level.join(ends, "node").select(F.col("dst").alias("node"), (F.col("cost") + F.col("cost_of")).alias("cost"))
        levels.append(level)
    return _least(reduce(DataFrame.unionByName, levels))


def check_premappable(arcs: DataFrame, facts: DataFrame) -> bool:
    """Whether the step gives the same minima from all facts as from their minima: the minimum may move inside."""

    def step(costs: DataFrame) -> DataFrame:
        return _least(costs.join(arcs, costs["node"] == arcs["src"]).select(arcs["dst"].alias("node"), (F.col("cost") + arcs["cost_of"]).alias("cost")))

    return step(facts).exceptAll(step(_least(facts))).isEmpty()


def monotone_threshold(arcs: DataFrame, seed: DataFrame, k: int, rounds: int | None = None) -> DataFrame:
    """Nodes that join once at least k of their predecessors have: a count that only grows, tested from below.

    Counts are kept, and each round adds what its new members give, so no arc is counted twice.
    """
    once = arcs.select("src", "dst").distinct()
    delta, n = keep_counted(seed.select("node").dropDuplicates())
    members, counts, done = delta, None, 0
    while n:
        _bounded(rounds, done)
        d = small(delta, n)
        more = once.join(d, once["src"] == d["node"]).groupBy(F.col("dst").alias("node")).agg(F.count(F.lit(1)).alias("n"))
        counts = keep(more if counts is None else counts.unionByName(more).groupBy("node").agg(F.sum("n").alias("n")))
        delta, n = keep_counted(counts.filter(F.col("n") >= k).select("node").join(members, "node", "left_anti"))
        if n:
            members = keep(members.unionByName(delta))
        done += 1
    return members


def reachable_from(arcs: DataFrame, source: int, strategy: str = "semi_naive", rounds: int | None = None) -> DataFrame:
    """node: reachable from source; the bound argument seeds the recursion instead of filtering a closure."""
    return reachable(arcs, arcs.sparkSession.createDataFrame([(source,)], "node bigint"), strategy, rounds)


def reachable(arcs: DataFrame, base: DataFrame, strategy: str = "semi_naive", rounds: int | None = None) -> DataFrame:
    """node: reachable from the nodes of base, these included."""

    def step(delta: DataFrame) -> DataFrame:
        return delta.join(arcs, delta["node"] == arcs["src"]).select(arcs["dst"].alias("node"))

    return (semi_naive if strategy == "semi_naive" else naive)(base, step, ["node"], rounds)[0]


def closure(arcs: DataFrame, rounds: int | None = None, strategy: str = "semi_naive") -> DataFrame:
    """src, dst of every path: the unbound recursion that a bound argument avoids."""
    base = arcs.select("src", "dst")

    def step(delta: DataFrame) -> DataFrame:
        return delta.alias("d").join(arcs.alias("a"), F.col("d.dst") == F.col("a.src")).select(F.col("d.src").alias("src"), F.col("a.dst").alias("dst"))

    return (semi_naive if strategy == "semi_naive" else naive)(base, step, ["src", "dst"], rounds)[0]
