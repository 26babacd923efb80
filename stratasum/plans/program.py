"""Rule programs: strata, the check that recursion is sound, evaluation, and rewrites of the finishing phase.

A program without cycles runs stratum by stratum. A cycle must be staged: its facts of stage J + 1 come
from those of stage J, and it runs as a staged fixpoint. How a rule's aggregate knows the end of its
input (`finish`) decides the plan: `complete` is one blocking aggregate; `precount` counts the groups of
its body in a stratum below and picks the running fact at that counter; `negation` and `max_running`
pick it by the absence of a successor and by the largest counter. How a top rule finds the last stage
decides what the loop keeps: `max_stage` keeps all stages and selects by a maximum above the recursion,
`chain_max` by a chain of maxima, `last_delta` keeps the last stage only. The rewrites below turn one into
another.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stratasum.functions.aggspec import SPECS

from .fixpoint import FixpointResult, StagedFixpoint, StopRule, Watch, last_step
from .materialize import keep

RUNNING = ("precount", "negation", "max_running")
TOP = {"max_stage": "all", "chain_max": "chain_max", "last_delta": "last"}


class NotStratifiable(ValueError):
    """A cycle passes through a negation or an aggregate that nothing makes monotone."""


@dataclass(frozen=True)
class Literal:
    """A body relation. shift: by how many stages the head is later than it; certified: its size is known beforehand."""

    relation: str
    negated: bool = False
    shift: int = 0
    certified: bool = False


@dataclass(frozen=True)
class Rule:
    """head from body; aggregate: sum, count, ... or None; finish: how a final aggregate knows the end of its input, or a top rule the last stage.

    build gives the rows of the body from the frames of its relations. by, value, item: the groups, the
    aggregated column and what orders the items of a group; out: the column of the result.
    """

    head: str
    body: tuple[Literal, ...]
    aggregate: str | None = None
    finish: str = "complete"
    build: Callable[[dict[str, DataFrame]], DataFrame] | None = field(default=None, compare=False)
    by: tuple[str, ...] = ()
    value: str | None = None
    item: tuple[str, ...] = ()
    out: str = "value"

    def blocking(self, literal: Literal) -> bool:
        return literal.negated or self.aggregate is not None

    def finished(self, body: DataFrame, sizes: DataFrame | None = None) -> DataFrame:
        """by, out: the aggregate of the body's rows. sizes: by, size of the groups, for `precount`; counted from the body where none are given."""
        if self.aggregate is None:
            return body
        spec, value = SPECS[self.aggregate], F.col(self.value) if self.value else F.lit(1)
        if self.finish not in RUNNING:
            return body.groupBy(*self.by).agg(spec.total(value).alias(self.out))
        w = Window.partitionBy(*self.by).orderBy(*self.item)
        facts = body.select(*self.by, F.row_number().over(w).cast("bigint").alias("__n"), spec.running(value, w).alias(self.out))
        if self.finish == "max_running":
            return facts.groupBy(*self.by).agg(F.max_by(self.out, "__n").alias(self.out))
        if self.finish == "negation":
            after = facts.select(*self.by, (F.col("__n") - 1).alias("__n"))
            return facts.join(after, [*self.by, "__n"], "left_anti").drop("__n")
        sizes = self.sizes(body) if sizes is None else sizes
        broken = F.raise_error(F.lit(f"a group of {self.head} does not have its certified size"))
        sized = facts.join(sizes, list(self.by), "full")
        last = sized.groupBy(*self.by).agg(F.max("__n").alias("__last"), F.max("__size").alias("__size"), F.max_by(self.out, F.when(F.col("__n") == F.col("__size"), F.col("__n"))).alias(self.out))
        return last.select(*self.by, F.when(F.col("__last") == F.col("__size"), F.col(self.out)).otherwise(broken).alias(self.out))

    def sizes(self, body: DataFrame) -> DataFrame:
        """by, __size: the cardinalities, in a stratum below."""
        return body.groupBy(*self.by).agg(F.count(F.lit(1)).alias("__size"))


@dataclass
class Evaluation:
    """Frames of all relations, and what the loops of staged relations did."""

    frames: dict[str, DataFrame]
    loops: dict[str, FixpointResult]
    strata: list[set[str]]


def _components(edges: dict[str, set[str]]) -> list[set[str]]:
    """Strongly connected components, each after those that it depends on."""
    index: dict[str, int] = {}
    low: dict[str, int] = {}
    stack: list[str] = []
    out: list[set[str]] = []

    def visit(v: str) -> None:
        index[v] = low[v] = len(index)
        stack.append(v)
        for w in sorted(edges.get(v, ())):
            if w not in index:
                visit(w)
                low[v] = min(low[v], low[w])
            elif w in stack:
                low[v] = min(low[v], index[w])
        if low[v] == index[v]:
            at = stack.index(v)
            out.append(set(stack[at:]))
            del stack[at:]

    for v in sorted(edges):
        if v not in index:
            visit(v)
    return out


@dataclass(frozen=True)
class Program:
    rules: tuple[Rule, ...]

    def strata(self) -> list[set[str]]:
        """Relations in the order of evaluation; raises NotStratifiable.

        In a cycle, a negation must reach back to an earlier stage. An aggregate must, too, unless
        the size of its body is certified. A cycle as a whole must not be free of stage steps where
        it passes through either.
        """
        edges: dict[str, set[str]] = {r.head: set() for r in self.rules}
        for r in self.rules:
            for literal in r.body:
                edges[r.head].add(literal.relation)
                edges.setdefault(literal.relation, set())
        found = _components(edges)
        for part in found:
            within = [(r, x) for r in self.rules if r.head in part for x in r.body if x.relation in part]
            # edges without a stage step, inside the cycle: what cycles remain must be monotone or certified
            flat: dict[str, set[str]] = {v: set() for v in part}
            for r, x in within:
                if x.shift <= 0:
                    flat[r.head].add(x.relation)
            for loop in _components(flat):
                for r, x in within:
                    if x.shift > 0 or r.head not in loop or x.relation not in loop:
                        continue
                    if len(loop) == 1 and r.head != x.relation:
                        continue
                    if x.negated:
                        raise NotStratifiable(f"{r.head} depends on the absence of {x.relation} in its own stage")
                    if r.aggregate and not x.certified:
                        raise NotStratifiable(f"{r.aggregate} in {r.head} needs all of {x.relation}, whose size is not known beforehand")
        return found

    def of(self, head: str) -> list[Rule]:
        return [r for r in self.rules if r.head == head]

    def run(self, given: dict[str, DataFrame], stop: StopRule | None = None, measure: str = "drop") -> Evaluation:
        """Evaluates the program, stratum by stratum; cycles as staged fixpoints that end by `stop`."""
        strata = self.strata()
        out = Evaluation(dict(given), {}, strata)
        for part in strata:
            if any(x.relation in part for r in self.rules if r.head in part for x in r.body):
                self._run_staged(part, out, stop, measure)
                continue
            for name in part:
                if own := self.of(name):
                    out.frames[name] = reduce(DataFrame.unionByName, [self._top(r, out) if r.finish in TOP else r.finished(r.build(out.frames)) for r in own])
        return out

    def _top(self, rule: Rule, out: Evaluation) -> DataFrame:
        """The last stage of the relation that a top rule reads."""
        relation = rule.body[0].relation
        found = out.loops[relation]
        return last_step(found.history) if rule.finish == "max_stage" else found.final

    def _run_staged(self, part: set[str], out: Evaluation, stop: StopRule | None, measure: str) -> None:
        if stop is None:
            raise ValueError(f"{sorted(part)} is recursive: give a stop rule")
        within = lambda r: [x for x in r.body if x.relation in part]
        staged = {r.head for r in self.rules if r.head in part and any(x.shift > 0 for x in within(r))}
        if len(staged) != 1:
            raise ValueError(f"{sorted(part)} needs one staged relation, not {sorted(staged)}")
        name = staged.pop()
        seeds = [r for r in self.of(name) if not within(r)]
        steps = [r for r in self.of(name) if within(r)]
        if any(r.aggregate is None or (r.by, r.out) != (steps[0].by, steps[0].out) for r in steps):
            raise ValueError(f"all rules of {name} need the same groups and result")
        order = [h for c in _components({h: {x.relation for r in self.of(h) for x in within(r) if x.shift <= 0} - {name} for h in part - {name}}) for h in c]
        sizes: dict[int, DataFrame] = {}

        def finished(rule: Rule, frames: dict[str, DataFrame], watch: Watch | None = None) -> DataFrame:
            body = rule.build(frames)
            if rule.finish == "precount" and id(rule) not in sizes:  # known before the recursion: the body of the seed has as many
                sizes[id(rule)] = keep(rule.sizes(body))
            return rule.finished(body if watch is None else watch(rule.head, body), sizes.get(id(rule)))

        def advance(state: DataFrame, watch: Watch | None) -> DataFrame:
            frames = {**out.frames, name: state}
            for head in order:
                frames[head] = reduce(DataFrame.unionByName, [finished(r, frames, watch) for r in self.of(head)])
            return reduce(DataFrame.unionByName, [finished(r, frames, watch) for r in steps])

        seed = reduce(DataFrame.unionByName, [r.finished(r.build(out.frames)) for r in seeds])
        if any(r.finish == "precount" for h in part for r in self.of(h)):
            seed = keep(seed)
            advance(seed, None)  # counts in a stratum below
        tops = {TOP[r.finish] for r in self.rules if r.finish in TOP and any(x.relation == name for x in r.body)}
        others = any(r.finish not in TOP for r in self.rules if r.head not in part for x in r.body if x.relation == name)
        retain = "all" if others or "all" in tops else "chain_max" if "chain_max" in tops else "last"
        found = StagedFixpoint(seed, advance, list(steps[0].by), [steps[0].out], stop, measure, retain, main_body=name).run()
        out.loops[name] = found
        out.frames[name] = found.final if found.history is None else found.history


def negation_to_lookup(program: Program) -> Program:
    """Finals that look for an absent successor look up the known size instead."""
    return Program(tuple(replace(r, finish="precount") if r.finish == "negation" else r for r in program.rules))


def drop_count_stratum(program: Program) -> Program:
    """Finals with a known size wait for the end of the body instead; rules that only feed sizes go."""
    sizes = {x.relation for r in program.rules if r.finish == "precount" for x in r.body if x.relation.startswith("size_of_")}
    rules = []
    for r in program.rules:
        if r.head in sizes:
            continue
        body = tuple(x for x in r.body if x.relation not in sizes)
        rules.append(replace(r, body=body, finish="complete" if r.finish == "precount" else r.finish))
    return Program(tuple(rules))


def last_delta(program: Program, stage_relation: str) -> Program:
    """A top rule that selects the largest stage, by a maximum or a chain of maxima, reads the loop's last state instead of all stages."""
    return Program(tuple(replace(r, finish="last_delta") if r.finish in ("max_stage", "chain_max") and any(x.relation == stage_relation for x in r.body) else r for r in program.rules))
