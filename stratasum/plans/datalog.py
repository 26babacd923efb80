"""Positive rules over relations: semi-naive evaluation, and the rewriting that pushes bound arguments into recursion.

A term is a variable (a text) or a constant (anything else). Relations are frames with columns c0, c1, ...
`push_bindings` adorns the rules with which arguments a query binds, passes bindings from left to right
through each body, and adds a relation of wanted bindings (`wanted_...`) that guards every rule. In
left-linear rules the wanted binding never changes, so only facts of the asked constant are made; in
right-linear ones the wanted bindings are the nodes that it reaches.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .fixpoint import _bounded, small
from .materialize import keep_counted
from .program import _components


@dataclass(frozen=True)
class Atom:
    relation: str
    terms: tuple

    def variables(self) -> list[str]:
        return list(dict.fromkeys(t for t in self.terms if isinstance(t, str)))


@dataclass(frozen=True)
class Clause:
    head: Atom
    body: tuple[Atom, ...] = ()


@dataclass
class Derived:
    """Frames of the derived relations, how many facts each has, and the rounds of the longest loop."""

    frames: dict[str, DataFrame]
    facts: dict[str, int]
    rounds: int


def _columns(n: int) -> list[str]:
    return [f"c{i}" for i in range(n)]


def _match(atom: Atom, frame: DataFrame) -> DataFrame:
    """The bindings of an atom's variables, a column each."""
    first: dict[str, str] = {}
    for i, t in enumerate(atom.terms):
        if not isinstance(t, str):
            frame = frame.filter(F.col(f"c{i}") == F.lit(t))
        elif t in first:
            frame = frame.filter(F.col(f"c{i}") == F.col(first[t]))
        else:
            first[t] = f"c{i}"
    return frame.select(*[F.col(c).alias(v) for v, c in first.items()])


def _derive(clause: Clause, frames: list[DataFrame]) -> DataFrame:
    """The heads that a body gives: a chain of joins on shared variables."""
    rows, bound = None, set()
    for atom, frame in zip(clause.body, frames, strict=True):
        own = _match(atom, frame)
        shared = [v for v in atom.variables() if v in bound]
        if rows is not None and not shared:
            raise ValueError(f"{atom} shares no variable with what stands before it")
        rows = own if rows is None else rows.join(own, shared)
        bound |= set(atom.variables())
    return rows.select(*[(F.col(t) if isinstance(t, str) else F.lit(t)).alias(f"c{i}") for i, t in enumerate(clause.head.terms)])


def evaluate(clauses: list[Clause], given: dict[str, DataFrame], rounds: int | None = None) -> Derived:
    """All facts of the derived relations. In each round, a clause joins the new facts of one of its recursive atoms with all facts of the others."""
    heads = {c.head.relation for c in clauses}
    edges = {h: {a.relation for c in clauses if c.head.relation == h for a in c.body if a.relation in heads} for h in heads}
    out = Derived({}, {}, 0)
    for part in _components(edges):
        own = [c for c in clauses if c.head.relation in part]
        spark = next(iter(given.values())).sparkSession
        frames = {**given, **out.frames}
        parts: dict[str, list[DataFrame]] = {h: [] for h in part}
        delta: dict[str, tuple[DataFrame, int]] = {}
        for h in part:
            made = []
            for c in own:
                if c.head.relation != h or any(a.relation in part for a in c.body):
                    continue
                if c.body:
                    made.append(_derive(c, [frames[a.relation] for a in c.body]))
                else:
                    made.append(spark.range(1).select(*[F.lit(t).alias(f"c{i}") for i, t in enumerate(c.head.terms)]))
            if made:
                delta[h] = keep_counted(reduce(DataFrame.unionByName, made).distinct())
                parts[h].append(delta[h][0])
        done, recursive = 0, [c for c in own if any(a.relation in part for a in c.body)]
        while recursive and any(n for _, n in delta.values()):
            _bounded(rounds, done)
            known = {h: reduce(DataFrame.unionByName, p) for h, p in parts.items() if p}
            offers: dict[str, list[DataFrame]] = {}
            for c in recursive:
                for k, atom in enumerate(c.body):
                    if atom.relation not in part or not delta.get(atom.relation, (None, 0))[1]:
                        continue
                    if any(a.relation in part and a.relation not in known for a in c.body):
                        continue
                    inputs = [small(*delta[a.relation]) if i == k else known[a.relation] if a.relation in part else frames[a.relation] for i, a in enumerate(c.body)]
                    offers.setdefault(c.head.relation, []).append(_derive(c, inputs))
            delta = {}
            for h, made in offers.items():
                new = reduce(DataFrame.unionByName, made).distinct()
                if h in known:
                    new = new.join(known[h], new.columns, "left_anti")
                delta[h] = keep_counted(new)
                if delta[h][1]:
                    parts[h].append(delta[h][0])
            done += 1
        out.rounds = max(out.rounds, done)
        for h, p in parts.items():
            if p:
                out.frames[h] = reduce(DataFrame.unionByName, p)
                out.facts[h] = out.frames[h].count()
    return out


def push_bindings(clauses: list[Clause], query: Atom) -> tuple[list[Clause], Atom]:
    """The rewritten clauses, and the atom that asks them the same."""
    heads = {c.head.relation for c in clauses}
    pattern = lambda atom, bound: "".join("b" if not isinstance(t, str) or t in bound else "f" for t in atom.terms)
    held = lambda atom, p: tuple(t for t, x in zip(atom.terms, p, strict=True) if x == "b")
    wanted = lambda relation, p, terms: Atom(f"wanted_{relation}_{p}", terms)
    asked = pattern(query, set())
    out: list[Clause] = [Clause(wanted(query.relation, asked, held(query, asked)))] if "b" in asked else []
    todo, seen = [(query.relation, asked)], set()
    while todo:
        relation, p = todo.pop()
        if (relation, p) in seen:
            continue
        seen.add((relation, p))
        for c in clauses:
            if c.head.relation != relation:
                continue
            guard = (wanted(relation, p, held(c.head, p)),) if "b" in p else ()
            bound = {t for t in held(c.head, p) if isinstance(t, str)}
            body: list[Atom] = []
            for atom in c.body:
                if atom.relation in heads:
                    q = pattern(atom, bound)
                    todo.append((atom.relation, q))
                    if "b" in q:
                        ask = Clause(wanted(atom.relation, q, held(atom, q)), (*guard, *body))
                        if ask.body != (ask.head,):
                            out.append(ask)
                    atom = Atom(f"{atom.relation}_{q}", atom.terms)
                body.append(atom)
                bound |= set(atom.variables())
            out.append(Clause(Atom(f"{relation}_{p}", c.head.terms), (*guard, *body)))
    return list(dict.fromkeys(out)), Atom(f"{query.relation}_{asked}", query.terms)


def ask(clauses: list[Clause], given: dict[str, DataFrame], query: Atom, push: bool = True) -> tuple[DataFrame, Derived]:
    """The bindings of the query's variables, and what was derived for them."""
    if push:
        clauses, query = push_bindings(clauses, query)
    found = evaluate(clauses, given)
    if query.relation not in found.frames:
        spark = next(iter(given.values())).sparkSession
        return spark.createDataFrame([], ", ".join(f"{v} bigint" for v in query.variables())), found
    return _match(query, found.frames[query.relation]).distinct(), found
