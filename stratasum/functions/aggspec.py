"""The template that all aggregates instantiate: an accumulating phase and a finishing phase.

An aggregate keeps, for a set of items, an accumulator and a counter. The accumulating phase only
ever adds facts (accumulator, counter); the finishing phase picks the accumulator whose counter is
the size of the set. Each spec gives the phases as Spark columns, so they stay in the JVM.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, Window, WindowSpec
from pyspark.sql import functions as F


@dataclass(frozen=True)
class AggSpec:
    """zero, step, merge and finish of an aggregate over numbers; `running` and `total` are its forms in Spark.

    step(acc, x) and merge(acc, acc) are columns too; merge must be associative and commutative.
    """

    kind: str
    zero: Callable[[], Column]
    step: Callable[[Column, Column], Column]
    merge: Callable[[Column, Column], Column]
    finish: Callable[[Column, Column], Column]
    over: Callable[[Column], Column]

    def running(self, value: Column, window: WindowSpec) -> Column:
        """The accumulator after each item of the window's order, finished as if the set ended there."""
        frame = window.rowsBetween(Window.unboundedPreceding, Window.currentRow)
        return self.finish(self.over(value).over(frame), F.count(F.lit(1)).over(frame))

    def total(self, value: Column) -> Column:
        """The finished aggregate when Spark sees the input end."""
        return self.finish(self.over(value), F.count(F.lit(1)))

    def fold(self, values: Column) -> Column:
        """The same over an array column, item by item."""
        return self.finish(F.aggregate(values, self.zero(), self.step), F.size(values))


def _same(acc: Column, n: Column) -> Column:
    return acc


SPECS: dict[str, AggSpec] = {}


def register(spec: AggSpec) -> AggSpec:
    SPECS[spec.kind] = spec
    return spec


def _long() -> Column:
    return F.lit(0).cast("bigint")


def _nothing() -> Column:
    return F.lit(None).cast("bigint")


register(AggSpec("count", _long, lambda a, x: a + 1, lambda a, b: a + b, _same, lambda v: F.count(F.lit(1))))
register(AggSpec("sum", _long, lambda a, x: a + x, lambda a, b: a + b, _same, F.sum))
register(AggSpec("avg", _long, lambda a, x: a + x, lambda a, b: a + b, lambda a, n: a / n, F.sum))
register(AggSpec("max", _nothing, lambda a, x: F.greatest(a, x), lambda a, b: F.greatest(a, b), _same, F.max))
register(AggSpec("min", _nothing, lambda a, x: F.least(a, x), lambda a, b: F.least(a, b), _same, F.min))
register(AggSpec("sum_squares", _long, lambda a, x: a + x * x, lambda a, b: a + b, _same, lambda v: F.sum(v * v)))


def grouped_udaf(step: Callable[[float, float], float], zero: float, finish: Callable[[float, int], float]):
    """A grouped-aggregate pandas UDF from plain Python phases, for folds that no column expression gives.

    Spark cannot merge its partial results, so a group must fit one task; the column forms have no such bound.
    """

    @F.pandas_udf("double")
    def run(values: pd.Series) -> float:
        acc = zero
        for x in values:
            acc = step(acc, x)
        return float(finish(acc, len(values)))

    return run


def pack_pair(high: Column, low: Column) -> Column:
    """Two numbers below 2^31 in one bigint, ordered by the first and then by the second."""
    return F.shiftleft(high.cast("bigint"), 32).bitwiseOR(low.cast("bigint"))


def unpack_pair(packed: Column) -> tuple[Column, Column]:
    return F.shiftright(packed, 32), packed.bitwiseAND(F.lit((1 << 32) - 1))


def vector_sum(values: Column, length: int) -> Column:
    """Sum of a vector of known length; a vector of another length gives null, never a wrong sum."""
    return F.when(F.size(values) == length, F.aggregate(values, F.lit(0.0), lambda a, x: a + x.cast("double")))
