"""Sub-probability measures over values of variables, in log space.

A measure is a DataFrame with a column for each variable it really depends on and `lp`, the log of the value; rows that
aren't there have value 0. A conditional measure p(y|x) sums to at most 1 for each x. Conditions a measure doesn't depend on
cost nothing: they're only named.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .sources.tables import bounded_broadcast

#: Rows of a measure that is broadcast to another with which it shares no variable.
MOST_PAIRED = 100_000
#: Comparisons with 1/B allow for rounding in the logs; nothing on the border is lost.
SLACK = 1e-9


@dataclass(frozen=True)
class Measure:
    given: tuple[str, ...]
    over: tuple[str, ...]
    df: DataFrame
    #: What made it, where a store keeps it.
    key: tuple | None = field(default=None, compare=False)
    #: Of a product cut at 1/B, its factors and the log of B.
    factors: tuple[Measure, Measure, float] | None = field(default=None, compare=False)

    @property
    def columns(self) -> list[str]:
        return [c for c in self.df.columns if c != "lp"]


def init_measure(df: DataFrame, over: Iterable[str], given: Iterable[str] = ()) -> Measure:
    """1 / (number of y with this x) for each (x, y) of a relation."""
    over, given = tuple(over), tuple(given)
    rows = df.select(*given, *over).distinct()
    if not given:
        total = rows.agg(F.count("*").alias("__n"))
        return Measure((), over, rows.crossJoin(F.broadcast(total)).select(*over, (-F.log(F.col("__n").cast("double"))).alias("lp")))
    degree = rows.groupBy(*given).agg(F.count("*").alias("__n"))
    return Measure(given, over, rows.join(degree, list(given)).select(*given, *over, (-F.log(F.col("__n").cast("double"))).alias("lp")))


def _log_sum(col: str = "lp"):
    """log of the sum of exponentials; a log is at most 0 and at least that of 1/B, so no scaling is needed."""
    return F.log(F.sum(F.exp(F.col(col))))


def marginal(p: Measure, keep: Iterable[str]) -> Measure:
    """The measure of some of the variables, the others summed out."""
    keep = tuple(v for v in (*p.given, *p.over) if v in set(keep))
    cols = [c for c in p.columns if c in keep]
    if not cols:
        return Measure((), keep, p.df.agg(_log_sum().alias("lp")).where("lp is not null"))
    return Measure(tuple(v for v in p.given if v in keep), tuple(v for v in p.over if v in keep), p.df.groupBy(*cols).agg(_log_sum().alias("lp")))


def condition(p: Measure, given: Iterable[str]) -> Measure:
    """p(rest | given) of an unconditional measure."""
    given = tuple(v for v in p.over if v in set(given))
    base = marginal(p, given)
    joined = p.df.join(base.df.withColumnRenamed("lp", "__b"), list(given)) if given else p.df.crossJoin(F.broadcast(base.df.withColumnRenamed("lp", "__b")))
    return Measure(given, tuple(v for v in p.over if v not in given), joined.select(*p.columns, (F.col("lp") - F.col("__b")).alias("lp")))


def extend_condition(p: Measure, more: Iterable[str]) -> Measure:
    """Conditions the measure doesn't depend on: no job at all."""
    return replace(p, given=tuple(dict.fromkeys((*p.given, *more))))


def geo_mean(measures: list[Measure]) -> Measure:
    """The geometric mean, on the common support; still at most 1 in sum. Measures may depend on different conditions."""
    first = measures[0]
    if len(measures) == 1:
        return first
    df, cols = first.df, list(first.columns)
    for i, m in enumerate(measures[1:]):
        other = m.df.withColumnRenamed("lp", f"__{i}")
        on = [c for c in cols if c in m.columns]
        df = df.join(other, on) if on else df.crossJoin(bounded_broadcast(other, MOST_PAIRED))
        cols += [c for c in m.columns if c not in cols]
    total = F.col("lp")
    for i in range(len(measures) - 1):
        total = total + F.col(f"__{i}")
    return replace(first, df=df.select(*cols, (total / len(measures)).alias("lp")))


def mean(measures: list[Measure]) -> Measure:
    """The arithmetic mean, on the union of supports."""
    first = measures[0]
    df = measures[0].df.select(*first.columns, "lp")
    for m in measures[1:]:
        df = df.unionByName(m.df.select(*first.columns, "lp"))
    shift = math.log(len(measures))
    if not first.columns:
        return replace(first, df=df.agg((_log_sum() - shift).alias("lp")).where("lp is not null"))
    return replace(first, df=df.groupBy(*first.columns).agg((_log_sum() - shift).alias("lp")))


def truncated_product(px: Measure, pyx: Measure, ln_budget: float, bucketed: bool = True) -> Measure:
    """p(x) * p(y|x), where at least 1/B.

    `bucketed` joins on x with a condition on halving levels of both values as well, so that pairs well over the budget fall out in the
    join and only those near the border are computed.
    """
    on = [c for c in px.columns if c in pyx.columns]
    right = pyx.df.withColumnRenamed("lp", "__r")
    left = px.df
    if bucketed:
        left = left.withColumn("__lb", F.floor(-F.col("lp") / math.log(2)))
        right = right.withColumn("__rb", F.floor(-F.col("__r") / math.log(2)))
        near = F.col("__lb") + F.col("__rb") <= math.ceil(ln_budget / math.log(2) + SLACK)
        joined = left.join(right, on) if on else left.crossJoin(right)
        joined = joined.where(near)
    else:
        joined = left.join(right, on) if on else left.crossJoin(right)
    cols = list(dict.fromkeys([*px.columns, *pyx.columns]))
    total = F.col("lp") + F.col("__r")
    out = joined.where(total >= -ln_budget - SLACK).select(*cols, total.alias("lp"))
    return Measure((), tuple(dict.fromkeys((*px.given, *px.over, *pyx.over))), out, factors=(px, pyx, ln_budget))


def at(p: Measure, rows: DataFrame, name: str) -> DataFrame:
    """The rows at which the measure isn't 0, with its log; a product is taken at these rows only and never made as a whole."""
    if p.factors is None:
        side = p.df.withColumnRenamed("lp", name)
        return rows.join(side, p.columns) if p.columns else rows.crossJoin(F.broadcast(side))
    px, pyx, ln_budget = p.factors
    both = at(pyx, at(px, rows, f"{name}x"), f"{name}y")
    total = F.col(f"{name}x") + F.col(f"{name}y")
    return both.where(total >= -ln_budget - SLACK).select(*rows.columns, total.alias(name))


def in_support(ln_budget: float, *weighted: tuple[float, str]):
    """Whether the product of powers of values (weight, column of logs) is at least 1/B."""
    total = F.lit(0.0)
    for w, c in weighted:
        total = total + F.col(c) * w
    return total >= -ln_budget - SLACK


def audit(p: Measure) -> DataFrame:
    """Conditions under which the values sum to more than 1: none in a sound measure."""
    given = [c for c in p.columns if c in p.given]
    total = p.df.groupBy(*given).agg(F.sum(F.exp("lp")).alias("total")) if given else p.df.agg(F.sum(F.exp("lp")).alias("total"))
    return total.where(F.col("total") > 1 + 1e-6)
