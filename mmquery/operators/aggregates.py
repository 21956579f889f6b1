"""Counts and sums over assignments, and aggregates that products can't take part in."""

from __future__ import annotations

import warnings

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query import Atom, ConjunctiveQuery, full_join
from .joins import BEST_OMEGA, _triangle_names, degrees, made_once, triangle_limit, wcoj
from .matmul import mm_blocked, mm_sparse


def triangle_weights(r: Atom, s: Atom, t: Atom, threshold: int | None = None, kernel: str = "blas") -> DataFrame:
    """The pairs (x, z) of T with n, the number of y that close a triangle with them.

    Each triangle is in exactly one class: by y's degree in S, light ones by joins, heavy ones by a counting product. Overlapping
    supports, harmless for a yes or no, would count twice, so classes are disjoint here.
    """
    x, y, z = _triangle_names(r, s, t)
    r, s, t = made_once(r, s, t)
    limit = threshold if threshold is not None else triangle_limit(r, s, t, BEST_OMEGA)
    heavy = degrees(s.df, [y]).select(y, (F.col("deg") > limit).alias("__h"))
    pick = lambda df, flag: df.join(heavy.where(F.col("__h") if flag else ~F.col("__h")).select(y), y, "left_semi")
    light = pick(s.df, False).join(r.df, y).join(t.df, [x, z], "left_semi").groupBy(x, z).agg(F.count("*").alias("n"))
    rh, sh = pick(r.df, True), pick(s.df, True)
    pairs = mm_sparse(rh, sh, [y], count=True) if kernel == "sparse" else mm_blocked(rh, sh, [y], kernel=kernel, count=True)
    dense = pairs.join(t.df, [x, z], "left_semi").select(x, z, "n")
    return light.union(dense).groupBy(x, z).agg(F.sum("n").alias("n"))


def triangle_count(r: Atom, s: Atom, t: Atom, threshold: int | None = None, kernel: str = "blas") -> DataFrame:
    """The number of triangles, through a counting product."""
    return triangle_weights(r, s, t, threshold, kernel).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def triangle_sum(r: Atom, s: Atom, t: Atom, weights: DataFrame, on: list[str], value: str, kernel: str = "blas") -> DataFrame:
    """The sum over all triangles of a weight of x, z or both, through a counting product."""
    return triangle_weights(r, s, t, None, kernel).join(weights, on).agg(F.sum(F.col("n") * F.col(value)).alias("total"))


def answer_sum(q: ConjunctiveQuery, weights: DataFrame, on: list[str], value: str) -> DataFrame:
    """The sum over all assignments of a weight of some of their variables."""
    return full_join(q).join(weights, on).agg(F.sum(value).alias("total"))


def answer_min_plus(q: ConjunctiveQuery, costs: list[tuple[DataFrame, list[str], str]], mm: bool = False) -> DataFrame:
    """The least total cost of an assignment, by joins: minima have no inverse, so products are refused."""
    if mm:
        raise ValueError("minima over sums can't go through a matrix product")
    df, total = full_join(q), F.lit(0)
    for i, (cost, on, value) in enumerate(costs):
        df = df.join(cost.withColumnRenamed(value, f"__c{i}"), on)
        total = total + F.col(f"__c{i}")
    return df.agg(F.min(total).alias("least"))


def answer_full(q: ConjunctiveQuery) -> DataFrame:
    """All assignments: products can't list witnesses, so this is the variable-at-a-time join, and says so."""
    warnings.warn("a full head goes by joins: products don't list witnesses", stacklevel=2)
    return wcoj(q)
