"""Query classes as hypergraphs."""

from __future__ import annotations

from itertools import combinations

from .hypergraph import Hypergraph


def clique(k: int) -> Hypergraph:
    return Hypergraph.of(combinations([f"X{i}" for i in range(1, k + 1)], 2))


def triangle() -> Hypergraph:
    return Hypergraph.of(["XY", "YZ", "XZ"])


def cycle(k: int) -> Hypergraph:
    return Hypergraph.of([(f"X{i}", f"X{i % k + 1}") for i in range(1, k + 1)])


def four_cycle() -> Hypergraph:
    """X - Y - Z - W - X."""
    return Hypergraph.of(["XY", "YZ", "ZW", "XW"])


def pyramid(k: int) -> Hypergraph:
    """An apex with an edge to each of k base variables, which share one edge of their own."""
    base = [f"X{i}" for i in range(1, k + 1)]
    return Hypergraph.of([base, *(("Y", x) for x in base)])


def double_triangle() -> Hypergraph:
    return Hypergraph.of(["XY", "YZ", "XZ", "YW", "XW"])


def path(k: int) -> Hypergraph:
    return Hypergraph.of([(f"X{i}", f"X{i + 1}") for i in range(1, k)])


def star(k: int) -> Hypergraph:
    return Hypergraph.of([("C", f"X{i}") for i in range(1, k + 1)])


def two_column_triangle() -> Hypergraph:
    """A triangle whose three corners are pairs of variables; only blocks of two reach its width."""
    corner = {c: (f"{c}1", f"{c}2") for c in "XYZ"}
    return Hypergraph.of([corner["X"] + corner["Y"], corner["Y"] + corner["Z"], corner["X"] + corner["Z"]])


def two_attribute_product() -> Hypergraph:
    return Hypergraph.of([("X", "Y1", "Y2"), ("Y1", "Y2", "Z")])
