"""Hypergraphs of queries: vertices are variables, held as bits of an int."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass


def bits(mask: int) -> Iterator[int]:
    while mask:
        low = mask & -mask
        yield low
        mask ^= low


def submasks(mask: int) -> Iterator[int]:
    """All subsets of a set, itself and the empty one among them."""
    sub = mask
    while True:
        yield sub
        if not sub:
            return
        sub = (sub - 1) & mask


@dataclass(frozen=True)
class Hypergraph:
    names: tuple[str, ...]
    edges: frozenset[int]

    @staticmethod
    def of(edges: Iterable[Iterable[str]]) -> Hypergraph:
        edges = [tuple(e) for e in edges]
        names = tuple(sorted({v for e in edges for v in e}))
        at = {v: 1 << i for i, v in enumerate(names)}
        return Hypergraph(names, frozenset(sum(at[v] for v in set(e)) for e in edges))

    @property
    def all(self) -> int:
        return (1 << len(self.names)) - 1

    def mask(self, variables: Iterable[str]) -> int:
        return sum(1 << self.names.index(v) for v in set(variables))

    def label(self, mask: int) -> str:
        return "".join(sorted(v for i, v in enumerate(self.names) if mask >> i & 1)) or "∅"

    def variables(self, mask: int) -> tuple[str, ...]:
        return tuple(v for i, v in enumerate(self.names) if mask >> i & 1)

    def incident(self, block: int) -> frozenset[int]:
        """Edges that meet the block."""
        return frozenset(e for e in self.edges if e & block)

    def closure(self, block: int) -> int:
        """The block and everything that shares an edge with it."""
        out = 0
        for e in self.incident(block):
            out |= e
        return out

    def neighbours(self, block: int) -> int:
        return self.closure(block) & ~block

    def without(self, block: int) -> Hypergraph:
        """The hypergraph after the block's elimination: its edges give way to one over its neighbours."""
        rest = set(self.edges - self.incident(block))
        if near := self.neighbours(block):
            rest.add(near)
        return Hypergraph(self.names, frozenset(rest))

    def components(self) -> list[int]:
        out: list[int] = []
        for e in self.edges:
            joined = [c for c in out if c & e]
            out = [c for c in out if not c & e]
            for c in joined:
                e |= c
            out.append(e)
        return sorted(out)
