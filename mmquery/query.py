"""Conjunctive queries bound to DataFrames, their text forms, and normalisation."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .hypergraph import Hypergraph


@dataclass(frozen=True)
class Atom:
    name: str
    variables: tuple[str, ...]
    df: DataFrame
    """One column a variable, named so; distinct and without nulls."""

    @staticmethod
    def of(name: str, df: DataFrame, variables: list[str] | str, constants: dict[int, object] | None = None) -> Atom:
        """Bind columns to variables by place; a variable twice asks for equality, a constant for a value."""
        names = list(variables)
        df = df.toDF(*[f"__{i}" for i in range(len(df.columns))])
        for field in df.schema.fields:
            if isinstance(field.dataType, T.MapType):
                raise TypeError("a map can't be compared, so it can't be a variable")
        first: dict[str, int] = {}
        for i, v in enumerate(names):
            if constants and i in constants:
                df = df.where(F.col(f"__{i}") == F.lit(constants[i]))
            elif v in first:
                df = df.where(F.col(f"__{i}") == F.col(f"__{first[v]}"))
            else:
                first[v] = i
        out = df.select(*[_comparable(df, f"__{i}").alias(v) for v, i in first.items()])
        return Atom(name, tuple(first), out.dropna().distinct())

    def on(self, variables: tuple[str, ...]) -> DataFrame:
        keep = [v for v in self.variables if v in variables]
        return self.df if len(keep) == len(self.variables) else self.df.select(*keep).distinct()


def _comparable(df: DataFrame, c: str):
    """Negative zero equals zero; a NaN equals itself in Spark's joins already."""
    return F.col(c) + F.lit(0.0) if isinstance(df.schema[c].dataType, T.DoubleType | T.FloatType) else F.col(c)


@dataclass(frozen=True)
class ConjunctiveQuery:
    atoms: tuple[Atom, ...]
    head: tuple[str, ...] = ()

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(sorted({v for a in self.atoms for v in a.variables}))

    @property
    def graph(self) -> Hypergraph:
        return Hypergraph.of([a.variables for a in self.atoms])

    def size(self) -> int:
        return sum(a.df.count() for a in self.atoms)


_ATOM = re.compile(r"(\w+)\s*\(([^)]*)\)")


def parse_rule(text: str, tables: dict[str, DataFrame]) -> ConjunctiveQuery:
    """`Q(X) :- R(X,Y), S(Y,3)`: names starting with a letter are variables, numbers and quoted strings constants."""
    head, _, body = text.partition(":-")
    found = _ATOM.search(head)
    atoms = []
    for name, args in _ATOM.findall(body):
        names, constants = [], {}
        for i, a in enumerate(x.strip() for x in args.split(",")):
            if re.fullmatch(r"-?\d+", a):
                constants[i] = int(a)
            elif a[:1] in "'\"":
                constants[i] = a[1:-1]
            names.append(a)
        atoms.append(Atom.of(name, tables[name], names, constants))
    return ConjunctiveQuery(tuple(atoms), tuple(x.strip() for x in found[2].split(",") if x.strip()) if found else ())


def from_sql(text: str, tables: dict[str, DataFrame]) -> ConjunctiveQuery:
    """`[SELECT EXISTS (] SELECT ... FROM r a JOIN s b ON a.x = b.y AND ... [WHERE a.z = 3] [)]`: equijoins and constants only."""
    inner = re.sub(r"(?is)^\s*select\s+exists\s*\((.*)\)\s*$", r"\1", text)
    scope = re.search(r"(?is)\bfrom\b(.*?)(?:\bwhere\b(.*))?$", inner)
    if not scope:
        raise ValueError("no FROM clause")
    aliases: dict[str, str] = {}
    conditions = [scope[2]] if scope[2] else []
    for part in re.split(r"(?i)\bjoin\b|,", scope[1]):
        item, *on = re.split(r"(?i)\bon\b", part, maxsplit=1)
        words = item.split()
        aliases[words[-1]] = words[0]
        conditions += on
    name: dict[tuple[str, str], str] = {}
    fixed: dict[tuple[str, str], object] = {}

    def find(c: tuple[str, str]) -> str:
        return name.setdefault(c, f"{c[0]}_{c[1]}")

    for c in (x.strip() for block in conditions for x in re.split(r"(?i)\band\b", block)):
        m = re.fullmatch(r"(\w+)\.(\w+)\s*=\s*(?:(\w+)\.(\w+)|(-?\d+)|'([^']*)')", c)
        if not m:
            raise ValueError(f"only equalities are understood: {c}")
        if m[3]:
            old, new = find((m[3], m[4])), find((m[1], m[2]))
            name.update({k: new for k, v in name.items() if v == old})
        else:
            fixed[(m[1], m[2])] = int(m[5]) if m[5] else m[6]
    atoms = []
    for alias, t in aliases.items():
        cols = [c for c in tables[t].columns if (alias, c) in name or (alias, c) in fixed]
        atoms.append(Atom.of(t, tables[t].select(*cols), [name.get((alias, c), f"{alias}_{c}") for c in cols], {i: fixed[(alias, c)] for i, c in enumerate(cols) if (alias, c) in fixed}))
    return ConjunctiveQuery(tuple(atoms))


def normalise(q: ConjunctiveQuery) -> ConjunctiveQuery:
    """Atoms of one schema are intersected, and an atom whose schema lies in another's filters that one."""
    by: dict[frozenset, list[Atom]] = {}
    for a in q.atoms:
        by.setdefault(frozenset(a.variables), []).append(a)
    merged = [Atom(g[0].name, g[0].variables, reduce(lambda x, y: x.join(y, list(g[0].variables), "left_semi"), [a.df for a in g])) for g in by.values()]
    out = []
    for a in merged:
        if any(set(a.variables) < set(b.variables) for b in merged):
            continue
        df = a.df
        for b in merged:
            if set(b.variables) < set(a.variables):
                df = df.join(b.df, list(b.variables), "left_semi")
        out.append(Atom(a.name, a.variables, df))
    return ConjunctiveQuery(tuple(out), q.head)


def full_join(q: ConjunctiveQuery) -> DataFrame:
    """The natural join of all atoms, connected ones first.

    Of a query of three atoms and more the two start whose join has the fewest rows, as their sizes and distinct values tell; then
    come those that filter what is there, then those that add the fewest rows to each.
    """
    left = list(q.atoms)
    stats = statistics_of(left) if len(left) > 2 else {}

    def fan(a: Atom, on: set[str]) -> float:
        """Rows of an atom for one value of some of its variables."""
        rows, distinct = stats.get(id(a), (1, {}))
        return rows / max(1, distinct.get(frozenset(on), rows))

    def pair(i: int, j: int) -> float:
        a, b = left[i], left[j]
        on = set(a.variables) & set(b.variables)
        return min(stats[id(a)][0] * fan(b, on), stats[id(b)][0] * fan(a, on)) if on else float("inf")

    first = 0
    if stats:
        first, second = min(((i, j) for i in range(len(left)) for j in range(i + 1, len(left))), key=lambda p: pair(*p))
        if stats[id(left[second])][0] < stats[id(left[first])][0]:
            first = second
    out = left.pop(first)
    df, have = out.df, set(out.variables)
    while left:
        if stats:
            met = [have & set(a.variables) for a in left]
            i = min(range(len(left)), key=lambda i: (not met[i], not set(left[i].variables) <= have, fan(left[i], met[i]), -len(met[i])))
        else:
            i = max(range(len(left)), key=lambda i: len(have & set(left[i].variables)))
        a = left.pop(i)
        on = [v for v in a.variables if v in have]
        df = df.join(a.df, on) if on else df.crossJoin(a.df)
        have |= set(a.variables)
    return df


def statistics_of(atoms: list[Atom]) -> dict[int, tuple[int, dict[frozenset, int]]]:
    """Of each atom its rows, and about how many values each set of variables has that it shares with another. One aggregate an atom."""
    out = {}
    for a in atoms:
        held = [set(a.variables) & set(b.variables) for b in atoms if b is not a]
        sets = list({frozenset(x) for x in [*held, set().union(*held), *({v} for v in a.variables)] if x and x != set(a.variables)})
        found = a.df.agg(F.count("*"), *(F.approx_count_distinct(F.xxhash64(*sorted(s))) for s in sets)).first()
        out[id(a)] = (found[0], dict(zip(sets, found[1:], strict=True)))
    return out


def exists(df: DataFrame) -> DataFrame:
    """One row: whether there is any."""
    return df.select(F.lit(1).alias("one")).limit(1).groupBy().agg((F.count("*") > 0).alias("answer"))
