"""Evaluation of cover rules: a proof script becomes joins, splits and products.

Each term of the right side carries a measure. Steps act on measures as they do on terms. After a composition, whose
product is cut at 1/B, the light branch goes on with the cut table; the heavy branch gives the composed term up, repairs the
inequality on the driver, and goes on with the measures it has. Leaves are join measures or groups of measures of a product.
What reaches the driver are row counts and largest degrees. Branches and rules share measures: a store makes each one once, as a
table in the shared folder.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace
from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import measures as M
from .flow import CoverRule, FlowInequality, Term, drop_unit, inequality_of
from .hypergraph import Hypergraph
from .measures import Measure
from .mmcost import MatMulTerm
from .proof import next_moves
from .query import Atom, ConjunctiveQuery
from .sources.tables import cut


@dataclass(frozen=True)
class JoinModel:
    closure: int
    measure: Measure


@dataclass(frozen=True)
class ProductModel:
    """A product's group-by and side measures, with the exponents of its sides (z is the odd one)."""

    term: MatMulTerm
    g: Measure | None
    x: Measure
    y: Measure
    z: Measure
    triple: tuple[Fraction, Fraction, Fraction]

    def parts(self) -> list[Measure | None]:
        return [self.g, self.x, self.y, self.z]


@dataclass
class Trace:
    """What was done: a line a node. With `check`, every node's measures are held against the invariants."""

    lines: list[tuple] = field(default_factory=list)
    check: bool = False

    def add(self, depth: int, kind: str, text: str) -> None:
        self.lines.append((len(self.lines), depth, kind, text))


class Store:
    """Measures by what made them: each is made once. With `tables`, those that joins make lie in the shared folder; aggregates are made again."""

    def __init__(self, tables: bool = False):
        self.tables, self.have, self.degrees = tables, {}, {}
        #: Measures that were held against the invariants, with their budgets.
        self.sound: set[tuple] = set()

    def measure(self, key: tuple, make) -> Measure:
        if key not in self.have:
            m = make()
            self.have[key] = replace(m, df=cut(m.df, "measure") if self.tables and key[0] in ("product", "geometric") else m.df, key=key)
        return self.have[key]

    def degree(self, key: tuple, make) -> int:
        if key not in self.degrees:
            self.degrees[key] = make()
        return self.degrees[key]

    def initial(self, at: int, atom: Atom, over: list[str], given: list[str]) -> Measure:
        return self.measure(("initial", at, tuple(over), tuple(given)), lambda: M.init_measure(atom.df, over, given))

    def marginal(self, p: Measure, keep: tuple[str, ...]) -> Measure:
        return self.measure(("marginal", p.key, keep), lambda: M.marginal(p, keep))

    def condition(self, p: Measure, given: tuple[str, ...]) -> Measure:
        return self.measure(("condition", p.key, given), lambda: M.condition(p, given))

    def extend(self, p: Measure, more: tuple[str, ...]) -> Measure:
        return replace(M.extend_condition(p, more), key=("extend", p.key, more))

    def product(self, p: Measure, q: Measure, ln_b: float) -> Measure:
        return self.measure(("product", p.key, q.key, ln_b), lambda: M.truncated_product(p, q, ln_b))

    def geo_mean(self, parts: list[Measure]) -> Measure:
        return parts[0] if len(parts) == 1 else self.measure(("geometric", *(p.key for p in parts)), lambda: M.geo_mean(parts))


def degree(df: DataFrame, over: list[str], given: list[str]) -> int:
    """The largest number of y for an x; the number of rows where there is no x."""
    rows = df.select(*given, *over) if {*given, *over} == set(df.columns) else df.select(*given, *over).distinct()  # atoms are sets
    if not given:
        return rows.count()
    found = rows.groupBy(*given).count().agg(F.max("count")).first()[0]
    return found or 0


def statistics(q: ConjunctiveQuery, terms: list[Term], store: Store | None = None) -> dict[Term, tuple[int, int]]:
    """For each term the least degree among the atoms that cover it, and that atom's number. One aggregate an atom and term."""
    graph, out, store = q.graph, {}, store or Store()
    for c, full in terms:
        names = graph.variables(full)
        given = [v for v in names if graph.mask([v]) & c]
        over = [v for v in names if v not in given]
        fit = [(i, a) for i, a in enumerate(q.atoms) if set(names) <= set(a.variables)]
        out[(c, full)] = min((store.degree((i, tuple(over), tuple(given)), lambda a=a: degree(a.df, over, given)), i) for i, a in fit)  # noqa: B023
    return out


def measured_degrees(q: ConjunctiveQuery) -> dict[tuple[int, int], Fraction]:
    """For each atom and each side x of it, log_N of its largest degree of the rest given x: rows for a width that knows the data."""
    graph, store, out = q.graph, Store(), {}
    total = max(2, sum(a.df.count() for a in q.atoms))
    for i, a in enumerate(q.atoms):
        full = graph.mask(a.variables)
        for v in a.variables:
            given = graph.mask([v])
            over = [x for x in a.variables if x != v]
            if over:
                most = store.degree((i, tuple(over), (v,)), lambda a=a, over=over, v=v: degree(a.df, over, [v]))
                part = Fraction(math.log(max(1, most)) / math.log(total)).limit_denominator(1000)
                out[given, full] = min(out.get((given, full), Fraction(1)), part)
    return out


def ln_budget(ineq: FlowInequality, stats: dict[Term, tuple[int, int]]) -> float:
    """log of (product of degrees to their weights) to the power 1 / mass."""
    total = sum(float(w) * math.log(max(1, stats[t][0])) for t, w in ineq.right.items())
    return total / float(ineq.mass)


def rule_eval(q: ConjunctiveQuery, rule: CoverRule, omega, ln_b: float | None = None, trace: Trace | None = None, store: Store | None = None) -> tuple[list[JoinModel | ProductModel], float]:
    """Interpretations of the rule's targets whose supports cover the join of q's atoms, and the log of their budget."""
    ineq, _ = inequality_of(q.graph, rule, omega)
    store = store or Store()
    stats = statistics(q, list(ineq.right), store)
    ln_b = ln_budget(ineq, stats) if ln_b is None else ln_b
    graph = q.graph
    start = {}
    for (c, full), (_, at) in stats.items():
        names = graph.variables(full)
        given = [v for v in names if graph.mask([v]) & c]
        start[(c, full)] = [(store.initial(at, q.atoms[at], [v for v in names if v not in given], given), ineq.right[(c, full)])]
    return _evaluate(ineq, start, ln_b, trace or Trace(), store, 0), ln_b


Holdings = dict[Term, list[tuple[Measure, Fraction]]]
"""The measures of each term, with how much of the term's weight each one carries."""


def _held(p: Holdings, term: Term, amount: Fraction, store: Store) -> Measure | None:
    """One measure for an amount of a term: the geometric mean of those that carry it."""
    parts = []
    for m, w in p.get(term, []):
        if amount > 0:
            parts.append(m)
            amount -= w
    return store.geo_mean(parts) if parts else None


def _trim(p: Holdings, ineq: FlowInequality) -> Holdings:
    """What is held of each term, cut to the weight that the inequality still has of it."""
    out: Holdings = {}
    for t, parts in p.items():
        left = ineq.right.get(t, Fraction(0))
        kept = []
        for m, w in parts:
            if (part := min(w, left)) > 0:
                kept.append((m, part))
                left -= part
        if kept:
            out[t] = kept
    return out


def check_invariants(ineq: FlowInequality, p: Holdings, ln_b: float, store: Store | None = None) -> None:
    """What must hold at every node: each term's weight is carried, measures sum to at most 1, and unconditional ones have at most B rows of at least 1/B.

    A measure stays what it is, so with a store it is read once for a budget, not again at each node that holds it.
    """
    for t, w in ineq.right.items():
        assert sum((x for _, x in p.get(t, [])), Fraction(0)) >= w, f"{ineq.graph.label(t[1])} is carried by less than its weight"
    assert ineq.mass <= sum((w for (c, _), w in ineq.right.items() if not c), Fraction(0)), "more targets than unconditional terms"
    for (c, _), parts in p.items():
        for m, _ in parts:
            seen = (m.key, bool(c), ln_b)
            if store and m.key and seen in store.sound:
                continue
            if c:
                assert M.audit(m).isEmpty(), "a measure sums to more than 1"
            else:
                rows, least, total = m.df.agg(F.count("*"), F.min("lp"), F.sum(F.exp("lp"))).first()
                assert not rows or total <= 1 + 1e-6, "a measure sums to more than 1"
                assert rows <= math.exp(ln_b) * (1 + 1e-6) and (not rows or least >= -ln_b - M.SLACK), f"{rows} rows, least value {least}, budget {ln_b}"
            if store and m.key:
                store.sound.add(seen)


def _evaluate(ineq: FlowInequality, p: Holdings, ln_b: float, trace: Trace, store: Store, depth: int) -> list:
    g = ineq.graph
    if not ineq.mass:
        return []
    if trace.check:
        check_invariants(ineq, p, ln_b, store)
    for u, w in ineq.joins.items():
        if w and ineq.right.get((0, u)):
            trace.add(depth, "join target", g.label(u))
            return [JoinModel(u, m) for m, _ in p[(0, u)]]
    for group in ineq.groups:
        terms = [(group.term.g, side | group.term.g) for _, side in group.sides()]
        needs = [group.a, group.b, group.z]
        base = (0, group.term.g)
        need: dict[Term, Fraction] = {}
        for t, n in [*zip(terms, needs, strict=True), *([(base, group.k)] if group.term.g else [])]:
            need[t] = need.get(t, Fraction(0)) + n
        # a side of weight 0 may have no measure left; it asks nothing of a value
        if all(ineq.right.get(t, 0) >= n for t, n in need.items()):
            sides = [_held(p, t, n, store) for t, n in zip(terms, needs, strict=True)]
            trace.add(depth, "product target", group.term.label(g))
            model = ProductModel(group.term, _held(p, base, group.k, store), sides[0], sides[1], sides[2], group.triple())
            rest = ineq.copy()
            for t, n in need.items():
                if n:
                    rest.right[t] -= n
            rest.groups = [h for h in rest.groups if h.term != group.term]
            rest.tidy()
            return [model, *_evaluate(rest, _trim(p, rest), ln_b, trace, store, depth)]
    moves = next_moves(ineq)
    first = moves[0]
    used = [(0, first.low), (first.low, first.full)] if first.kind == "compose" else [(first.low, first.full)] if first.kind == "submodular" else [(0, first.full)]
    amount = min([first.weight, *(p[t][0][1] for t in used)])
    light, q = ineq.copy(), {t: list(parts) for t, parts in p.items()}
    for step in moves:
        trace.add(depth, step.kind, step.text(g))
        _apply(light, q, step, amount, ln_b, g, store)
    light.tidy()
    if first.kind != "compose":
        return _evaluate(light, q, ln_b, trace, store, depth)
    out = _evaluate(light, q, ln_b, trace, store, depth + 1)
    heavy = drop_unit(light, first.full, amount)
    trace.add(depth, "heavy branch", heavy.text())
    without = dict(q)
    without[(0, first.full)] = q[(0, first.full)][:-1]
    return out + _evaluate(heavy, _trim(without, heavy), ln_b, trace, store, depth + 1)


def _apply(ineq: FlowInequality, p: Holdings, step, amount: Fraction, ln_b: float, g: Hypergraph, store: Store) -> None:
    """Replace an amount of the step's terms on the right side and in the witness, and the measures that carry it."""

    def spend(term: Term, last: bool = False) -> Measure:
        ineq.right[term] -= amount
        at = -1 if last else 0
        m, w = p[term][at]
        if w > amount:
            p[term][at] = (m, w - amount)
        else:
            p[term].pop(at)
        return m

    def gain(term: Term, m: Measure) -> None:
        p.setdefault(term, []).append((m, amount))
        ineq.right[term] = ineq.right.get(term, Fraction(0)) + amount

    if step.kind == "decompose":
        whole = spend((0, step.full))
        gain((0, step.low), store.marginal(whole, g.variables(step.low)))
        gain((step.low, step.full), store.condition(whole, g.variables(step.low)))
    elif step.kind == "monotone":
        whole = spend((0, step.full))
        if step.low:
            gain((0, step.low), store.marginal(whole, g.variables(step.low)))
        ineq.mono[(step.low, step.full)] -= amount
    elif step.kind == "submodular":
        m = spend((step.low, step.full), last=True)  # what the move has just made
        gain((step.low | step.extra, step.full | step.extra), store.extend(m, g.variables(step.extra)))
        key = next(k for k, v in ineq.sub.items() if v >= amount and k[0] == step.low and {k[1], k[2]} == {step.full, step.low | step.extra})
        ineq.sub[key] -= amount
    else:
        gain((0, step.full), store.product(spend((0, step.low)), spend((step.low, step.full)), ln_b))


def merge_products(models: list[ProductModel]) -> list[list[ProductModel]]:
    """Models of one oriented product by their exponents, each once: those of a group are taken together, by means of their measures."""
    by: dict[tuple, dict[tuple, ProductModel]] = {}
    for i, m in enumerate(models):
        by.setdefault(m.triple, {})[tuple(x and (x.key or (i, k)) for k, x in enumerate(m.parts()))] = m
    return [list(same.values()) for same in by.values()]


def union_support(models: list[JoinModel], variables: tuple[str, ...]) -> DataFrame | None:
    """Tuples in any of the join measures."""
    dfs = [m.df.select(*variables) for m in {m.measure.key or i: m.measure for i, m in enumerate(models)}.values()]
    return reduce(DataFrame.union, dfs).distinct() if dfs else None


# -- rules and their models, tested against the full join --


def is_model(full: DataFrame, head: list[DataFrame]) -> DataFrame:
    """Tuples of a rule's body that no head table covers: none, if the tables are a model."""
    left = full
    for t in head:
        left = left.join(t, list(t.columns), "left_anti")
    return left


def model_size(head: list[DataFrame]) -> int:
    return sum(t.count() for t in head)


def uncovered(full: DataFrame, models: list, ln_b: float) -> DataFrame:
    """Tuples of the full join outside the B-supports of all interpretations: none, if they are a model."""
    left = full
    for m in models:
        if isinstance(m, JoinModel):
            inside = M.at(m.measure, full.select(*m.measure.columns).distinct(), "__lp").where(F.col("__lp") >= -ln_b - M.SLACK)
            left = left.join(inside.select(*m.measure.columns), m.measure.columns, "left_anti")
        else:
            left = left.join(_product_support(full, m, ln_b), full.columns, "left_anti")
    return left


def _product_support(full: DataFrame, m: ProductModel, ln_b: float) -> DataFrame:
    df, weighted = full, []
    for i, (part, w) in enumerate(((m.g, Fraction(1)), (m.x, m.triple[0]), (m.y, m.triple[1]), (m.z, m.triple[2]))):
        if part is None or not w:
            continue
        df = M.at(part, df, f"__l{i}")
        weighted.append((float(w), f"__l{i}"))
    return df.where(M.in_support(ln_b, *weighted)).select(*full.columns)
