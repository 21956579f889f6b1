"""The two-phase solver: cover rules first, then elimination plans over their models.

Phase one evaluates a rule for every choice of a step of each plan and of an odd side for each of its products. Phase two
runs each plan once: a join step joins what the rules' join models support, a product step multiplies within what their
product models support, and a step's result is the union of its options'. Supports may be supersets, since every
step also joins the atoms themselves; and any choice of targets supports some plan, so nothing is missed.
"""

from __future__ import annotations

import math
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import measures as M
from .elimination import eliminate, essential
from .flow import CoverRule
from .hypergraph import Hypergraph
from .mmcost import MatMulTerm, exponent, step_options, tighten
from .operators.matmul import mm_blocked
from .query import Atom, ConjunctiveQuery, exists, normalise
from .rule_eval import JoinModel, ProductModel, Store, Trace, merge_products, rule_eval, union_support
from .sources.tables import cut
from .widths import Plans, reduce_plans

MOST_VARIABLES = 6


def cover_rules(plans: Plans) -> list[CoverRule]:
    """One rule for each choice of a step of every plan and of an odd side of each product of the chosen steps."""
    out: dict[CoverRule, None] = {}
    for pick in product(*(sorted(p) for p in plans.plans)):
        chosen = sorted(set(pick))
        joins = tuple(sorted({plans.steps[s][0] for s in chosen}))
        terms = sorted({t for s in chosen for t in plans.steps[s][1]}, key=str)
        for odd in product(*((t.z, t.y, t.x) for t in terms)):
            out.setdefault(CoverRule(joins, tuple(t.oriented(o) for t, o in zip(terms, odd, strict=True))))
    return list(out)


def target_choices(rules: list[CoverRule]) -> int:
    """How many ways there are to pick a target from every rule; never listed."""
    n = 1
    for r in rules:
        n *= len(r.joins) + len(r.products)
    return n


def supported_plan(plans: Plans, choice: list[int | MatMulTerm]) -> tuple[int, dict[int, int | MatMulTerm]] | None:
    """A plan whose every step has its join target, or all three orientations of one of its products, among the chosen targets."""
    joins = {c for c in choice if isinstance(c, int)}
    terms = {c for c in choice if isinstance(c, MatMulTerm)}
    for i, plan in enumerate(plans.plans):
        how: dict[int, int | MatMulTerm] = {}
        for s in sorted(plan):
            closure, options = plans.steps[s]
            if closure in joins:
                how[s] = closure
            elif (t := next((t for t in options if all(t.oriented(o) in terms for o in (t.x, t.y, t.z))), None)) is not None:
                how[s] = t
            else:
                break
        else:
            return i, how
    return None


def _mean(df: DataFrame, measures: list[M.Measure], name: str) -> DataFrame:
    """Rows with the log of the mean of the measures at them, where it isn't 0; a measure may depend on fewer variables than others."""
    if not measures:
        return df.withColumn(name, F.lit(0.0))
    cols = df.columns
    for i, m in enumerate(measures):
        df = df.join(m.df.withColumnRenamed("lp", f"__lp{i}"), m.columns, "left" if len(measures) > 1 else "inner")
    if len(measures) == 1:
        return df.select(*cols, F.col("__lp0").alias(name))
    total = sum((F.coalesce(F.exp(f"__lp{i}"), F.lit(0.0)) for i in range(len(measures))), F.lit(0.0))
    return df.withColumn(name, total / len(measures)).where(F.col(name) > 0).select(*cols, F.log(name).alias(name))


def mm_targets(models: list[list[ProductModel]], m1: DataFrame, m2: DataFrame, graph: Hypergraph, ln_b: float, kernel: str = "sparse", metrics: list | None = None) -> DataFrame:
    """Pairs of the outer sides that share a value of the eliminated one, within the support of product models of all three orientations.

    The models of one orientation have the same exponents. All measures of a side are merged by their mean; the eliminated and the row
    side fall into buckets of halving values, and for each pair of buckets the column side is cut at the least value that the three
    conditions allow. All bucket pairs are one job: the pair is part of the block key. The kernel "sparse" joins instead.
    `metrics` gets a DataFrame: the group's columns, the bucket pair, and the numbers of values dim_m, dim_n, dim_o of the
    row, eliminated and column side.
    """
    term = models[0][0].term
    g_mask = term.g
    sides = {s for group in models for m in group for s in (m.term.x, m.term.y, m.term.z)}
    block = next(s for s in sides if set(graph.variables(s)) <= set(m1.columns) & set(m2.columns))
    row = next(s for s in sides if s != block and set(graph.variables(s)) <= set(m1.columns))
    col = next(s for s in sides if s not in (block, row))
    named = {block: "x", row: "y", col: "z"}
    held: dict[str, dict] = {"x": {}, "y": {}, "z": {}, "g": {}}
    for m in (m for group in models for m in group):
        for where, part in ((named[m.term.x], m.x), (named[m.term.y], m.y), (named[m.term.z], m.z), ("g", m.g)):
            if part is not None:
                held[where][part.key or id(part)] = part
    p = {k: list(v.values()) for k, v in held.items()}
    if not g_mask:
        p["g"] = []
    group = list(graph.variables(g_mask))
    names = {k: list(graph.variables(s)) for s, k in named.items()}
    half = math.log(2)
    a = _mean(_mean(_mean(m1, p["x"], "__x"), p["y"], "__y"), p["g"], "__g")
    b = _mean(_mean(m2, p["x"], "__x"), p["z"], "__z")
    bucket = lambda c: F.greatest(F.floor(-F.col(c) / half), F.lit(0)).cast("int")
    a = a.withColumn("__i", bucket("__x")).withColumn("__j", bucket("__y"))
    b = b.withColumn("__i", bucket("__x"))
    lows = []
    for m in (g[0] for g in models):
        weight = {named[m.term.x]: m.triple[0], named[m.term.y]: m.triple[1], named[m.term.z]: m.triple[2]}
        odd = named[m.term.z]
        others = [k for k in "xyz" if k != odd]
        tight = tighten(weight[others[0]], weight[others[1]], weight[odd], min(sum(m.triple), exponent(3)))
        weight = {others[0]: tight[0], others[1]: tight[1], odd: tight[2]}
        # a mean of n measures is at least each one's n-th part
        ln_k = math.log(max(1, len(p["g"]))) + sum(float(w) * math.log(max(1, len(p[k]))) for k, w in weight.items())
        spent = -(ln_b + ln_k) - F.col("__g") + half * (F.col("__i") * float(weight["x"]) + F.col("__j") * float(weight["y"]))
        if weight["z"]:
            lows.append(spent / float(weight["z"]))
        else:  # the column side isn't asked: the bucket pair is in or out
            lows.append(F.when(spent <= M.SLACK, F.lit(-1e30)).otherwise(F.lit(1e30)))
    a = a.withColumn("__low", F.greatest(*lows) - M.SLACK if len(lows) > 1 else lows[0] - M.SLACK).where(F.col("__low") <= M.SLACK)
    keys = [*group, "__i"]
    pairs = a.select(*keys, "__j", "__low").distinct()
    within = b.join(pairs, keys).where(F.col("__z") >= F.col("__low"))
    if metrics is not None:
        a, within = cut(a, "rows"), cut(within, "columns")
        size = lambda df, k, n: df.groupBy(*keys, "__j").agg(F.count_distinct(*(F.struct(c) for c in names[k])).alias(n))
        metrics.append(size(a, "y", "dim_m").join(size(a, "x", "dim_n"), [*keys, "__j"]).join(size(within, "z", "dim_o"), [*keys, "__j"]).withColumnsRenamed({"__i": "bucket_x", "__j": "bucket_y"}))
    if kernel == "sparse":
        joined = a.select(*keys, *names["x"], *names["y"], "__low").join(b.select(*keys, *names["x"], *names["z"], "__z"), [*keys, *names["x"]])
        return joined.where(F.col("__z") >= F.col("__low")).select(*group, *names["y"], *names["z"]).distinct()
    left = a.select(*keys, "__j", *names["x"], *names["y"]).distinct()
    right = within.select(*keys, "__j", *names["x"], *names["z"]).distinct()
    out = mm_blocked(left, right, names["x"], [*keys, "__j"], kernel=kernel)
    return out.select(*group, *names["y"], *names["z"]).distinct()


def _join_all(tables: list[DataFrame]) -> DataFrame:
    def both(x: DataFrame, y: DataFrame) -> DataFrame:
        on = [c for c in x.columns if c in y.columns]
        return x.join(y, on) if on else x.crossJoin(y)

    return reduce(both, tables)


def run_plan(q: ConjunctiveQuery, order: tuple[int, ...], models: list, ln_b: float, kernel: str = "sparse", trace: Trace | None = None, store: Store | None = None, metrics: list | None = None) -> DataFrame:
    """Eliminate the blocks of an order over the models; the answer of what is left. With a store of tables, so is each step's result."""
    graph, store = q.graph, store or Store()
    tables: list[tuple[int, DataFrame]] = [(graph.mask(a.variables), a.df) for a in q.atoms]
    steps = eliminate(graph, order)
    kept = {id(s) for s in essential(steps)}
    joins: dict[int, list[JoinModel]] = {}
    products: dict[MatMulTerm, list[ProductModel]] = {}
    for m in models:
        if isinstance(m, JoinModel):
            joins.setdefault(m.closure, []).append(m)
        else:
            products.setdefault(m.term, []).append(m)
    products = {t: merge_products(ms) for t, ms in products.items()}
    for s in steps:
        inside = [(m, t) for m, t in tables if m & s.block]
        outside = [(m, t) for m, t in tables if not m & s.block]
        names = graph.variables(s.near)
        results = []
        if id(s) not in kept:
            results.append(_project(_join_all([t for _, t in inside]), names))
        else:
            if (support := union_support(joins.get(s.closure, []), graph.variables(s.closure))) is not None:
                results.append(_project(_join_all([support, *(t for _, t in inside)]), names))
                if trace:
                    trace.add(0, "join step", graph.label(s.closure))
            for t in step_options(s):
                turned = [t.oriented(o) for o in (t.x, t.y, t.z)]
                if not all(o in products for o in turned):
                    continue
                one = _join_all([tab for m, tab in inside if m & ~(s.block | t.x | t.g) == 0])
                two = _join_all([tab for m, tab in inside if m & ~(s.block | t.y | t.g) == 0])
                for trio in product(*(products[o] for o in turned)):
                    results.append(mm_targets(list(trio), one, two, graph, ln_b, kernel, metrics).select(*names))
                if trace:
                    trace.add(0, "product step", t.label(graph))
        if not results:
            return exists(q.atoms[0].df.where(F.lit(False)))
        merged = reduce(DataFrame.union, results).distinct() if len(results) > 1 else results[0]
        if store.tables:
            merged = cut(merged)
        tables = [*outside, (s.near, merged)]
    return exists(_join_all([t for _, t in tables]))


def _project(df: DataFrame, names: tuple[str, ...]) -> DataFrame:
    return df.select(*names).distinct() if names else df.select(F.lit(1).alias("__true")).limit(1)


def answer_boolean(q: ConjunctiveQuery, omega, kernel: str = "sparse", mm: bool = True, trace: Trace | None = None, tables: bool = True, metrics: list | None = None) -> DataFrame:
    """Whether the query has an answer, by rules and plans. Queries in several components are answered part by part.

    With `tables`, atoms, measures and steps are made once, as tables in the shared folder, and plans run one after
    another until one says yes; without, all is one lazy plan. Where `metrics` are asked for, the last plan's products are
    measured and only multiplied if the answer is read.
    """
    q = normalise(q)
    if len(q.variables) > MOST_VARIABLES:
        raise ValueError(f"more than {MOST_VARIABLES} variables: use a shape's own operator or joins")
    graph = q.graph
    parts = graph.components()
    if len(parts) > 1:
        answers = [answer_boolean(ConjunctiveQuery(tuple(a for a in q.atoms if graph.mask(a.variables) & c)), omega, kernel, mm, trace, tables, metrics) for c in parts]
        return reduce(DataFrame.union, answers).agg(F.bool_and("answer").alias("answer"))
    omega = exponent(omega)
    plans = plan_set(graph, omega, mm)
    rules = cover_rules(plans)
    # a join measure may have as many rows as the budget: the last plan's products are measured without it
    store = Store(tables and (metrics is None or len(plans.orders) > 1))
    if tables:
        q = ConjunctiveQuery(tuple(Atom(a.name, a.variables, cut(a.df, "atom")) for a in q.atoms), q.head)
    models, budget = [], 0.0
    for rule in rules:
        found, ln_b = rule_eval(q, rule, omega, trace=trace, store=store)
        models += found
        budget = max(budget, ln_b)
    if not tables:
        answers = [run_plan(q, order, models, budget, kernel, trace, store, metrics) for order in plans.orders]
        return answers[0] if len(answers) == 1 else reduce(DataFrame.union, answers).agg(F.bool_or("answer").alias("answer"))
    for order in plans.orders:
        if metrics is not None and order == plans.orders[-1]:  # nothing follows from its answer, so what it multiplies stays undone
            return run_plan(q, order, models, budget, "sparse", trace, Store(), metrics)
        answer = run_plan(q, order, models, budget, kernel, trace, store, metrics)
        if answer.first()["answer"]:
            break
        if trace:
            trace.add(0, "plan says no", " ".join(map(graph.label, order)))
    return answer


def plan_set(graph: Hypergraph, omega, mm: bool = True) -> Plans:
    """Few plans that keep the width; without products, those of the single orders."""
    if mm:
        return reduce_plans(graph, omega)[0]
    from .elimination import single_orders

    return Plans.of(graph, single_orders(graph), mm=False)
