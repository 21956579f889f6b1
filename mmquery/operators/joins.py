"""Join-only ways to answer a query, and the simple triangle algorithm with one product."""

from __future__ import annotations

import math
from collections.abc import Callable
from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..elimination import bags_in_order, decompositions, reduce_bags
from ..lp import maximise
from ..mmcost import exponent
from ..query import Atom, ConjunctiveQuery, exists, full_join, statistics_of
from ..sources.tables import cut, dropped_after, let_go
from ..widths import edge_cover
from .matmul import fuse, mm_bits, mm_blocked, mm_sparse, mm_total


def spark_answer(q: ConjunctiveQuery) -> DataFrame:
    """Pairwise joins as Catalyst orders them.

    Of three atoms that share variables two by two, each row of the first is joined first to the other in which it has fewer
    partners, so no row that closes nothing is made for a value of many partners where the other side has few.
    """
    if not _has_three_sides(q):
        return exists(full_join(q))
    r, s, t = made_once(*q.atoms)
    on_s, on_t = ([v for v in a.variables if v in r.variables] for a in (s, t))
    sized = r.df.join(degrees(s.df, on_s).withColumnRenamed("deg", "__s"), on_s).join(degrees(t.df, on_t).withColumnRenamed("deg", "__t"), on_t)
    fewer = F.col("__s") <= F.col("__t")
    one = sized.where(fewer).select(*r.variables).join(s.df, on_s).join(t.df, list(t.variables), "left_semi")
    two = sized.where(~fewer).select(*r.variables).join(t.df, on_t).join(s.df, list(s.variables), "left_semi")
    return exists(one.select(*q.variables).union(two.select(*q.variables)))


def _has_three_sides(q: ConjunctiveQuery) -> bool:
    """Whether there are three atoms, any two of them share variables and every variable is in two."""
    pairs = all(set(a.variables) & set(b.variables) for a in q.atoms for b in q.atoms)
    return len(q.atoms) == 3 and pairs and all(sum(v in a.variables for a in q.atoms) == 2 for v in q.variables)


def count_answer(q: ConjunctiveQuery) -> DataFrame:
    """The number of full assignments: joins of distinct atoms, which repeat nothing.

    Of three atoms that share variables two by two, two are joined in tiles where they have many rows for each of theirs, and
    the third filters the pairs of what they don't share with how often each was met.
    """
    if (sides := _three_sides(q)) is not None:
        r, s, t, inner = sides
        return mm_sparse(r.df, s.df, inner, count=True, tiles=True).join(t.df, list(t.variables)).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))
    return full_join(q).agg(F.count("*").alias("n"))


#: Rows of a join for each row of its sides from which it is done in tiles.
MANY_ROWS = 20


def _three_sides(q: ConjunctiveQuery) -> tuple[Atom, Atom, Atom, list[str]] | None:
    """The two atoms whose join has fewest rows, the third and what the two share, if every variable is in two of three atoms and those rows are many."""
    if not _has_three_sides(q):
        return None
    q = ConjunctiveQuery(made_once(*q.atoms))
    stats = statistics_of(list(q.atoms))
    best = None
    for i in range(3):
        r, s = (a for k, a in enumerate(q.atoms) if k != i)
        inner = sorted(set(r.variables) & set(s.variables))
        n, m = stats[id(r)], stats[id(s)]
        rows = n[0] * m[0] / max(1, n[1].get(frozenset(inner), n[0]), m[1].get(frozenset(inner), m[0]))
        if best is None or rows < best[0]:
            best = rows, n[0] + m[0], (r, s, q.atoms[i], inner)
    return best[2] if best[0] > MANY_ROWS * best[1] else None


def edges_answer(q: ConjunctiveQuery, head: tuple[str, ...]) -> DataFrame:
    """A partly projected head that lies in one atom: that atom, filtered by the rest."""
    inner = next(a for a in q.atoms if set(head) <= set(a.variables))
    rest = ConjunctiveQuery(tuple(a for a in q.atoms if a is not inner))
    joined = full_join(rest)
    shared = [v for v in inner.variables if v in joined.columns]
    return inner.df.join(joined.select(*shared).distinct(), shared, "left_semi").select(*head).distinct()


def wcoj(q: ConjunctiveQuery, order: list[str] | None = None) -> DataFrame:
    """Variable at a time: each prefix is extended by the atom with the fewest extensions, the others filter.

    Which atom that is is told from counts joined to the prefixes, so a prefix never meets more values than its rarest atom has. Each
    variable is a stage; the work is bounded by the fractional edge cover of the query. Prefixes that several atoms extend are
    tables in the shared folder: each is made once, so scans grow with atoms times variables.
    """
    asked = order or list(q.variables)
    order = connected_order(q, asked)
    first = order[0]
    prefix = reduce(lambda a, b: a.join(b, first, "left_semi"), [a.on((first,)) for a in q.atoms if first in a.variables])
    for i, v in enumerate(order[1:], 1):
        have = tuple(order[:i])
        holders = [a for a in q.atoms if v in a.variables]
        tables = [(a.on((*have, v)), [x for x in a.variables if x in have]) for a in holders]
        keyed = [(t, on) for t, on in tables if on]
        free = [t for t, on in tables if not on]
        if len(keyed) == 1:
            prefix = prefix.join(keyed[0][0], keyed[0][1])
        else:
            sized = prefix
            for k, (t, on) in enumerate(keyed):
                sized = sized.join(t.groupBy(*on).agg(F.count("*").alias(f"__n{k}")), on)
            names = [F.col(f"__n{k}") for k in range(len(keyed))]
            least = F.array_position(F.array(*names), F.least(*names)) - 1
            sized = cut(sized.select(*have, least.cast("int").alias("__least")), "prefix")
            parts = []
            for k, (t, on) in enumerate(keyed):
                part = sized.where(F.col("__least") == k).select(*have).join(t, on)
                for other, (t2, on2) in enumerate(keyed):
                    if other != k:
                        part = part.join(t2, [*on2, v], "left_semi")
                parts.append(part.select(*have, v))
            prefix = reduce(DataFrame.union, parts)
        for t in free:
            prefix = prefix.join(t, v, "left_semi")
    return prefix.select(*asked)


def connected_order(q: ConjunctiveQuery, order: list[str]) -> list[str]:
    """The order, but a variable waits until one before it shares an atom with it, so that no prefix is a product of parts."""
    left, out = list(order), []
    while left:
        v = next((v for v in left if not out or any(v in a.variables and set(out) & set(a.variables) for a in q.atoms)), None)
        if v is None:
            raise ValueError(f"{', '.join(left)} share no atom with {', '.join(out)}: parts of a query are answered apart")
        left.remove(v)
        out.append(v)
    return out


def wcoj_answer(q: ConjunctiveQuery, order: list[str] | None = None) -> DataFrame:
    return exists(wcoj(q, order))


#: Rows of all atoms from which a Boolean query is answered in slices, each of about so many.
SLICE_ROWS = 200_000


def in_slices(q: ConjunctiveQuery, answer: Callable[[ConjunctiveQuery], DataFrame], rows: int = SLICE_ROWS, by: str | None = None) -> DataFrame:
    """A Boolean query answered slice by slice of the values of one variable, until a slice says yes.

    Every assignment lies in one slice, so where all say no, so does the query. The variable is `by`, or that of most values; atoms without it are
    cut to what the slice's other atoms can meet. What a slice writes is deleted before the next.
    """
    spark = q.atoms[0].df.sparkSession
    q = ConjunctiveQuery(made_once(*q.atoms), q.head)
    stats = statistics_of(list(q.atoms))
    slices = -(-sum(n for n, _ in stats.values()) // rows)
    if slices <= 1:
        return answer(q)
    values = {v: min(stats[id(a)][1].get(frozenset([v]), stats[id(a)][0]) for a in q.atoms if v in a.variables) for v in q.variables}
    by = by or max(values, key=values.get)
    for i in range(slices):
        with dropped_after(spark):
            held = [a for a in q.atoms if by in a.variables]
            held = list(made_once(*(Atom(a.name, a.variables, a.df.where(F.pmod(F.xxhash64(by), F.lit(slices)) == i)) for a in held)))
            others = []
            for a in (a for a in q.atoms if by not in a.variables):
                df = a.df
                for b in held:
                    if on := tuple(v for v in a.variables if v in b.variables):
                        df = df.join(b.on(on), list(on), "left_semi")
                others.append(Atom(a.name, a.variables, df.select(*a.variables)))
            yes = answer(ConjunctiveQuery((*held, *made_once(*others)), q.head)).first()["answer"]
        if yes:
            break
    return spark.range(1).select(F.lit(yes).alias("answer"))


def join_bound(q: ConjunctiveQuery) -> float:
    """The most rows the full join can have for its atoms' sizes: the least product of sizes to the power of a fractional edge cover."""
    graph = q.graph
    names = list(graph.names)
    sizes = [a.df.count() for a in q.atoms]
    if not all(sizes):
        return 0.0
    # the dual: weights of variables, at most log of its size on each atom
    rows = [{names.index(v): Fraction(1) for v in a.variables} for a in q.atoms]
    most = [Fraction(math.log(n)).limit_denominator(10**6) + Fraction(1, 10**6) for n in sizes]
    return math.exp(float(maximise(rows, most, {i: Fraction(1) for i in range(len(names))}, len(names)).value))


def best_bags(q: ConjunctiveQuery) -> frozenset[int]:
    """The decomposition whose largest bag has the least edge cover."""
    graph = q.graph
    return min(decompositions(graph), key=lambda d: (max(edge_cover(graph, b) for b in d), len(d), sorted(d)))


def bag_parts(q: ConjunctiveQuery, names: tuple[str, ...], told: list[Atom]) -> list[Atom]:
    """The relations whose product a bag is, each of connected variables and joined variable by variable.

    `told` are projections of bags that were joined before. An atom that reaches out of the bag is projected into it where nothing else
    holds its variables there; another bag joins the whole of it.
    """
    inside = [a for a in q.atoms if set(a.variables) <= set(names)] + told
    reach = [Atom(a.name, tuple(v for v in a.variables if v in names), a.on(names)) for a in q.atoms if set(a.variables) & set(names) and not set(a.variables) <= set(names)]
    for a in sorted(reach, key=lambda a: -len(a.variables)):
        if not any(set(a.variables) <= set(b.variables) for b in inside):
            inside.append(a)
    parts: list[list[Atom]] = []
    for a in inside:
        met = [x for x in parts if any(set(a.variables) & set(b.variables) for b in x)]
        parts = [x for x in parts if x not in met] + [[*(b for x in met for b in x), a]]
    out = []
    for x in parts:
        part = ConjunctiveQuery(tuple(x))
        out.append(x[0] if len(x) == 1 else Atom("bag", part.variables, wcoj(part)))
    return out


def tree_answer(q: ConjunctiveQuery, bags: list[int] | None = None) -> DataFrame:
    """Bags by worst-case-optimal joins, from the leaves of their tree, first ones of the list first; each tells its parent what they share.

    A bag may hold variables that no atom connects within it, but bags below it do. Those that nothing connects stay
    relations apart, so no product of them is made.
    """
    graph = q.graph
    bags = list(bags) if bags is not None else sorted(best_bags(q))
    most = reduce_bags(bags)
    left = [graph.variables(b) for b in dict.fromkeys(bags) if b in most]
    told: dict[tuple[str, ...], list[Atom]] = {names: [] for names in left}
    answers = []
    while left:
        for names in left:
            others = [b for b in left if b != names]
            shared = [v for v in names if any(v in b for b in others)]
            into = next((b for b in others if set(shared) <= set(b)), None) if shared else None
            if into is not None or not shared:
                break
        else:
            raise ValueError("the bags are not those of a tree")
        left.remove(names)
        for part in bag_parts(q, names, told.pop(names)):
            on = tuple(v for v in part.variables if v in shared)
            if on:
                told[into].append(Atom("told", on, cut(part.on(on), "bag")))
            else:
                answers.append(exists(part.df))
    return _all(answers)


def _all(answers: list[DataFrame]) -> DataFrame:
    return answers[0] if len(answers) == 1 else reduce(DataFrame.union, answers).agg(F.bool_and("answer").alias("answer"))


def semijoin_answer(q: ConjunctiveQuery) -> DataFrame:
    """Acyclic queries: ears are semi-joined into the atom that holds what they share, until one atom a component is left."""
    left = list(q.atoms)
    roots = []
    while left:
        for a in left:
            others = [b for b in left if b is not a]
            shared = {v for v in a.variables if any(v in b.variables for b in others)}
            if not shared:
                left.remove(a)
                roots.append(exists(a.df))
                break
            into = next((b for b in others if shared <= set(b.variables)), None)
            if into is not None:
                on = sorted(shared)
                left[left.index(into)] = Atom(into.name, into.variables, into.df.join(a.on(tuple(on)), on, "left_semi"))
                left.remove(a)
                break
        else:
            raise ValueError("the query is cyclic")
    return _all(roots)


def degree_split_answer(q: ConjunctiveQuery, atom: int, by: str, threshold: int | None = None, light: list[int] | None = None, heavy: list[int] | None = None) -> DataFrame:
    """One atom is split by the degree of a variable; each part gets the decomposition that suits it.

    light and heavy are orders of variables (masks); the split variable's light values have at most `threshold` partners.
    """
    a = q.atoms[atom]
    limit = threshold if threshold is not None else max(1, int(a.df.count() ** 0.5))
    deg = a.df.groupBy(by).agg(F.count("*").alias("__d"))
    few = a.df.join(deg.where(F.col("__d") <= limit).select(by), by, "left_semi")
    many = a.df.join(deg.where(F.col("__d") > limit).select(by), by, "left_semi")
    parts = []
    for df, order in ((few, light), (many, heavy)):
        part = ConjunctiveQuery(tuple(Atom(x.name, x.variables, df) if i == atom else x for i, x in enumerate(q.atoms)), q.head)
        parts.append(tree_answer(part, bags_in_order(part.graph, order) if order else None))
    return reduce(DataFrame.union, parts).agg(F.bool_or("answer").alias("answer"))


def four_cycle_answer(q: ConjunctiveQuery, kernel: str = "blas", omega=None) -> DataFrame:
    """The earlier way with one product a side: a cycle is a pair of opposite values joined through both other variables.

    Values of the variable between that have few partners are joined through; heavy ones go by a product, whose pairs are only
    those that the other side still needs.
    """
    q = ConjunctiveQuery(made_once(*q.atoms))
    first = q.atoms[0]
    a, b = first.variables
    nxt = next(x for x in q.atoms if x is not first and b in x.variables)
    c = next(v for v in nxt.variables if v != b)
    rest = [x for x in q.atoms if x is not first and x is not nxt]
    last = next(x for x in rest if a in x.variables)
    d = next(v for v in last.variables if v != a)
    other = next(x for x in rest if x is not last)
    limit = triangle_threshold(sum(x.df.count() for x in q.atoms), omega or BEST_OMEGA)

    def through(r: DataFrame, s: DataFrame, y: str) -> DataFrame:
        deg = degrees(s, [y])
        few, many = (s.join(deg.where(c_).select(y), y, "left_semi") for c_ in (F.col("deg") <= limit, F.col("deg") > limit))
        heavy = r.join(many.select(y).distinct(), y, "left_semi")
        dense = mm_sparse(heavy, many, [y]) if kernel == "sparse" else mm_blocked(heavy, many, [y], kernel=kernel)
        return r.join(few, y).select(a, c).union(dense.select(a, c)).distinct()

    one = cut(through(first.df, nxt.df, b), "opposite")
    ends = [x.df.join(one.select(v).distinct(), v, "left_semi") for x, v in ((last, a), (other, c))]
    return exists(one.join(through(*ends, d), [a, c], "left_semi"))


def degrees(df: DataFrame, given: list[str]) -> DataFrame:
    return df.groupBy(*given).agg(F.count("*").alias("deg"))


def heavy_light(df: DataFrame, given: str, threshold: int) -> DataFrame:
    """Each value with its degree and whether it is heavy."""
    return degrees(df, [given]).withColumn("heavy", F.col("deg") > threshold)


def degree_classes(df: DataFrame, given: str) -> DataFrame:
    """How many values fall in each power-of-two class of degrees."""
    return degrees(df, [given]).withColumn("deg_class", F.floor(F.log2("deg")).cast("int")).groupBy("deg_class").agg(F.count("*").alias("values"), F.sum("deg").alias("tuples"))


#: The best exponent known, by which the triangle algorithm sets its threshold.
BEST_OMEGA = Fraction(2371552, 1000000)


def triangle_threshold(n: int, omega) -> int:
    """N to the power (w - 1) / (w + 1)."""
    w = exponent(omega)
    return max(1, int(n ** float((w - 1) / (w + 1))))


def _triangle_names(r: Atom, s: Atom, t: Atom) -> tuple[str, str, str]:
    return (next(v for v in r.variables if v in t.variables), next(v for v in r.variables if v in s.variables), next(v for v in s.variables if v in t.variables))


def made_once(*atoms: Atom) -> tuple[Atom, ...]:
    """Atoms as tables in the shared folder: degrees, light and heavy parts all read them."""
    return tuple(Atom(a.name, a.variables, cut(a.df, "atom")) for a in atoms)


def triangle_limit(r: Atom, s: Atom, t: Atom, omega) -> int:
    return triangle_threshold(r.df.count() + s.df.count() + t.df.count(), omega)


def heavy_parts(r: Atom, s: Atom, t: Atom, limit: int) -> tuple[DataFrame, DataFrame]:
    """R and S restricted to values heavy in all three: x in R, y in S, z in T have more than `limit` partners."""
    x, y, z = _triangle_names(r, s, t)
    heavy = {v: degrees(a.df, [v]).where(F.col("deg") > limit).select(v) for a, v in ((r, x), (s, y), (t, z))}
    return r.df.join(heavy[x], x, "left_semi").join(heavy[y], y, "left_semi"), s.df.join(heavy[y], y, "left_semi").join(heavy[z], z, "left_semi")


def triangle(r: Atom, s: Atom, t: Atom, omega=BEST_OMEGA, threshold: int | None = None, kernel: str = "sparse") -> DataFrame:
    """The pairs (x, z) of T that lie in a triangle R(x,y), S(y,z), T(z,x): light values by joins, heavy ones by a product.

    A value of x with few y in R is joined through, likewise y in S and z in T. The variable whose join has the fewest rows goes first, and the
    next ones join only what is heavy in those before; what is left are values heavy in all three, of which there are at most
    N / threshold a variable, so their product is small and dense.
    """
    x, y, z = _triangle_names(r, s, t)
    r, s, t = made_once(r, s, t)
    limit = threshold if threshold is not None else triangle_limit(r, s, t, omega)
    ends = {x: (r, t), y: (s, r), z: (t, s)}
    far = {x: s, y: t, z: r}

    def through(v: str) -> int:
        """Rows of the join through the light values of a variable."""
        a, b = ends[v]
        few = degrees(a.df, [v]).where(F.col("deg") <= limit)
        return few.join(degrees(b.df, [v]).withColumnRenamed("deg", "__o"), v).agg(F.sum(F.col("deg") * F.col("__o"))).first()[0] or 0

    light, before = [], []
    for v in sorted((x, y, z), key=through):
        a, b = (_only(df, before) for df in (x_.df for x_ in ends[v]))
        few = degrees(ends[v][0].df, [v]).where(F.col("deg") <= limit).select(v)
        joined = a.join(few, v, "left_semi").join(b, v)
        light.append(joined.join(far[v].df, list(far[v].variables), "left_semi").select(x, z))
        before.append((v, degrees(ends[v][0].df, [v]).where(F.col("deg") > limit).select(v)))
    rh, sh = heavy_parts(r, s, t, limit)
    product = {"sparse": lambda: mm_sparse(rh, sh, [y]), "bits": lambda: mm_bits(rh, sh, y, x, z)}.get(kernel, lambda: mm_blocked(rh, sh, [y], kernel=kernel))()
    heavy = t.df.join(product, [x, z], "left_semi").select(x, z)
    return reduce(DataFrame.union, [*light, heavy]).distinct()


def _only(df: DataFrame, heavy: list[tuple[str, DataFrame]]) -> DataFrame:
    """Rows whose values are heavy in the variables given."""
    return reduce(lambda d, h: d.join(h[1], h[0], "left_semi") if h[0] in d.columns else d, heavy, df)


def triangle_answer(r: Atom, s: Atom, t: Atom, **options) -> DataFrame:
    return exists(triangle(r, s, t, **options))


def _clique_parts(edges: DataFrame, k: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Adjacent pairs of the three groups of vertices, each group as one index: A B, B C and A C."""
    parts = [-(-k // 3), -(-(k - 1) // 3), k // 3]
    first, second, third = (small_cliques(edges, n, f"g{i}_") for i, n in enumerate(parts))
    ab = _adjacent(edges, first, parts[0], "g0_", second, parts[1], "g1_")
    bc = _adjacent(edges, second, parts[1], "g1_", third, parts[2], "g2_")
    ac = _adjacent(edges, first, parts[0], "g0_", third, parts[2], "g2_")
    a, b, c = ([f"g{i}_{j}" for j in range(n)] for i, n in enumerate(parts))
    return tuple(_fused(_fused(df, p, pn), q_, qn) for df, p, pn, q_, qn in ((ab, a, "A", b, "B"), (bc, b, "B", c, "C"), (ac, a, "A", c, "C")))


#: Side of a piece of a clique's product: the pairs asked of it are few, so small pieces multiply fewer zeros.
CLIQUE_SIDE = 512


def _clique_tables(edges: DataFrame, k: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The parts as tables, each made once.

    Of four vertices A C is A B by another name; only those B are kept that a C of the same A follows, those C that a B precedes, and
    those B C that end a triangle.
    """
    spark = edges.sparkSession
    edges = cut(edges, "edges")
    let_go(spark)
    r, s, t = _clique_parts(edges, k)
    r = cut(r, "clique")
    let_go(spark)
    if k != 4:
        return r, cut(s, "clique"), cut(t, "clique")
    ends = r.groupBy("A").agg(F.min("B").alias("__first"), F.max("B").alias("__last")).where("__first < __last")
    sized = cut(r.join(ends, "A"), "clique")
    last = r.select(F.col("A.g0_1").alias("B"), F.col("B").alias("C")).distinct()
    r, s, t = sized.where("B < __last").select("A", "B"), cut(last, "clique"), sized.where("B > __first").select("A", F.col("B").alias("C"))
    let_go(spark)
    return r, s, t


def clique_count(edges: DataFrame, k: int, kernel: str = "sparse") -> DataFrame:
    """Cliques u1 < ... < uk of an oriented graph (u, v) by three groups of vertices and one counting product.

    Each group is a small clique; two groups are adjacent when all their members are. Groups follow each other in the vertex
    order, so each clique is counted once. Parts of k: as even as they come. With a dense kernel edges and pairs of groups are tables in the
    shared folder, and pairs of A and C that aren't adjacent are never made.
    """
    if kernel != "sparse":
        r, s, t = _clique_tables(edges, k)
        return mm_total(r, s, t, ["B"], kernel=kernel, side=CLIQUE_SIDE)
    r, s, t = _clique_parts(edges, k)
    product = mm_sparse(r, s, ["B"], count=True)
    return product.join(t, ["A", "C"], "left_semi").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def clique_answer(edges: DataFrame, k: int, kernel: str = "sparse") -> DataFrame:
    """Whether there is a clique of k vertices, by the Boolean product of the three groups."""
    r, s, t = _clique_parts(edges, k)
    product = mm_sparse(r, s, ["B"]) if kernel == "sparse" else mm_blocked(r, s, ["B"], kernel=kernel)
    return exists(t.join(product, ["A", "C"], "left_semi"))


def _fused(df: DataFrame, cols: list[str], name: str) -> DataFrame:
    return df.withColumnRenamed(cols[0], name) if len(cols) == 1 else fuse(df, cols, name)


def small_cliques(edges: DataFrame, k: int, prefix: str) -> DataFrame:
    """Cliques of k vertices in ascending order, a column each."""
    if k == 1:
        return edges.select(F.col("u").alias(f"{prefix}0")).union(edges.select(F.col("v").alias(f"{prefix}0"))).distinct()
    out = edges.select(F.col("u").alias(f"{prefix}0"), F.col("v").alias(f"{prefix}1"))
    for j in range(2, k):
        e = edges.select(F.col("u").alias(f"{prefix}{j - 1}"), F.col("v").alias(f"{prefix}{j}"))
        out = out.join(e, f"{prefix}{j - 1}")
        for i in range(j - 1):
            out = out.join(edges.select(F.col("u").alias(f"{prefix}{i}"), F.col("v").alias(f"{prefix}{j}")), [f"{prefix}{i}", f"{prefix}{j}"], "left_semi")
    return out


def _adjacent(edges: DataFrame, a: DataFrame, n: int, pa: str, b: DataFrame, m: int, pb: str) -> DataFrame:
    """Pairs of small cliques all of whose members are joined, the first's all before the second's."""
    link = edges.select(F.col("u").alias(f"{pa}{n - 1}"), F.col("v").alias(f"{pb}0"))
    out = a.join(link, f"{pa}{n - 1}").join(b, f"{pb}0")
    for i in range(n):
        for j in range(m):
            if (i, j) != (n - 1, 0):
                out = out.join(edges.select(F.col("u").alias(f"{pa}{i}"), F.col("v").alias(f"{pb}{j}")), [f"{pa}{i}", f"{pb}{j}"], "left_semi")
    return out
