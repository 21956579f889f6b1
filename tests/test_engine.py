"""Operators on Spark against brute force, and workloads against SQL."""

import itertools
import math
import random
from fractions import Fraction as Fr

import duckdb
import pytest
from pyspark.sql import functions as F

from mmquery import measures as M
from mmquery import rule_eval as RE
from mmquery import workloads as W
from mmquery.functions import sql as sqlfn
from mmquery.operators import aggregates as A
from mmquery.operators import joins as J
from mmquery.operators.matmul import mm_bits, mm_blocked, mm_sparse, mm_total, mm_words, word_count, word_sum
from mmquery.query import Atom, ConjunctiveQuery, from_sql, full_join, normalise, parse_rule
from mmquery.solver import answer_boolean, cover_rules, plan_set


def edges(spark, pairs, cols, kind="long"):
    return spark.createDataFrame(pairs, ", ".join(f"{c} {kind}" for c in cols))


def triangle_of(spark, r, s, t):
    return ConjunctiveQuery((Atom.of("R", edges(spark, r, "xy"), "xy"), Atom.of("S", edges(spark, s, "yz"), "yz"), Atom.of("T", edges(spark, t, "zx"), "zx")))


def brute(r, s, t):
    return {(x, y, z) for (x, y) in set(r) for (y2, z) in set(s) if y == y2 and (z, x) in set(t)}


CASES = {
    "empty": ([(1, 2)], [], [(3, 1)]),
    "one": ([(1, 2)], [(2, 3)], [(3, 1)]),
    "none": ([(1, 2), (4, 5)], [(2, 3)], [(3, 4)]),
    "full": (list(itertools.product(range(4), repeat=2)),) * 3,
    "hub": ([(i, 0) for i in range(12)], [(0, j) for j in range(12)], [(j, i) for i in range(12) for j in range(12) if (i + j) % 5 == 0]),
}


@pytest.mark.parametrize("case", CASES)
def test_triangle_answers(spark, case):
    r, s, t = CASES[case]
    q = triangle_of(spark, r, s, t)
    want = brute(r, s, t)
    pairs = {(x, z) for x, _, z in want}
    for threshold in (0, 2, 1000):
        got = {(a["x"], a["z"]) for a in J.triangle(*q.atoms, threshold=threshold).collect()}
        assert got == pairs
    assert {tuple(a) for a in J.wcoj(q, ["x", "y", "z"]).collect()} == want
    assert J.tree_answer(q).first()["answer"] == bool(want)
    assert A.triangle_count(*q.atoms, threshold=2).first()["n"] == len(want)


@pytest.mark.parametrize("case", ["none", "hub"])
def test_solver_on_triangles(spark, case):
    r, s, t = CASES[case]
    q = triangle_of(spark, r, s, t)
    assert answer_boolean(q, Fr(12, 5)).first()["answer"] == bool(brute(r, s, t))


@pytest.mark.parametrize("answer", [True, False])
def test_solver_multiplies_on_the_four_cycle(spark, answer):
    """Two plans, 36 rules, a product of dense blocks a step; both answers, with the product steps in the trace."""
    n = 8
    pairs = [(i, j) for i in range(n) for j in range(n)]
    last = pairs if answer else [(i + 100, j) for i, j in pairs]
    atoms = [Atom.of(v, edges(spark, e, v), v) for v, e in (("wx", pairs), ("xy", pairs), ("yz", [(i, j) for i, j in pairs if i != j]), ("zw", last))]
    q = ConjunctiveQuery(tuple(atoms))
    plans = plan_set(q.graph, Fr(12, 5))
    assert len(plans.orders) == 2 and len(cover_rules(plans)) == 36
    trace, metrics = RE.Trace(), []
    assert answer_boolean(q, Fr(12, 5), kernel="blas", trace=trace, metrics=metrics).first()["answer"] == answer
    kinds = [k for _, _, k, _ in trace.lines]
    assert "product step" in kinds and "product target" in kinds and metrics
    assert ("plan says no" in kinds) != answer  # a yes ends it


def test_solver_on_a_pyramid_with_products(spark):
    base = [(a, b, c) for a in range(4) for b in range(4) for c in range(4) if (a + b + c) % 3]
    side = [(a, a % 2) for a in range(4)]
    for extra, want in ((0, True), (1, False)):
        third = [(c, 5) for c in range(4)] if extra else side
        q = ConjunctiveQuery((Atom.of("b", edges(spark, base, "abc"), "abc"), Atom.of("x", edges(spark, side, "ay"), "ay"), Atom.of("y", edges(spark, side, "by"), "by"), Atom.of("z", edges(spark, third, "cy"), "cy")))
        assert answer_boolean(q, Fr(12, 5), kernel="bitset").first()["answer"] == want


def test_invariants_hold_at_every_node(spark):
    q = triangle_of(spark, *CASES["hub"])
    for rule in cover_rules(plan_set(q.graph, Fr(12, 5))):
        models, ln_b = RE.rule_eval(q, rule, Fr(12, 5), trace=RE.Trace(check=True))
        assert models
    with pytest.raises(AssertionError):
        RE.rule_eval(q, rule, Fr(12, 5), ln_b=0.1, trace=RE.Trace(check=True))


def test_heavy_parts_hold_rows(spark):
    """On the hub relations the threshold that N and the exponent set leaves values heavy in all three, and light ones."""
    r, s, t = W.bind(spark, "/root/testdata/sf0.01", W.HUB).atoms
    limit = J.triangle_limit(r, s, t, J.BEST_OMEGA)
    rh, sh = J.heavy_parts(r, s, t, limit)
    assert rh.count() > 5000 and sh.count() > 5000
    assert J.degrees(r.df, ["p"]).where(F.col("deg") <= limit).count() > 100


def test_prior_four_cycle(spark):
    rng = random.Random(7)
    for n in (3, 30):
        es = [[(rng.randrange(12), rng.randrange(12)) for _ in range(n)] for _ in range(4)]
        q = ConjunctiveQuery(tuple(Atom.of(v, edges(spark, e, v), v) for v, e in zip(("ab", "bc", "cd", "da"), es, strict=True)))
        want = any(b == b2 and c == c2 and d == d2 and a == a2 for a, b in es[0] for b2, c in es[1] for c2, d in es[2] for d2, a2 in es[3])
        for kernel in ("sparse", "blas"):
            assert J.four_cycle_answer(q, kernel).first()["answer"] == want


def test_scans_of_variable_at_a_time_joins_stay_few(spark, sf_dir):
    """Scans of the last variable's plan: an atom is read a few times, however many variables came before."""
    for atoms, most in ((W.TRIANGLE, 12), (W.PYRAMID3, 24), (W.PYRAMID4, 32)):
        plan = J.wcoj(W.bind(spark, sf_dir, atoms))._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("Relation [") <= most


def test_wcoj_refuses_to_pair_what_shares_nothing(spark):
    a = edges(spark, [(1, 2)], "xy")
    with pytest.raises(ValueError):
        J.wcoj(ConjunctiveQuery((Atom.of("a", a, "xy"), Atom.of("b", a, "zw"))))


def test_orders_and_bags_whose_variables_no_atom_connects(spark):
    """Prefixes and bags that atoms don't connect by themselves: reordered, told by other bags, or parts apart."""
    from mmquery.elimination import bags_in_order

    rng = random.Random(5)
    names = ["ab", "bc", "cd", "de", "ea"]
    for n in (4, 14):
        es = [sorted({(rng.randrange(8), rng.randrange(8)) for _ in range(n)}) for _ in names]
        q = ConjunctiveQuery(tuple(Atom.of(v, edges(spark, e, v), v) for v, e in zip(names, es, strict=True)))
        want = {(a, b, c, d, e) for a, b in es[0] for b2, c in es[1] if b == b2 for c2, d in es[2] if c == c2 for d2, e in es[3] if d == d2 if (e, a) in es[4]}
        assert {tuple(r) for r in J.wcoj(q, list("acebd")).select(*"abcde").collect()} == want
        for order in ("bdace", "abcde"):
            assert J.tree_answer(q, bags_in_order(q.graph, [q.graph.mask([v]) for v in order])).first()["answer"] == bool(want)
    q = ConjunctiveQuery((Atom.of("r", edges(spark, [(1, 2)], "xy"), "xy"), Atom.of("s", edges(spark, [(2, 3)], "yz"), "yz"), Atom.of("one", edges(spark, [(7,)], "y"), "y")))
    assert not J.tree_answer(q).first()["answer"]
    assert not J.tree_answer(q, [q.graph.mask(["x", "z"]), q.graph.mask(["x", "y"]), q.graph.mask(["y", "z"])][1:]).first()["answer"]


def test_stream_triangles_whatever_the_batches(spark, sf_dir, tmp_path):
    from mmquery.streaming import events

    whole = spark.read.parquet(f"{sf_dir}/events.parquet")
    whole.repartition(5).write.parquet(f"{tmp_path}/events.parquet")
    want = sorted(map(str, events.batch_triangles(spark, sf_dir).collect()))
    assert want and sorted(map(str, events.batch_triangles(spark, str(tmp_path), files=1).collect())) == want


def test_products_of_fused_and_skewed_dimensions(spark):
    """Strings and numbers fused into one index, more values than the estimate says in one block, one hot inner value."""
    r = spark.createDataFrame([(i, "a" if i % 3 else "b", i % 7) for i in range(200)], "x long, k1 string, k2 long")
    s = spark.createDataFrame([("a" if j % 2 else "b", j % 7, f"z{j}") for j in range(90)], "k1 string, k2 long, z string")
    want = {(a["x"], b["z"]) for a in r.collect() for b in s.collect() if (a["k1"], a["k2"]) == (b["k1"], b["k2"])}
    from mmquery.operators.matmul import fuse

    a, b = fuse(r, ["k1", "k2"], "y"), fuse(s, ["k1", "k2"], "y")
    for kernel, side in (("blas", 5), ("bitset", 64), ("recursive7", None)):
        assert {(v["x"], v["z"]) for v in mm_blocked(a, b, ["y"], kernel=kernel, side=side).collect()} == want
    assert {(v["x"], v["z"]) for v in mm_blocked(r, s, ["k2"], ["k1"], side=8).collect()} == want


def test_rule_models_cover_the_join(spark):
    q = triangle_of(spark, *CASES["hub"])
    for rule in cover_rules(plan_set(q.graph, Fr(12, 5)))[:2]:
        models, ln_b = RE.rule_eval(q, rule, Fr(12, 5))
        assert RE.uncovered(full_join(q), models, ln_b).count() == 0
        assert RE.uncovered(full_join(q), models, ln_b + 1).count() == 0  # a larger budget covers no less
        for m in models:
            for part in [m.measure] if isinstance(m, RE.JoinModel) else [x for x in (m.x, m.y, m.z) if x]:
                assert M.audit(part).count() == 0


def test_the_gap_counts_every_rule(spark, sf_dir, monkeypatch):
    """A rule whose models lose all tuples shows, whichever rule it is."""
    rules = cover_rules(plan_set(W.bind(spark, sf_dir, W.TRIANGLE).graph, W.OMEGA))
    assert len(rules) > 1 and W.queries()["cover_model_gap"](spark, sf_dir).first()["n"] == 0
    every = W.queries()["tri_count"](spark, sf_dir).first()["n"]
    whole = RE.rule_eval
    for lost in rules:
        monkeypatch.setattr(W.RE, "rule_eval", lambda q, rule, omega: ([], 0.0) if rule == lost else whole(q, rule, omega))
        assert W.queries()["cover_model_gap"](spark, sf_dir).first()["n"] == every > 0


def test_products_agree(spark):
    rng = random.Random(2)
    r = [(rng.randrange(30), rng.randrange(40)) for _ in range(200)]
    s = [(rng.randrange(40), rng.randrange(25)) for _ in range(200)]
    want = {(x, z) for x, y in r for y2, z in s if y == y2}
    a, b = edges(spark, r, "xy").distinct(), edges(spark, s, "yz").distinct()
    assert {tuple(v) for v in mm_sparse(a, b, ["y"]).select("x", "z").collect()} == want
    assert {tuple(v) for v in mm_bits(a, b, "y", "x", "z").collect()} == want
    for kernel in ("blas", "bitset", "recursive7"):
        assert {tuple(v) for v in mm_blocked(a, b, ["y"], kernel=kernel, side=16).select("x", "z").collect()} == want
    counted = {(v["x"], v["z"]): v["n"] for v in mm_blocked(a, b, ["y"], side=16, count=True).collect()}
    assert counted == {p: sum(1 for x, y in set(r) for y2, z in set(s) if y == y2 and (x, z) == p) for p in want}


def test_products_in_tiles_shuffle_no_pair(spark, monkeypatch):
    """Many bands and small pieces give the same pairs, each in one tile: above the product nothing is exchanged or made distinct."""
    from mmquery.operators import matmul

    rng = random.Random(5)
    r, s = ({(rng.randrange(40), rng.randrange(15)) for _ in range(150)} for _ in range(2))
    s = {(y, z) for z, y in s}
    want = {}
    for x, y in r:
        for y2, z in s:
            if y == y2:
                want[x, z] = want.get((x, z), 0) + 1
    a, b = edges(spark, sorted(r), "xy"), edges(spark, sorted(s), "yz")
    for name, value in (("TILE_ROWS", 40), ("CHUNK", 50), ("BATCH", 7)):
        monkeypatch.setattr(matmul, name, value)
    for kernel in (None, "blas", "bitset", "recursive7"):
        out = mm_sparse(a, b, ["y"], count=True, tiles=True) if kernel is None else mm_blocked(a, b, ["y"], kernel=kernel, side=8, count=True)
        rows = [(v["x"], v["z"], v["n"]) for v in out.collect()]
        assert len(rows) == len(want) and {(x, z): n for x, z, n in rows} == want
    plan = mm_blocked(a, b, ["y"])._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")[0]
    assert "Aggregate" not in plan and "Repartition" not in plan
    assert mm_blocked(a, edges(spark, [], "yz"), ["y"]).count() == 0


def pairs_of(r, s):
    """Rows with the counts of their pairs, and what _dense() takes."""
    import numpy as np

    want = {}
    for x, y in r:
        for y2, z in s:
            if y == y2:
                want[x, z] = want.get((x, z), 0) + 1
    return want, [np.array([e[i] for e in sorted(of)]) for of, i in ((r, 0), (r, 1), (s, 0), (s, 1))]


def multiplied(kernel, args, side, count, monkeypatch):
    """The pairs of _dense(), and the shapes that its kernel was given."""
    import dataclasses

    from mmquery.operators import matmul

    shapes, k = [], matmul.KERNELS[kernel]

    def noted(f):
        return f and (lambda a, b: shapes.append((*a.shape, b.shape[1])) or f(a, b))

    k = dataclasses.replace(k, multiply=noted(k.multiply), meets=noted(k.meets))
    out = [(int(i), int(j), int(n)) for i, j, n in ((a, b, c) for part in matmul._dense(k, *args, side, count) for a, b, c in zip(*part, strict=True))]
    return out, shapes


def scattered():
    """Rows of few inner values, each with few columns: hardly a value of a large block is a pair."""
    rng = random.Random(3)
    r = {(x, y) for x in range(900) for y in rng.sample(range(1200), 3)}
    s = {(y, z) for y in range(1200) for z in rng.sample(range(4800), 10)}
    by = {y: {z for y2, z in s if y2 == y} for y in range(1200)}
    want = {(x, z) for x, y in r for z in by[y]}
    return want, pairs_of(r, set())[1][:2] + pairs_of(set(), s)[1][2:]


@pytest.mark.parametrize("kernel", ["bitset", "blas", "recursive7"])
def test_blocks_are_packed(monkeypatch, kernel):
    """Rows and columns that no pair joins aren't multiplied: less than an eighth of the whole matrices, and every pair comes once."""
    want, args = scattered()
    out, shapes = multiplied(kernel, args, 2048, False, monkeypatch)
    assert len(out) == len(want) and {(i, j) for i, j, _ in out} == want
    assert 0 < 8 * sum(r * k * c for r, k, c in shapes) < 900 * 1200 * 4800


def test_seven_products_of_any_shape(monkeypatch):
    """Odd and unequal dimensions are halved without a square of their largest, down to the cutoff."""
    import numpy as np

    from mmquery.operators import matmul

    rng, monkey = np.random.default_rng(4), monkeypatch.setattr
    for m, k, n, cutoff in ((37, 41, 203, 4), (130, 67, 129, 64), (1, 90, 300, 1), (16, 16, 16, 1)):
        monkey(matmul, "CUTOFF", cutoff)
        a, b = (rng.random((m, k)) < 0.3).astype(np.int8), (rng.random((k, n)) < 0.3).astype(np.int8)
        assert (matmul.KERNELS["recursive7"].multiply(a, b) == a.astype(int) @ b.astype(int)).all()


@pytest.mark.parametrize("kernel", ["bitset", "blas", "recursive7"])
def test_blocks_of_every_form_hold_the_same_pairs(monkeypatch, kernel):
    """Scattered and hub rows, hub columns and a full corner, in packed blocks, square pieces and rows cut by inner values."""
    rng = random.Random(11)
    r = {(x, y) for x in range(40) for y in rng.sample(range(120), 3)} | {(40, y) for y in range(120)} | {(x, y) for x in range(41, 60) for y in range(20)}
    s = {(y, z) for y in range(120) for z in rng.sample(range(200), 4)} | {(y, 200) for y in range(120)} | {(y, z) for y in range(20) for z in range(201, 240)}
    want, args = pairs_of(r, s)
    for side in (4, 7, 32, 2048):
        out, _ = multiplied(kernel, args, side, True, monkeypatch)
        assert sorted(out) == sorted((i, j, n) for (i, j), n in want.items())
        assert sorted((i, j) for i, j, _ in multiplied(kernel, args, side, False, monkeypatch)[0]) == sorted(want)


def test_a_row_of_a_product_is_summed_in_its_tile(spark, monkeypatch):
    """Measures of a left value equal those of its pairs, also beside a column named n, with strings and negative numbers."""
    from mmquery.operators import matmul

    rng = random.Random(12)
    r = spark.createDataFrame([(f"x{i}", y) for i in range(30) for y in rng.sample(range(25), 3)], "n string, y long")
    s = spark.createDataFrame([(y, z - 20) for y in range(25) for z in rng.sample(range(40), 4)], "y long, o long")
    pairs = mm_sparse(r, s, ["y"], count=False).groupBy("n").agg(F.count("*").alias("a"), F.sum("o").alias("b"))
    want = sorted(tuple(v) for v in pairs.collect())
    paths = sorted(tuple(v) for v in r.join(s, "y").groupBy("n", "o").count().groupBy("n").agg(F.sum("count"), F.max("count")).collect())
    for name, value in (("TILE_ROWS", 40), ("BATCH", 7)):
        monkeypatch.setattr(matmul, name, value)
    for kernel in ("blas", "bitset", "recursive7"):
        assert "n" in mm_blocked(r, s, ["y"], kernel=kernel).columns
        out = mm_blocked(r, s, ["y"], kernel=kernel, side=8, per_row={"a": "pairs", "b": "o", "c": "paths", "d": "most"})
        rows = out.groupBy("n").agg(F.sum("a"), F.sum("b"), F.sum("c"), F.max("d")).collect()
        assert sorted((v[0], v[1], v[2]) for v in rows) == want and sorted((v[0], v[3], v[4]) for v in rows) == paths


def test_a_product_lists_plain_values_unless_null(spark):
    """A single column travels as it is, without a struct about each value; null outer values still make pairs."""
    r = spark.createDataFrame([(1, 5), (2, 5), (2, 6)], "x long, y long")
    s = spark.createDataFrame([(5, "a"), (6, None)], "y long, z string")
    out = mm_blocked(r, s, ["y"])
    assert {tuple(v) for v in out.collect()} == {(1, "a"), (2, "a"), (2, None)}
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "struct(z" in plan and "struct(x" not in plan


def test_a_product_is_summed_at_pairs_within_its_tiles(spark, monkeypatch):
    """Counts at the pairs asked for, many bands and small pieces; above the product there is one sum and no join."""
    from mmquery.operators import matmul

    rng = random.Random(8)
    r, s, t = ({(rng.randrange(m), rng.randrange(n)) for _ in range(150)} for m, n in ((40, 15), (15, 40), (45, 45)))
    want = sum((x, z) in t for x, y in r for y2, z in s if y == y2)
    for name, value in (("TILE_ROWS", 40), ("BATCH", 7)):
        monkeypatch.setattr(matmul, name, value)
    a, b, c = (edges(spark, sorted(e), v) for e, v in ((r, "xy"), (s, "yz"), (t, "xz")))
    for kernel in ("blas", "bitset", "recursive7"):
        assert mm_total(a, b, c, ["y"], kernel=kernel, side=8).first()["n"] == want > 0
    assert mm_total(a, b, edges(spark, [], "xz"), ["y"]).first()["n"] == 0
    pairs = [(i, j) for i in range(9) for j in range(i + 1, 9) if (i * j) % 3 != 1]
    for k in (3, 4, 5, 6):
        out = J.clique_count(edges(spark, pairs, "uv"), k, kernel="blas")
        assert out.first()["n"] == sum(all(p in pairs for p in itertools.combinations(v, 2)) for v in itertools.combinations(range(9), k))
        assert "Join" not in out._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")[0]


def test_products_are_measured_without_being_made(spark, sf_dir, monkeypatch):
    """The only plan's product isn't multiplied for its dimensions, and no measure that they don't need is made."""
    from mmquery import solver

    def never(*args, **options):
        raise AssertionError("made")

    monkeypatch.setattr(solver, "mm_blocked", never)
    monkeypatch.setattr(RE, "cut", never)
    rows = W.queries()["product_metrics"](spark, sf_dir).collect()
    assert rows and all(min(r["dim_m"], r["dim_n"], r["dim_o"]) >= 1 for r in rows)


def test_words_hold_a_product_and_no_pair_is_shuffled(spark, sf_dir, monkeypatch):
    """Counts and sums of the right values of each left one, negative and large ones too, in many bands; above the pairs nothing is exchanged."""
    from mmquery.operators import matmul

    rng = random.Random(9)
    r = {(rng.randrange(40), rng.randrange(15)) for _ in range(150)}
    s = {(rng.randrange(15), rng.choice((rng.randrange(-300, 700), 2**40 + rng.randrange(64)))) for _ in range(300)}
    want = {x: {z for x2, y in r for y2, z in s if x2 == x and y == y2} for x, _ in r}
    monkeypatch.setattr(matmul, "BAND_PAIRS", 100)
    out = mm_words(edges(spark, sorted(r), "xy"), edges(spark, sorted(s), "yz"), "y", "x", "z")
    got = {v["x"]: (v["n"], v["total"]) for v in out.groupBy("x").agg(F.sum(word_count()).alias("n"), F.sum(word_sum()).alias("total")).collect()}
    assert got == {x: (len(zs), sum(zs)) for x, zs in want.items() if zs}
    plan = W.queries()["mm_catalyst_bits"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "MapInArrow" not in plan
    assert "Exchange" not in out._jdf.queryExecution().executedPlan().toString().split("Generate")[0]
    assert mm_words(edges(spark, [], "xy"), edges(spark, [(1, 2)], "yz"), "y", "x", "z").count() == 0


def test_joins_start_where_rows_are_fewest(spark, monkeypatch):
    """The first two atoms share one value, so their join is a product; the plan starts with the others."""
    r, s, t = [(i, 0) for i in range(60)], [(0, j) for j in range(60)], [(j, i) for i in range(60) for j in range(60) if i == j or (i + j) % 59 == 0]
    q = triangle_of(spark, r, s, t)
    assert {tuple(v) for v in full_join(q).select("x", "y", "z").collect()} == brute(r, s, t)
    n = len(brute(r, s, t))
    monkeypatch.setattr(J, "MANY_ROWS", 0)
    assert J._three_sides(q)[3] != ["y"] and J.count_answer(q).first()["n"] == n
    monkeypatch.setattr(J, "MANY_ROWS", 10**9)
    assert J._three_sides(q) is None and J.count_answer(q).first()["n"] == n


def test_pairwise_joins_pass_by_a_hub(spark):
    """A bipartite star both ways: joined through its hub it has 900 * 900 rows, the other way 900."""
    star = [(0, i) for i in range(1, 901)]
    e = star + [(j, i) for i, j in star]
    q = triangle_of(spark, e, e, e)
    assert not J.spark_answer(q).first()["answer"]
    assert "deg" in J.spark_answer(q)._jdf.queryExecution().analyzed().toString()
    assert J.spark_answer(triangle_of(spark, e, e, [*e, (1, 2), (2, 1)])).first()["answer"]
    assert J.spark_answer(triangle_of(spark, e, [*e, (1, 2), (2, 1)], e)).first()["answer"]


def test_light_values_are_joined_through_once(spark):
    """z has one value of many partners either side and comes last: what is light in x or y is done, so its join finds nothing left."""
    r, s, t = [(i, i) for i in range(30)], [(i, 0) for i in range(30)], [(0, i) for i in range(30)]
    q = triangle_of(spark, r, s, t)
    got = J.triangle(*q.atoms, threshold=40)
    assert {(v["x"], v["z"]) for v in got.collect()} == {(i, 0) for i in range(30)}
    assert got.count() == 30
    plan = got._jdf.queryExecution().analyzed().toString()
    assert plan.count("Join LeftSemi") == 14  # three more than without


def test_grouped_product(spark):
    r, s = edges(spark, [(1, 1, 1), (1, 2, 1), (2, 1, 5)], "gxy"), edges(spark, [(1, 1, 7), (2, 5, 7), (2, 1, 8)], "gyz")
    want = {(1, 1, 7), (1, 2, 7), (2, 1, 7)}
    assert {tuple(v) for v in mm_blocked(r, s, ["y"], ["g"], side=4).select("g", "x", "z").collect()} == want
    assert {tuple(v) for v in mm_sparse(r, s, ["y"], ["g"]).select("g", "x", "z").collect()} == want


@pytest.mark.parametrize("closed", [True, False])
def test_boolean_queries_in_slices(spark, tmp_path, monkeypatch, closed):
    """Every slice is asked until one says yes, none sees the whole, and what they write goes."""
    pairs = [(i, (i * 7 + j) % 40) for i in range(40) for j in range(3)]
    last = [(w, z + 100) for w in range(40) for z in range(3)] if not closed else [(39, (39 * 7) % 40)]
    atoms = [Atom.of(v, edges(spark, e, v), v) for v, e in (("wx", pairs), ("xy", [(i, i) for i in range(40)]), ("yz", pairs), ("zw", [(b, a) for a, b in last]))]
    q = ConjunctiveQuery(tuple(atoms))
    want = J.wcoj_answer(q).first()["answer"]
    for answer in (J.four_cycle_answer, J.wcoj_answer):
        sizes = []
        monkeypatch.setattr("mmquery.sources.tables.shared_dir", lambda _, answer=answer: f"file://{tmp_path}/{answer.__name__}")
        got = J.in_slices(q, lambda part: (sizes.append(part.size()), answer(part))[1], rows=100).first()["answer"]  # noqa: B023
        assert got == want
        assert max(sizes) < q.size() and (closed or len(sizes) == -(-q.size() // 100))
        assert len(list((tmp_path / answer.__name__ / "mmquery").iterdir())) == len(q.atoms)


def test_query_forms(spark):
    e = edges(spark, [(1, 1), (1, 2), (2, 3), (2, 3), (None, 4)], "ab")
    q = parse_rule("Q() :- E(X,X), E(X,Y), E(Y,3)", {"E": e})
    assert J.spark_answer(q).first()["answer"]
    assert [a.variables for a in q.atoms] == [("X",), ("X", "Y"), ("Y",)] or len(q.atoms) == 3
    assert Atom.of("E", e, ["X", "X"]).df.count() == 1 and Atom.of("E", e, ["X", "Y"]).df.count() == 3
    s = from_sql("SELECT 1 FROM e a JOIN e b ON a.b = b.a WHERE b.b = 3", {"e": e})
    assert J.spark_answer(s).first()["answer"]
    with pytest.raises(ValueError):
        from_sql("SELECT 1 FROM e a JOIN e b ON a.b < b.a", {"e": e})


def test_normalise(spark):
    e, f = edges(spark, [(1, 2), (3, 4)], "ab"), edges(spark, [(1, 2), (5, 6)], "ab")
    v = edges(spark, [(1,)], "a")
    q = normalise(ConjunctiveQuery((Atom.of("e", e, "xy"), Atom.of("f", f, "xy"), Atom.of("v", v, "x"))))
    assert len(q.atoms) == 1 and [tuple(r) for r in q.atoms[0].df.collect()] == [(1, 2)]


def test_disconnected_and_string_keys(spark):
    a = spark.createDataFrame([("a", "b")], "p string, q string")
    b = spark.createDataFrame([], "p string, q string")
    yes = ConjunctiveQuery((Atom.of("a", a, "xy"), Atom.of("b", a, "zw")))
    no = ConjunctiveQuery((Atom.of("a", a, "xy"), Atom.of("b", b, "zw")))
    assert answer_boolean(yes, 3, mm=False).first()["answer"] and not answer_boolean(no, 3, mm=False).first()["answer"]
    assert J.semijoin_answer(yes).first()["answer"] and not J.semijoin_answer(no).first()["answer"]


def test_cliques(spark):
    n = 7
    pairs = [(i, j) for i in range(n) for j in range(i + 1, n) if (i * j) % 3 != 1]
    e = edges(spark, pairs, "uv")
    for k in (3, 4, 5, 6):
        want = sum(all((a, b) in set(pairs) for a, b in itertools.combinations(c, 2)) for c in itertools.combinations(range(n), k))
        assert J.clique_count(e, k).first()["n"] == want
    assert J.clique_count(e, 4, kernel="bitset").first()["n"] == J.clique_count(e, 4).first()["n"]


def test_measures(spark):
    df = edges(spark, [(1, 1), (1, 2), (2, 1)], "xy")
    p = M.init_measure(df, ["x", "y"])
    px = {r["x"]: math.exp(r["lp"]) for r in M.marginal(p, ["x"]).df.collect()}
    assert px == pytest.approx({1: 2 / 3, 2: 1 / 3})
    c = M.condition(p, ["x"])
    assert M.audit(c).count() == 0
    whole = M.truncated_product(M.marginal(p, ["x"]), c, math.log(10))
    assert whole.df.count() == 3
    assert M.truncated_product(M.marginal(p, ["x"]), c, math.log(2.9)).df.count() == 0
    assert M.truncated_product(M.marginal(p, ["x"]), c, math.log(3)).df.count() == 3  # on the border, kept


def test_a_product_is_taken_at_rows_without_being_made(spark):
    df = edges(spark, [(1, 1), (1, 2), (2, 1)], "xy")
    p = M.init_measure(df, ["x", "y"])
    for ln_b in (math.log(3), math.log(2.9)):
        whole = M.truncated_product(M.marginal(p, ["x"]), M.condition(p, ["x"]), ln_b)
        rows = edges(spark, [(1, 2, 5), (2, 2, 6), (2, 1, 7)], "xyz")
        got = {tuple(r) for r in M.at(whole, rows, "lp").select("x", "y", "z", F.round("lp", 9)).collect()}
        assert got == {tuple(r) for r in rows.join(whole.df, ["x", "y"]).select("x", "y", "z", F.round("lp", 9)).collect()}
        assert len(got) == (2 if ln_b == math.log(3) else 0)


def test_a_measure_is_held_against_the_invariants_once(spark, monkeypatch):
    q = triangle_of(spark, *CASES["full"])
    seen, store, audit = [], RE.Store(), M.audit
    monkeypatch.setattr(M, "audit", lambda m: seen.append(m.key) or audit(m))
    for rule in cover_rules(plan_set(q.graph, Fr(12, 5))):
        RE.rule_eval(q, rule, Fr(12, 5), trace=RE.Trace(check=True), store=store)
    assert seen and len(seen) == len(set(seen))
    bad = M.Measure((), ("x",), edges(spark, [(1,), (2,)], "x").withColumn("lp", F.lit(0.0)), key=("bad",))
    ineq, _ = RE.inequality_of(q.graph, rule, Fr(12, 5))
    with pytest.raises(AssertionError):
        RE.check_invariants(ineq, {t: [(bad, w)] for t, w in ineq.right.items()}, 9.0, store)


def test_min_plus_refuses_products(spark):
    q = triangle_of(spark, *CASES["one"])
    with pytest.raises(ValueError):
        A.answer_min_plus(q, [], mm=True)


def test_plans_push_down(spark, sf_dir):
    from mmquery.sources.relations import relation

    plan = relation(spark, sf_dir, "part_supp")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "l_returnflag" in plan and "l_extendedprice" not in plan
    bits = mm_bits(edges(spark, [(1, 2)], "xy"), edges(spark, [(2, 3)], "yz"), "y", "x", "z")
    assert "Python" not in bits._jdf.queryExecution().executedPlan().toString()


def test_bucketed_relations_join_without_a_shuffle(spark):
    from mmquery.sources.tables import bounded_broadcast, write_bucketed

    a, b = (write_bucketed(edges(spark, [(i, i % 5) for i in range(50)], "xy"), n, ["x"], 4) for n in ("bucketed_a", "bucketed_b"))
    plan = a.hint("merge").join(b, "x")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    assert "broadcast" in bounded_broadcast(a, 50)._jdf.queryExecution().logical().toString().lower()
    assert "broadcast" not in bounded_broadcast(a, 49)._jdf.queryExecution().logical().toString().lower()


def test_sql_functions(spark):
    sqlfn.register(spark)
    assert spark.sql("SELECT mm_width_sql('triangle', 3, '2') AS w").first()["w"] == "4/3"
    assert spark.sql("SELECT count(*) AS n FROM expand_blocks(5L, 3)").first()["n"] == 3


def normal(rows):
    return sorted(str(tuple(int(v) if isinstance(v, float) and v == int(v) else v for v in r)) for r in rows)


FAST = ["tri_bool_td", "tri_count", "tri_count_mm", "tri_edges", "tri_edges_mm", "tri_sum_mm", "dtri_edges", "cyc4_count", "cyc4_bool_split", "cyc6_bool", "clq4_count", "pyr3_count", "prod2_group", "prod2_fuse", "chain_bool", "hub_tri_bool", "hub_pairs_join", "hub_pairs_bits", "hub_pairs_blas", "hub_tri_count_mm", "mm_dense_sparse", "mm_dense_bits", "mm_dense_blas", "prod2_group_blas", "prod2_fuse_blas", "cyc4_bool_prior", "pyr3_bool_split", "clq6_count", "join_bounds", "measured_width", "rule_two_heads_damaged", "counts_table", "exponents_table", "chat_tri_count", "label_tri_count", "host_classes", "events_tri_count", "measure_truncated", "measure_geomean", "mm_recursive7", "rel_asof", "rel_range", "rel_sets", "rel_cube", "rel_full_outer", "stream_hourly", "stream_triangles", "stream_sessions", "stream_joined"]


@pytest.mark.parametrize("name", FAST)
def test_workloads_equal_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "labels", "pages", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    got, want = W.queries()[name](spark, sf_dir), con.sql(W.oracle_sql()[name])
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    assert normal(got.select(*cols).collect()) == normal(con.sql(f"SELECT {', '.join(cols)} FROM ({W.oracle_sql()[name]}) q").fetchall())


@pytest.mark.parametrize("name", ["widths_table", "counts_table", "exponents_table", "plan_trace", "proof_trace"])
def test_what_the_planner_decides_is_sized_by_a_table(spark, sf_dir, name):
    got = W.queries()[name](spark, sf_dir)
    assert "lineitem" in str(got.inputFiles())
    assert {r["n"] for r in got.select("n").collect()} == {W.relation(spark, sf_dir, "part_supp").count()}


def test_every_query_has_a_name_and_sql_fits():
    assert set(W.oracle_sql()) <= set(W.queries())
    assert len(W.queries()) > 70


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).where(F.col("p").isNotNull()).count() > 0
