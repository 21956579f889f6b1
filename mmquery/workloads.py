"""The workloads: query classes on the given tables by every method, with SQL that says the same."""

from __future__ import annotations

from collections.abc import Callable
from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import measures as M
from . import rule_eval as RE
from .elimination import bags_in_order
from .functions import sql as sqlfn
from .operators import aggregates as A
from .operators import joins as J
from .operators import relational as R
from .operators.matmul import fuse, mm_bits, mm_blocked, mm_sparse, mm_words, word_count, word_sum
from .plans import explain
from .query import Atom, ConjunctiveQuery, from_sql, full_join, parse_rule
from .solver import answer_boolean, cover_rules, plan_set
from .sources.relations import inline, relation
from .sources.tables import cut, table
from .streaming import events
from .widths import mm_width

Query = Callable[[SparkSession, str], DataFrame]
#: The exponent that plans are priced with; kernels of the engine stand for 281/100 and 3.
OMEGA = Fraction(12, 5)

TRIANGLE = (("part_supp", "ps"), ("supp_order", "so"), ("part_order", "po"))
DOUBLE = (*TRIANGLE, ("cust_supp", "cs"), ("cust_part", "cp"))
FOUR_CYCLE = (("cust_part", "cp"), ("part_supp", "ps"), ("supp_nation", "sn"), ("nation_cust", "nc"))
FIVE_CYCLE = (("nation_cust", "nc"), ("cust_order", "co"), ("part_order", "po"), ("part_supp", "ps"), ("supp_nation", "sn"))
SIX_CYCLE = (("region_cust", "rc"), ("cust_order", "co"), ("part_order", "po"), ("part_supp", "ps"), ("supp_nation", "sn"), ("nation_region", "nr"))
SEVEN_CYCLE = (("nation_cust", ("n1", "c")), ("cust_order", "co"), ("part_order", "po"), ("part_supp", "ps"), ("supp_nation", ("s", "n2")), ("nation_region", ("n2", "r")), ("nation_region", ("n1", "r")))
PYRAMID3 = (("line3", "ops"), ("cust_order", "co"), ("cust_part", "cp"), ("cust_supp", "cs"))
PYRAMID4 = (("line4", "opsd"), ("cust_order", "co"), ("cust_part", "cp"), ("cust_supp", "cs"), ("cust_date", "cd"))
EVENTS = (("user_type", "ut"), ("type_hour", "th"), ("user_hour", "uh"))
TWO_COLUMN = (("item_vendor", ("x1", "x2", "y1", "y2")), ("vendor_class", ("y1", "y2", "z1", "z2")), ("item_class", ("x1", "x2", "z1", "z2")))
HUB = (("hub_po", "po"), ("hub_od", "od"), ("hub_pd", "pd"))
#: A bipartite graph holds no triangle: a large instance whose answer is no.
BIPARTITE = (("bip", "xy"), ("bip", "yz"), ("bip", "zx"))
EDGE_CYCLE = (("copart", "ab"), ("copart", "bc"), ("copart", "cd"), ("copart", "ad"))
CHAT = (("conv_role", "cr"), ("role_turn", "rt"), ("conv_turn", "ct"))
LABELS = (("lang_source", "ls"), ("source_quality", "sq"), ("lang_quality", "lq"))


def bind(spark: SparkSession, d: str, atoms) -> ConjunctiveQuery:
    return ConjunctiveQuery(tuple(Atom.of(n, relation(spark, d, n), list(v)) for n, v in atoms))


def sql_body(atoms) -> str:
    """The natural join of the atoms as SQL, by conditions on equal variables."""
    seen: dict[str, str] = {}
    parts, where = [], []
    from .sources.relations import SQL

    for i, (n, variables) in enumerate(atoms):
        cols = _columns(SQL[n])
        parts.append(f"{n} t{i}")
        for c, v in zip(cols, variables, strict=True):
            if v in seen:
                where.append(f"t{i}.{c} = {seen[v]}")
            else:
                seen[v] = f"t{i}.{c}"
    return f"FROM {', '.join(parts)} WHERE {' AND '.join(where)}"


def _columns(text: str) -> list[str]:
    head = text.split(" FROM ")[0].removeprefix("SELECT DISTINCT ")
    depth, item, items = 0, "", []
    for ch in head + ",":
        depth += (ch == "(") - (ch == ")")
        if ch == "," and not depth:
            items.append(item)
            item = ""
        else:
            item += ch
    return [x.split(" AS ")[-1].strip() for x in items]


def _with(atoms) -> str:
    return inline(*dict.fromkeys(n for n, _ in atoms))


def _bool_sql(atoms) -> str:
    return _with(atoms) + "SELECT count(*) > 0 AS answer FROM (SELECT 1 " + sql_body(atoms) + " LIMIT 1) q"


def _count_sql(atoms) -> str:
    return _with(atoms) + "SELECT count(*) AS n " + sql_body(atoms)


def _split_cycle(spark: SparkSession, d: str) -> DataFrame:
    """The 4-cycle with parts of many suppliers and of few taken through different decompositions."""
    q = bind(spark, d, FOUR_CYCLE)
    g = q.graph
    m = lambda *vs: [g.mask([v]) for v in vs]
    return J.degree_split_answer(q, 1, "p", None, m("c", "s", "p", "n"), m("p", "n", "c", "s"))


def _split_pyramid(spark: SparkSession, d: str) -> DataFrame:
    """The 3-pyramid by joins alone: orders of few lines and of many through different decompositions."""
    q = bind(spark, d, PYRAMID3)
    g = q.graph
    m = lambda *vs: [g.mask([v]) for v in vs]
    at = next(i for i, a in enumerate(q.atoms) if len(a.variables) == 2)
    return J.degree_split_answer(q, at, "c", None, m("c", "o", "p", "s"), m("o", "c", "p", "s"))


def _hub_pairs(spark: SparkSession, d: str, how: str) -> DataFrame:
    """The pairs (p, d) that close a triangle through an order, by part: how many, and the sum of d."""
    q = bind(spark, d, HUB)
    r, s, t = q.atoms
    if how == "join":
        out = t.df.join(mm_sparse(r.df, s.df, ["o"]), ["p", "d"], "left_semi")
    else:
        out = J.triangle(r, s, t, kernel=how)
    return out.groupBy("p").agg(F.count("*").alias("n"), F.sum("d").alias("sum_d"))


HUB_PAIRS_SQL = inline("hub_po", "hub_od", "hub_pd") + "SELECT p, count(*) AS n, sum(d)::BIGINT AS sum_d FROM hub_pd t WHERE EXISTS (SELECT 1 FROM hub_po a JOIN hub_od b ON a.o = b.o WHERE a.p = t.p AND b.d = t.d) GROUP BY p"


def _edges_mm(spark: SparkSession, d: str) -> DataFrame:
    """The edges (p, s) of W1 that lie in a triangle, through the triangle algorithm with part_supp as its last atom."""
    ps, so, po = bind(spark, d, TRIANGLE).atoms
    return J.triangle(po, so, ps, kernel="blas").select("p", "s")


def _sum_mm(spark: SparkSession, d: str) -> DataFrame:
    size = table(spark, d, "part").select(F.col("p_partkey").alias("p"), F.col("p_size").cast("long").alias("w"))
    ps, so, po = bind(spark, d, TRIANGLE).atoms
    return A.triangle_sum(ps, so, po, size, ["p"], "w")


def _dense(spark: SparkSession, d: str, how: str) -> DataFrame:
    """Nations and days that share a part, a dense product: by nation, how many days."""
    r, s = relation(spark, d, "nation_part"), relation(spark, d, "part_week")
    out = mm_sparse(r, s, ["p"]) if how == "sparse" else mm_bits(r, s, "p", "n", "d") if how == "bits" else mm_blocked(r, s, ["p"], kernel=how)
    return out.groupBy("n").agg(F.count("*").alias("days"), F.sum("d").alias("sum_d"))


DENSE_SQL = inline("nation_part", "part_week") + "SELECT n, count(*) AS days, sum(d)::BIGINT AS sum_d FROM (SELECT DISTINCT n, d FROM nation_part a JOIN part_week b ON a.p = b.p) q GROUP BY n"


def _hosts(spark: SparkSession, d: str) -> DataFrame:
    """Pages by the power-of-two class of their host's degree."""
    return J.degree_classes(relation(spark, d, "page_host"), "h")


def _bounds(spark: SparkSession, d: str) -> DataFrame:
    """The size of each full join beside the most that its atoms' sizes allow."""
    out = None
    for name, atoms in (("triangle", TRIANGLE), ("cycle", FOUR_CYCLE), ("pyramid", PYRAMID3), ("hub", HUB)):
        q = bind(spark, d, atoms)
        most = J.join_bound(q)
        one = J.count_answer(q).select(F.lit(name).alias("query"), "n", (F.col("n") <= most * (1 + 1e-9)).alias("within"))
        out = one if out is None else out.union(one)
    return out


def _bounds_sql() -> str:
    parts = []
    for name, atoms in (("triangle", TRIANGLE), ("cycle", FOUR_CYCLE), ("pyramid", PYRAMID3), ("hub", HUB)):
        parts.append(f"SELECT '{name}' AS query, n, true AS within FROM ({_count_sql(atoms)}) q_{name}")
    return " UNION ALL ".join(parts)


def _measured_width(spark: SparkSession, d: str) -> DataFrame:
    """Widths under the degrees of the data: never above those without, and 1 for a chain of keys."""
    rows = []
    for name, atoms in (("triangle", TRIANGLE), ("cycle", FOUR_CYCLE)):
        q = bind(spark, d, atoms)
        rows.append((name, mm_width(q.graph, OMEGA, degrees=RE.measured_degrees(q)) <= mm_width(q.graph, OMEGA)))
    q = ConjunctiveQuery(tuple(Atom.of(n, relation(spark, d, n), list(v)) for n, v in (("nation_region", "nr"), ("nation_cust", "nc"))))
    rows.append(("keys", mm_width(q.graph, OMEGA, degrees=RE.measured_degrees(q)) == 1))
    return spark.createDataFrame(rows, "query string, holds boolean")


def _damaged(spark: SparkSession, d: str) -> DataFrame:
    """What the rule Q1(p) or Q2(s) leaves uncovered where the second head has lost every odd supplier."""
    r = relation(spark, d, "part_supp")
    many = J.degrees(r, ["p"]).where("deg > 3").select("p")
    rest = r.join(many, "p", "left_anti").select("s").distinct()
    return RE.is_model(r, [many, rest.where("s % 2 = 0")]).agg(F.count("*").alias("n"))


def _lost(spark: SparkSession, d: str) -> DataFrame:
    """Triangles that are left uncovered where one rule's models are lost, for each rule in turn."""
    q = ConjunctiveQuery(J.made_once(*bind(spark, d, TRIANGLE).atoms))
    rules = cover_rules(plan_set(q.graph, OMEGA))
    every, store = cut(full_join(q), "triangles"), RE.Store()
    out = None
    for lost in range(len(rules)):
        for i, rule in enumerate(rules):
            models, ln_b = ([], 0.0) if i == lost else RE.rule_eval(q, rule, OMEGA, store=store)
            one = RE.uncovered(every, models, ln_b).agg(F.count("*").alias("n")).select(F.lit(lost).alias("lost"), F.lit(i).alias("rule"), "n")
            out = one if out is None else out.union(one)
    return out


def _copart(spark: SparkSession, d: str) -> DataFrame:
    return relation(spark, d, "copart")


def _clique_sql(k: int) -> str:
    v = [f"x{i}" for i in range(k)]
    pairs = [(i, j) for i in range(k) for j in range(i + 1, k)]
    tables = ", ".join(f"copart e{i}_{j}" for i, j in pairs)
    col = {v[0]: "e0_1.u"} | {v[j]: f"e{j - 1}_{j}.v" for j in range(1, k)}
    where = [f"e{i}_{j}.u = {col[v[i]]} AND e{i}_{j}.v = {col[v[j]]}" for i, j in pairs]
    return inline("copart") + f"SELECT count(*) AS n FROM {tables} WHERE {' AND '.join(where)}"


def _prod2(spark: SparkSession, d: str, how: str, kernel: str = "sparse") -> DataFrame:
    r, s = relation(spark, d, "line_a"), relation(spark, d, "line_r")
    if how == "group":
        out = mm_blocked(r, s, ["s"], ["p"], kernel=kernel) if kernel != "sparse" else mm_sparse(r, s, ["s"], ["p"])
    else:
        r, s = (fuse(df, ["p", "s"], "y") for df in (r, s))
        out = mm_blocked(r, s, ["y"], kernel=kernel) if kernel != "sparse" else mm_sparse(r, s, ["y"])
    return out.select("o", "o2").distinct()


PROD2_SQL = inline("line_a", "line_r") + "SELECT DISTINCT a.o AS o, b.o2 AS o2 FROM line_a a JOIN line_r b ON a.p = b.p AND a.s = b.s"


def _mm(spark: SparkSession, d: str, kernel: str) -> DataFrame:
    """Parts and orders that share a supplier, a dense product: the number of orders of each part and the sum of their keys."""
    r, s = relation(spark, d, "part_supp"), relation(spark, d, "supp_order")
    if kernel == "sparse":
        out = mm_sparse(r, s, ["s"], tiles=True)
    elif kernel == "bits":
        return mm_words(r, s, "s", "p", "o").groupBy("p").agg(F.sum(word_count()).alias("n_orders"), F.sum(word_sum()).alias("sum_orders"))
    else:
        out = mm_blocked(r, s, ["s"], kernel=kernel, per_row={"n_orders": "pairs", "sum_orders": "o"})
        return out.groupBy("p").agg(F.sum("n_orders").alias("n_orders"), F.sum("sum_orders").alias("sum_orders"))
    return out.groupBy("p").agg(F.count("*").alias("n_orders"), F.sum("o").alias("sum_orders"))


MM_SQL = inline("part_supp", "supp_order") + "SELECT p, count(*) AS n_orders, sum(o)::BIGINT AS sum_orders FROM (SELECT DISTINCT p, o FROM part_supp a JOIN supp_order b ON a.s = b.s) q GROUP BY p"


def _mm_count(spark: SparkSession, d: str) -> DataFrame:
    """The counting product, by part: pairs, paths, and the most paths of a pair."""
    measures = {"n_orders": "pairs", "n_paths": "paths", "most_paths": "most"}
    out = mm_blocked(relation(spark, d, "part_supp"), relation(spark, d, "supp_order"), ["s"], kernel="recursive7", count=True, per_row=measures)
    return out.groupBy("p").agg(F.sum("n_orders").alias("n_orders"), F.sum("n_paths").alias("n_paths"), F.max("most_paths").alias("most_paths"))


def _value(m: M.Measure, *cols: str) -> DataFrame:
    return m.df.select(*cols, F.round(F.exp("lp"), 9).alias("value"))


def _ps(spark: SparkSession, d: str) -> M.Measure:
    return M.init_measure(relation(spark, d, "part_supp"), ["p", "s"])


def _truncated(spark: SparkSession, d: str) -> DataFrame:
    """p(s) from one relation times p(o|s) from another, cut at 1/50000."""
    import math

    ps = M.marginal(_ps(spark, d), ["s"])
    pos = M.init_measure(relation(spark, d, "supp_order"), ["o"], ["s"])
    return _value(M.truncated_product(ps, pos, math.log(50_000)), "s", "o")


def _geo(spark: SparkSession, d: str) -> DataFrame:
    a = M.marginal(_ps(spark, d), ["s"])
    b = M.marginal(M.init_measure(relation(spark, d, "supp_order"), ["s", "o"]), ["s"])
    return _value(M.geo_mean([a, b]), "s")


def _gap(spark: SparkSession, d: str) -> DataFrame:
    """Triangles that the interpretations of some rule's targets leave uncovered, summed over all rules: none."""
    q = ConjunctiveQuery(J.made_once(*bind(spark, d, TRIANGLE).atoms))
    gaps, every = [], cut(full_join(q), "triangles")
    for rule in cover_rules(plan_set(q.graph, OMEGA)):
        models, ln_b = RE.rule_eval(q, rule, OMEGA)
        gaps.append(RE.uncovered(every, models, ln_b))
    return reduce(DataFrame.union, gaps).agg(F.count("*").alias("n"))


def _two_heads(spark: SparkSession, d: str) -> DataFrame:
    """The rule Q1(p) or Q2(s) over part_supp: parts of many suppliers, suppliers of few such parts; what they don't cover."""
    r = relation(spark, d, "part_supp")
    many = J.degrees(r, ["p"]).where("deg > 3").select("p")
    rest = r.join(many, "p", "left_anti")
    return RE.is_model(r, [many, rest.select("s").distinct()]).agg(F.count("*").alias("n"))



def _rollup(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("q"))


def _cube(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus")
    return lines.agg(F.count("*").alias("n"), F.count_distinct("l_suppkey").alias("suppliers"), F.grouping_id().cast("int").alias("level"))


CUBE_SQL = "SELECT l_returnflag, l_linestatus, count(*) AS n, count(DISTINCT l_suppkey) AS suppliers, grouping_id(l_returnflag, l_linestatus)::INT AS level FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"


def _full_outer(spark: SparkSession, d: str) -> DataFrame:
    """Customers with orders, and either without the other."""
    c = table(spark, d, "customer").select("c_custkey")
    o = table(spark, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("orders"))
    return c.join(o, "c_custkey", "full_outer")


FULL_OUTER_SQL = "SELECT coalesce(c.c_custkey, o.o_custkey) AS c_custkey, orders FROM customer c FULL OUTER JOIN (SELECT o_custkey, count(*) AS orders FROM orders GROUP BY o_custkey) o ON c.c_custkey = o.o_custkey"


def _pivot(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1))).select("l_linestatus", F.col("A").alias("a"), F.col("N").alias("n"), F.col("R").alias("r"))


def _asof(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").where("ts is not null")
    left = e.where("event_type = 'click'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("seen"))
    return R.asof_join(left, right, ["user_id"], "ts", "seen").select("event_id", "seen_asof")


ASOF_SQL = """
WITH r AS (SELECT user_id, ts, max(event_id) AS seen FROM events WHERE event_type = 'view' AND ts IS NOT NULL GROUP BY ALL)
SELECT l.event_id, r.seen AS seen_asof FROM (SELECT * FROM events WHERE event_type = 'click' AND ts IS NOT NULL) l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts
"""


def _interval(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    a = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    b = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return R.interval_join(a, b, ["user_id"], "ta", "tb", 3600).select("user_id", "a", "b")


INTERVAL_SQL = "SELECT a.user_id, a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id WHERE a.event_type = 'click' AND b.event_type = 'view' AND abs(floor(epoch(a.ts)) - floor(epoch(b.ts))) <= 3600"


def _range(spark: SparkSession, d: str) -> DataFrame:
    """Every part with the size bands it falls in; a band starts at each size that occurs."""
    p = table(spark, d, "part").select("p_partkey", F.col("p_size").cast("long").alias("size"))
    r = p.select(F.col("size").alias("low"), (F.col("size") + 3).alias("high")).distinct()
    return R.range_join(p, r, "size", "low", "high", 4).select("p_partkey", "low")


RANGE_SQL = "SELECT p_partkey, low FROM part JOIN (SELECT DISTINCT p_size::BIGINT AS low FROM part) r ON p_size >= low AND p_size < low + 3"


def _windows(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    o = table(spark, d, "orders")
    return o.select("o_orderkey", F.row_number().over(w).alias("rn"), F.lag("o_orderkey").over(w).alias("prev"), F.count("*").over(w.rowsBetween(Window.unboundedPreceding, 0)).cast("long").alias("running"))


WINDOWS_SQL = "SELECT o_orderkey, row_number() OVER w AS rn, lag(o_orderkey) OVER w AS prev, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS running FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)"


def _sets(spark: SparkSession, d: str) -> DataFrame:
    a, b = (relation(spark, d, "part_supp").select(c).withColumnRenamed(c, "k") for c in ("p", "s"))
    n = lambda df, op: df.agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "n")
    return n(a.intersect(b), "intersect").union(n(b.subtract(a), "except")).union(n(a.union(b).distinct(), "union"))


SETS_SQL = inline("part_supp") + "SELECT 'intersect' AS op, count(*) AS n FROM (SELECT p FROM part_supp INTERSECT SELECT s FROM part_supp) UNION ALL SELECT 'except', count(*) FROM (SELECT s FROM part_supp EXCEPT SELECT p FROM part_supp) UNION ALL SELECT 'union', count(*) FROM (SELECT p FROM part_supp UNION SELECT s FROM part_supp)"


def _json(spark: SparkSession, d: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, d, "events").groupBy(k.alias("k")).agg(F.count("*").alias("n"))


def _tokens(spark: SparkSession, d: str) -> DataFrame:
    w = table(spark, d, "documents").select("doc_id", F.explode(F.split(F.lower("text"), " ")).alias("w"))
    return w.where("w <> ''").select(F.col("doc_id").alias("d"), "w").distinct()


def _doc_paths(spark: SparkSession, d: str) -> DataFrame:
    """Row sums of the token matrix times its transpose, diagonal aside, by two aggregates: no pair of documents is ever a row."""
    t = _tokens(spark, d)
    degree = t.groupBy("w").agg(F.count("*").alias("deg"))
    return t.join(degree, "w").groupBy("d").agg(F.count("*").alias("n_tokens"), F.sum(F.col("deg") - 1).alias("n_paths"))


DOC_PATHS_SQL = "WITH t AS (SELECT DISTINCT doc_id AS d, w FROM (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS w FROM documents) WHERE w <> ''), g AS (SELECT w, count(*) AS deg FROM t GROUP BY w) SELECT d, count(*) AS n_tokens, sum(deg - 1)::BIGINT AS n_paths FROM t JOIN g USING (w) GROUP BY d"


def _subquery(spark: SparkSession, d: str) -> DataFrame:
    for t in ("customer", "orders"):
        table(spark, d, t).createOrReplaceTempView(t)
    return spark.sql(SUBQUERY_SQL)


SUBQUERY_SQL = "SELECT count(*) AS n FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey) OR c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')"


def _udtf(spark: SparkSession, d: str) -> DataFrame:
    sqlfn.register(spark)
    table(spark, d, "nation").createOrReplaceTempView("nation")
    return spark.sql("SELECT b.block, b.value FROM nation, LATERAL expand_blocks(CAST(n_nationkey AS BIGINT), 3) b")


def _sql_form(spark: SparkSession, d: str) -> DataFrame:
    tables = {n: relation(spark, d, n) for n in ("part_supp", "supp_order", "part_order")}
    text = "SELECT EXISTS (SELECT 1 FROM part_supp a JOIN supp_order b ON a.s = b.s JOIN part_order c ON c.p = a.p AND c.o = b.o)"
    return J.spark_answer(from_sql(text, tables))


def _rule_form(spark: SparkSession, d: str) -> DataFrame:
    tables = {n: relation(spark, d, n) for n in ("part_supp", "supp_order", "part_order")}
    return J.wcoj_answer(parse_rule("Q() :- part_supp(P,S), supp_order(S,O), part_order(P,O)", tables))


def _join_rule(spark: SparkSession, d: str) -> DataFrame:
    return answer_boolean(bind(spark, d, TRIANGLE), 3, mm=False)


def _tree(atoms, order: tuple[str, ...]) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        q = bind(spark, d, atoms)
        return J.tree_answer(q, bags_in_order(q.graph, [q.graph.mask([v]) for v in order]))

    return run


def _min_plus(spark: SparkSession, d: str) -> DataFrame:
    price = table(spark, d, "part").select(F.col("p_partkey").alias("p"), F.floor("p_retailprice").cast("long").alias("w"))
    return A.answer_min_plus(bind(spark, d, TRIANGLE), [(price, ["p"], "w")])


def _sum(spark: SparkSession, d: str) -> DataFrame:
    size = table(spark, d, "part").select(F.col("p_partkey").alias("p"), F.col("p_size").cast("long").alias("w"))
    return A.answer_sum(bind(spark, d, TRIANGLE), size, ["p"], "w")


SESSIONS_SQL = """
WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, min(ts) AS begin, count(*) AS n FROM s GROUP BY user_id, k
"""


def _lost_sql() -> str:
    """Every triangle is uncovered by the rule whose models are lost, none by another; a triangle has three rules."""
    n = "(" + _count_sql(TRIANGLE) + ")"
    return f"SELECT l::INT AS lost, r::INT AS rule, CASE WHEN l = r THEN {n} ELSE 0 END AS n FROM range(3) a(l), range(3) b(r)"


EXPONENTS_SQL = inline("part_supp") + """
, w(omega, w) AS (VALUES ('2', 2.0::DOUBLE), ('12/5', 2.4::DOUBLE), ('5/2', 2.5::DOUBLE), ('3', 3.0::DOUBLE)),
p AS (SELECT k, (k + 2) // 3 AS a, (k + 1) // 3 AS b, k // 3 AS c FROM range(4, 9) t(k))
SELECT q.*, m.n, round(exponent * ln(greatest(m.n, 1)), 6) AS ln_budget FROM (SELECT count(*) AS n FROM part_supp) m, (
SELECT 'clique' AS shape, k::INT AS k, omega, round(a / 2 + b / 2 + c / 2 * (w - 2), 9) AS exponent, round(least(a / 2 + b / 2 + c / 2 * (w - 2), (a + b) / 2), 9) AS rectangular FROM p, w
UNION ALL SELECT 'triangle', 3, omega, round(2 * w / (w + 1), 9), NULL FROM w
UNION ALL SELECT 'cycle', 4, omega, round(CASE WHEN w < 2.5 THEN (4 * w - 1) / (2 * w + 1) ELSE 1.5 END, 9), NULL FROM w
UNION ALL SELECT 'pyramid', 3, omega, round(2 - 1 / w, 9), NULL FROM w
UNION ALL SELECT 'pyramid', k::INT, omega, round(2 - 2 / (w * (k - 1) - k + 3), 9), NULL FROM w, range(4, 6) t(k)
) q
"""


def _counts_sql() -> str:
    """Ordered set partitions by their recurrence; programs by the distinct products of single eliminations: one for the triangle, two for each of the
    2 * 2 choices of the 4-cycle, 3 + 3 of the 3-pyramid and 6 + 4 of the 4-clique; a rule's choices are its joins and products."""
    return """
WITH RECURSIVE """ + inline("part_supp").removeprefix("WITH ") + """, b(k, x) AS (
  SELECT 0, [1::HUGEINT] UNION ALL SELECT k + 1, list_append(x, list_sum([x[i + 1] * (factorial((k + 1)::INT) // (factorial(i::INT) * factorial((k + 1 - i)::INT)))::HUGEINT for i in range(0, k + 1)])::HUGEINT) FROM b WHERE k < 4
), o AS (SELECT k, x[k + 1] AS orders FROM b)
SELECT shape, k::INT AS k, orders::VARCHAR AS orders, programs::HUGEINT::VARCHAR AS programs, rules::HUGEINT::VARCHAR AS rules, choices, n, (length(bin(n)) * length(bin(n)))::BIGINT AS pairs FROM (SELECT count(*) AS n FROM part_supp) m, (
  VALUES ('triangle', 3, 3 ** 1, 3, (2 ** 3)::BIGINT::VARCHAR),
         ('cycle', 4, 2 * 2 * 3 ** 2, 2 * 2 * 3 ** 2, '4722366482869645213696'),
         ('pyramid', 4, 3 ** (3 + 3), 3, (2 ** 3)::BIGINT::VARCHAR),
         ('clique', 4, 3 ** (6 + 4), 3 ** 3, (4 ** 27)::BIGINT::VARCHAR)
) t(shape, k, programs, rules, choices) JOIN o USING (k)
"""


def _widths_sql() -> str:
    """The published exponents of the classes, as literals."""
    w = {"triangle": ["4/3", "24/17", "10/7", "3/2"], "double_triangle": ["4/3", "24/17", "10/7", "3/2"], "clique": ["3/2", "17/10", "7/4", "2"], "cycle": ["7/5", "43/29", "3/2", "3/2"], "pyramid": ["3/2", "19/12", "8/5", "5/3"], "path": ["1"] * 4}
    other = {"triangle": ("3/2", "3/2", "3/2"), "double_triangle": ("2", "3/2", "3/2"), "clique": ("2", "2", "2"), "cycle": ("2", "2", "3/2"), "pyramid": ("5/3", "5/3", "5/3"), "path": ("2", "1", "1")}
    k = {"triangle": 3, "double_triangle": 4, "clique": 4, "cycle": 4, "pyramid": 3, "path": 4}
    rows = [f"('{s}', {k[s]}, '{o}', '{other[s][0]}', '{other[s][1]}', '{other[s][2]}', '{x}')" for s, xs in w.items() for o, x in zip(("2", "12/5", "5/2", "3"), xs, strict=True)]
    power = "CASE WHEN contains(width, '/') THEN split_part(width, '/', 1)::DOUBLE / split_part(width, '/', 2)::DOUBLE ELSE width::DOUBLE END"
    return inline("part_supp") + f"SELECT t.*, n, round({power} * ln(greatest(n, 1)), 6) AS ln_budget FROM (VALUES {', '.join(rows)}) t(shape, k, omega, edge_cover, hypertree, submodular, width), (SELECT count(*) AS n FROM part_supp) m"


def queries() -> dict[str, Query]:
    def on(atoms, f, **options) -> Query:
        return lambda spark, d: f(bind(spark, d, atoms), **options)

    def tri(**options) -> Query:
        return lambda spark, d: J.triangle_answer(*bind(spark, d, TRIANGLE).atoms, **options)

    return {
        "tri_bool_spark": on(TRIANGLE, J.spark_answer),
        "tri_bool_wcoj": on(TRIANGLE, J.wcoj_answer),
        "tri_bool_td": on(TRIANGLE, J.tree_answer),
        "tri_bool_split": lambda spark, d: J.degree_split_answer(bind(spark, d, TRIANGLE), 0, "p"),
        "tri_bool_joinrule": _join_rule,
        "tri_bool_mm": tri(),
        "tri_bool_mm_bits": tri(kernel="bits"),
        "tri_bool_mm_blas": tri(kernel="blas"),
        "tri_bool_solver_blas": on(TRIANGLE, answer_boolean, omega=OMEGA, kernel="blas"),
        "bip_tri_bool_solver": on(BIPARTITE, answer_boolean, omega=OMEGA, kernel="blas"),
        "bip_tri_bool_spark": on(BIPARTITE, J.spark_answer),
        "tri_edges_mm": _edges_mm,
        "tri_sum_mm": _sum_mm,
        "dtri_count": on(DOUBLE, J.count_answer),
        "cyc4_bool_prior": on(FOUR_CYCLE, J.in_slices, answer=J.four_cycle_answer, rows=50_000, by="c"),
        "cyc4h_count": on(EDGE_CYCLE, J.count_answer),
        "pyr3_bool_split": _split_pyramid,
        "clq4_bool": lambda spark, d: J.clique_answer(_copart(spark, d), 4),
        "clq5_bool": lambda spark, d: J.clique_answer(_copart(spark, d), 5),
        "clq6_count": lambda spark, d: J.clique_count(_copart(spark, d), 6),
        "hub_pairs_join": lambda spark, d: _hub_pairs(spark, d, "join"),
        "hub_pairs_sparse": lambda spark, d: _hub_pairs(spark, d, "sparse"),
        "hub_pairs_bits": lambda spark, d: _hub_pairs(spark, d, "bits"),
        "hub_pairs_blas": lambda spark, d: _hub_pairs(spark, d, "blas"),
        "hub_pairs_bitset": lambda spark, d: _hub_pairs(spark, d, "bitset"),
        "hub_tri_count_mm": lambda spark, d: A.triangle_count(*bind(spark, d, HUB).atoms),
        "mm_dense_sparse": lambda spark, d: _dense(spark, d, "sparse"),
        "mm_dense_bits": lambda spark, d: _dense(spark, d, "bits"),
        "mm_dense_blas": lambda spark, d: _dense(spark, d, "blas"),
        "prod2_group_blas": lambda spark, d: _prod2(spark, d, "group", "blas"),
        "prod2_fuse_blas": lambda spark, d: _prod2(spark, d, "fuse", "blas"),
        "chat_tri_count": on(CHAT, J.count_answer),
        "label_tri_count": on(LABELS, J.count_answer),
        "host_classes": _hosts,
        "join_bounds": _bounds,
        "measured_width": _measured_width,
        "rule_two_heads_damaged": _damaged,
        "cover_model_lost": _lost,
        "tri_bool_solver": on(TRIANGLE, answer_boolean, omega=OMEGA),
        "tri_bool_sqlform": _sql_form,
        "tri_bool_ruleform": _rule_form,
        "tri_count": on(TRIANGLE, J.count_answer),
        "tri_count_mm": lambda spark, d: A.triangle_count(*bind(spark, d, TRIANGLE).atoms),
        "tri_sum": _sum,
        "tri_min_plus": _min_plus,
        "tri_edges": on(TRIANGLE, J.edges_answer, head=("p", "s")),
        "tri_full": on(TRIANGLE, A.answer_full),
        "dtri_bool_td": _tree(DOUBLE, ("o", "c", "p", "s")),
        "dtri_bool_wcoj": on(DOUBLE, J.wcoj_answer),
        "dtri_edges": lambda spark, d: _double_edges(spark, d),
        "cyc4_bool_spark": on(FOUR_CYCLE, J.spark_answer),
        "cyc4_bool_td": on(FOUR_CYCLE, J.tree_answer),
        "cyc4_bool_split": _split_cycle,
        "cyc4_bool_solver": on(FOUR_CYCLE, J.in_slices, answer=lambda q: answer_boolean(q, 3, mm=False)),
        "cyc4_count": on(FOUR_CYCLE, J.count_answer),
        "cyc5_bool": _tree(FIVE_CYCLE, ("o", "p", "s", "n", "c")),
        "cyc6_bool": _tree(SIX_CYCLE, ("o", "p", "s", "n", "r", "c")),
        "cyc7_bool": _tree(SEVEN_CYCLE, ("o", "p", "s", "n2", "r", "n1", "c")),
        "clq3_count": lambda spark, d: J.clique_count(_copart(spark, d), 3),
        "clq4_count": lambda spark, d: J.clique_count(_copart(spark, d), 4),
        "clq4_count_blas": lambda spark, d: J.clique_count(_copart(spark, d), 4, kernel="blas"),
        "clq5_count": lambda spark, d: J.clique_count(_copart(spark, d), 5),
        "pyr3_bool": on(PYRAMID3, J.wcoj_answer),
        "pyr3_count": on(PYRAMID3, J.count_answer),
        "pyr4_bool": on(PYRAMID4, J.wcoj_answer),
        "prod2_group": lambda spark, d: _prod2(spark, d, "group"),
        "prod2_fuse": lambda spark, d: _prod2(spark, d, "fuse"),
        "w13_count": on(TWO_COLUMN, J.count_answer),
        "w13_bool": on(TWO_COLUMN, J.in_slices, answer=J.wcoj_answer),
        "chain_bool": lambda spark, d: _chain(spark, d),
        "hub_tri_bool": lambda spark, d: J.triangle_answer(*bind(spark, d, HUB).atoms, kernel="bits"),
        "hub_tri_count": on(HUB, J.count_answer),
        "events_tri_bool": on(EVENTS, J.wcoj_answer),
        "events_tri_count": on(EVENTS, J.count_answer),
        "degrees_part": lambda spark, d: J.degrees(relation(spark, d, "part_supp"), ["p"]),
        "heavy_light_supp": lambda spark, d: J.heavy_light(relation(spark, d, "supp_order"), "s", 190),
        "degree_classes": lambda spark, d: J.degree_classes(relation(spark, d, "hub_part_supp"), "p"),
        "measure_init": lambda spark, d: _value(M.init_measure(relation(spark, d, "part_supp"), ["s"], ["p"]), "p", "s"),
        "measure_marginal": lambda spark, d: _value(M.marginal(_ps(spark, d), ["p"]), "p"),
        "measure_conditional": lambda spark, d: _value(M.condition(_ps(spark, d), ["p"]), "p", "s"),
        "measure_geomean": _geo,
        "measure_truncated": _truncated,
        "rule_two_heads_cover": _two_heads,
        "cover_model_gap": _gap,
        "mm_sparse": lambda spark, d: _mm(spark, d, "sparse"),
        "mm_blocked": lambda spark, d: _mm(spark, d, "blas"),
        "mm_bitset": lambda spark, d: _mm(spark, d, "bitset"),
        "mm_catalyst_bits": lambda spark, d: _mm(spark, d, "bits"),
        "mm_recursive7": lambda spark, d: _mm(spark, d, "recursive7"),
        "mm_counting": _mm_count,
        "widths_table": lambda spark, d: explain.widths_table(spark, relation(spark, d, "part_supp")),
        "counts_table": lambda spark, d: explain.counts_table(spark, relation(spark, d, "part_supp")),
        "exponents_table": lambda spark, d: explain.exponents_table(spark, relation(spark, d, "part_supp")),
        "plan_trace": lambda spark, d: _trace(spark, d, explain.plan_trace),
        "proof_trace": lambda spark, d: _trace(spark, d, explain.proof_trace),
        "rule_metrics": lambda spark, d: explain.rule_metrics(spark, bind(spark, d, TRIANGLE), OMEGA),
        "rel_rollup": _rollup,
        "rel_pivot": _pivot,
        "rel_asof": _asof,
        "rel_interval": _interval,
        "rel_range": _range,
        "rel_windows": _windows,
        "rel_sets": _sets,
        "rel_json": _json,
        "rel_tokens": _tokens,
        "rel_doc_paths": _doc_paths,
        "rel_subquery": _subquery,
        "rel_udtf": _udtf,
        "rel_topk": lambda spark, d: R.top_per_group(table(spark, d, "orders").select("o_custkey", "o_orderkey"), ["o_custkey"], [F.desc("o_orderkey")], 2).select("o_custkey", "o_orderkey"),
        "rel_salted": lambda spark, d: R.salted_count(table(spark, d, "events").select("event_type", "event_id"), ["event_type"]),
        "stream_hourly": events.hourly_counts,
        "stream_triangles": events.batch_triangles,
        "stream_first_seen": events.first_seen,
        "stream_sessions": events.sessions,
        "stream_joined": events.clicks_after_views,
        "rel_cube": _cube,
        "rel_full_outer": _full_outer,
        "rule_budgets": lambda spark, d: explain.rule_budgets(spark, bind(spark, d, TRIANGLE), OMEGA),
        "product_metrics": lambda spark, d: explain.product_metrics(spark, bind(spark, d, HUB), OMEGA),
    }


def _trace(spark: SparkSession, d: str, trace) -> DataFrame:
    """What is planned for the triangle, with budgets for the tuples of its first atom."""
    q = bind(spark, d, TRIANGLE)
    return trace(spark, q.graph, OMEGA, q.atoms[0].df)


def _double_edges(spark: SparkSession, d: str) -> DataFrame:
    """Edges (p, s) that lie in a triangle on either side: the shared edge, filtered by both products' pairs."""
    q = bind(spark, d, DOUBLE)
    ps, so, po, cs, cp = (a.df for a in q.atoms)
    one = ps.join(mm_sparse(po, so, ["o"]), ["p", "s"], "left_semi")
    return one.join(mm_sparse(cp, cs, ["c"]), ["p", "s"], "left_semi").select("p", "s")


def _chain(spark: SparkSession, d: str) -> DataFrame:
    t = lambda n, *cols: Atom.of(n, table(spark, d, n).select(*cols), [c.split("_")[1] for c in cols])
    q = ConjunctiveQuery((
        t("region", "r_regionkey"),
        Atom.of("nation", table(spark, d, "nation").select("n_nationkey", "n_regionkey"), ["nationkey", "regionkey"]),
        Atom.of("customer", table(spark, d, "customer").select("c_custkey", "c_nationkey"), ["custkey", "nationkey"]),
        Atom.of("orders", table(spark, d, "orders").select("o_orderkey", "o_custkey"), ["orderkey", "custkey"]),
        Atom.of("lineitem", table(spark, d, "lineitem").select("l_orderkey"), ["orderkey"]),
    ))
    return J.semijoin_answer(q)


def oracle_sql() -> dict[str, str]:
    tri_bool = _bool_sql(TRIANGLE)
    ps = "SELECT p, s, count(*) OVER () AS n, count(*) OVER (PARTITION BY p) AS np, count(*) OVER (PARTITION BY s) AS ns FROM part_supp"
    out = {k: tri_bool for k in queries() if k.startswith("tri_bool_")}
    out |= {
        "tri_count": _count_sql(TRIANGLE),
        "tri_count_mm": _count_sql(TRIANGLE),
        "tri_sum": _with(TRIANGLE) + "SELECT sum(p_size)::BIGINT AS total " + sql_body(TRIANGLE).replace(" WHERE", ", part WHERE p_partkey = t0.p AND"),
        "tri_min_plus": _with(TRIANGLE) + "SELECT min(floor(p_retailprice)::BIGINT) AS least " + sql_body(TRIANGLE).replace(" WHERE", ", part WHERE p_partkey = t0.p AND"),
        "tri_edges": _with(TRIANGLE) + "SELECT DISTINCT t0.p AS p, t0.s AS s " + sql_body(TRIANGLE),
        "tri_full": _with(TRIANGLE) + "SELECT t0.p AS p, t0.s AS s, t1.o AS o " + sql_body(TRIANGLE),
        "dtri_bool_td": _bool_sql(DOUBLE),
        "dtri_bool_wcoj": _bool_sql(DOUBLE),
        "dtri_edges": _with(DOUBLE) + "SELECT p, s FROM part_supp a WHERE EXISTS (SELECT 1 FROM supp_order b JOIN part_order c ON b.o = c.o WHERE b.s = a.s AND c.p = a.p) AND EXISTS (SELECT 1 FROM cust_supp b JOIN cust_part c ON b.c = c.c WHERE b.s = a.s AND c.p = a.p)",
        "cyc4_bool_spark": _bool_sql(FOUR_CYCLE),
        "cyc4_bool_td": _bool_sql(FOUR_CYCLE),
        "cyc4_bool_split": _bool_sql(FOUR_CYCLE),
        "cyc4_bool_solver": _bool_sql(FOUR_CYCLE),
        "cyc4_count": _count_sql(FOUR_CYCLE),
        "cyc5_bool": _bool_sql(FIVE_CYCLE),
        "cyc6_bool": _bool_sql(SIX_CYCLE),
        "cyc7_bool": _bool_sql(SEVEN_CYCLE),
        "clq3_count": _clique_sql(3),
        "clq4_count": _clique_sql(4),
        "clq4_count_blas": _clique_sql(4),
        "clq5_count": _clique_sql(5),
        "pyr3_bool": _bool_sql(PYRAMID3),
        "pyr3_count": _count_sql(PYRAMID3),
        "pyr4_bool": _bool_sql(PYRAMID4),
        "prod2_group": PROD2_SQL,
        "prod2_fuse": PROD2_SQL,
        "w13_count": _count_sql(TWO_COLUMN),
        "w13_bool": _bool_sql(TWO_COLUMN),
        "chain_bool": "SELECT count(*) > 0 AS answer FROM (SELECT 1 FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey LIMIT 1) q",
        "hub_tri_bool": _bool_sql(HUB),
        "hub_tri_count": _count_sql(HUB),
        "events_tri_bool": _bool_sql(EVENTS),
        "events_tri_count": _count_sql(EVENTS),
        "degrees_part": inline("part_supp") + "SELECT p, count(*) AS deg FROM part_supp GROUP BY p",
        "heavy_light_supp": inline("supp_order") + "SELECT s, count(*) AS deg, count(*) > 190 AS heavy FROM supp_order GROUP BY s",
        "degree_classes": inline("hub_part_supp") + 'SELECT floor(log2(deg))::INT AS deg_class, count(*) AS "values", sum(deg)::BIGINT AS tuples FROM (SELECT p, count(*) AS deg FROM hub_part_supp GROUP BY p) q GROUP BY 1',
        "measure_init": inline("part_supp") + f"SELECT p, s, round(1.0::DOUBLE / np, 9) AS value FROM ({ps}) q",
        "measure_marginal": inline("part_supp") + f"SELECT DISTINCT p, round(np::DOUBLE / n, 9) AS value FROM ({ps}) q",
        "measure_conditional": inline("part_supp") + f"SELECT p, s, round(1.0::DOUBLE / np, 9) AS value FROM ({ps}) q",
        "measure_geomean": inline("part_supp", "supp_order") + "SELECT a.s, round(sqrt(a.v * b.v), 9) AS value FROM (SELECT s, count(*)::DOUBLE / (SELECT count(*) FROM part_supp) AS v FROM part_supp GROUP BY s) a JOIN (SELECT s, count(*)::DOUBLE / (SELECT count(*) FROM supp_order) AS v FROM supp_order GROUP BY s) b ON a.s = b.s",
        "measure_truncated": inline("part_supp", "supp_order") + "SELECT o.s, o.o, round(a.v / d.n, 9) AS value FROM (SELECT s, count(*)::DOUBLE / (SELECT count(*) FROM part_supp) AS v FROM part_supp GROUP BY s) a JOIN (SELECT s, count(*) AS n FROM supp_order GROUP BY s) d ON a.s = d.s JOIN supp_order o ON o.s = a.s WHERE a.v / d.n >= (1 - 1e-9) / 50000",
        "rule_two_heads_cover": "SELECT 0::BIGINT AS n",
        "cover_model_gap": "SELECT 0::BIGINT AS n",
        **{k: MM_SQL for k in ("mm_sparse", "mm_blocked", "mm_bitset", "mm_catalyst_bits", "mm_recursive7")},
        "mm_counting": inline("part_supp", "supp_order") + "SELECT p, count(*) AS n_orders, sum(n)::BIGINT AS n_paths, max(n) AS most_paths FROM (SELECT p, o, count(*) AS n FROM part_supp a JOIN supp_order b ON a.s = b.s GROUP BY p, o) q GROUP BY p",
        "widths_table": _widths_sql(),
        "rel_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::BIGINT)::BIGINT AS q FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
        "rel_pivot": "SELECT l_linestatus, nullif(count(*) FILTER (l_returnflag = 'A'), 0) AS a, nullif(count(*) FILTER (l_returnflag = 'N'), 0) AS n, nullif(count(*) FILTER (l_returnflag = 'R'), 0) AS r FROM lineitem GROUP BY l_linestatus",
        "rel_asof": ASOF_SQL,
        "rel_interval": INTERVAL_SQL,
        "rel_range": RANGE_SQL,
        "rel_windows": WINDOWS_SQL,
        "rel_sets": SETS_SQL,
        "rel_json": "SELECT (props->>'$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1",
        "rel_tokens": "SELECT DISTINCT doc_id AS d, w FROM (SELECT doc_id, unnest(string_split(lower(text), ' ')) AS w FROM documents) q WHERE w <> ''",
        "rel_doc_paths": DOC_PATHS_SQL,
        "rel_subquery": SUBQUERY_SQL,
        "rel_udtf": "SELECT b.block::INT AS block, n_nationkey::BIGINT AS value FROM nation, (SELECT unnest(range(3)) AS block) b",
        "rel_topk": "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey DESC) <= 2",
        "rel_salted": "SELECT event_type, count(*) AS n FROM events GROUP BY event_type",
        "stream_hourly": "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n FROM events GROUP BY 1, 2",
        "stream_first_seen": "SELECT DISTINCT user_id, event_type FROM events",
        "stream_triangles": "WITH e AS (SELECT user_id AS u, event_type AS t, date_trunc('hour', ts) AS h, value FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL AND ts IS NOT NULL) SELECT DISTINCT a.u, b.h FROM (SELECT DISTINCT u, t FROM e WHERE value < 20) a JOIN (SELECT DISTINCT t, h FROM e WHERE value >= 20) b USING (t) JOIN (SELECT DISTINCT u, h FROM e) c ON c.u = a.u AND c.h = b.h",
        "stream_sessions": SESSIONS_SQL,
        "stream_joined": "SELECT v.event_id AS view, c.event_id AS click FROM events v JOIN events c ON v.user_id = c.user_id AND c.ts >= v.ts AND c.ts <= v.ts + INTERVAL 10 MINUTE WHERE v.event_type = 'view' AND c.event_type = 'click'",
        "rel_cube": CUBE_SQL,
        "rel_full_outer": FULL_OUTER_SQL,
        "bip_tri_bool_solver": _bool_sql(BIPARTITE),
        "bip_tri_bool_spark": _bool_sql(BIPARTITE),
        "tri_edges_mm": _with(TRIANGLE) + "SELECT DISTINCT t0.p AS p, t0.s AS s " + sql_body(TRIANGLE),
        "tri_sum_mm": _with(TRIANGLE) + "SELECT sum(p_size)::BIGINT AS total " + sql_body(TRIANGLE).replace(" WHERE", ", part WHERE p_partkey = t0.p AND"),
        "dtri_count": _count_sql(DOUBLE),
        "cyc4_bool_prior": _bool_sql(FOUR_CYCLE),
        "cyc4h_count": _count_sql(EDGE_CYCLE),
        "pyr3_bool_split": _bool_sql(PYRAMID3),
        "clq4_bool": _clique_sql(4).replace("count(*) AS n", "count(*) > 0 AS answer"),
        "clq5_bool": _clique_sql(5).replace("count(*) AS n", "count(*) > 0 AS answer"),
        "clq6_count": _clique_sql(6),
        **{f"hub_pairs_{k}": HUB_PAIRS_SQL for k in ("join", "sparse", "bits", "blas", "bitset")},
        "hub_tri_count_mm": _count_sql(HUB),
        **{f"mm_dense_{k}": DENSE_SQL for k in ("sparse", "bits", "blas")},
        "prod2_group_blas": PROD2_SQL,
        "prod2_fuse_blas": PROD2_SQL,
        "chat_tri_count": _count_sql(CHAT),
        "label_tri_count": _count_sql(LABELS),
        "host_classes": inline("page_host") + 'SELECT floor(log2(deg))::INT AS deg_class, count(*) AS "values", sum(deg)::BIGINT AS tuples FROM (SELECT h, count(*) AS deg FROM page_host GROUP BY h) q GROUP BY 1',
        "join_bounds": _bounds_sql(),
        "measured_width": "SELECT * FROM (VALUES ('triangle', true), ('cycle', true), ('keys', true)) t(query, holds)",
        "rule_two_heads_damaged": inline("part_supp") + "SELECT count(*) AS n FROM part_supp a WHERE (SELECT count(*) FROM part_supp b WHERE b.p = a.p) <= 3 AND s % 2 = 1",
        "cover_model_lost": _lost_sql(),
        "counts_table": _counts_sql(),
        "exponents_table": EXPONENTS_SQL,
        "rule_budgets": "SELECT r::INT AS rule, true AS within FROM range(3) t(r)",
    }
    return out
