"""Relations of the workloads, as distinct null-free projections of the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Each relation as SQL over the tables; the same text runs in other engines.
SQL = {
    "part_supp": "SELECT DISTINCT l_partkey AS p, l_suppkey AS s FROM lineitem WHERE l_returnflag = 'A'",
    "supp_order": "SELECT DISTINCT l_suppkey AS s, l_orderkey AS o FROM lineitem WHERE l_returnflag = 'N'",
    "part_order": "SELECT DISTINCT l_partkey AS p, l_orderkey AS o FROM lineitem WHERE l_returnflag = 'R'",
    "cust_part": "SELECT DISTINCT o_custkey AS c, l_partkey AS p FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'R'",
    "cust_supp": "SELECT DISTINCT o_custkey AS c, l_suppkey AS s FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'N'",
    "cust_date": "SELECT DISTINCT o_custkey AS c, l_shipdate AS d FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'A'",
    "supp_nation": "SELECT DISTINCT s_suppkey AS s, s_nationkey AS n FROM supplier",
    "nation_cust": "SELECT DISTINCT c_nationkey AS n, c_custkey AS c FROM customer",
    "nation_region": "SELECT DISTINCT n_nationkey AS n, n_regionkey AS r FROM nation",
    "region_cust": "SELECT DISTINCT n_regionkey AS r, c_custkey AS c FROM customer JOIN nation ON c_nationkey = n_nationkey",
    "cust_order": "SELECT DISTINCT o_custkey AS c, o_orderkey AS o FROM orders",
    "line3": "SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM lineitem",
    "line4": "SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s, l_shipdate AS d FROM lineitem",
    "copart": "SELECT DISTINCT a.l_partkey AS u, b.l_partkey AS v FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey WHERE a.l_returnflag = 'A' AND b.l_returnflag = 'A'",
    "hub": "SELECT DISTINCT l_partkey % 50 AS p, l_suppkey AS s FROM lineitem",
    "hub_part_supp": "SELECT DISTINCT l_partkey % 50 AS p, l_suppkey AS s FROM lineitem UNION SELECT DISTINCT l_partkey AS p, l_suppkey AS s FROM lineitem WHERE l_returnflag = 'A'",
    "item_vendor": "SELECT DISTINCT p_brand AS x1, p_size AS x2, s_nationkey AS y1, s_suppkey AS y2 FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey WHERE l_returnflag = 'A'",
    "vendor_class": "SELECT DISTINCT s_nationkey AS y1, s_suppkey AS y2, l_shipdate AS z1, o_orderpriority AS z2 FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'N'",
    "item_class": "SELECT DISTINCT p_brand AS x1, p_size AS x2, l_shipdate AS z1, o_orderpriority AS z2 FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R'",
    "user_type": "SELECT DISTINCT user_id AS u, event_type AS t FROM events WHERE value < 20",
    "type_hour": "SELECT DISTINCT event_type AS t, date_trunc('hour', ts) AS h FROM events WHERE value >= 20",
    "user_hour": "SELECT DISTINCT user_id AS u, date_trunc('hour', ts) AS h FROM events",
    "line_a": "SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM lineitem WHERE l_returnflag = 'A'",
    "line_r": "SELECT DISTINCT l_partkey AS p, l_suppkey AS s, l_orderkey AS o2 FROM lineitem WHERE l_returnflag = 'R'",
    # keys folded to 300 make every value a hub of its two relations; lines of flag A stay apart as a sparse part
    "hub_po": "SELECT DISTINCT l_partkey % 300 AS p, l_orderkey % 300 AS o FROM lineitem UNION SELECT DISTINCT 1000 + l_partkey AS p, 1000 + l_orderkey AS o FROM lineitem WHERE l_returnflag = 'A'",
    "hub_od": "SELECT DISTINCT l_orderkey % 300 AS o, dayofyear(l_shipdate) % 300 AS d FROM lineitem UNION SELECT DISTINCT 1000 + l_orderkey AS o, 1000 + dayofyear(l_shipdate) AS d FROM lineitem WHERE l_returnflag = 'A'",
    "hub_pd": "SELECT DISTINCT l_partkey % 300 AS p, dayofyear(l_shipdate) % 300 AS d FROM lineitem UNION SELECT DISTINCT 1000 + l_partkey AS p, 1000 + dayofyear(l_shipdate) AS d FROM lineitem WHERE l_returnflag = 'A'",
    # a dense matrix: most nations' customers order most parts
    "nation_part": "SELECT DISTINCT c_nationkey AS n, l_partkey AS p FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey",
    "part_week": "SELECT DISTINCT l_partkey AS p, dayofyear(l_shipdate) AS d FROM lineitem",
    # a bipartite graph, both ways: no odd cycle
    "bip": "SELECT DISTINCT concat('c', c_custkey) AS u, concat('n', c_nationkey) AS v FROM customer UNION SELECT DISTINCT concat('n', c_nationkey) AS u, concat('c', c_custkey) AS v FROM customer",
    "conv_role": "SELECT DISTINCT conv_id AS c, role AS r FROM conversations",
    "role_turn": "SELECT DISTINCT role AS r, turn AS t FROM conversations",
    "conv_turn": "SELECT DISTINCT conv_id AS c, turn AS t FROM conversations",
    "lang_source": "SELECT DISTINCT lang AS l, source AS s FROM documents",
    "source_quality": "SELECT DISTINCT source AS s, quality AS q FROM documents JOIN labels ON documents.doc_id = labels.doc_id",
    "lang_quality": "SELECT DISTINCT lang AS l, quality AS q FROM documents JOIN labels ON documents.doc_id = labels.doc_id",
    "page_host": "SELECT DISTINCT page_id AS g, regexp_extract(url, '://([^/]+)', 1) AS h FROM pages",
}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "conversations", "pages", "documents", "labels")


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A derived relation; only the tables its SQL names are opened."""
    text = SQL[name]
    words = set(text.replace(",", " ").split())
    for t in TABLES:
        if t in words:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
    out = spark.sql(text)
    return out.dropna()


def inline(*names: str) -> str:
    """The relations as SQL common table expressions, nulls dropped."""
    parts = []
    for n in names:
        parts.append(f"{n} AS (SELECT * FROM ({SQL[n]}) q)")
    return "WITH " + ", ".join(parts) + " "
