"""Approximate nearest neighbours by an inverted file with product-quantised residuals and exact reranking.

Coarse centroids cut the unit sphere into lists; a vector's residual from its centroid, in units of its list's usual
residual, is coded by one byte a subspace. A query looks into the lists of its nearest centroids, ranks their codes through a
table of squared distances a subspace (the asymmetric distance), and the best of them are scored exactly on the original vectors.
Centroids and codebooks are fitted on a bounded sample; every row is indexed. How many lists a query looks into is fitted
too, for each list that is nearest to a query: the fewest with which sampled queries from there find their neighbours among the
sample at the aimed recall.

Lists are cut into units of bounded rows and queries into blocks of bounded number, so a list that holds a third of
all vectors spreads over as many tasks as its size asks for. Only ids and codes travel to the blocks of queries; vectors meet
the few candidates that are left. Where codes don't tell rows apart (tight groups within one list), rows that were left out may be
as near as those found: what exact scores of a query's candidates make of their approximate ones says so, and that list is
searched exactly for that query. Queries that find too few, and vectors of a dimension other than the commonest, are
searched exactly, all rows against the block of queries.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

TOP = 5
#: The sample that centroids and codebooks are fitted on: rows, more where there are many lists, and numbers at most.
SAMPLE_ROWS, ROWS_A_LIST, SAMPLE_VALUES = 20_000, 8, 8_000_000
MOST_LISTS = 16_384
SUBSPACE, CODES = 4, 256
#: Candidates that a unit keeps of each query, and that are reranked of each query; rows and queries of a unit.
KEPT, RERANK, UNIT_ROWS, UNIT_QUERIES = 64, 320, 16_384, 512
#: Rows of a unit of the exact search.
EXACT_ROWS = 4096
AIM, FIT_QUERIES, FIT_EACH = 0.99, 2048, 8
#: Deviations of the coding error that a row left out may be better than its approximate score; scores alike to so many digits are a tie in the exact search.
DEVIATIONS, DIGITS = 2.0, 12


def _kmeans(x: np.ndarray, k: int, seed: int, rounds: int = 8, spherical: bool = False) -> np.ndarray:
    r = np.random.default_rng(seed)
    c = x[r.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = _nearest(x, c)
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        size = np.bincount(near, minlength=len(c))
        some = size > 0
        c[some] = total[some] / size[some, None]
        if spherical:
            c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    return c


def _nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    out = np.empty(len(x), np.int64)
    bias = (c * c).sum(1) / 2
    for lo in range(0, len(x), 4096):
        out[lo : lo + 4096] = (x[lo : lo + 4096] @ c.T - bias).argmax(1)
    return out


class Index:
    """Centroids, the size of each list's residuals, codebooks, and the number of lists that a query looks into by its nearest one."""

    def __init__(self, dim: int, centroids: np.ndarray, scale: np.ndarray, books: list[np.ndarray], probes: np.ndarray):
        self.dim, self.centroids, self.scale, self.books, self.probes = dim, centroids, scale, books, probes

    def lists(self, unit: np.ndarray) -> np.ndarray:
        return _nearest(unit, self.centroids)

    def codes(self, unit: np.ndarray, lists: np.ndarray) -> np.ndarray:
        rest = (unit - self.centroids[lists]) / self.scale[lists, None]
        return np.stack([_nearest(np.ascontiguousarray(p), b) for p, b in zip(self._parts(rest), self.books, strict=True)], axis=1).astype(np.uint8)

    @staticmethod
    def _cuts(dim: int) -> list[tuple[int, int]]:
        return [(a, min(a + SUBSPACE, dim)) for a in range(0, dim, SUBSPACE)]

    def _parts(self, x: np.ndarray) -> list[np.ndarray]:
        return [x[:, a:b] for a, b in self._cuts(self.dim)]

    def near(self, unit: np.ndarray) -> list[np.ndarray]:
        """The lists that each query looks into."""
        order = np.argsort(-(unit @ self.centroids.T), axis=1, kind="stable").astype(np.int32)
        return [row[: self.probes[row[0]]] for row in order]

    def approximate(self, query: np.ndarray, which: int, codes: np.ndarray) -> np.ndarray:
        """Likeness of the query to coded vectors of one list, by a table a subspace of squared distances to the codes.

        Distances tell vectors of one tight group apart, where inner products would drown in the part of the coding error along the query.
        """
        rest = (query - self.centroids[which]) / self.scale[which]
        out = np.zeros(len(codes))
        for s, ((a, b), book) in enumerate(zip(self._cuts(self.dim), self.books, strict=True)):
            out += ((book - rest[a:b]) ** 2).sum(1)[codes[:, s]]
        return 1 - out * self.scale[which] ** 2 / 2


def _units_of(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def lists_for(rows: int) -> int:
    return int(np.clip(round(np.sqrt(rows) / 2), 1, MOST_LISTS))


def build(sample: np.ndarray, rows: int) -> Index | None:
    """Fit an index for a table of `rows` vectors on a sample of them."""
    if not len(sample):
        return None
    unit = _units_of(sample)
    k = min(lists_for(rows), max(1, len(unit) // ROWS_A_LIST))
    centroids = _kmeans(unit, k, 1, spherical=True)
    k = len(centroids)
    lists = _nearest(unit, centroids)
    rest = unit - centroids[lists]
    total = np.bincount(lists, (rest * rest).sum(1), k)
    scale = np.maximum(np.sqrt(total / np.maximum(np.bincount(lists, minlength=k), 1)), 1e-9)
    rest /= scale[lists, None]
    books = [_kmeans(np.ascontiguousarray(rest[:, a:b]), CODES, 2 + a) for a, b in Index._cuts(unit.shape[1])]
    return Index(unit.shape[1], centroids, scale, books, _probes(unit, lists, centroids))


def _probes(unit: np.ndarray, lists: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """For each list, how many lists queries from there need to reach those of their neighbours in the sample; a list without a query needs what any does."""
    k = len(centroids)
    order = np.argsort(lists, kind="stable")
    place = np.arange(len(order)) - np.searchsorted(lists[order], lists[order])
    asked = order[place < max(1, min(FIT_EACH, FIT_QUERIES // k))]
    need = np.zeros((len(asked), min(TOP, max(1, len(unit) - 1))), np.int64)
    for lo in range(0, len(asked), 256):
        part = asked[lo : lo + 256]
        like = unit[part] @ unit.T
        like[np.arange(len(part)), part] = -np.inf
        best = np.argpartition(-like, min(need.shape[1], len(unit) - 1) - 1, axis=1)[:, : need.shape[1]]
        rank = np.argsort(np.argsort(-(unit[part] @ centroids.T), axis=1, kind="stable"), axis=1)
        need[lo : lo + 256] = np.take_along_axis(rank, lists[best], axis=1)
    out = np.full(k, int(need.max()) + 1)
    for which in np.unique(lists[asked]):
        mine = np.sort(need[lists[asked] == which].ravel())
        out[which] = mine[min(len(mine) - 1, int(np.ceil(AIM * len(mine))))] + 1
    return np.minimum(k, out + max(1, k // 8))


def _valid(v: str):
    """Non-null, no null or non-finite component, not zero."""
    x = F.col(v)
    bad = F.exists(x, lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf")))
    return x.isNotNull() & (F.size(x) > 0) & ~F.coalesce(bad, F.lit(True)) & F.exists(x, lambda e: e != 0)


def _matrix(array: pa.Array, dim: int) -> np.ndarray:
    flat = array.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(-1, dim)


def _score(a: str, b: str):
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda t, p: t + p)
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def _dealt(df: DataFrame, on: list[str], shape: DataFrame, number: str, own: str, other: str, key: str, salt: int) -> DataFrame:
    """Rows dealt to their own of `own` shares of a group, and repeated for each of the `other` shares."""
    met = df.join(shape, on)
    mine = F.pmod(F.xxhash64(key, F.lit(salt)), F.col(own)).alias(f"{own}_at")
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.col(other).cast("long") - 1)).alias(f"{other}_at")
    return met.select("*", mine).select("*", every).withColumn("unit", F.xxhash64(*on, "parts_at", "blocks_at", F.lit(number)))


def _shape(rows: DataFrame, asked: DataFrame, on: list[str], unit_rows: int) -> DataFrame:
    """Of each group that is asked, in how many parts its rows and in how many blocks its queries are dealt."""
    parts = rows.groupBy(*on).agg(F.ceil(F.count("*") / unit_rows).cast("int").alias("parts"))
    return parts.join(asked.groupBy(*on).agg(F.ceil(F.count("*") / UNIT_QUERIES).cast("int").alias("blocks")), on)


def _exact(queries: DataFrame, base: DataFrame, on: str, top: int) -> DataFrame:
    """query_id, u of the nearest rows of the same group (dimension or list), from each unit of rows and queries; twice as many as asked, to be scored."""
    shape = common.materialise(_shape(base, queries, [on], EXACT_ROWS), "exact-units")
    stored = _dealt(base.select(on, "u", "vec_id", "v"), [on], shape, "exact", "parts", "blocks", "u", 1).select("unit", "u", "vec_id", "v")
    asked = _dealt(queries.select(on, "query_id", "q"), [on], shape, "exact", "blocks", "parts", "query_id", 2).select("unit", "query_id", "q")

    def best(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        if left.num_rows and right.num_rows:
            ids, rows_of = left["vec_id"].to_numpy(), left["u"].to_numpy()
            dim = len(left["v"][0])
            v, qs = (_units_of(_matrix(t.combine_chunks(), dim)) for t in (left["v"], right["q"]))
            for query_id, q in zip(right["query_id"].to_pylist(), qs, strict=True):
                at = np.flatnonzero(ids != query_id)
                score = np.round(v[at] @ q, DIGITS)
                if len(at) > 2 * top:
                    least = np.partition(score, len(at) - 2 * top)[len(at) - 2 * top]
                    at, score = at[score >= least], score[score >= least]
                first = at[np.lexsort((ids[at], -score))][: 2 * top]
                out.append((np.full(len(first), query_id), rows_of[first]))
        return _table(out, ["query_id", "u"])

    return stored.groupBy("unit").cogroup(asked.groupBy("unit")).applyInArrow(best, "query_id long, u long")


def _table(parts: list[tuple[np.ndarray, ...]], names: list[str]) -> pa.Table:
    cols = [np.concatenate(x) for x in zip(*parts, strict=True)] if parts else [np.zeros(0)] * len(names)
    return pa.table({n: pa.array(c, pa.float64() if n in ("score", "cut") else pa.int64()) for n, c in zip(names, cols, strict=True)})


def _crowded(near: DataFrame, scored: DataFrame, top: int) -> DataFrame:
    """query_id, list: where a row left out may be among the nearest, going by how far the exact scores of candidates are above the approximate ones.

    Left out are rows of a unit beyond those it keeps, and kept ones beyond those that are reranked; neither has a better
    approximate score than the least that wasn't left out.
    """
    above = F.col("score") - F.col("about")
    told = scored.groupBy("query_id").agg(
        F.count("*").alias("n"), F.min("about").alias("last"), (F.avg(above) + DEVIATIONS * F.stddev_pop(above)).alias("above"), F.sort_array(F.collect_list("score"), asc=False).alias("best")
    )
    told = told.where(F.size("best") >= top).select("query_id", F.when(F.col("n") >= RERANK, F.col("last")).alias("last"), "above", F.element_at("best", top).alias("least"))
    # of a list in several units, the highest of what they left out at most
    lists = near.groupBy("query_id", "list").agg(F.max("score").alias("high"), F.min("score").alias("low"), F.max("cut").alias("cut"))
    beyond = F.when(F.col("last").isNotNull() & (F.col("low") <= F.col("last")), F.least("last", "high"))
    met = lists.join(told, "query_id").withColumn("out", F.greatest("cut", beyond))
    return met.where(F.col("out") + F.col("above") >= F.col("least")).select("query_id", "list")


def search(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", every: int = 50, top: int = TOP) -> DataFrame:
    """The `top` nearest rows by cosine of every row whose id is divisible by `every`: query_id, rank, vec_id, score.

    Vectors that are null, empty, zero, or hold null or non-finite components take no part, nor do null ids. Vectors
    meet only those of their own dimension. A query's own id is no candidate; ties go to the smaller id. A repeated id is one
    query, and a candidate once for each of its rows. Fewer candidates than `top` give fewer rows; an empty table none. Extra
    columns are ignored; very long vectors are rows like any other.
    Scores are exact on the original vectors in double precision; only the choice of candidates is approximate. Lists in which codes
    leave out rows that may be as near as a query's nearest are searched exactly for it, and a query that finds fewer than `top` is
    searched exactly among all.
    """
    spark = common.bounded(vectors).sparkSession
    base = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v")).where(F.col(id_col).isNotNull() & _valid(vector_col))
    base = common.materialise(base.withColumn("d", F.size("v")).withColumn("u", F.monotonically_increasing_id()), "vectors")
    dims = base.groupBy("d").count().orderBy(F.desc("count"), "d").limit(1).collect()
    if not dims:
        return base.select(F.lit(0).cast("long").alias("query_id"), F.lit(0).alias("rank"), "vec_id", F.lit(0.0).alias("score")).where(F.lit(False))
    dim, rows = dims[0]["d"], dims[0]["count"]
    common_dim = base.where(F.col("d") == dim)
    limit = max(256, min(max(SAMPLE_ROWS, ROWS_A_LIST * lists_for(rows)), SAMPLE_VALUES // dim))
    picked = common_dim.orderBy(F.xxhash64("vec_id", F.lit("fit")), "vec_id").limit(limit).select("vec_id", "v").toArrow()
    index = build(_matrix(picked["v"].combine_chunks(), dim), rows)
    shared = spark.sparkContext.broadcast(index)  # bounded by MOST_LISTS and CODES

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ix = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            x = _units_of(_matrix(common.column(batch, "v"), ix.dim))
            lists = ix.lists(x)
            codes = ix.codes(x, lists)
            yield pa.RecordBatch.from_arrays([common.column(batch, "u"), common.column(batch, "vec_id"), pa.array(lists.astype(np.int32)), pa.array([c.tobytes() for c in codes], pa.binary())], ["u", "vec_id", "list", "code"])

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ix = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            near = ix.near(_units_of(_matrix(common.column(batch, "q"), ix.dim)))
            yield pa.RecordBatch.from_arrays([common.column(batch, "query_id"), common.column(batch, "q"), pa.array(near, pa.list_(pa.int32()))], ["query_id", "q", "lists"])

    coded = common.materialise(common_dim.select("u", "vec_id", "v").mapInArrow(common.tidy(assign), "u long, vec_id long, list int, code binary"), "codes")
    queries = common.materialise(base.where(F.pmod("vec_id", F.lit(every)) == 0).dropDuplicates(["vec_id"]).select(F.col("vec_id").alias("query_id"), F.col("v").alias("q"), "d"), "queries")
    asked = queries.where(F.col("d") == dim).select("query_id", "q").mapInArrow(common.tidy(probe), "query_id long, q array<double>, lists array<int>")
    asked = common.materialise(asked.select("query_id", "q", F.explode("lists").alias("list")), "probes")
    shape = common.materialise(_shape(coded, asked, ["list"], UNIT_ROWS), "units")
    shape = F.broadcast(shape)  # at most MOST_LISTS rows
    stored = _dealt(coded, ["list"], shape, "near", "parts", "blocks", "u", 1).select("unit", "list", "u", "vec_id", "code")
    wanted = _dealt(asked, ["list"], shape, "near", "blocks", "parts", "query_id", 2).select("unit", "query_id", "q")

    def best(left: pa.Table, right: pa.Table) -> pa.Table:
        ix = shared.value
        out = []
        if left.num_rows and right.num_rows:
            ids, rows_of = left["vec_id"].to_numpy(), left["u"].to_numpy()
            codes = np.frombuffer(b"".join(left["code"].to_pylist()), np.uint8).reshape(len(ids), -1)
            which = left["list"][0].as_py()
            for query_id, q in zip(right["query_id"].to_pylist(), _units_of(_matrix(right["q"].combine_chunks(), ix.dim)), strict=True):
                near = ix.approximate(q, which, codes)
                at = np.flatnonzero(ids != query_id)
                most = len(at)
                if len(at) > KEPT:
                    least = np.partition(near[at], len(at) - KEPT)[len(at) - KEPT]
                    at = at[near[at] >= least]
                first = at[np.lexsort((ids[at], -near[at]))][:KEPT]
                out.append((np.full(len(first), query_id), ids[first], rows_of[first], np.full(len(first), which), near[first], np.full(len(first), near[first[-1]] if len(first) < most else -np.inf)))
        return _table(out, ["query_id", "vec_id", "u", "list", "score", "cut"])

    near = stored.groupBy("unit").cogroup(wanted.groupBy("unit")).applyInArrow(best, "query_id long, vec_id long, u long, list long, score double, cut double")
    near = common.materialise(near, "near")
    by_query = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    picked = near.withColumn("r", F.row_number().over(by_query)).where(F.col("r") <= RERANK).select("query_id", "u", "list", F.col("score").alias("about"))
    vector = base.select("u", "vec_id", "v")
    scored = picked.join(vector, "u").join(queries, "query_id").select("query_id", "vec_id", "list", "about", _score("q", "v").alias("score"))
    scored = common.materialise(scored, "scored")
    rank = F.row_number().over(by_query)
    first = lambda df: df.withColumn("rank", rank).where(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")
    crowded = common.materialise(_crowded(near, scored, top), "crowded")
    if not crowded.isEmpty():
        held = coded.select("u", F.col("list").cast("long").alias("list")).join(crowded.select("list").distinct(), "list").join(vector, "u")
        again = _exact(crowded.join(queries, "query_id").select("query_id", "list", "q"), held, "list", top).join(vector, "u").join(queries, "query_id")
        scored = scored.join(crowded, ["query_id", "list"], "left_anti").select("query_id", "vec_id", "score").union(again.select("query_id", "vec_id", _score("q", "v").alias("score")))
    found = common.materialise(first(scored), "found")
    enough = found.groupBy("query_id").agg(F.count("*").alias("n")).where(F.col("n") >= top).select("query_id")
    rest = common.materialise(queries.join(enough, "query_id", "left_anti"), "rest")
    out = found.join(enough, "query_id", "left_semi").select("query_id", "rank", "vec_id", "score")
    if not rest.isEmpty():
        again = _exact(rest, base, "d", top).join(vector, "u").join(queries, "query_id").select("query_id", "vec_id", _score("q", "v").alias("score"))
        out = out.union(first(again))
    return out.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op9_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
