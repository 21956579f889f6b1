"""Self-join of texts on the Jaccard likeness of their word n-grams, by a chosen-path forest.

A text is the set of hashes of its n-grams of words. In each run every set grows a tree of paths: a path is followed by each of
the set's tokens whose hash, salted with the path, falls under 1 / (likeness * size): about one token that two like sets share.
Sets with a path in common meet in its bucket. A bucket that is too large is split on the paths that follow, sampled
anew from the whole set, up to a depth; runs are repeated until a pair at the threshold is met with the target recall. Pairs that
meet are held against small minhash sketches, and those that pass are settled exactly on the texts. Every pair has one home, the
least bucket its two sets share, so nothing is counted twice and no pair is ever a row: rows are sets in buckets.

Texts with the same set are one node with a number of copies; a huge final bucket is cut into blocks that meet
two at a time.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .components import components

NGRAM = 5
LIKENESS = 0.8
RECALL = 0.9995
DEPTH = 3
#: A bucket of more sets than this is split while depth is left.
BUCKET = 1024
#: Sets, and tokens of all its sets, of a block of a bucket that can't be split further.
BLOCK, BLOCK_TOKENS = 2048, 1 << 21
SKETCH = 128
#: Tokens of a set whose paths are drawn at a time.
DRAW = 1 << 13
_NGRAM, _SET, _OTHER = common.U64(0xC2B2AE3D27D4EB4F), common.U64(0x165667B19E3779F9), common.U64(0x27D4EB2F165667C5)
_MINS = common.seeds(SKETCH, 11) | common.U64(1)


def runs_for(recall: float = RECALL, depth: int = DEPTH, likeness: float = LIKENESS) -> int:
    """Runs after which a pair at the threshold has met with this probability, even at full depth.

    A path that two sets share is followed by at least one token on average that both draw, whatever the likeness; that one of
    `depth` generations of such shared paths is left has a probability that is the same for every likeness.
    """
    together = 1.0
    for _ in range(depth):
        together = 1 - math.exp(-together)
    return math.ceil(math.log(1 - recall) / math.log(1 - together))


def shingles(part: pa.RecordBatch, n: int) -> list[np.ndarray]:
    """The sorted distinct n-gram hashes of each text; a shorter text is one gram; no words, no gram."""
    raw, offsets = common.utf8(common.column(part, "text"))
    s, e, first = common.word_spans(raw, offsets)
    words = common.word_hashes(raw, s, e)
    grams = common.window_hashes(words, n, _NGRAM)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= n:
            out.append(np.unique(grams[a : b - n + 1]))
        elif b > a:
            out.append(common.mix64(common.window_hashes(words[a:b], b - a, _NGRAM) ^ common.U64(b - a)))
        else:
            out.append(words[:0])
    return out


def _follow(tokens: np.ndarray, paths: np.ndarray, salt: np.uint64, likeness: float) -> tuple[np.ndarray, np.ndarray]:
    """The paths that follow each path: the number of the path before, and the longer path."""
    chance = min(1.0, 1 / (likeness * len(tokens)))
    under = common.U64(min(chance * 2.0**64, 2.0**64 - 2048))
    key = common.mix64(paths ^ salt)
    rows, found = [], []
    for lo in range(0, len(tokens), DRAW):
        drawn = common.mix64(tokens[None, lo : lo + DRAW] ^ key[:, None])
        r, t = np.nonzero(drawn <= under) if chance < 1 else np.indices(drawn.shape).reshape(2, -1)
        rows.append(r)
        found.append(common.mix64(drawn[r, t] ^ paths[r]))
    r, longer = np.concatenate(rows), np.concatenate(found)
    order = np.argsort(r, kind="stable")
    return r[order], longer[order]


def _forest(sets: list[np.ndarray], runs: int, likeness: float) -> list[pa.Array]:
    """Of each set the paths of every level, as lists within lists: those of level two lie by the path they follow, and so on."""
    roots, salts = common.seeds(runs, 5), common.seeds(DEPTH, 6007)
    found: list[list[np.ndarray]] = [[] for _ in range(DEPTH)]
    sizes: list[list[np.ndarray]] = [[] for _ in range(DEPTH)]
    for tokens in sets:
        paths = roots
        for k in range(DEPTH):
            if len(tokens) and len(paths):
                r, longer = _follow(tokens, paths, salts[k], likeness)
            else:
                r, longer = np.zeros(0, np.int64), paths[:0]
            # the first level hangs on the set itself
            sizes[k].append(np.bincount(r, minlength=len(paths)) if k else np.array([len(longer)]))
            found[k].append(longer)
            paths = longer
    out = []
    for k in range(DEPTH):
        array = pa.array((np.concatenate(found[k]) if sets else np.zeros(0, np.uint64)).view(np.int64))
        for level in range(k, -1, -1):
            size = np.concatenate(sizes[level]) if sets else np.zeros(0, np.int64)
            array = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(size)].astype(np.int32)), array)
        out.append(array)
    return out


def set_id(tokens: np.ndarray) -> bytes | None:
    """128 bits that stand for the whole set; null for the empty one."""
    if not len(tokens):
        return None
    return common.mix64(tokens ^ _SET).sum(dtype=np.uint64).tobytes() + common.mix64(tokens ^ _OTHER).sum(dtype=np.uint64).tobytes()


def _sketch(tokens: np.ndarray) -> bytes:
    least = np.full(SKETCH, np.uint64(0xFFFFFFFFFFFFFFFF))
    for lo in range(0, len(tokens), 512):
        np.minimum(least, (tokens[lo : lo + 512, None] * _MINS[None, :]).min(0), out=least)
    return (common.mix64(least) >> common.U64(56)).astype(np.uint8).tobytes()


def describe(docs: DataFrame, ngram: int = NGRAM, likeness: float = LIKENESS, recall: float = RECALL) -> DataFrame:
    """doc_id, row key, set id, set size, sketch and paths of every row."""
    keyed = common.bounded(docs.select("doc_id", "text", row_key().alias("k")))
    runs = runs_for(recall, likeness=likeness)
    names = ["doc_id", "k", "sid", "size", "sketch", *(f"p{d}" for d in range(1, DEPTH + 1))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in common.text_slices(batch):
                part = batch.slice(lo, hi - lo)
                sets = shingles(part, ngram)
                yield pa.RecordBatch.from_arrays(
                    [
                        common.column(part, "doc_id"),
                        common.column(part, "k"),
                        pa.array([set_id(s) for s in sets], pa.binary()),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array([_sketch(s) if len(s) else None for s in sets], pa.binary()),
                        *_forest(sets, runs, likeness),
                    ],
                    names,
                )

    kind = keyed.schema["doc_id"].dataType.simpleString()
    paths = ", ".join(f"p{d} {'array<' * d}long{'>' * d}" for d in range(1, DEPTH + 1))
    return keyed.mapInArrow(common.tidy(run), f"doc_id {kind}, k binary, sid binary, size long, sketch binary, {paths}")


def row_key() -> Column:
    """128 bits of a row's id and text."""
    own = F.coalesce(F.col("doc_id").cast("string"), F.lit("-"))
    return F.unhex(F.md5(F.concat_ws("/", F.length(own).cast("string"), own, F.coalesce(F.concat(F.lit("="), "text"), F.lit("-")))))


def groups(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """The runs of equal keys of sorted batches."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = common.column(batch, key).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if held and keys[a] != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = keys[a]
    if held:
        yield pa.Table.from_batches(held)


def _met(inc: DataFrame, name: str) -> DataFrame:
    """Of incidences (s, p, size, ...) those whose path several sets have, with the number n of its sets and w of their tokens."""
    crowd = common.materialise(inc.groupBy("p").agg(F.count("*").alias("n"), F.sum("size").alias("w")).where("n > 1"), f"{name}-paths")
    met = common.materialise(inc.join(crowd, "p"), name)  # a join of two tables, so a path that very many sets have can be dealt to several tasks
    common.discard(crowd)
    return met


def _buckets(sets: DataFrame) -> DataFrame:
    """(s, p, n, w): the final buckets of every set that meets another; a large bucket is split on the paths that follow."""
    inc = sets.select("s", "size", F.posexplode("p1").alias("i", "p"))
    deeper = sets.select("s", *(f"p{d}" for d in range(2, DEPTH + 1)))
    out = None
    for depth in range(1, DEPTH + 1):
        met = _met(inc, f"met{depth}")
        last = depth == DEPTH
        done = met.where(F.lit(last) | (F.col("n") <= BUCKET)).select("s", "p", "n", "w")
        out = done if out is None else out.union(done)
        large = met.where(F.col("n") > BUCKET)
        if last or large.isEmpty():
            break
        rest = [f"p{d}" for d in range(depth + 1, DEPTH + 1)]
        if depth == 1:  # only sets in large buckets fetch their longer paths, each of them once
            at = large.groupBy("s", "size").agg(F.collect_list("i").alias("at"))
            each = F.transform("at", lambda i: F.struct(*(F.get(c, i).alias(c) for c in rest)))  # noqa: B023  used at once
            large = at.join(deeper, "s").select("s", "size", F.explode(each).alias("x")).select("s", "size", *(F.col(f"x.{c}") for c in rest))
        inc = large.select("s", "size", F.explode(F.arrays_zip(*rest)).alias("x")).select("s", "size", F.col(f"x.{rest[0]}").alias("p"), *(F.col(f"x.{c}") for c in rest[1:]))
    return out


def _units(sets: DataFrame, buckets: DataFrame) -> DataFrame:
    """Sets dealt to the units of their buckets; a unit is a bucket, or two blocks of a huge one."""
    blocks = F.ceil(F.greatest(F.col("n") / BLOCK, F.col("w") / BLOCK_TOKENS)).cast("int")
    listed = buckets.groupBy("s").agg(F.array_sort(F.collect_set(F.struct("p", blocks.alias("m")))).alias("b"))
    held = sets.select("s", "size", "sketch", "copies", "k").join(listed, "s")
    each = held.select("s", "size", "sketch", "copies", "k", F.col("b.p").alias("homes"), F.explode("b").alias("x")).select("s", "size", "sketch", "copies", "k", "homes", "x.p", "x.m")
    mine = F.pmod(F.xxhash64("s", "p"), F.col("m")).cast("int")
    met = each.withColumn("mine", mine).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("m") - 1)))
    return met.withColumn("unit", F.xxhash64("p", F.least("mine", "other"), F.greatest("mine", "other"))).withColumn("alone", F.col("mine") == F.col("other"))


def _candidates(likeness: float):
    # four deviations and a half of a share of SKETCH equal minima below the threshold
    least = math.floor((likeness - 4.5 * math.sqrt(likeness * (1 - likeness) / SKETCH)) * SKETCH)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in groups(batches, "unit"):
            n = g.num_rows
            if n < 2:
                continue
            # in a unit of two blocks only pairs across count; `alone` units hold one block
            sketch = np.frombuffer(b"".join(g["sketch"].to_pylist()), np.uint8).reshape(n, SKETCH)
            size, mine, p, s = (g[c].to_numpy() for c in ("size", "mine", "p", "s"))
            alone = g["alone"][0].as_py()
            # a pair is met here if it shares no home below this one
            before = [h[: int(np.searchsorted(h, p[i]))] for i, h in enumerate(g["homes"].to_numpy())]
            flat, owner = np.concatenate(before), np.repeat(np.arange(n), [len(h) for h in before])
            order = np.argsort(flat, kind="stable")
            flat, owner = flat[order], owner[order]
            partners: dict[int, np.ndarray] = {}
            some = np.zeros(n, bool)
            for i in range(n - 1):
                ok = p == p[i]
                ok[: i + 1] = False
                if not alone:
                    ok &= mine != mine[i]
                for a, b in zip(np.searchsorted(flat, before[i]), np.searchsorted(flat, before[i], side="right"), strict=True):
                    ok[owner[a:b]] = False
                js = np.flatnonzero(ok)
                js = js[np.minimum(size[js], size[i]) >= likeness * np.maximum(size[js], size[i]) - 1e-9]
                js = js[(sketch[js] == sketch[i]).sum(1) >= least]
                if len(js):
                    partners[i] = s[js]
                    some[i] = True
                    some[js] = True
            if partners:
                who = np.flatnonzero(some)
                nothing = s[:0]
                yield pa.RecordBatch.from_arrays(
                    [*(g[c].combine_chunks().take(pa.array(who)) for c in ("unit", "s", "k", "copies")), pa.array([partners.get(i, nothing).tobytes() for i in who.tolist()], pa.binary())],
                    ["unit", "s", "k", "copies", "partners"],
                )

    return common.tidy(run)


def _settle(ngram: int, likeness: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in groups(batches, "unit"):
            ids, copies = g["s"].to_numpy(), g["copies"].to_numpy()
            n = len(ids)
            sets: list[np.ndarray] = []
            for b in g.select(["text"]).to_batches():
                sets += [x for lo, hi in common.text_slices(b) for x in shingles(b.slice(lo, hi - lo), ngram)]
            size = np.array([len(x) for x in sets])
            _, token = np.unique(np.concatenate(sets), return_inverse=True)
            start = np.r_[0, np.cumsum(size)]
            del sets
            has = np.zeros(len(token), bool)
            by_id = np.argsort(ids, kind="stable")
            links, root = np.zeros(n, np.int64), list(range(n))

            def top(i: int, root: list[int] = root) -> int:
                while root[i] != i:
                    root[i] = root[root[i]]
                    i = root[i]
                return i

            for i, held in enumerate(g["partners"].to_pylist()):
                if not held:
                    continue
                js = by_id[np.searchsorted(ids, np.frombuffer(held, np.int64), sorter=by_id)]
                own = token[start[i] : start[i + 1]]
                has[own] = True
                if len(js) * 8 > n:  # all sets at once; none is empty
                    both = np.add.reduceat(has[token], start[:-1], dtype=np.int64)[js]
                else:
                    both = np.array([int(has[token[start[j] : start[j + 1]]].sum()) for j in js])
                has[own] = False
                js = js[both >= likeness * (size[i] + size[js] - both) - 1e-9]
                links[i] += copies[js].sum()
                links[js] += copies[i]
                for j in js.tolist():
                    a, b = top(i), top(j)
                    root[max(a, b)] = min(a, b)
            tops = np.array([top(i) for i in range(n)])
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(links), pa.array(ids[tops])], ["s", "links", "root"])

    return common.tidy(run)


def join_rows(docs: DataFrame, ngram: int = NGRAM, likeness: float = LIKENESS, recall: float = RECALL) -> DataFrame:
    """doc_id, k (row key), class_id, class_k, n_links, for every row of `docs` (doc_id, text).

    Two rows are linked when the Jaccard likeness of their n-gram sets is at least `likeness`; rows with equal sets
    always are. n_links counts the other rows a row is linked to; class_id is the least doc_id among the rows
    reached by links (nulls aside), class_k the row key of one such row. A text of fewer words than `ngram` has one gram, its
    words; null, empty and blank texts have none and are classes of their own with no links. Repeated rows are
    copies of each other. A very long text is one set like any other; a worker holds eight bytes a word of it. Extra columns are
    ignored; an empty table gives an empty result.

    Verification is exact; a pair at the threshold is met with probability `recall`, a likelier pair with more.
    """
    n = common.partitions(docs.sparkSession)
    rows = common.materialise(describe(docs, ngram, likeness, recall).withColumn("u", F.monotonically_increasing_id()), "sets")
    # a set is known by the number of one of its rows
    nodes = rows.where("sid is not null").groupBy("sid").agg(F.min("u").alias("s"), F.count("*").alias("copies"))
    sets = common.materialise(rows.select("u", "k", "size", "sketch", *(f"p{d}" for d in range(1, DEPTH + 1))).join(nodes.select(F.col("s").alias("u"), "copies"), "u").withColumnRenamed("u", "s"), "nodes")
    units = _units(sets, _buckets(sets)).select("unit", "s", "size", "sketch", "copies", "k", "homes", "p", "mine", "alone")
    part = units.repartition(n, "unit").sortWithinPartitions("unit").mapInArrow(_candidates(likeness), "unit long, s long, k binary, copies long, partners binary")
    part = common.materialise(part, "candidates")
    # by a shuffle at every size: the side that is sought grows with the corpus
    texts = docs.select(row_key().alias("k"), "text").join(part.select("k").distinct().hint("shuffle_hash"), "k").dropDuplicates(["k"])
    held = part.join(texts, "k")
    found = held.repartition(n, "unit").sortWithinPartitions("unit").mapInArrow(_settle(ngram, likeness), "s long, links long, root long")
    found = common.materialise(found, "links")
    common.discard(part)
    linked = found.groupBy("s").agg(F.sum("links").alias("links"))
    roots = components(found.select(F.col("s").alias("u"), F.col("root").alias("v")))
    node = rows.where("sid is not null").groupBy("sid").agg(F.min("u").alias("s"), F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "k")).alias("least"), F.count("*").alias("copies"))
    node = node.join(roots.withColumnRenamed("node", "s"), "s", "left").join(linked, "s", "left").withColumn("root", F.coalesce("root", "s"))
    least = node.groupBy("root").agg(F.min("least").alias("class"))
    node = node.join(least, "root").select("sid", "class", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    out = rows.select("doc_id", "k", "sid").join(node, "sid", "left")
    own = F.col("sid").isNull()
    return out.select("doc_id", "k", F.when(own, F.col("doc_id")).otherwise(F.col("class.doc_id")).alias("class_id"), F.when(own, F.col("k")).otherwise(F.col("class.k")).alias("class_k"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), own.alias("wordless"))


def keep_one(docs: DataFrame, ngram: int = NGRAM, likeness: float = LIKENESS, recall: float = RECALL) -> DataFrame:
    """The rows of `docs`, one of each class of join_rows(): that of the least doc_id.

    Rows whose text has no words all stay. Of rows alike in id and text, which may differ in other columns, any one stands for
    the others. The name __k is reserved.
    """
    keep = join_rows(docs, ngram, likeness, recall).where("k = class_k").select(F.col("k").alias("__k"), "wordless").distinct()
    met = docs.withColumn("__k", row_key()).join(keep, "__k")
    return met.where("not wordless").dropDuplicates(["__k"]).unionByName(met.where("wordless")).select(*docs.columns)


def op1_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return join_rows(docs).select("doc_id", "class_id", "n_links")


OP1_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents
), g AS (
  SELECT DISTINCT doc_id, CASE WHEN len(words) < 5 THEN md5(array_to_string(words, ' ')) ELSE md5(array_to_string(words[i:i + 4], ' ')) END AS s
  FROM (SELECT doc_id, words, unnest(range(1, greatest(len(words) - 4, 1) + 1)) AS i FROM w WHERE len(words) > 0)
), n AS (
  SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id
), met AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM g a JOIN g b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL
), e AS (
  SELECT a, b FROM met JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE c * 10 >= 8 * (x.n + y.n - c)
), reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents
  UNION
  SELECT r.a, e.b FROM reach r JOIN e ON r.b = e.a
)
SELECT d.doc_id, min(r.b) AS class_id, coalesce(max(l.n), 0)::BIGINT AS n_links
FROM documents d JOIN reach r ON r.a = d.doc_id LEFT JOIN (SELECT a, count(*) AS n FROM e GROUP BY a) l ON l.a = d.doc_id
GROUP BY d.doc_id
"""
