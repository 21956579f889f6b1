"""Removal of repeated word windows, found through difference-cover anchors.

Word positions of a text count from 0; only those whose remainder modulo a period lies in a difference cover carry
an anchor, a hash of the next L words. For any two positions i, j some shift below the period takes both to cover
positions, so two equal windows of L + period - 1 words or more share an aligned anchor. Anchors that occur
twice are then extended: only windows of full length around them are hashed and compared.

Anchors only say where to look, and 64 bits do for them. A window is judged by two hashes of 64 bits each, made from
two independent hashes of its words; equal windows are those that agree in both. A row is known by 64 bits of its id and text; keys
that different rows turn out to share are replaced before anything is sent.

Hashes go to their bucket packed, as a few arrays per slice of text rather than a row each. A hash that occurs
twice within a slice is settled there and sends one witness, so however often a passage occurs, a bucket gets it
at most once or twice from each slice. The texts are shuffled once, by a key of the row; all three passes over
them and both sets of answers share that partitioning.
"""

from __future__ import annotations

import functools
import hashlib
import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

WINDOW = 35
PERIOD = 21
#: Text of a slice; a larger slice settles more hashes at home, a smaller one needs less memory.
SLICE = 2 << 20
#: In place of a position: the hash occurs at least twice in the slice it comes from.
WITNESS = np.uint32(0xFFFFFFFF)
_ANCHOR, _FULL, _ROUTE, _SECOND = common.U64(0xE7037ED1A0B428DB), common.U64(0x8EBC6AF09C88C6E3), common.U64(0x589965CC75374CC3), common.U64(0x1D8E4E27C47D124F)
_OTHER_BYTE = common.seeds(256, 173)


@functools.cache
def difference_cover(period: int) -> tuple[int, ...]:
    """The smallest set of residues whose differences give every residue, first in order."""
    for size in range(1, period + 1):
        for rest in itertools.combinations(range(1, period), size - 1):
            cover = (0, *rest)
            if len({(a - b) % period for a in cover for b in cover}) == period:
                return cover
    raise AssertionError


def plan_of(window: int) -> tuple[int, int]:
    """Period and anchor length for a window: anchor + period - 1 = window."""
    period = min(PERIOD, max(1, window * 3 // 5))
    return period, window - period + 1


def _words(part: pa.RecordBatch, second: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    raw, offsets = common.utf8(common.column(part, "text"))
    s, e, first = common.word_spans(raw, offsets)
    return common.word_hashes(raw, s, e), first, common.word_hashes(raw, s, e, _OTHER_BYTE) if second else None


class Packer:
    """Sends (hash, row key, place) triples to buckets, and those settled at home past them."""

    SCHEMA = "bucket int, hashes binary, keys binary, places binary"

    def __init__(self, buckets: int):
        self.buckets = buckets

    def pack(self, h: np.ndarray, key: np.ndarray, place: np.ndarray) -> pa.RecordBatch:
        """h: a column of hashes, or two side by side; triples whose hashes all agree are alike."""
        order = np.lexsort(h.T[::-1])
        h, key, place = h[order], key[order], place[order]
        first = np.r_[True, (h[1:] != h[:-1]).any(1)] if len(h) else np.zeros(0, bool)
        size = np.diff(np.r_[np.flatnonzero(first), len(h)])
        many = np.repeat(size > 1, size)
        home_key, home_place = key[many], place[many].astype(np.uint32)
        h, key = h[first], key[first]
        place = np.where(many, WITNESS, place)[first].astype(np.uint32)
        bucket = (common.mix64(h[:, 0] ^ _ROUTE) % common.U64(self.buckets)).astype(np.int32)
        order = np.lexsort((place, key, bucket))
        h, key, place, bucket = h[order], key[order], place[order], bucket[order]
        cuts = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]) if len(bucket) else np.zeros(0, int)
        ends = np.r_[cuts[1:], len(bucket)] if len(cuts) else cuts
        rows = [(int(bucket[a]), h[a:b].tobytes(), key[a:b].tobytes(), place[a:b].tobytes()) for a, b in zip(cuts, ends, strict=True)]
        if len(home_key):
            rows.append((int(home_key[0] % self.buckets), b"", home_key.tobytes(), home_place.tobytes()))
        cols = list(zip(*rows, strict=True)) or [[], [], [], []]
        return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], ["bucket", "hashes", "keys", "places"])


def _by_part(key: np.ndarray, place: np.ndarray, n: int) -> pa.RecordBatch:
    """Places packed for the part of the rows that each key belongs to: a row a part."""
    part = (common.mix64(key.view(np.uint64)) % common.U64(n)).astype(np.int32)
    order = np.lexsort((place, key, part))
    key, place, part = key[order], place[order], part[order]
    cuts = np.flatnonzero(np.r_[True, part[1:] != part[:-1]]) if len(part) else np.zeros(0, int)
    ends = np.r_[cuts[1:], len(part)] if len(cuts) else cuts
    spans = list(zip(cuts, ends, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(part[cuts], pa.int32()), pa.array([key[x:y].tobytes() for x, y in spans], pa.binary()), pa.array([place[x:y].tobytes() for x, y in spans], pa.binary())], ["part", "keys", "places"])


def _settle(n: int, width: int):
    """Of a partition's triples, the places whose `width` hashes occur at least twice, packed by part of the row keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hs, ks, ps, home_k, home_p = [], [], [], [], []
        for batch in batches:
            for h, k, p in zip(*(common.column(batch, c).to_pylist() for c in ("hashes", "keys", "places")), strict=True):
                key, place = np.frombuffer(k, np.int64), np.frombuffer(p, np.uint32)
                if h:
                    hs.append(np.frombuffer(h, np.uint64))
                    ks.append(key)
                    ps.append(place)
                else:
                    home_k.append(key)
                    home_p.append(place)
        if hs:
            h, k, p = np.concatenate(hs).reshape(-1, width), np.concatenate(ks), np.concatenate(ps)
            del hs, ks, ps
            order = np.lexsort(h.T[::-1])
            same = np.ones(max(0, len(order) - 1), bool)
            for w in range(width):
                s = h[order, w]
                same &= s[1:] == s[:-1]
            del h, s
            twin = np.zeros(len(order), bool)
            twin[1:] |= same
            twin[:-1] |= same
            # a witness alone says that the hash is repeated only where it came from, and that is settled
            keep = order[twin]
            keep = keep[p[keep] != WITNESS]
            home_k.append(k[keep])
            home_p.append(p[keep])
            del k, p, order, twin, same
        if home_k:
            yield _by_part(np.concatenate(home_k), np.concatenate(home_p), n)

    return common.tidy(run)


def _gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The packed places of a part, one row for each row key."""
    keys, places = [], []
    for batch in batches:
        for k, p in zip(*(common.column(batch, c).to_pylist() for c in ("keys", "places")), strict=True):
            keys.append(np.frombuffer(k, np.int64))
            places.append(np.frombuffer(p, np.uint32))
    if not keys:
        return
    k, p = np.concatenate(keys), np.concatenate(places)
    del keys, places
    order = np.lexsort((p, k))
    k, p = k[order], p[order]
    cuts = np.flatnonzero(np.r_[True, k[1:] != k[:-1]]) if len(k) else np.zeros(0, int)
    ends = np.r_[cuts[1:], len(k)] if len(cuts) else cuts
    for lo in range(0, len(cuts), 4096):
        a, b = cuts[lo : lo + 4096], ends[lo : lo + 4096]
        yield pa.RecordBatch.from_arrays([pa.array(k[a], pa.int64()), pa.array([p[x:y].tobytes() for x, y in zip(a, b, strict=True)], pa.binary())], ["__k", "places"])


def _answers(packed: DataFrame, n: int, name: str, width: int) -> DataFrame:
    """One row per row key with its repeated places."""
    found = packed.repartitionById(n, "bucket").mapInArrow(_settle(n, width), "part int, keys binary, places binary")
    return found.repartitionById(n, "part").mapInArrow(common.tidy(_gather), "__k long, places binary").withColumnRenamed("places", name)


def _places(packed: bytes | None) -> np.ndarray:
    return np.unique(np.frombuffer(packed or b"", np.uint32)).astype(np.int64)


def _anchors(n: int, window: int, period: int, length: int):
    cover = np.zeros(period, bool)
    cover[list(difference_cover(period))] = True

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(n)
        for batch in batches:
            for lo, hi in common.text_slices(batch, "text", SLICE):
                part = batch.slice(lo, hi - lo)
                words, first, _ = _words(part)
                count = np.diff(first)
                ok = common.inside(first, length)
                at = np.flatnonzero(ok)
                doc = np.repeat(np.arange(len(count)), count)[at]
                local = at - first[doc]
                keep = cover[local % period] & (count[doc] >= window)
                at, doc, local = at[keep], doc[keep], local[keep]
                if len(at):
                    key = common.column(part, "__k").to_numpy()
                    yield packer.pack(common.window_hashes(words, length, _ANCHOR)[at][:, None], key[doc], local)

    return common.tidy(run)


def _windows(n: int, window: int, period: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(n)
        for batch in batches:
            for lo, hi in common.text_slices(batch, "text", SLICE):
                part = batch.slice(lo, hi - lo)
                found = [_places(packed) for packed in common.column(part, "__anchors").to_pylist()]
                if not any(map(len, found)):
                    continue
                words, first, others = _words(part, second=True)
                touched = np.zeros(len(words) + 1, np.int32)
                for d, p in enumerate(found):
                    # every window start from which the anchor is within reach
                    np.add.at(touched, first[d] + np.maximum(p - period + 1, 0), 1)
                    np.add.at(touched, np.minimum(first[d] + p + 1, len(words)), -1)
                full = common.inside(first, window)
                if not len(full):
                    continue
                at = np.flatnonzero(full & (np.cumsum(touched)[: len(full)] > 0))
                if len(at):
                    doc = np.searchsorted(first, at, side="right") - 1
                    h = np.stack([common.window_hashes(words, window, _FULL)[at], common.window_hashes(others, window, _SECOND)[at]], axis=1)
                    key = common.column(part, "__k").to_numpy()
                    yield packer.pack(h, key[doc], at - first[doc])

    return common.tidy(run)


def _keyed(docs: DataFrame, key: Column | None = None) -> DataFrame:
    """Rows with a key __k of their id and text. Keys that rows share whose second hash differs, a handful at most, give way to a hash of both."""
    own = (F.col("doc_id").cast("string"), F.col("text"))
    key, check = F.xxhash64(*own) if key is None else key, F.xxhash64(F.lit(1), *reversed(own))
    shared = docs.select(key.alias("__k"), check.alias("c")).groupBy("__k").agg(F.min("c").alias("a"), F.max("c").alias("b")).where("a <> b").select("__k")
    shared = common.materialise(shared, "shared-keys")
    keyed = docs.withColumn("__k", key)
    if shared.isEmpty():
        return keyed
    met = keyed.join(shared.withColumn("__met", F.lit(True)), "__k", "left")
    return met.select(*docs.columns, F.when(F.col("__met"), F.xxhash64("__k", check)).otherwise(F.col("__k")).alias("__k"))


def remove_repeats(docs: DataFrame, window: int = WINDOW, joined: bool = True) -> DataFrame:
    """All columns of `docs` (at least doc_id and text), text without its repeated words, and __n_words, __n_removed.

    A word is removed where a window of `window` consecutive words of its text covers it whose words also start
    anywhere else, in the same text too; all windows are judged on the input. Words are runs of bytes outside 0x20
    and 0x09-0x0D. `joined` gives every text as its kept words joined by one space; otherwise only texts that lost
    words are rewritten. Null texts have no words and stay null unless joined, then empty. Texts shorter than the
    window lose nothing. Rows alike in id and text are separate texts, so their windows repeat each other. A very long text is
    a slice of its own: a worker holds it and some twenty bytes a word beside it. Extra columns pass through (names starting
    with two underscores are reserved); an empty table stays empty.
    """
    spark = common.bounded(docs).sparkSession
    n = common.partitions(spark)
    period, length = plan_of(window)
    keyed = _keyed(docs)
    x = keyed.repartition(n, "__k")
    anchors = _answers(x.mapInArrow(_anchors(n, window, period, length), Packer.SCHEMA), n, "__anchors", 1)
    near = x.join(anchors.hint("shuffle_hash"), "__k")
    full = _answers(near.mapInArrow(_windows(n, window, period), Packer.SCHEMA), n, "__windows", 2)
    judged = x.join(full.hint("shuffle_hash"), "__k", "left")
    schema = T.StructType([*docs.schema.fields, T.StructField("__n_words", T.LongType()), T.StructField("__n_removed", T.LongType())])
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in common.text_slices(batch):
                part = batch.slice(lo, hi - lo)
                texts, counts, gone = [], [], []
                for text, packed in zip(common.column(part, "text").to_pylist(), common.column(part, "__windows").to_pylist(), strict=True):
                    words = (text or "").encode().split()
                    lost = np.zeros(len(words) + 1, np.int32)
                    if packed:
                        p = _places(packed)
                        np.add.at(lost, p, 1)
                        np.add.at(lost, p + window, -1)
                    lost = np.cumsum(lost)[: len(words)] > 0
                    k = int(lost.sum())
                    counts.append(len(words))
                    gone.append(k)
                    if joined or k:
                        texts.append(b" ".join(itertools.compress(words, ~lost) if k else words).decode())
                    else:
                        texts.append(text)
                cols = [pa.array(texts, pa.string()) if c == "text" else common.column(part, c) for c in names]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(counts, pa.int64()), pa.array(gone, pa.int64())], [*names, "__n_words", "__n_removed"])

    return judged.mapInArrow(common.tidy(run), schema)


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return remove_repeats(docs).select("doc_id", F.col("__n_words").alias("n_words"), F.col("__n_removed").alias("n_removed"), F.sha2(F.col("text"), 256).alias("kept_sha256"))


OP8_SQL = r"""
WITH w AS (
  SELECT doc_id, row_number() OVER () AS r, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents
), s AS (
  SELECT r, i, md5(array_to_string(words[i:i + 34], ' ')) AS h FROM (SELECT r, words, unnest(range(1, len(words) - 33)) AS i FROM w WHERE len(words) >= 35)
), d AS (
  SELECT r, i FROM s WHERE h IN (SELECT h FROM s GROUP BY h HAVING count(*) > 1)
), c AS (
  SELECT DISTINCT r, unnest(range(i, i + 35)) AS i FROM d
), g AS (
  SELECT r, list(i) AS gone, count(*) AS n FROM c GROUP BY r
)
SELECT doc_id, len(words)::BIGINT AS n_words, coalesce(n, 0)::BIGINT AS n_removed,
       sha256(array_to_string(CASE WHEN n IS NULL THEN words ELSE list_filter(words, lambda x, i: NOT list_contains(gone, i)) END, ' ')) AS kept_sha256
FROM w LEFT JOIN g USING (r)
"""
