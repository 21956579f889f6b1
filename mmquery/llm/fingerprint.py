"""Document fingerprints by locally consistent parsing.

A text is parsed level by level. Runs of one symbol become a symbol; deterministic coin tossing then turns symbols
into a handful of labels that differ between neighbours: a label says at which lowest bit a symbol differs from the
one before it and what that bit is, and the rule is applied again to the labels until six remain. Phrases start where a
label is a local maximum, so a phrase is named by its symbols and bounded by a constant number of neighbours: two
texts that share a passage parse its interior alike wherever it stands. Names of a level are the symbols of the next.

The fingerprint keeps, for each of a few groups of levels, the least name in each of a number of bins. Likeness is
twice the estimated share of common names over one plus that share: about the part of its content that a text has in common
with the other.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Bins for the second, third and all higher levels.
BINS = (32, 64, 32)
LEVELS = 14
#: Sections that the ids are first cut into for each partition.
FINE = 4
#: Code points parsed at a time.
SLICE = 1 << 19
_NAME = common.U64(0x2545F4914F6CDD1D)
_ONE = common.U64(1)


def _labels(symbols: np.ndarray, before: np.ndarray, bits: int) -> np.ndarray:
    differ = symbols ^ before
    lowest = np.bitwise_count((differ & (~differ + symbols.dtype.type(1))) - symbols.dtype.type(1)).astype(symbols.dtype)
    return (lowest << symbols.dtype.type(1)) | ((symbols >> lowest) & symbols.dtype.type(1))


def _toss_table(size: int) -> np.ndarray:
    """The label of each (before, symbol) pair of labels under `size`; equal pairs, only met at text starts, get 0."""
    before, now = np.meshgrid(np.arange(size), np.arange(size), indexing="ij")
    differ = before ^ now
    lowest = np.where(differ == 0, 0, np.round(np.log2(np.maximum(differ & -differ, 1))).astype(int))
    return (2 * lowest + ((now >> lowest) & 1)).astype(np.uint8).ravel()


_TOSS = _toss_table(128)


def parse(symbols: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One level: names of the phrases of texts that lie end to end (starts: offsets, none empty), and their offsets."""
    head = np.zeros(len(symbols), bool)
    head[starts] = True
    first = head.copy()
    first[1:] |= symbols[1:] != symbols[:-1]
    at = np.flatnonzero(first)
    run = np.diff(np.r_[at, len(symbols)])
    symbols = symbols[at]
    symbols = np.where(run > 1, common.mix64(symbols + run.astype(common.U64) * _NAME), symbols) if (run > 1).any() else symbols
    head = head[at]
    # a run's name may equal its neighbour's symbol only by collision; labels then just don't differ there
    before = np.empty_like(symbols)
    before[1:] = symbols[:-1]
    before[head] = ~symbols[head]
    label = np.minimum(_labels(symbols, before, 64), 127).astype(np.uint8)
    for _ in range(3):
        left = np.empty_like(label)
        left[1:] = label[:-1]
        left[head] = label[head] ^ 1
        label = _TOSS[left.astype(np.int16) * 128 + label]
    low = np.zeros(len(label), bool)
    low[1:-1] = (label[1:-1] > label[:-2]) & (label[1:-1] > label[2:])
    tail = np.zeros(len(label), bool)
    tail[:-1] = head[1:]
    if len(tail):
        tail[-1] = True
    after = np.zeros(len(label), bool)
    after[1:] = head[:-1]
    cut = head | (low & ~tail & ~after)
    begin = np.flatnonzero(cut)
    names = common.segment_hashes(lambda a, b: common.mix64(symbols[a:b]), begin, np.r_[begin[1:], len(symbols)], _NAME | _ONE)
    return names, np.flatnonzero(head[begin])


def sketches(texts: list[str]) -> np.ndarray:
    """A row of 16-bit bins for each text; 0 is an empty bin."""
    out = np.zeros((len(texts), sum(BINS)), np.uint16)
    size = np.array([len(t) for t in texts], np.int64)
    lo = 0
    while lo < len(texts):
        hi = max(lo + 1, lo + int(np.searchsorted(np.cumsum(size[lo:]), SLICE, side="right")))
        _sketch(texts[lo:hi], out[lo:hi])
        lo = hi
    return out


def _sketch(texts: list[str], out: np.ndarray) -> None:
    rows = np.array([i for i, t in enumerate(texts) if t], np.int64)
    if not len(rows):
        return
    sizes = np.array([len(texts[i]) for i in rows])
    symbols = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(common.U64) + _ONE
    starts = np.r_[0, np.cumsum(sizes)[:-1]]
    least = np.full((len(texts), sum(BINS)), np.uint64(0xFFFFFFFFFFFFFFFF))
    base = np.cumsum((0, *BINS))
    for level in range(1, LEVELS + 1):
        symbols, starts = parse(symbols, starts)
        count = np.diff(np.r_[starts, len(symbols)])
        owner = np.repeat(rows, count)
        group = 0 if level <= 2 else min(level - 2, len(BINS) - 1)
        if level == 1:  # a text of one phrase has no second level of its own
            keep = np.repeat(count == 1, count)
        else:
            keep = np.ones(len(symbols), bool)
        name = common.mix64(symbols[keep] + common.U64(group))
        bins = (name % common.U64(BINS[group])).astype(np.int64) + base[group]
        np.minimum.at(least, (owner[keep], bins), name)
        more = np.repeat(count > 1, count)
        if not more.any():
            break
        rows = rows[count > 1]
        symbols = symbols[more]
        starts = np.r_[0, np.cumsum(count[count > 1])[:-1]]
    filled = least != np.uint64(0xFFFFFFFFFFFFFFFF)
    out[filled] = np.maximum((common.mix64(least[filled]) >> common.U64(48)).astype(np.uint16), 1)


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row, 0 to 1; two texts without any symbol are alike."""
    some = ((a > 0) | (b > 0)).sum(1)
    share = ((a == b) & (a > 0)).sum(1) / np.maximum(some, 1)
    return np.where(some == 0, 1.0, 2 * share / (1 + share))


def edited(text: str, following: str) -> str:
    """`text` with its last half (rounded down) replaced by as many first characters of `following`, or all of it."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def _above(cuts: list[int], key: Column, equal: bool = False) -> Column:
    """How many of the cuts, in descending order, lie above the key (or equal it): first among every so many, then in the block that is left."""
    if not cuts:
        return F.lit(0)
    step = max(1, math.isqrt(len(cuts)))
    listed = lambda x: F.array(*(F.lit(c).cast("long") for c in x))
    blocks = [cuts[i : i + step] for i in range(0, len(cuts), step)]
    many = lambda x: F.size(F.filter(x, lambda c: c >= key if equal else c > key))
    heads = many(listed(b[0] for b in blocks))
    inner = many(F.get(F.array(*map(listed, blocks)), heads - 1))
    return F.when(heads == 0, 0).otherwise((heads - 1) * step + inner)


def _deal(docs: DataFrame) -> DataFrame:
    """Rows in sections of descending doc_id, each with the first row of the next section as its `trailer`.

    Cut points come from a quantile sketch, several a partition; neighbouring sections are then joined to about the same bytes.
    What reaches the driver is an id and a size a section.
    """
    spark = common.bounded(docs).sparkSession
    n = common.partitions(spark)
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))  # nulls last in descending order
    slim = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), key.alias("key"))
    fine = FINE * n
    cuts = slim.agg(F.percentile_approx("key", [i / fine for i in range(1, fine)], 20 * fine).alias("c")).first()["c"] if fine > 1 else []
    cuts = sorted(set(cuts or []), reverse=True)
    found = slim.withColumn("fine", _above(cuts, F.col("key"))).groupBy("fine").agg(F.max("key").alias("key"), F.sum(F.octet_length("text") + 64).alias("bytes")).orderBy("fine").collect()
    most = sum(r["bytes"] for r in found) / n
    heads: list[int] = []  # the first key of each section
    held = 0.0
    for r in found:
        if not heads or held + r["bytes"] / 2 > most:
            heads.append(r["key"])
            held = 0.0
        held += r["bytes"]
    # a key lies in the last section whose head isn't below it
    placed = slim.withColumn("section", (_above(heads, F.col("key"), equal=True) - 1).cast("int"))
    to = {h: (i - 1) % len(heads) for i, h in enumerate(heads)}  # the section before takes this one's head; the last takes the first's
    firsts = placed.where(F.col("key").isin([*to])).groupBy("key").agg(F.min("text").alias("text"))
    back = F.create_map(*[x for k, s in to.items() for x in (F.lit(k).cast("long"), F.lit(s))]) if to else F.create_map(F.lit(0).cast("long"), F.lit(0))
    trailers = firsts.select(F.lit(None).cast(docs.schema["doc_id"].dataType).alias("doc_id"), "text", F.lit(-(1 << 63)).alias("key"), back[F.col("key")].alias("section"), F.lit(True).alias("trailer"))
    every = placed.withColumn("trailer", F.lit(False)).unionByName(trailers)
    return every.repartition(n, "section").sortWithinPartitions("section", "trailer", F.desc("key"), "text")


def _row(ids: list, texts: list[str], following: list[str]) -> list:
    changed = [edited(t, f) for t, f in zip(texts, following, strict=True)]
    s = sketches([*texts, *changed, *following])
    k = len(texts)
    own, new, other = s[:k], s[k : 2 * k], s[2 * k :]
    return [
        ids,
        [len(t) for t in texts],
        [hashlib.sha256(c.encode()).hexdigest() for c in changed],
        [r.astype(">u2").tobytes().hex() for r in own],
        [r.astype(">u2").tobytes().hex() for r in new],
        likeness(own, new).tolist(),
        likeness(own, other).tolist(),
    ]


FIELDS = "n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def fingerprints(docs: DataFrame) -> DataFrame:
    """Fingerprints of every whole text, of its edited text, and their likeness; and the likeness to the next text's.

    The next row is that of the next lower doc_id (ties: the next text in order; null ids last; after the last the
    first). Null texts are empty: no bin is filled, and two empty texts have likeness 1, an empty and another 0. The
    only row of a table is its own next. Repeated rows keep a row each; a very long text is parsed as a whole; extra columns are ignored; an empty
    table stays empty. Texts are shuffled once, into sections of the id order of about the same bytes (rows of one id, or without one,
    lie in one section).
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    names = ["doc_id", *(x.split()[0] for x in FIELDS.split(", "))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the row that waits for its next
        waiting: tuple[list, list, list] = ([], [], [])
        size, schema = 0, None

        def flush() -> pa.RecordBatch:
            cols = _row(*map(list, waiting))
            for x in waiting:
                x.clear()
            return pa.RecordBatch.from_arrays([pa.array(cols[0], schema), pa.array(cols[1], pa.int64()), *(pa.array(c, pa.string()) for c in cols[2:5]), *(pa.array(c, pa.float64()) for c in cols[5:])], names)

        for batch in batches:
            schema = common.column(batch, "doc_id").type
            for doc, text, section, trailer in zip(*(common.column(batch, c).to_pylist() for c in ("doc_id", "text", "section", "trailer")), strict=True):
                if held is not None and held[2] == section:
                    waiting[0].append(held[0])
                    waiting[1].append(held[1])
                    waiting[2].append(text)
                    size += len(held[1])
                    if size > SLICE or len(waiting[0]) >= 4096:
                        yield flush()
                        size = 0
                held = None if trailer else (doc, text, section)
        if waiting[0]:
            yield flush()

    return _deal(docs).select("doc_id", "text", "section", "trailer").mapInArrow(common.tidy(run), f"doc_id {kind}, {FIELDS}")


def op5_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(spark.read.parquet(f"{sf_dir}/documents.parquet"))
