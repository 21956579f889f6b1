"""Shared plumbing of the training-data operators: shared-folder tables, Arrow text buffers, word hashing.

Python workers see texts as Arrow buffers and work on them in slices of bounded bytes, so a worker's
memory follows the slice (or the longest single text), never the partition.
"""

from __future__ import annotations

import ctypes
import functools
import re
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Bytes of text a Python worker turns into number arrays at a time.
SLICE_BYTES = 1 << 20
U64 = np.uint64


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, from spark.checkpoint.dir; on one machine a folder of our own where that is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file:/tmp/mmquery-shared"
    return found.rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut lineage with a Parquet table in the shared folder; a lost executor then costs a reread, not a recompute."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/mmquery/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Delete the files of a table made by materialise() that nothing reads any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    for f in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/mmquery/" in f:
            p = jvm.org.apache.hadoop.fs.Path(f)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


#: Bytes of an Arrow batch on its way to a worker; both ends hold a batch or two besides the slice in work.
BATCH_BYTES = 4 << 20


def bounded(df: DataFrame) -> DataFrame:
    """The same rows, which Python workers will get in batches of at most BATCH_BYTES (a runtime setting, only ever lowered).

    By rows alone a batch of long texts would have no bound.
    """
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    conf = df.sparkSession.conf
    now = re.fullmatch(r"(\d+)b?", conf.get(key))
    if not now or not 0 < int(now[1]) <= BATCH_BYTES:
        conf.set(key, str(BATCH_BYTES))
    return df


_FORGET: dict[str, list[Callable[[], object]]] = {}


def forgets(owner: str, *clear: Callable[[], object]) -> None:
    """Register how the caches that an operator keeps in a Python worker are emptied."""
    _FORGET.setdefault(owner, []).extend(clear)


@functools.cache
def _malloc_trim():
    try:
        return ctypes.CDLL(None).malloc_trim
    except (AttributeError, OSError):  # another C library
        return lambda _: 0


def forget_others(owner: str) -> None:
    """Empty what other operators keep in this worker."""
    for name, clears in _FORGET.items():
        if name != owner:
            for clear in clears:
                clear()


def trim() -> None:
    """Hand free memory back to the system."""
    pa.default_memory_pool().release_unused()
    _malloc_trim()(0)


def tidy(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], owner: str = "") -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The same map, before which the caches of other operators go, and after which the worker hands back what it doesn't need.

    Workers outlive their tasks: what one stage leaves in them would count against the next.
    """

    def tidied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_others(owner)
        trim()
        yield from run(batches)
        trim()

    return tidied


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def text_slices(batch: pa.RecordBatch, name: str = "text", most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of the batch whose texts hold about `most` bytes, a single longer text alone."""
    if batch.num_rows == 0:
        return
    ends = np.cumsum(byte_lengths(column(batch, name)))
    lo = 0
    while lo < len(ends):
        base = ends[lo - 1] if lo else 0
        hi = max(lo + 1, int(np.searchsorted(ends, base + most, side="right")))
        yield lo, hi
        lo = hi


def byte_lengths(array: pa.Array) -> np.ndarray:
    import pyarrow.compute as pc

    return pc.fill_null(pc.binary_length(array), 0).to_numpy(zero_copy_only=False).astype(np.int64)


def utf8(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of all texts in one array, and their n + 1 offsets; a null counts as empty."""
    import pyarrow.compute as pc

    array = pc.fill_null(array, "").cast(pa.large_binary())
    offsets = np.frombuffer(array.buffers()[1], dtype=np.int64)[array.offset : array.offset + len(array) + 1]
    data = array.buffers()[2]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def is_space(raw: np.ndarray) -> np.ndarray:
    return (raw == 32) | ((raw - np.uint8(9)) < 5)


def word_spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of bytes outside 0x20 and 0x09-0x0D, and per text the first word's number.

    Words never cross texts. Multi-byte characters hold no byte under 0x80, so bytes suffice.
    """
    n = len(raw)
    ink = ~is_space(raw)
    starts, ends = ink.copy(), ink.copy()
    starts[1:] &= ~ink[:-1]
    ends[:-1] &= ~ink[1:]
    cut = offsets[1:-1]
    cut = cut[(cut > 0) & (cut < n)]
    starts[cut] |= ink[cut]
    ends[cut - 1] |= ink[cut - 1]
    s, e = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    return s, e, np.searchsorted(s, offsets)


def mix64(x: np.ndarray) -> np.ndarray:
    """A finaliser that spreads every input bit over all 64."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def seeds(n: int, seed: int) -> np.ndarray:
    return mix64(np.arange(1, n + 1, dtype=U64) * U64(0x9E3779B97F4A7C15) + U64(seed))


_BYTE = seeds(256, 71)
_BASE, _STEP = U64(0xD6E8FEB86659FD93), U64(0xA0761D6478BD642F)
#: Bytes or words hashed at a time: the sums over them take some forty bytes each.
CHUNK = 1 << 17
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n; base is odd."""
    have = _POWERS.get(int(base))
    if have is None or len(have[0]) < n:
        size = max(n, 1 << 16)
        inverse = U64(pow(int(base), -1, 1 << 64))
        up, down = np.full(size, base, U64), np.full(size, inverse, U64)
        up[0] = down[0] = 1
        have = np.cumprod(up, dtype=U64), np.cumprod(down, dtype=U64)
        if size <= 4 * CHUNK:
            _POWERS[int(base)] = have
    return have[0][:n], have[1][:n]


def segment_hashes(values: Callable[[int, int], np.ndarray], s: np.ndarray, e: np.ndarray, base: np.uint64) -> np.ndarray:
    """A hash of each of the segments [s, e), which ascend and don't overlap; values(a, b) gives the numbers between two places."""
    out = np.zeros(len(s), U64)
    lo = 0
    while lo < len(s):
        at = int(s[lo])
        hi = max(lo + 1, int(np.searchsorted(e, at + CHUNK, side="right")))
        part = values(at, int(e[hi - 1]))
        up, down = powers(base, len(part) + 1)
        total = np.zeros(len(part) + 1, U64)
        np.cumsum(part * up[:-1], out=total[1:])
        a, b = s[lo:hi] - at, e[lo:hi] - at
        out[lo:hi] = mix64((total[b] - total[a]) * down[a] + (b - a).astype(U64))
        lo = hi
    return out


def word_hashes(raw: np.ndarray, s: np.ndarray, e: np.ndarray, byte: np.ndarray = _BYTE) -> np.ndarray:
    """A 64-bit hash of each word, the same wherever it stands; `byte` has a number for each byte, another table gives another hash."""
    return segment_hashes(lambda a, b: byte[raw[a:b]], s, e, _BASE)


def window_hashes(words: np.ndarray, size: int, base: np.uint64 = _STEP) -> np.ndarray:
    """Hash of each run of `size` consecutive entries (the caller drops those that cross texts)."""
    n = max(0, len(words) - size + 1)
    out = np.zeros(n, U64)
    for lo in range(0, n, CHUNK):
        part = words[lo : lo + CHUNK + size - 1]
        up, down = powers(base, len(part) + 1)
        total = np.zeros(len(part) + 1, U64)
        np.cumsum(part * up[:-1], out=total[1:])
        out[lo : lo + CHUNK] = mix64((total[size:] - total[:-size]) * down[: len(part) - size + 1])
    return out


def inside(first: np.ndarray, size: int) -> np.ndarray:
    """Of the windows of `size` words starting at each word, those that end in the text they start in."""
    n = int(first[-1])
    if n < size:
        return np.zeros(0, bool)
    end = np.repeat(first[1:], np.diff(first))
    return np.arange(n - size + 1) + size <= end[: n - size + 1]


class PairTable:
    """A read-only hash table from 64-bit keys to 64-bit values with vectorised lookups."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.bits = max(8, int(len(keys) * 3).bit_length())
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.values = np.zeros(1 << self.bits, np.int64)
        todo, at = np.arange(len(keys)), self._slot(keys)
        while len(todo):
            free = self.keys[at] < 0
            _, first = np.unique(at[free], return_index=True)
            put = np.flatnonzero(free)[first]
            self.keys[at[put]], self.values[at[put]] = keys[todo[put]], values[todo[put]]
            rest = np.ones(len(todo), bool)
            rest[put] = False
            todo, at = todo[rest], (at[rest] + 1) & (len(self.keys) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(U64) * U64(0x9E3779B97F4A7C15)) >> U64(64 - self.bits)).astype(np.int64)

    def get(self, keys: np.ndarray, missing: int) -> np.ndarray:
        """Values of non-negative keys; `missing` where there is none."""
        shape, keys = keys.shape, keys.ravel()
        at = self._slot(keys)
        seen = self.keys[at]
        out = np.where(seen == keys, self.values[at], missing)
        left = np.flatnonzero((seen != keys) & (seen >= 0))
        at = at[left]
        while len(left):
            at = (at + 1) & (len(self.keys) - 1)
            seen = self.keys[at]
            hit = seen == keys[left]
            out[left[hit]] = self.values[at[hit]]
            more = ~hit & (seen >= 0)
            left, at = left[more], at[more]
        return out.reshape(shape)
