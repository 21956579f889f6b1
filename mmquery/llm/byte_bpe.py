"""Byte-level BPE encoding and decoding with a segment tree of pair ranks.

Byte positions are the leaves of a tree of minima; a leaf holds rank * size + position of the pair that starts
at a live symbol, so the root is the leftmost pair of lowest rank. A merge updates three leaves (the merged
symbol, the one it swallowed, its left neighbour) and the paths above them. Short pre-tokens of one size class run
in lockstep, a row each; long ones run alone on plain lists.
"""

from __future__ import annotations

import base64
import functools
import hashlib
from array import array
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import common
from .pretokens import splitter

RANKS = "byte_bpe_50k.tiktoken"
MEMO_CHARS = 48
MEMO_ENTRIES = 150_000
#: Size classes above this run one pre-token at a time.
LOCKSTEP = 128
#: Cells of the trees of one lockstep run.
CELLS = 1 << 18
NONE = np.int64(1) << 60


class SegmentTreeBPE:
    def __init__(self, ranks: dict[bytes, int]):
        self.bytes_of = {i: t for t, i in ranks.items()}
        self.base = max(ranks.values()) + 1
        # numbers in arrays: a dictionary of the pairs takes some twenty times as much
        pair, rank_of = array("q"), array("q")
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                a, b = ranks.get(token[:cut]), ranks.get(token[cut:])
                if a is not None and b is not None:
                    pair.append(a * self.base + b)
                    rank_of.append(rank)
        self.ranks = ranks
        self.table = common.PairTable(np.frombuffer(pair, np.int64), np.frombuffer(rank_of, np.int64))
        self.single = np.array([ranks[bytes([b])] for b in range(256)], np.int64)

    def _rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair, NONE where it doesn't merge or a side is missing (-1)."""
        return np.where((left >= 0) & (right >= 0), self.table.get(np.maximum(left * self.base + right, 0), NONE), NONE)

    def encode(self, tokens: list[bytes]) -> list[list[int]]:
        """Ids of each pre-token. A pre-token that is itself in the vocabulary is its own id."""
        out: list[list[int] | None] = [None] * len(tokens)
        classes: dict[int, list[int]] = {}
        for i, t in enumerate(tokens):
            if (whole := self.ranks.get(t)) is not None:
                out[i] = [whole]
            elif not t:
                out[i] = []
            else:
                classes.setdefault(max(2, 1 << (len(t) - 1).bit_length()), []).append(i)
        for size, members in classes.items():
            if size > LOCKSTEP:
                for i in members:
                    out[i] = self._alone(tokens[i])
            else:
                step = max(1, CELLS // (2 * size))
                for lo in range(0, len(members), step):
                    part = members[lo : lo + step]
                    for i, ids in zip(part, self._lockstep([tokens[i] for i in part], size), strict=True):
                        out[i] = ids
        return out

    def _lockstep(self, tokens: list[bytes], size: int) -> list[list[int]]:
        n = len(tokens)
        length = np.array([len(t) for t in tokens])
        # symbols keep a column of -1 at the left (-1 wraps to it) and at the right end
        sym = np.full((n, size + 1), -1, np.int64)
        live = np.arange(size)[None, :] < length[:, None]
        sym[:, :size][live] = self.single[np.frombuffer(b"".join(tokens), np.uint8)]
        after = np.tile(np.minimum(np.arange(1, size + 2), size), (n, 1))
        before = np.tile(np.arange(-1, size), (n, 1))
        tree = np.full((n, 2 * size), NONE, np.int64)
        rank = self._rank(sym[:, :size], sym[:, 1:])
        tree[:, size:] = np.where(rank < NONE, rank * size + np.arange(size), NONE)
        for lo in reversed([1 << k for k in range(size.bit_length() - 1)]):
            tree[:, lo : 2 * lo] = np.minimum(tree[:, 2 * lo : 4 * lo : 2], tree[:, 2 * lo + 1 : 4 * lo : 2])
        rows = np.flatnonzero(tree[:, 1] < NONE)
        while len(rows):
            best = tree[rows, 1]
            at, new = best % size, best // size
            gone = after[rows, at]
            right = after[rows, gone]
            left = before[rows, at]
            sym[rows, at], sym[rows, gone] = new, -1
            after[rows, at] = right
            before[rows, right] = at
            self._put(tree, rows, gone, np.full(len(rows), NONE), size)
            r = self._rank(new, sym[rows, right])
            self._put(tree, rows, at, np.where(r < NONE, r * size + at, NONE), size)
            inner = left >= 0
            r = self._rank(np.where(inner, sym[rows, left], -1), new)
            self._put(tree, rows[inner], left[inner], np.where(r < NONE, r * size + left, NONE)[inner], size)
            rows = rows[tree[rows, 1] < NONE]
        body = sym[:, :size]
        keep = body >= 0
        flat, cuts = body[keep].tolist(), np.cumsum(keep.sum(1)).tolist()
        return [flat[a:b] for a, b in zip([0, *cuts], cuts, strict=False)]

    @staticmethod
    def _put(tree: np.ndarray, rows: np.ndarray, leaf: np.ndarray, value: np.ndarray, size: int) -> None:
        node = leaf + size
        tree[rows, node] = value
        while size > 1:
            node, size = node >> 1, size >> 1
            tree[rows, node] = np.minimum(tree[rows, 2 * node], tree[rows, 2 * node + 1])

    def _alone(self, token: bytes) -> list[int]:
        n = len(token)
        size = 1 << (n - 1).bit_length()
        none, spelt, ranks = int(NONE), self.bytes_of, self.ranks.get
        sym = self.single[np.frombuffer(token, np.uint8)].tolist()
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        tree = [none] * (2 * size)
        for i in range(n - 1):
            if (r := ranks(spelt[sym[i]] + spelt[sym[i + 1]])) is not None:
                tree[size + i] = r * size + i
        for k in range(size - 1, 0, -1):
            tree[k] = min(tree[2 * k], tree[2 * k + 1])

        def put(i: int, value: int) -> None:
            k = i + size
            tree[k] = value
            while k > 1:
                k >>= 1
                a, b = tree[2 * k], tree[2 * k + 1]
                tree[k] = a if a < b else b

        def leaf(i: int) -> int:
            j = after[i]
            r = ranks(spelt[sym[i]] + spelt[sym[j]]) if j < n else None
            return none if r is None else r * size + i

        while tree[1] < none:
            new, at = divmod(tree[1], size)
            gone = after[at]
            sym[at], sym[gone] = new, -1
            after[at] = after[gone]
            if after[at] < n:
                before[after[at]] = at
            put(gone, none)
            put(at, leaf(at))
            if before[at] >= 0:
                put(before[at], leaf(before[at]))
        return [s for s in sym if s >= 0]


class Codec:
    """Texts to ids and back, under a rank file of the tiktoken library."""

    def __init__(self, ranks: str):
        with open(public_tokenizers.path(ranks), "rb") as f:
            table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.bpe = SegmentTreeBPE(table)
        self.split = splitter("tiktoken")
        self.memo: dict[str, bytes] = {}

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        memo = self.memo
        if len(memo) > MEMO_ENTRIES:
            memo.clear()
        found = [self.split(t) for t in texts]
        fresh = list(set().union(*found) - memo.keys()) if found else []
        for t, ids in zip(fresh, self.bpe.encode([t.encode() for t in fresh]), strict=True):
            memo[t] = np.array(ids, "<u4").tobytes()
        out = [b"".join(map(memo.__getitem__, x)) for x in found]
        for t in fresh:
            if len(t) > MEMO_CHARS:
                del memo[t]
        return out

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bpe.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@functools.cache
def codec(ranks: str) -> Codec:
    return Codec(ranks)


common.forgets("byte_bpe", codec.cache_clear)


def _apply(docs: DataFrame, id_col: str, text_col: str, row, schema: str, ranks: str) -> DataFrame:
    slim = common.bounded(docs.select(docs[id_col].alias(id_col), docs[text_col].alias("__text")))
    kind = slim.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(ranks)
        for batch in batches:
            for lo, hi in common.text_slices(batch, "__text"):
                part = batch.slice(lo, hi - lo)
                ids = c.encode([t or "" for t in common.column(part, "__text").to_pylist()])
                yield pa.RecordBatch.from_arrays([common.column(part, id_col), *row(c, ids)], [id_col, *names])

    names = [x.split()[0] for x in schema.split(", ")]
    return slim.mapInArrow(common.tidy(run, "byte_bpe"), f"`{id_col}` {kind}, {schema}")


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ranks: str = RANKS) -> DataFrame:
    """id, n_tokens, ids (little-endian unsigned 32-bit integers) of each row's whole text.

    Null text is empty: no ids. Repeated rows keep a row each. A very long text is a slice of its own, and a long pre-token a tree of
    its own, whose merges take the logarithm of its length. Extra columns are ignored; an empty table stays empty.
    """
    return _apply(docs, id_col, text_col, lambda c, ids: [pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())], "n_tokens long, ids binary", ranks)


def decode(encoded: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", ranks: str = RANKS) -> DataFrame:
    """id and decoded bytes of each row of ids.

    Null and empty ids decode to no bytes; repeated rows keep a row each; ids of a very long text are decoded as a whole; extra columns
    are ignored; an empty table stays empty. An id outside the vocabulary is an error.
    """
    slim = common.bounded(encoded.select(encoded[id_col].alias(id_col), encoded[ids_col].alias("__ids")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(ranks)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                raw = [c.decode(x or b"") for x in common.column(part, "__ids").to_pylist()]
                yield pa.RecordBatch.from_arrays([common.column(part, id_col), pa.array(raw, pa.binary())], [id_col, "decoded"])

    return slim.mapInArrow(common.tidy(run, "byte_bpe"), f"`{id_col}` {slim.schema[id_col].dataType.simpleString()}, decoded binary")


def round_trip(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ranks: str = RANKS) -> DataFrame:
    """Encode every whole text, decode the ids, and return digests of both: id, n_tokens, ids_sha256, decoded_sha256.

    Null text is empty: 0 tokens, digests of no bytes. Repeated rows keep a row each; very long texts are taken as encode() takes
    them; extra columns are ignored; an empty table stays empty.
    Encoding and decoding share one pass, so ids never leave the worker: no shuffle.
    """

    def row(c: Codec, ids: list[bytes]) -> list[pa.Array]:
        return [
            pa.array([len(x) // 4 for x in ids], pa.int64()),
            pa.array([hashlib.sha256(x).hexdigest() for x in ids], pa.string()),
            pa.array([hashlib.sha256(c.decode(x)).hexdigest() for x in ids], pa.string()),
        ]

    return _apply(docs, id_col, text_col, row, "n_tokens long, ids_sha256 string, decoded_sha256 string", ranks)


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(spark.read.parquet(f"{sf_dir}/documents.parquet"))
