"""Token counts by rank-synchronous merging of ragged arrays.

The pre-tokens of a batch lie end to end in one number array. In each round every sequence finds its pair of
lowest rank and merges all of that pair's occurrences at once, left to right; sequences without a mergeable
pair leave with as many tokens as they have symbols. A pair made by a merge ranks after the merge that made
its part, so merging all occurrences of the lowest pair together equals merging them one by one.

Long sequences would be read as often as they have rounds. They lie in an array of their own whose rounds are by rank: the places
of each waiting rank are kept, a round merges those of the least one in all sequences, and only the pairs beside a merge
are ranked anew.
"""

from __future__ import annotations

import functools
import heapq
import json
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .pretokens import splitter

VOCABULARY = "byte_bpe_50k.json"
LIMIT = 512
#: Pre-tokens longer than this many characters aren't kept in a worker's memo.
MEMO_CHARS = 48
MEMO_ENTRIES = 200_000
#: Sequences longer than this are merged in an array whose rounds touch merged places only.
LONG = 1024
NEVER = np.int64(1) << 40


def printable_bytes() -> dict[str, int]:
    """Byte of each character by which byte-level vocabularies spell bytes: printable ones as themselves, others from 256 up."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class RankMerger:
    """Counts tokens of pre-tokens under a merge list."""

    def __init__(self, merges: list[tuple[bytes, bytes]]):
        ids = {bytes([b]): b for b in range(256)}
        left, right, new = [], [], []
        for a, b in merges:
            left.append(ids[a])
            right.append(ids[b])
            new.append(ids.setdefault(a + b, len(ids)))
        self.base = np.int64(len(ids))
        keys = np.array(left, np.int64) * self.base + np.array(right, np.int64)
        self.rank_of = {k: i for i, k in reversed(list(enumerate(keys.tolist())))}
        self.table = common.PairTable(*(np.fromiter(x, np.int64, len(self.rank_of)) for x in (self.rank_of.keys(), self.rank_of.values())))
        self.new = np.array(new, np.int64)

    def _lookup(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        return self.table.get(left * self.base + right, NEVER)

    def count(self, tokens: list[bytes]) -> np.ndarray:
        """Symbols left of each pre-token."""
        out = np.zeros(len(tokens), np.int64)
        short = [i for i, t in enumerate(tokens) if len(t) <= LONG]
        if short:
            out[short] = self._rounds([tokens[i] for i in short])
        long = [i for i, t in enumerate(tokens) if len(t) > LONG]
        if long:
            out[long] = self._rank_rounds([tokens[i] for i in long])
        return out

    def _ragged(self, tokens: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Symbols and sequence numbers end to end, and the rank of the pair that starts at each symbol."""
        sym = np.frombuffer(b"".join(tokens), np.uint8).astype(np.int64)
        seq = np.repeat(np.arange(len(tokens)), [len(t) for t in tokens])
        rank = np.full(len(sym), NEVER)
        same = np.flatnonzero(seq[1:] == seq[:-1])
        rank[same] = self._lookup(sym[same], sym[same + 1])
        return sym, seq, rank

    @staticmethod
    def _alternate(at: np.ndarray, joined: np.ndarray) -> np.ndarray:
        """Of hits in order, those to merge: aa merges in a run a a a from the left, so every second of hits that overlap (`joined` to the one before)."""
        head = np.r_[True, ~joined] if len(at) else np.zeros(0, bool)
        run = np.maximum.accumulate(np.where(head, np.arange(len(at)), 0)) if len(at) else at
        return at[(np.arange(len(at)) - run) % 2 == 0]

    def _rounds(self, tokens: list[bytes]) -> np.ndarray:
        out = np.zeros(len(tokens), np.int64)
        sym, seq, rank = self._ragged(tokens)
        while len(sym):
            same = seq[1:] == seq[:-1]
            first = np.flatnonzero(np.r_[True, ~same])
            low = np.minimum.reduceat(rank, first)
            size = np.diff(np.r_[first, len(sym)])
            out[seq[first[low == NEVER]]] = size[low == NEVER]
            live = np.repeat(low != NEVER, size)
            hit = (rank == np.repeat(low, size)) & live
            at = np.flatnonzero(hit)
            at = self._alternate(at, np.diff(at) == 1)
            sym[at] = self.new[rank[at]]
            live[at + 1] = False
            sym, seq = sym[live], seq[live]
            rank = np.full(len(sym), NEVER)
            same = np.flatnonzero(seq[1:] == seq[:-1])
            rank[same] = self._lookup(sym[same], sym[same + 1])
        return out

    def _rank_rounds(self, tokens: list[bytes]) -> np.ndarray:
        sym, seq, rank = self._ragged(tokens)
        n = len(sym)
        after, before = np.arange(1, n + 1), np.arange(-1, n - 1)  # a pair across sequences never ranks
        waiting: dict[int, list[np.ndarray]] = {}
        heap: list[int] = []

        def wait(places: np.ndarray) -> None:
            places = places[rank[places] != NEVER]
            places = places[np.argsort(rank[places], kind="stable")]
            cuts = np.flatnonzero(np.diff(rank[places])) + 1
            for part in np.split(places, cuts) if len(places) else ():
                r = int(rank[part[0]])
                if r not in waiting:
                    heapq.heappush(heap, r)
                waiting.setdefault(r, []).append(part)

        wait(np.arange(n))
        alive = np.ones(n, bool)
        while heap:
            r = heapq.heappop(heap)
            at = np.unique(np.concatenate(waiting.pop(r)))
            at = at[rank[at] == r]
            if not len(at):
                continue
            at = self._alternate(at, after[at[:-1]] == at[1:])
            gone = after[at]
            alive[gone] = False
            sym[at], rank[gone] = self.new[r], NEVER
            after[at] = after[gone]
            inner = after[at] < n
            before[after[at][inner]] = at[inner]
            around = np.unique(np.concatenate([at, before[at][before[at] >= 0]]))
            end = after[around]
            ok = end < n
            ok[ok] = seq[around[ok]] == seq[end[ok]]
            rank[around] = NEVER
            rank[around[ok]] = self._lookup(sym[around[ok]], sym[end[ok]])
            wait(around)
        return np.bincount(seq[alive], minlength=len(tokens))


class Counter:
    """Token counts of texts under a byte-level vocabulary file of the tokenizers library."""

    def __init__(self, vocabulary: str):
        with open(public_tokenizers.path(vocabulary), encoding="utf-8") as f:
            spec = json.load(f)
        byte = printable_bytes()
        spell = lambda s: bytes(byte[c] for c in s)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        self.merger = RankMerger([(spell(a), spell(b)) for a, b in pairs])
        special = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.special = regex.compile("|".join(map(regex.escape, special))) if special else None
        self.split = splitter("tokenizers")
        self.memo: dict[str, int] = {}

    def pretokens(self, text: str) -> tuple[list[str], int]:
        """Pre-tokens of the text, and how many added tokens its text spells out."""
        if self.special is None or not self.special.search(text):
            return self.split(text), 0
        parts = self.special.split(text)
        return [t for p in parts for t in self.split(p)], len(parts) - 1

    def counts(self, texts: list[str]) -> list[int]:
        if len(self.memo) > MEMO_ENTRIES:
            self.memo.clear()
        found = [self.pretokens(t) for t in texts]
        memo = self.memo
        fresh = list(set().union(*(x for x, _ in found)) - memo.keys())
        now = dict(zip(fresh, self.merger.count([t.encode() for t in fresh]).tolist(), strict=True))
        memo.update(now)
        out = [sum(map(memo.__getitem__, x)) + k for x, k in found]
        for t in fresh:
            if len(t) > MEMO_CHARS:
                del memo[t]
        return out


@functools.cache
def counter(vocabulary: str) -> Counter:
    return Counter(vocabulary)


common.forgets("token_count", counter.cache_clear)


def token_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY, limit: int = LIMIT) -> DataFrame:
    """One row per row of `docs`: its id, n_bytes, n_tokens and whether n_tokens exceeds `limit`.

    Null text counts as empty: 0 bytes, 0 tokens. Repeated rows and repeated or null ids each keep a row of their
    own. Very long texts and pre-tokens take time in proportion to their length (times its logarithm), and a worker holds one such text at a time.
    Extra columns are ignored, whatever their names. An empty table gives an empty result. A narrow map: no shuffle.
    """
    slim = common.bounded(docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(vocabulary).counts
        for batch in batches:
            texts = common.column(batch, "text")
            n_bytes = common.byte_lengths(texts)
            tokens: list[int] = []
            for lo, hi in common.text_slices(batch):
                tokens += count([t or "" for t in texts.slice(lo, hi - lo).to_pylist()])
            yield pa.RecordBatch.from_arrays([common.column(batch, "id"), pa.array(n_bytes, pa.int64()), pa.array(tokens, pa.int64())], ["id", "n_bytes", "n_tokens"])

    out = slim.mapInArrow(common.tidy(run, "token_count"), f"id {slim.schema['id'].dataType.simpleString()}, n_bytes long, n_tokens long")
    return out.select(F.col("id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"))
