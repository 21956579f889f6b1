"""Language identification by unigram piece models summed over all segmentations.

Each language has a probability for every piece of one fixed public vocabulary. The likelihood of a word is the
sum over all ways to cut it into pieces, by a forward pass over its characters; words are independent, so a
text's log likelihood is the sum over its words, and a worker scores each distinct word once. The probabilities
come from a few rounds of expectation maximisation, with the same forward pass and its mirror image. Words whose
likelihood is too small for double precision are passed again in extended precision.
"""

from __future__ import annotations

import functools
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

VOCABULARY = "piece_bpe_32k.model"
UNKNOWN = "und"
#: The fit's bound: labelled rows with a text of each language, those of smallest hash; and of all languages together, shared evenly.
SAMPLE_ROWS = 300
SAMPLE_TOTAL = 60_000
#: Shares in which a language's rows are ranked before the least of all shares are.
SHARES = 32
ROUNDS = 3
SMOOTHING = 0.05
#: Words above this many characters are scored alone; the fit takes them in pieces of this length.
LOCKSTEP = 48
MEMO_ENTRIES = 100_000
MEMO_CHARS = 48
#: Words of a block times languages: a forward pass holds as many numbers for each character.
CELLS = 1 << 14
#: Likelihoods below this are taken again with a wider exponent (80 bits and more where the machine has them).
TINY = 1e-250
_LETTER = regex.compile(r"\p{L}").search
_MASK = common.U64((1 << 63) - 1)
_STEP = common.U64(0x9E3779B97F4A7C15)


class Vocabulary:
    """Pieces by string, and by a rolling hash of their code points."""

    def __init__(self, name: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(name))
        self.id_of: dict[str, int] = {}
        self.byte = [0] * 256
        for i in range(sp.get_piece_size()):
            if sp.is_byte(i):
                self.byte[int(sp.id_to_piece(i)[3:-1], 16)] = i
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                self.id_of.setdefault(sp.id_to_piece(i), i)
        self.size = sp.get_piece_size()
        self.longest = max(map(len, self.id_of))
        by_hash = {self._hash(p): i for p, i in self.id_of.items()}
        self.table = common.PairTable(*(np.fromiter(x, np.int64, len(by_hash)) for x in (by_hash.keys(), by_hash.values())))
        self.singles = {p for p in self.id_of if len(p) == 1}

    @staticmethod
    def _hash(piece: str) -> int:
        h = 0
        for c in piece:
            h = (h * int(_STEP) + ord(c) + 1) & ((1 << 64) - 1)
        return h & int(_MASK)

    def edges(self, code: np.ndarray) -> list[np.ndarray]:
        """Per length, the piece id (-1: none) that starts at each column of a block of words padded with 0."""
        out, h = [], np.zeros(code.shape, common.U64)
        width = code.shape[1]
        for n in range(1, min(self.longest, width) + 1):
            h = h[:, : width - n + 1] * _STEP + code[:, n - 1 :].astype(common.U64) + common.U64(1)
            found = self.table.get((h & _MASK).astype(np.int64), -1)
            out.append(np.where(code[:, n - 1 :] > 0, found, -1))
        return out


@functools.cache
def vocabulary(name: str) -> Vocabulary:
    return Vocabulary(name)


class Model:
    """Piece probabilities, one column a language."""

    def __init__(self, name: str, languages: list[str], p: np.ndarray):
        self.name, self.languages, self.p = name, languages, p

    def _tables(self) -> tuple[Vocabulary, np.ndarray, np.ndarray]:
        v = vocabulary(self.name)
        if not hasattr(self, "_padded"):
            self._padded = np.vstack([self.p, np.zeros((1, self.p.shape[1]))])  # -1 reads the last row
            self._bytes = self.p[v.byte]
        return v, self._padded, self._bytes

    def _fallback(self, code: np.ndarray, missing: np.ndarray) -> np.ndarray:
        """Probability of each character that is no piece: the product over its UTF-8 bytes."""
        _, _, byte = self._tables()
        out = np.zeros((*code.shape, self.p.shape[1]))
        for c in np.unique(code[missing]):
            out[missing & (code == c)] = byte[list(chr(c).encode("utf-8", "replace"))].prod(0)
        return out

    def block(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, list[np.ndarray], np.ndarray]:
        length = np.array([len(t) for t in texts])
        code = np.zeros((len(texts), int(length.max())), np.int64)
        inner = np.arange(code.shape[1])[None, :] < length[:, None]
        code[inner] = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
        v, _, _ = self._tables()
        edges = v.edges(code)
        return code, length, edges, self._fallback(code, (edges[0] < 0) & (code > 0))

    def step(self) -> int:
        """Words of a block."""
        return max(16, min(4096, CELLS // max(1, len(self.languages))))

    def forward(self, code: np.ndarray, edges: list[np.ndarray], single: np.ndarray, kind: type = np.float64) -> np.ndarray:
        _, p, _ = self._tables()
        n, width = code.shape
        a = np.zeros((n, width + 1, p.shape[1]), kind)
        a[:, 0] = 1
        for end in range(1, width + 1):
            total = a[:, end - 1] * (p[edges[0][:, end - 1]] + single[:, end - 1])
            for k in range(2, min(len(edges), end) + 1):
                total += a[:, end - k] * p[edges[k - 1][:, end - k]]
            a[:, end] = total
        return a

    def words(self, words: list[str]) -> np.ndarray:
        """Log likelihood of each word under each language."""
        out = np.zeros((len(words), self.p.shape[1]))
        classes: dict[int, list[int]] = {}
        for i, w in enumerate(words):
            if len(w) > LOCKSTEP:
                out[i] = self._alone(w)
            else:
                classes.setdefault(-(-len(w) // 4), []).append(i)
        step = self.step()
        for members in classes.values():
            for lo in range(0, len(members), step):
                part = members[lo : lo + step]
                code, length, edges, single = self.block(["▁" + words[i] for i in part])
                last = self.forward(code, edges, single)[np.arange(len(part)), length]
                out[part] = np.log(np.maximum(last, TINY))
                if len(small := np.flatnonzero((last < TINY).any(1))):
                    wide = self.forward(code[small], [e[small] for e in edges], single[small], np.longdouble)
                    out[np.array(part)[small]] = np.log(wide[np.arange(len(small)), length[small]]).astype(float)
        return out

    def _alone(self, word: str) -> np.ndarray:
        v, p, byte = self._tables()
        text = "▁" + word
        one = np.ones(p.shape[1], np.longdouble)
        recent, log = [one], np.zeros(p.shape[1])
        get, longest = v.id_of.get, v.longest
        for end in range(1, len(text) + 1):
            total = 0 * one
            for k in range(1, min(len(recent), longest) + 1):
                if (i := get(text[end - k : end])) is not None:
                    total = total + recent[-k] * p[i]
            if text[end - 1] not in v.singles:
                total = total + recent[-1] * byte[list(text[end - 1].encode("utf-8", "replace"))].prod(0)
            recent.append(total)
            if len(recent) > longest + 1:
                recent = recent[-longest:]
            if end % 8 == 0:
                top = np.max(recent[-longest:], axis=0)
                log += np.log(top).astype(float)
                recent = [r / top for r in recent[-longest:]]
        return log + np.log(recent[-1]).astype(float)


def _cuts(word: str) -> list[tuple[str, float]]:
    """What the fit learns of a word, with weights: the marked word; a long one in pieces, tiled twice half a piece apart, each tiling counting half."""
    text = "▁" + word
    if len(word) <= LOCKSTEP:
        return [(text, 1.0)]
    return [(text[max(lo, 0) : lo + LOCKSTEP], 0.5) for start in (0, -(LOCKSTEP // 2)) for lo in range(start, len(text), LOCKSTEP)]


def count_words(texts: list[str], languages: list[str]) -> dict[tuple[str, str], float]:
    """How often, by weight, the texts of each language teach each word or piece of a word."""
    found: dict[tuple[str, str], float] = defaultdict(float)
    for text, g in zip(texts, languages, strict=True):
        for w, n in Counter(text.split()).items():
            for piece, share in _cuts(w):
                found[g, piece] += share * n
    return found


def fit(rows: list[tuple[str, str]], name: str = VOCABULARY, rounds: int = ROUNDS) -> Model:
    """Piece probabilities of each language from (text, language) pairs."""
    found = count_words([t for t, _ in rows], [g for _, g in rows])
    return fit_counts([(g, w, n) for (g, w), n in found.items()], name, rounds)


def fit_counts(counts: list[tuple[str, str, float]], name: str = VOCABULARY, rounds: int = ROUNDS, languages: list[str] | None = None) -> Model:
    """Piece probabilities of each language from (language, word, weight) triples."""
    languages = languages if languages is not None else sorted({g for g, _, _ in counts})
    v = vocabulary(name)
    at = {g: i for i, g in enumerate(languages)}
    by_word: dict[str, list[tuple[int, float]]] = defaultdict(list)
    for g, w, n in counts:
        by_word[w].append((at[g], n))
    words = sorted(by_word)
    model = Model(name, languages, np.full((v.size, len(languages)), 1 / v.size))
    blocks: dict[int, list[str]] = defaultdict(list)
    for w in words:
        blocks[-(-(len(w) - 1) // 4)].append(w)
    step = model.step()
    for _ in range(rounds if words else 0):
        expected = np.zeros_like(model.p)
        for members in blocks.values():
            for lo in range(0, len(members), step):
                part = members[lo : lo + step]
                weight = np.zeros((len(part), len(languages)))
                for i, w in enumerate(part):
                    for g, n in by_word[w]:
                        weight[i, g] += n
                _expect(model, part, weight, expected)
        expected += SMOOTHING
        model = Model(name, languages, expected / expected.sum(0))
    return model


def _expect(model: Model, words: list[str], weight: np.ndarray, expected: np.ndarray) -> None:
    """Add the expected piece counts of a block of words."""
    code, length, edges, single = model.block(words)
    v, p, _ = model._tables()
    rows = np.arange(len(words))
    a = model.forward(code, edges, single)
    if (a[rows, length] < TINY).any():
        a = model.forward(code, edges, single, np.longdouble)
    width = code.shape[1]
    b = np.zeros_like(a)
    b[rows, length] = weight / a[rows, length]
    for start in range(width - 1, -1, -1):
        total = b[:, start] + b[:, start + 1] * (p[edges[0][:, start]] + single[:, start])
        for k in range(2, min(len(edges), width - start) + 1):
            total += b[:, start + k] * p[edges[k - 1][:, start]]
        b[:, start] = total
    for k, e in enumerate(edges, 1):
        r, s = np.nonzero(e >= 0)
        ids = e[r, s]
        mass = (a[r, s] * p[ids] * b[r, s + k]).astype(float)
        for g in range(mass.shape[1]):
            expected[:, g] += np.bincount(ids, mass[:, g], len(expected))
    r, s = np.nonzero((edges[0] < 0) & (code > 0))
    mass = (a[r, s] * single[r, s] * b[r, s + 1]).astype(float)
    for i, j, m in zip(r, s, mass, strict=True):
        for x in chr(code[i, j]).encode("utf-8", "replace"):
            expected[v.byte[x]] += m


class Scorer:
    def __init__(self, model: Model):
        self.model, self.index = model, {}
        self.rows = np.zeros((1 << 16, max(1, len(model.languages))))

    def texts(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        names, scores = [], []
        split = [t.split() if t is not None and _LETTER(t) else None for t in texts]
        if not self.model.languages:
            return [UNKNOWN] * len(texts), [0.0] * len(texts)
        index = self.index
        if len(index) > MEMO_ENTRIES:
            index.clear()
            self.rows = np.zeros((1 << 16, self.rows.shape[1]))
        fresh = list(set().union(*(w for w in split if w)) - index.keys())
        lo = len(index)
        if lo + len(fresh) > len(self.rows):
            self.rows = np.vstack([self.rows[:lo], np.zeros((lo + 2 * len(fresh), self.rows.shape[1]))])
        self.rows[lo : lo + len(fresh)] = self.model.words(fresh)
        index.update(zip(fresh, range(lo, lo + len(fresh)), strict=True))
        for words in split:
            if words is None:
                names.append(UNKNOWN)
                scores.append(0.0)
                continue
            log = self.rows[np.fromiter(map(index.__getitem__, words), np.int64, len(words))].sum(0)
            best = int(log.argmax())
            names.append(self.model.languages[best])
            scores.append(float(1 / np.exp(np.minimum(log - log[best], 0)).sum()))
        if any(len(w) > MEMO_CHARS for w in fresh):  # long words go at once
            for w in fresh:
                del index[w]
        return names, scores


def held_out(doc_id: Column) -> Column:
    """Whether crc32 of the id as text, modulo 4, is 2; a null id is not held out."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def learn(docs: DataFrame, sample_rows: int = SAMPLE_ROWS, name: str = VOCABULARY, total: int = SAMPLE_TOTAL) -> Model:
    """Fit on labelled rows with a text, none held out: at most `sample_rows` of each language and about `total` of all, every language at least one.

    Which rows those are is told from their ids alone. Their words are counted where the texts are; the driver gets words
    with weights, never texts.
    """
    known = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    slim = known.select("doc_id", "lang", F.xxhash64(F.col("doc_id").cast("string"), F.lit("fit")).alias("h"), F.xxhash64("text").alias("t"))
    names = sorted(r["lang"] for r in slim.select("lang").distinct().collect())
    if not names:
        return fit([], name)
    most = max(1, min(sample_rows, total // len(names)))
    least = lambda df, *by: df.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy("h", "doc_id", "t"))).where(F.col("r") <= most)
    dealt = slim.withColumn("share", F.pmod("h", F.lit(SHARES)))
    picked = least(least(dealt, "lang", "share"), "lang").select("doc_id", "lang", "t").distinct()
    # the sample's bound is known: `total` ids, or one a language
    texts = known.withColumn("t", F.xxhash64("text")).join(F.broadcast(picked), ["doc_id", "lang", "t"], "left_semi").select("text", "lang")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in common.text_slices(batch):
                part = batch.slice(lo, hi - lo)
                found = count_words(common.column(part, "text").to_pylist(), common.column(part, "lang").to_pylist())
                yield pa.RecordBatch.from_arrays([pa.array([g for g, _ in found], pa.string()), pa.array([w for _, w in found], pa.string()), pa.array(list(found.values()), pa.float64())], ["lang", "word", "n"])

    counted = common.bounded(texts).mapInArrow(common.tidy(run, "language_id"), "lang string, word string, n double").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    found = counted.toArrow()
    return fit_counts(sorted(zip(*(found[c].to_pylist() for c in ("lang", "word", "n")), strict=True)), name, languages=names)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """All columns of `docs` with __lang and __score (names with two leading underscores are reserved): a narrow map that reads nothing but the text."""
    schema = common.bounded(docs).schema
    shared = docs.sparkSession.sparkContext.broadcast(model)  # a quarter of a MB a language

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = _scorer(shared.value)
        for batch in batches:
            for lo, hi in common.text_slices(batch):
                part = batch.slice(lo, hi - lo)
                names, scores = scorer.texts(common.column(part, "text").to_pylist())
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=[*part.schema.names, "__lang", "__score"])

    out = type(schema)([*schema.fields]).add("__lang", "string").add("__score", "double")
    return docs.mapInArrow(common.tidy(run, "language_id"), out)


_LAST: list = [None, None]
common.forgets("language_id", lambda: _LAST.__setitem__(slice(None), [None, None]), vocabulary.cache_clear)


def _scorer(model: Model) -> Scorer:
    """A worker keeps its memo while it meets the same model."""
    key = hash((tuple(model.languages), model.p.tobytes()))
    if _LAST[0] != key:
        _LAST[:] = [key, Scorer(model)]
    return _LAST[1]


def identify(docs: DataFrame, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row of `docs` (doc_id, text, lang).

    Null texts and texts without a letter are `und` with score 0; so are all where no labelled row exists. Only text
    enters a prediction. Repeated rows keep a row each; ties go to the first language by name; extra columns are
    ignored; an empty table gives an empty result. Every label of a row that isn't held out can be predicted. A very long text
    is a slice of its own; words above 48 characters are scored one at a time, at any length.
    """
    model = learn(docs, sample_rows)
    slim = docs.select("doc_id", "text")
    return predict(slim, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("__lang").alias("lang_pred"), F.col("__score").alias("score"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(spark.read.parquet(f"{sf_dir}/documents.parquet"))
