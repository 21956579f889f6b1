import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from mmquery.llm import common, components, fingerprint, ngram_join, substring_dedup, vector_search

from .conftest import rows_of


@pytest.mark.parametrize("bucket,block", [(1024, 1024), (1, 2)])
def test_join_equals_sql(spark, sf_dir, sql, monkeypatch, bucket, block):
    """Whole buckets, and buckets split to the last level and cut into tiny blocks."""
    monkeypatch.setattr(ngram_join, "BUCKET", bucket)
    monkeypatch.setattr(ngram_join, "BLOCK", block)
    cols = ["doc_id", "class_id", "n_links"]
    assert rows_of(ngram_join.op1_ngram_jaccard_join(spark, sf_dir), cols) == sql(ngram_join.OP1_SQL, cols)


def near_copies(rng, n, words=120):
    base = [f"t{rng.randrange(10**6)}" for _ in range(words)]
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(rng.randrange(4)):
            w[rng.randrange(words)] = f"e{rng.randrange(10**6)}"
        out.append(" ".join(w))
    return out


def test_join_equals_brute_force(spark):
    rng = random.Random(9)
    texts = near_copies(rng, 25) + near_copies(rng, 6, 40) + ["a b c", "a b c", "a b", None, "", " "]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")

    def grams(t):
        w = (t or "").split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets = [grams(t) for t in texts]
    links = [[j for j in range(len(sets)) if i != j and sets[i] and sets[j] and len(sets[i] & sets[j]) * 10 >= 8 * len(sets[i] | sets[j])] for i in range(len(sets))]
    label = list(range(len(sets)))
    for _ in sets:
        label = [min([label[i], *(label[j] for j in links[i])]) for i in range(len(sets))]
    got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in ngram_join.join_rows(docs).collect()}
    assert got == {i: (label[i], len(links[i])) for i in range(len(sets))}
    kept = sorted(r["doc_id"] for r in ngram_join.keep_one(docs).collect())
    assert kept == sorted(set(label))


def test_join_at_a_lower_threshold(spark, monkeypatch):
    """Pairs that share 40 of their 80 grams, in buckets split to the last level: at 0.5 every one is linked."""
    monkeypatch.setattr(ngram_join, "BUCKET", 1)
    assert ngram_join.runs_for(recall=0.99) < ngram_join.runs_for(recall=0.9995)
    texts = []
    for i in range(120):
        both = [f"s{i}x{j}" for j in range(44)]
        texts += [" ".join(both + [f"{side}{i}x{j}" for j in range(20)]) for side in "ab"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = sorted((r["doc_id"], r["class_id"], r["n_links"]) for r in ngram_join.join_rows(docs, likeness=0.5).collect())
    assert got == [(i, i - i % 2, 1) for i in range(len(texts))]
    assert ngram_join.join_rows(docs, likeness=0.51).where("n_links > 0").count() == 0


def test_paths_meet_at_every_depth():
    """Pairs exactly at the threshold share paths as often as the runs promise; each level is drawn anew."""
    rng = np.random.default_rng(4)
    runs, met = ngram_join.runs_for(), [0] * ngram_join.DEPTH
    for _ in range(400):
        tokens = np.unique(rng.integers(0, 1 << 63, 120, dtype=np.uint64))
        a, b = tokens[:108], np.r_[tokens[:96], tokens[108:120]]  # 96 shared of 120
        forest = ngram_join._forest([a, np.sort(b)], runs, 0.8)
        for d, level in enumerate(forest):
            x, y = (np.array(level[i].as_py(), dtype=object) for i in range(2))
            for _ in range(d):
                x, y = ([v for part in z for v in part] for z in (x, y))
            met[d] += bool(set(x) & set(y))
        # a path of level two hangs on one of level one
        assert [len(v) for v in forest[1].to_pylist()] == [len(v) for v in forest[0].to_pylist()]
    assert met[0] >= met[1] >= met[2] >= 397


def test_long_sets_are_drawn_in_pieces(monkeypatch):
    tokens = np.unique(np.random.default_rng(1).integers(0, 1 << 63, 3000, dtype=np.uint64))
    whole = ngram_join._forest([tokens, tokens[:0], tokens[:1]], 5, 0.8)
    monkeypatch.setattr(ngram_join, "DRAW", 64)
    pieces = ngram_join._forest([tokens, tokens[:0], tokens[:1]], 5, 0.8)
    for x, y in zip(whole, pieces, strict=True):
        assert x.to_pylist()[1:] == y.to_pylist()[1:] and len(x[0]) == len(y[0])
    assert sorted(whole[0][0].as_py()) == sorted(pieces[0][0].as_py())


def test_join_of_odd_rows(odd, empty):
    got = ngram_join.join_rows(odd).collect()
    assert len(got) == odd.count()
    by = {}
    for r in got:
        by.setdefault(r["doc_id"], []).append((r["class_id"], r["n_links"]))
    assert by[1] == [(1, 0)] and by[2] == [(2, 0)] and by[3] == [(3, 0)]
    assert by[4] == [(4, 1), (4, 1)]
    assert by[6] == [(5, 1)] and by[5] == [(5, 1)]
    assert by[9] == [(8, 1)]  # 56 of 66 grams are shared
    assert ngram_join.keep_one(odd).count() == odd.count() - 3
    assert ngram_join.join_rows(empty).count() == 0 and ngram_join.keep_one(empty).count() == 0


def test_components(spark):
    rng = random.Random(1)
    chain = [(i, i + 1) for i in range(60)]
    others = [(100 + rng.randrange(30), 100 + rng.randrange(30)) for _ in range(20)]
    label = {}
    for a, b in chain + others:
        if a != b:
            label.setdefault(a, a), label.setdefault(b, b)
    for _ in range(100):
        for a, b in chain + others:
            if a != b:
                label[a] = label[b] = min(label[a], label[b])
    got = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(chain + others, "u long, v long")).collect()}
    assert got == label


def test_difference_covers():
    for v in (1, 2, 7, 13, 21):
        cover = substring_dedup.difference_cover(v)
        assert {(a - b) % v for a in cover for b in cover} == set(range(v))
    assert len(substring_dedup.difference_cover(21)) == 5
    period, length = substring_dedup.plan_of(35)
    assert length + period - 1 == 35


def test_dedup_equals_sql(spark, sf_dir, sql):
    cols = ["doc_id", "n_words", "n_removed", "kept_sha256"]
    assert rows_of(substring_dedup.op8_substring_dedup(spark, sf_dir), cols) == sql(substring_dedup.OP8_SQL, cols)


@pytest.mark.parametrize("window", [1, 4, 35])
def test_dedup_equals_brute_force(odd, window):
    rows = odd.collect()
    words = [(r["text"] or "").encode().split() for r in rows]
    seen = {}
    for d, w in enumerate(words):
        for i in range(len(w) - window + 1):
            seen.setdefault(tuple(w[i : i + window]), []).append((d, i))
    gone = [set() for _ in words]
    for places in seen.values():
        if len(places) > 1:
            for d, i in places:
                gone[d] |= set(range(i, i + window))
    want = sorted((str(r["doc_id"]), len(w), len(g), b" ".join(x for i, x in enumerate(w) if i not in g).decode()) for r, w, g in zip(rows, words, gone, strict=True))
    out = substring_dedup.remove_repeats(odd, window)
    assert out.columns[: len(odd.columns)] == odd.columns
    assert sorted((str(r["doc_id"]), r["__n_words"], r["__n_removed"], r["text"]) for r in out.collect()) == want


def test_dedup_compares_both_hashes():
    """Windows that agree in one hash of two aren't alike, at home or in a bucket."""
    packer = substring_dedup.Packer(4)
    h = np.array([[7, 1], [7, 2], [7, 1], [8, 1]], np.uint64)
    place = np.arange(4)
    packed = packer.pack(h, np.array([5, 6, 7, 8]), place).to_pydict()
    home = [np.frombuffer(p, np.uint32).tolist() for hs, p in zip(packed["hashes"], packed["places"], strict=True) if not hs]
    assert home == [[0, 2]]
    settled = [b for b in substring_dedup._settle(2, 2)(iter([packer.pack(h[i : i + 1], np.array([i]), place[i : i + 1]) for i in range(4)]))]
    assert sorted(x for b in settled for p in b.column(2).to_pylist() for x in np.frombuffer(p, np.uint32).tolist()) == [0, 2]


def test_rows_of_one_key_are_told_apart(odd):
    """Where all keys collide, rows get keys of their own but for those alike in id and text."""
    keys = [r["__k"] for r in substring_dedup._keyed(odd, F.lit(7).cast("long")).collect()]
    assert len(keys) == odd.count() and len(set(keys)) == odd.select("doc_id", "text").distinct().count()
    assert substring_dedup._keyed(odd).columns == [*odd.columns, "__k"]


def test_hashes_in_chunks(monkeypatch):
    raw = b" ".join(f"w{i}".encode() * (1 + i % 5) for i in range(500))
    buf = np.frombuffer(raw, np.uint8)
    s, e, _ = common.word_spans(buf, np.array([0, len(buf)]))
    whole, windows = common.word_hashes(buf, s, e), common.window_hashes(common.word_hashes(buf, s, e), 7)
    monkeypatch.setattr(common, "CHUNK", 64)
    assert (common.word_hashes(buf, s, e) == whole).all() and (common.window_hashes(whole, 7) == windows).all()


def test_dedup_leaves_clean_texts_alone(odd, empty):
    out = {(r["doc_id"], r["k"]): r["text"] for r in substring_dedup.remove_repeats(odd, joined=False).collect()}
    for r in odd.where("doc_id in (1, 2, 3, 4, 7, 10, 11)").collect():
        assert out[(r["doc_id"], r["k"])] == r["text"]
    assert substring_dedup.remove_repeats(empty).count() == 0


def test_word_hashes_match_words():
    raw = "ab  ab\tabc é ab\n".encode()
    s, e, first = common.word_spans(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
    h = common.word_hashes(np.frombuffer(raw, np.uint8), s, e)
    assert [raw[a:b] for a, b in zip(s, e, strict=True)] == raw.split() and first.tolist() == [0, 5]
    assert h[0] == h[1] == h[4] != h[2]


def test_fingerprints(spark, documents, odd, empty):
    for docs in (documents, odd):
        rows = sorted(docs.collect(), key=lambda r: (r["doc_id"] is None, -(r["doc_id"] or 0), r["text"] or ""))
        got = fingerprint.fingerprints(docs).collect()
        assert len(got) == len(rows)
        import hashlib

        want = sorted(hashlib.sha256(fingerprint.edited(r["text"] or "", rows[(i + 1) % len(rows)]["text"] or "").encode()).hexdigest() for i, r in enumerate(rows))
        assert sorted(r["edited_sha256"] for r in got) == want
        assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in got)
        by_text = {}
        text_of = {r["doc_id"]: r["text"] or "" for r in rows}
        for r in got:
            by_text.setdefault(text_of[r["doc_id"]], set()).add(r["fingerprint"])
        assert all(len(v) == 1 for v in by_text.values())
    assert fingerprint.fingerprints(empty).count() == 0
    one = fingerprint.fingerprints(spark.createDataFrame([(1, "abcdef")], "doc_id long, text string")).first()
    assert one["edited_sha256"] == hashlib.sha256(b"abcabc").hexdigest() and one["near_next"] == 1.0


def slow_fingerprint(text):
    """The bins of one text, phrase by phrase in plain Python numbers: runs, labels by coin tossing, phrases from one local maximum to the next."""
    wide = (1 << 64) - 1

    def mix(x):
        x ^= x >> 30
        x = x * 0xBF58476D1CE4E5B9 & wide
        x ^= x >> 27
        x = x * 0x94D049BB133111EB & wide
        return x ^ x >> 31

    name, base = int(fingerprint._NAME), int(fingerprint._NAME) | 1

    def lowest(a, b):
        d = a ^ b
        k = (d & -d).bit_length() - 1
        return 2 * k + (b >> k & 1)

    def phrases(symbols):
        runs = []
        for x in symbols:
            if runs and runs[-1][0] == x:
                runs[-1][1] += 1
            else:
                runs.append([x, 1])
        line = [x if n == 1 else mix((x + n * name) & wide) for x, n in runs]
        label = [lowest(line[i - 1] if i else ~line[0] & wide, x) for i, x in enumerate(line)]
        for _ in range(3):
            label = [lowest(label[i - 1] if i else label[0] ^ 1, x) if (label[i - 1] if i else label[0] ^ 1) != x else x & 1 for i, x in enumerate(label)]
        cuts = [0] + [i for i in range(2, len(label) - 1) if label[i] > label[i - 1] and label[i] > label[i + 1]]
        out = []
        for a, b in zip(cuts, [*cuts[1:], len(line)], strict=True):
            out.append(mix((sum(mix(x) * pow(base, j, 1 << 64) for j, x in enumerate(line[a:b])) + b - a) & wide))
        return out

    bins = [[None] * n for n in fingerprint.BINS]
    symbols = [ord(c) + 1 for c in text]
    for level in range(1, fingerprint.LEVELS + 1):
        if not symbols:
            break
        symbols = phrases(symbols)
        group = 0 if level <= 2 else min(level - 2, len(bins) - 1)
        if level > 1 or len(symbols) == 1:
            for x in symbols:
                h = mix((x + group) & wide)
                k = h % len(bins[group])
                bins[group][k] = h if bins[group][k] is None else min(h, bins[group][k])
        if len(symbols) == 1:
            break
    return [0 if h is None else max(1, mix(h) >> 48) for g in bins for h in g]


def test_fingerprints_equal_a_slow_parse(odd):
    rng = np.random.default_rng(5)
    texts = ["", "a", "aa", "ab", "aaaa bbbb", "abcabcabc" * 20, "日本語 текст ☃" * 9, "".join(chr(97 + x) for x in rng.integers(0, 4, 900)), *(" ".join(f"w{x}" for x in rng.integers(0, 50, n)) for n in (3, 40, 200))]
    fast = fingerprint.sketches(texts)
    slow = np.array([slow_fingerprint(t) for t in texts])
    assert (fast == slow).all()
    for a, b, got in zip(slow, slow[1:], fingerprint.likeness(fast[:-1], fast[1:]), strict=False):
        some, same = sum(1 for x, y in zip(a, b, strict=True) if x or y), sum(1 for x, y in zip(a, b, strict=True) if x and x == y)
        assert got == pytest.approx(1.0 if not some else 2 * same / some / (1 + same / some))
    rows = sorted(odd.collect(), key=lambda r: (r["doc_id"] is None, -(r["doc_id"] or 0), r["text"] or ""))
    want = {}
    for i, r in enumerate(rows):
        if len(r["text"] or "") < 3000:
            text, after = r["text"] or "", rows[(i + 1) % len(rows)]["text"] or ""
            want.setdefault(r["doc_id"], set()).add((bytes(np.array(slow_fingerprint(text), ">u2")).hex(), bytes(np.array(slow_fingerprint(fingerprint.edited(text, after)), ">u2")).hex()))
    for r in fingerprint.fingerprints(odd).collect():
        assert r["doc_id"] not in want or (r["fingerprint"], r["edited_fingerprint"]) in want[r["doc_id"]]


def test_sections_follow_bytes(spark, monkeypatch):
    """Ids at both ends of their range, one document as large as all others, and many ids in few sections: the order is that of the ids."""
    ids = [2**63 - 1, -(2**63) + 1, *range(0, 400, 2)]
    texts = ["x" * 40000 if i == 100 else f"text {i}" for i in ids]
    got = {r["doc_id"]: r["edited_sha256"] for r in fingerprint.fingerprints(spark.createDataFrame(list(zip(ids, texts, strict=True)), "doc_id long, text string")).collect()}
    order = sorted(zip(ids, texts, strict=True), reverse=True)
    import hashlib

    for (i, t), (_, after) in zip(order, [*order[1:], order[0]], strict=True):
        assert got[i] == hashlib.sha256(fingerprint.edited(t, after).encode()).hexdigest()


def test_shared_passages_share_phrases():
    rng = np.random.default_rng(3)
    a, b, c = ("".join(chr(97 + x) for x in rng.integers(0, 26, 4000)) for _ in range(3))
    s = fingerprint.sketches([a, "zz" + a, a[:2000] + b[:2000], b])
    near = fingerprint.likeness(np.repeat(s[:1], 4, 0), s)
    assert near[0] == 1 and near[1] > 0.95 and 0.3 < near[2] < 0.7 and near[3] < 0.05


def brute_nearest(ids, v, every, top):
    unit = v / np.sqrt((v * v).sum(1))[:, None]
    out = {}
    for i in np.flatnonzero(ids % every == 0):
        score = unit @ unit[i]
        others = np.flatnonzero(ids != ids[i])
        order = others[np.lexsort((ids[others], -np.round(score[others], 12)))][:top]
        out[int(ids[i])] = [int(x) for x in ids[order]]
    return out


def test_search_recall(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").collect()
    want = brute_nearest(np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], float), 50, 5)
    got = {}
    for r in vector_search.op9_vector_search(spark, sf_dir).collect():
        got.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
    assert got.keys() == want.keys()
    assert all(sorted(x) == [1, 2, 3, 4, 5] for x in got.values())
    hits = sum(len({v for v, _ in got[q].values()} & set(want[q])) for q in want)
    assert hits >= 0.9 * 5 * len(want)


def test_search_of_uneven_vectors(spark):
    """Scattered vectors beside a hundred times as many near-equal ones: both groups find their neighbours."""
    rng = np.random.default_rng(11)
    center = rng.normal(size=64)
    v = np.vstack([rng.normal(size=(60, 64)), center + 0.01 * rng.normal(size=(6000, 64))])
    ids = np.arange(len(v)) * 5
    want = brute_nearest(ids, v, 50, 5)
    got = {}
    for r in vector_search.search(spark.createDataFrame([(int(i), x.tolist()) for i, x in zip(ids, v, strict=True)], "vec_id long, embedding array<double>")).collect():
        got.setdefault(r["query_id"], set()).add(r["vec_id"])
    for mine in ([q for q in want if q < 300], [q for q in want if q >= 300]):
        assert sum(len(got[q] & set(want[q])) for q in mine) >= 0.9 * 5 * len(mine)


def test_search_finds_enough(spark, monkeypatch):
    """Lists of a row or two, one looked into: what is missing is searched exactly, in blocks; so are vectors of a rarer dimension."""
    monkeypatch.setattr(vector_search, "_probes", lambda unit, lists, centroids: np.ones(len(centroids), int))
    monkeypatch.setattr(vector_search, "lists_for", lambda rows: 40)
    monkeypatch.setattr(vector_search, "ROWS_A_LIST", 2)
    monkeypatch.setattr(vector_search, "EXACT_ROWS", 7)
    monkeypatch.setattr(vector_search, "UNIT_QUERIES", 2)
    rng = np.random.default_rng(3)
    v, w = rng.normal(size=(80, 8)), rng.normal(size=(30, 5))
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(1000 + i, x.tolist()) for i, x in enumerate(w)]
    want = brute_nearest(np.arange(80), v, 10, 5) | brute_nearest(np.arange(1000, 1030), w, 10, 5)
    got = {}
    for r in vector_search.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), every=10).orderBy("rank").collect():
        got.setdefault(r["query_id"], []).append(r["vec_id"])
    assert got.keys() == want.keys() and all(len(x) == 5 for x in got.values())
    assert all(got[q] == want[q] for q in want if q >= 1000)


def test_search_of_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (50, [0.0, 0.0]), (1, None), (2, [1.0, None]), (3, [float("nan"), 1.0]), (4, [2.0, 0.0]), (5, [2.0, 0.0]), (6, [0.0, 3.0]), (7, []), (None, [1.0, 1.0]), (8, [1.0, 1.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").selectExpr("*", "vec_id AS unit", "vec_id AS v")
    got = [(r["query_id"], r["rank"], r["vec_id"], round(r["score"], 6)) for r in vector_search.search(df).orderBy("rank").collect()]
    assert got == [(0, 1, 4, 1.0), (0, 2, 5, 1.0), (0, 3, 6, 0.0)]
    assert vector_search.search(df.where("false")).count() == 0
    assert vector_search.search(df.where("vec_id = 0")).count() == 0


def test_vector_search_tells_rows_of_many_tight_groups_apart(spark, monkeypatch):
    """Several tight groups in one list: their rows have equal codes, so far more rows tie than are kept."""
    monkeypatch.setattr(vector_search, "lists_for", lambda rows: 6)
    r = np.random.default_rng(9)
    v = np.repeat(r.normal(size=(20, 16)), 300, 0) + 1e-4 * r.normal(size=(6000, 16))
    u = v / np.linalg.norm(v, axis=1, keepdims=True)
    hit = total = 0
    found = vector_search.search(spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<double>"), every=100).collect()
    assert len(found) == 300
    for q in range(0, 6000, 100):
        score = u @ u[q]
        score[q] = -1
        hit += len({a["vec_id"] for a in found if a["query_id"] == q} & set(np.argsort(-score)[:5].tolist()))
        total += 5
    assert hit >= 0.98 * total


def test_sets_fetch_their_longer_paths_once(spark, monkeypatch):
    """A set in many large buckets is one row of the join with its longer paths, and its paths are those it had in each."""
    monkeypatch.setattr(ngram_join, "BUCKET", 2)
    seen = []
    met = ngram_join._met
    monkeypatch.setattr(ngram_join, "_met", lambda inc, name: (seen.append(inc), met(inc, name))[1])
    paths = [(s, 5, [10, 11, 100 + s], [[s, 7], [8], [9]], [[[1], [2]], [[3]], [[4]]]) for s in range(4)]
    ngram_join._buckets(spark.createDataFrame(paths, "s long, size long, p1 array<long>, p2 array<array<long>>, p3 array<array<array<long>>>"))
    assert sorted((r["s"], r["p"]) for r in seen[1].collect()) == sorted([(s, p) for s in range(4) for p in (s, 7, 8)])
    plan = seen[1]._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Join Inner") < plan.index("Aggregate")
