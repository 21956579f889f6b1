import base64
import io
import math
import random
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import tiktoken
import zstandard
from pyspark.sql import functions as F

import corpus_pipeline
from mmquery.llm import language_id, mixing, quotes, warc

from .conftest import rows_of


def test_chats_equal_sql(spark, sf_dir, sql):
    cols = ["conv_id", "turn", "role", "parent_turn", "depth", "root_turn", "position", "n_quoted", "n_linked", "body", "chat"]
    assert rows_of(quotes.op4_chat_formatting(spark, sf_dir), cols) == sql(quotes.OP4_SQL, cols)


def test_quotes_are_linked(spark):
    rows = [
        (1, 0, "user", "Hello there\nsecond line"),
        (1, 1, "assistant", "> hello   there\nYes"),
        (1, 2, "user", ">> hello there\n> Yes\nand more"),
        (1, 3, "user", "> nobody said this\nx"),
        (1, 4, None, None),
        (1, 5, "user", "> and more\nlast"),
        (2, 0, "user", "> hello there"),
        (None, None, "user", "> hello there\nz"),
        (1, 4, None, None),
    ]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("level", F.lit(1)).withColumn("path", F.lit("x"))
    got = [(r["conv_id"], r["turn"], r["parent_turn"], r["depth"], r["n_quoted"], r["n_linked"], r["body"]) for r in quotes.format_chats(df).orderBy("conv_id", "root_turn", "position", "turn").collect()]
    assert got == [
        (None, None, None, 0, 0, 0, "z"),
        (1, 0, None, 0, 0, 0, "Hello there\nsecond line"),
        (1, 1, 0, 1, 1, 1, "Yes"),
        (1, 2, 1, 2, 2, 2, "and more"),
        (1, 5, 2, 3, 1, 1, "last"),
        (1, 3, None, 0, 1, 0, "x"),
        (1, 4, None, 0, 0, 0, ""),
        (1, 4, None, 0, 0, 0, ""),
        (2, 0, None, 0, 1, 0, ""),
    ]
    assert quotes.format_chats(df.where("false")).count() == 0


def test_passages_are_linked(spark):
    """Re-wrapped, repeated, partial and broken passages; each case is a conversation of texts by turn, with the parents wanted."""
    cases = [
        (["alpha beta gamma delta", "> alpha beta\n> gamma delta"], [None, 0]),
        (["alpha beta\ngamma delta", "> alpha beta gamma delta\nyes"], [None, 0]),
        (["Hi all\nA", "Hi all\nB", "> Hi all\n> B"], [None, None, 1]),
        (["Hi all\nA", "Hi all\nB", "> other\n> Hi all\n> B\n> C"], [None, None, 1]),
        (["Yes indeed", "Intro\nYes", "> yes"], [None, None, 1]),
        (["Yes indeed", "Intro\nYes", "Yes", "> yes"], [None, None, None, 2]),
        (["one two three four five six seven", "x", "> three four\n> five\nok"], [None, None, 0]),
        (["one two three four five six seven", "> four three"], [None, None]),
        (["later", "> after all", "after all"], [None, None, None]),
        (["top", "> top\nmid", "mid", ">> top\n> mid\n>> nobody\nend"], [None, 0, None, 1]),
        (["a\n\nb", "> a\n>\n> b"], [None, 0]),
        ([" ".join(f"w{i}" for i in range(200)), "z", "> " + "\n> ".join(f"w{i}" for i in range(20, 180))], [None, None, 0]),
        ([" ".join(f"w{i}" for i in range(200)), "z", "> " + "\n> ".join(f"w{i}" for i in [*range(20, 180), 7])], [None, None, 0]),
    ]
    rows = [(c, t, "user", x) for c, (texts, _) in enumerate(cases) for t, x in enumerate(texts)]
    got = {(r["conv_id"], r["turn"]): r for r in quotes.format_chats(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    for c, (texts, parents) in enumerate(cases):
        assert [got[c, t]["parent_turn"] for t in range(len(texts))] == parents, texts
    assert (got[3, 2]["n_quoted"], got[3, 2]["n_linked"]) == (4, 2)
    assert (got[12, 2]["n_quoted"], got[12, 2]["n_linked"]) == (161, 161)


def reply_order(parents):
    """root, position and depth of each turn, by walking the threads."""
    kids, out = {}, {}
    for t, p in parents.items():
        kids.setdefault(p, []).append(t)
    for root in sorted(kids.get(None, [])):
        stack, n = [(root, 0)], 0
        while stack:
            t, d = stack.pop()
            out[t] = (root, n, d)
            n += 1
            stack += [(k, d + 1) for k in sorted(kids.get(t, []), reverse=True)]
    return out


def test_reply_order_of_deep_and_wide_threads(spark, monkeypatch):
    """A chain of 10,000 messages, a message with many answers, random trees, and turns below zero and of 13 digits."""
    monkeypatch.setattr(quotes, "SPAN", 16)
    rng = random.Random(6)
    convs = [
        {t: t - 1 if t else None for t in range(10_000)},
        {t: 0 if t else None for t in range(300)},
        {t: rng.choice([None, *range(t)]) for t in range(200)},
        {-3: None, -2: -3, 5: -2, 7 * 10**12: 5, 7 * 10**12 + 1: -3, 9: None},
    ]
    rows = [(c, t, p) for c, parents in enumerate(convs) for t, p in parents.items()]
    links = spark.createDataFrame(rows, "conv_id long, turn long, parent long")
    got = {(r["conv_id"], r["turn"]): (r["root_turn"], r["position"], r["depth"]) for r in quotes._order(links).collect()}
    for c, parents in enumerate(convs):
        for t, want in reply_order(parents).items():
            if parents[t] is None and t not in parents.values():
                assert (c, t) not in got  # a thread of its own
            else:
                assert got[c, t] == want


def test_warc_equals_sql(spark, sf_dir, sql):
    cols = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    assert rows_of(warc.op6_warc(spark, sf_dir), cols) == sql(warc.OP6_SQL, cols)


def test_warc_of_odd_pages(spark):
    rows = [(1, "http://a", "x"), (2, "http://b\r\nEvil: 1", "x"), (3, None, None), (4, "u", ""), (5, "u", "é" * 10000), (None, "u", "x"), (2, "again", "x")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("sha", F.lit(1)).withColumn("owner", F.lit(2))
    files = warc.write(pages)
    got = sorted((str(r["page_id"]), r["payload_bytes"], r["record_type"], str(r["refers_to"])) for r in warc.read(files).collect())
    assert got == sorted([("1", 1, "revisit", "2"), ("2", 1, "response", "None"), ("2", 1, "response", "None"), ("None", 1, "revisit", "2"), ("3", 0, "revisit", "4"), ("4", 0, "response", "None"), ("5", 20000, "response", "None")])
    texts = {r["page_id"]: r["payload"] for r in warc.read(files, payloads=True).where("record_type = 'response'").collect()}
    assert bytes(texts[5]).decode() == "é" * 10000
    small = warc.read(warc.write(pages, least_bytes=2))
    assert small.where("record_type = 'revisit'").count() == 0
    assert warc.read(warc.write(pages.where("false"))).count() == 0


def archive(records, dictionary=None):
    out = io.BytesIO()
    warc.write_archive(out, iter(records), dictionary)
    return out.getvalue()


def one(page_id=1, payload=b"<p>hello</p>"):
    return warc.record(page_id, "http://a", payload, warc.digest(payload), False, None)


def test_archives_with_a_dictionary():
    samples = [one(i, f"<html><body>page {i} of many, alike</body></html>".encode() * 3) for i in range(200)]
    d = warc.dictionary_of(samples)
    data = archive(samples, d)
    assert data[:4] == bytes([0x5D, 0x2A, 0x4D, 0x18]) and len(data) < len(archive(samples))
    for chunk in (1, 7, 1 << 20):
        if chunk > 1 or len(data) < 100_000:
            assert list(warc.read_archive(io.BytesIO(data), chunk)) == samples
    raw = zstandard.ZstdCompressionDict(d.as_bytes())
    plain = bytes([0x5D, 0x2A, 0x4D, 0x18]) + len(raw.as_bytes()).to_bytes(4, "little") + raw.as_bytes() + zstandard.ZstdCompressor(dict_data=raw).compress(samples[0])
    assert list(warc.read_archive(io.BytesIO(plain))) == samples[:1]
    assert list(warc.read_archive(io.BytesIO(b""))) == []


@pytest.mark.parametrize("damage", [lambda d: d[:-3], lambda d: d[:5] , lambda d: b"junk" + d])
def test_damaged_archives(damage):
    with pytest.raises((warc.WarcError, zstandard.ZstdError)):
        list(warc.read_archive(io.BytesIO(damage(archive([one()])))))


@pytest.mark.parametrize("change", [(b"WARC/1.1", b"HTTP/1.1"), (b"hello", b"jello"), (b"Content-Length: ", b"Content-Length: 1"), (b"WARC-Record-ID", b"X-Record-ID"), (b"WARC-Type: response", b"WARC-Type: metadata")])
def test_invalid_records(change):
    assert warc.parse(one())["payload"] == b"<p>hello</p>"
    with pytest.raises(warc.WarcError):
        warc.parse(one().replace(*change))


def targets_by_hand(sizes, share=1.5, bound=2.0):
    """Reshare what is above the caps, round after round."""
    names = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [s for s in sizes if s is None]
    weight = {s: (3.0, 1.0, 2.0)[i % 3] for i, s in enumerate(names)}
    left, open_, out = share * sum(sizes.values()), set(names), {}
    while open_:
        total = sum(weight[s] for s in open_)
        above = [s for s in open_ if left * weight[s] / total > bound * sizes[s] + 1e-9]
        if not above:
            out |= {s: left * weight[s] / total for s in open_}
            break
        for s in above:
            out[s] = bound * sizes[s]
            left -= out[s]
            open_.remove(s)
    return out


def check_mix(docs):
    rows = mixing.mix(docs).collect()
    assert len(rows) == docs.count()
    sizes, taken = {}, {}
    for r in rows:
        assert r["__size"] == len((r["text"] or "").encode().split())
        assert 0 <= r["__copies"] <= 2
        sizes[r["source"]] = sizes.get(r["source"], 0) + r["__size"]
        taken[r["source"]] = taken.get(r["source"], 0) + r["__size"] * r["__copies"]
    want = targets_by_hand(sizes)
    for r in rows:
        assert r["__source_size"] == sizes[r["source"]] and r["__target"] == pytest.approx(want[r["source"]])
    return sizes, taken, want, rows


def test_mixing(documents, odd, empty):
    sizes, taken, want, rows = check_mix(documents)
    for s in sizes:
        assert abs(taken[s] - want[s]) <= 0.05 * want[s] + 60
    again = mixing.mix(documents.repartition(3)).collect()
    key = lambda rs: sorted((r["doc_id"], r["__copies"]) for r in rs)
    assert key(rows) == key(again)
    check_mix(odd)
    assert mixing.mix(empty).count() == 0


def test_mixing_of_equal_texts(spark):
    """One cell holds every document of a hot source; ranks are dealt in groups."""
    rows = [(i, "a b c", "hot") for i in range(900)] + [(1000 + i, "d " * (1 + i % 7), "x") for i in range(300)]
    sizes, taken, want, _ = check_mix(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    assert all(abs(taken[s] - want[s]) <= 3 for s in sizes)


def test_mixing_of_many_sources(spark):
    """Sources by the hundred, names out of order and beyond ASCII, sizes that all differ, one document alone, texts without words."""
    rng = random.Random(2)
    names = [None, "", "é", "Z", "a", "\U0001f600", *(f"s{i}" for i in range(300))]
    rows = [(i, "w " * rng.choice([0, 1, 2, 5, 40, rng.randrange(1, 3000)]), names[i % len(names)]) for i in range(3000)] + [(9000, "only one", "lonely")]
    sizes, taken, want, got = check_mix(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    by = {}
    for r in got:
        by.setdefault(r["source"], []).append(r["__size"])
    off = {s: abs(taken[s] - want[s]) for s in by}
    assert all(off[s] < max(1, *x) for s, x in by.items())
    assert sum(o <= 5 for o in off.values()) >= 0.6 * len(off)


def test_rates_are_those_of_exact_sizes(spark):
    """Sizes above four thousand words keep rates of their own: exp(lambda * size), under the bound, that spend the target."""
    rows = [(i, "w " * n, "ab"[i % 2]) for i, n in enumerate([4100, 4101, 4140, 6000, 6001, 9, 20, 300, 5, 70, 7000, 123])]
    _, _, want, got = check_mix(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    for s in "ab":
        mine = [r for r in got if r["source"] == s]
        assert sum(r["__size"] * r["__rate"] for r in mine) == pytest.approx(want[s], rel=1e-9)
        slopes = [math.log(r["__rate"]) / r["__size"] for r in mine if r["__rate"] < 2]
        assert max(slopes) - min(slopes) <= 1e-9


def test_mixing_is_native(documents):
    plan = mixing.mix(documents)._jdf.queryExecution().executedPlan().toString()
    assert not any(x in plan for x in ("Python", "Pandas", "Arrow", "ExistingRDD"))


def test_languages_are_told_apart(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language_id.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.count() > 100
    assert got.where("lang_pred = lang").count() >= 0.97 * got.count()
    assert got.where("score < 0 or score > 1").count() == 0


def test_languages_of_odd_rows(odd, empty, documents):
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language_id.identify(odd).collect()}
    assert got[1] == got[2] == got[3] == got[11] == ("und", 0.0)
    assert got[5][0] != "und"
    assert language_id.identify(empty).count() == 0
    none = language_id.identify(documents.withColumn("lang", F.lit(None).cast("string")))
    assert none.where("lang_pred <> 'und'").count() == 0


def test_languages_without_spaces(spark):
    rng = random.Random(8)
    syllables = {"x": ("ka", "to", "mi", "ru"), "y": ("ze", "lu", "po", "gi")}
    rows = [(i, "".join(rng.choice(syllables[g]) for _ in range(200)), g) for i, g in enumerate("xy" * 40)]
    got = language_id.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
    assert {r["doc_id"]: r["lang_pred"] for r in got} == {i: g for i, _, g in rows}
    text = "▁" + "abcdefgh" * 20
    pieces = language_id._cuts(text[1:])
    assert sum(len(p) * w for p, w in pieces) == len(text) and all(len(p) <= language_id.LOCKSTEP for p, _ in pieces)


def test_null_texts_take_no_place_in_the_sample(spark):
    rows = [(i, None, "a") for i in range(300)] + [(1000 + i, "das haus am see", "a") for i in range(12)] + [(2000 + i, "le lac et la mer", "b") for i in range(12)]
    got = language_id.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string"), sample_rows=4).where("doc_id >= 1000").collect()
    assert all(r["lang_pred"] == ("a" if r["doc_id"] < 2000 else "b") for r in got)


def test_predictions_ignore_labels(documents):
    """The labels of held-out rows change nothing."""
    other = documents.withColumn("lang", F.when(language_id.held_out(F.col("doc_id")), F.lit("zz")).otherwise(F.col("lang")))
    key = lambda d: sorted((r["doc_id"], r["lang_pred"], round(r["score"], 9)) for r in language_id.identify(d).collect())
    assert key(documents) == key(other)


def test_forward_pass_sums_all_cuts():
    model = language_id.fit([("haus im haus am see", "a"), ("house on a lake", "b"), ("le lac", "c")])
    v = language_id.vocabulary(model.name)

    def total(text, at=0):
        if at == len(text):
            return 1.0
        out = 0.0
        for end in range(at + 1, len(text) + 1):
            if (i := v.id_of.get(text[at:end])) is not None:
                out = out + model.p[i] * total(text, end)
        if text[at] not in v.id_of:
            out = out + model.p[[v.byte[b] for b in text[at].encode()]].prod(0) * total(text, at + 1)
        return out

    import numpy as np

    for w in ("haus", "lake", "é☃", "x"):
        want = np.log(total("▁" + w))
        assert np.allclose(model.words([w])[0], want) and np.allclose(model._alone(w), want)
    assert np.allclose(model.p.sum(0), 1)


def test_pipeline_stages(spark, sf_dir, tmp_path):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, counts = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        counts.append(docs.count())
        if name != "byte_bpe":
            assert docs.columns == columns
    assert counts[1] >= counts[2] == counts[3] and counts[4] == counts[5]
    assert docs.columns == ["doc_id", "n_tokens", "ids"]


def test_ties_are_languages_too(spark, sf_dir):
    """Three languages that were taught the same: every text scores a third, and none is rejected."""
    rows = [(i, "to je isto", "abc"[i % 3]) for i in range(60)] + [(100, "123 !!", "a"), (101, None, "b")]
    kept = corpus_pipeline.identify(spark, spark.createDataFrame(rows, "doc_id long, text string, lang string"), sf_dir)
    assert sorted(r["doc_id"] for r in kept.collect()) == list(range(60))


def copies_by_hand(rows):
    """Copies of (doc_id, words, source) rows whose sizes differ within a source: rates that spend the target, rounded by their running sum
    from the largest down; what is left goes to documents with room, the largest first, eight of each magnitude."""
    sizes = {}
    for _, n, source in rows:
        sizes[source] = sizes.get(source, 0) + n
    out = {}
    for source, target in targets_by_hand(sizes).items():
        mine = sorted(((n, i) for i, n, s in rows if s == source), reverse=True)
        assert len({n for n, _ in mine}) == len(mine)
        rate = lambda n, lam: min(2.0, math.exp(min(lam * n, 1.0)))
        low, high = -1.0, 1.0
        for _ in range(200):
            mid = (low + high) / 2
            low, high = (mid, high) if sum(n * rate(n, mid) for n, _ in mine) < target else (low, mid)
        upto = 0.0
        for n, i in mine:
            out[i] = math.floor(upto + rate(n, low) + 0.5) - math.floor(upto + 0.5)
            upto += rate(n, low)
        left = target - sum(n * out[i] for n, i in mine)
        room = lambda i: 2 - out[i] if left > 0 else out[i]
        classes = {}
        for n, i in mine:
            if room(i):
                classes.setdefault(n.bit_length(), []).append((-room(i), n, i))
        offered = sorted(((n, i) for c in classes.values() for _, n, i in sorted(c)[:8]), reverse=True)
        for n, i in offered:
            change = math.floor(abs(left) / n + 0.5) * (1 if left > 0 else -1)
            change = max(-out[i], min(2 - out[i], change))
            out[i] += change
            left -= change * n
    return out


def test_pipeline_equals_brute_force(spark, tmp_path):
    rng = random.Random(5)
    made = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    passage, near = made(50), made(200)
    texts = [made(20 + 7 * i) for i in range(24)]
    texts[3:3], texts[9:9] = [near], [[*near[:199], "changed"]]
    for i in (5, 12, 17):
        texts[i] = texts[i][:9] + passage + texts[i][9:]
    rows = [(i, " ".join(t), "ab"[i % 2], ("news", "web", None)[i % 3], -1) for i, t in enumerate(texts)]
    rows += [(90, None, "a", "web", -1), (91, "12 34", "a", "news", -1), (92, "", "b", None, -1)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    # a letter makes a language; of near copies the least id stays; windows of 35 words that start twice go
    docs = {i: (t.split(" "), s) for i, t, _, s, _ in rows if t is not None and any(c.isalpha() for c in t)}
    grams = {i: {tuple(t[k : k + 5]) for k in range(len(t) - 4)} for i, (t, _) in docs.items()}
    gone = [b for a in docs for b in docs if a < b and len(grams[a] & grams[b]) >= 0.8 * len(grams[a] | grams[b])]
    docs = {i: d for i, d in docs.items() if i not in gone}
    starts = Counter(tuple(t[k : k + 35]) for t, _ in docs.values() for k in range(len(t) - 34))
    left = {}
    for i, (t, s) in docs.items():
        cut = {j for k in range(len(t) - 34) if starts[tuple(t[k : k + 35])] > 1 for j in range(k, k + 35)}
        left[i] = ([w for j, w in enumerate(t) if j not in cut], s)
    assert gone == [9] and sum(len(t) for t, _ in docs.values()) - sum(len(t) for t, _ in left.values()) == 150
    copies = copies_by_hand([(i, len(t), s) for i, (t, s) in left.items()])
    assert set(copies.values()) >= {1, 2}
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb"))}
    reference = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = sorted((i, reference.encode_ordinary(" ".join(t))) for i, (t, _) in left.items() for _ in range(copies[i]))
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert sorted((r["doc_id"], np.frombuffer(r["ids"], "<u4").tolist()) for r in got) == want
    assert all(r["n_tokens"] == len(r["ids"]) // 4 for r in got)


def test_pipeline_stages_take_odd_tables(spark, odd, empty, sf_dir):
    base = ["doc_id", "text", "lang", "source", "n_chars"]
    for docs in (odd.select(*base), empty.select(*base)):
        for _, stage in corpus_pipeline.STAGES:
            stage(spark, docs, sf_dir).count()


