import base64
import hashlib
import random
import tracemalloc

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from mmquery.llm import byte_bpe, token_count
from mmquery.llm.pretokens import splitter


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(P.path("byte_bpe_50k.json"))


@pytest.fixture(scope="module")
def ranks():
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_50k.tiktoken"), "rb"))}


@pytest.fixture(scope="module")
def reference(ranks):
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=60))
def test_counts_and_ids_of_any_text(text):
    t = Tokenizer.from_file(P.path("byte_bpe_50k.json")) if not hasattr(test_counts_and_ids_of_any_text, "t") else test_counts_and_ids_of_any_text.t
    test_counts_and_ids_of_any_text.t = t
    assert token_count.counter(token_count.VOCABULARY).counts([text]) == [len(t.encode(text, add_special_tokens=False).ids)]
    c = byte_bpe.codec(byte_bpe.RANKS)
    assert c.decode(c.encode([text])[0]) == text.encode()


def test_new_letters_are_split_as_the_library_does(library):
    texts = ["a՘b", "a࢏1", "x\U00010940\U00010940y"]
    assert token_count.counter(token_count.VOCABULARY).counts(texts) == [len(library.encode(t, add_special_tokens=False).ids) for t in texts]
    assert "".join(splitter("tiktoken")(texts[0])) == texts[0]


def test_long_pretokens(library, reference):
    r = random.Random(4)
    texts = ["".join(r.choice("abcdeé") for _ in range(n)) for n in (100, 200, 1500, 4000)] + ["a" * 3001, "ab" * 900]
    assert token_count.Counter(token_count.VOCABULARY).counts(texts) == [len(library.encode(t, add_special_tokens=False).ids) for t in texts]
    got = byte_bpe.Codec(byte_bpe.RANKS).encode(texts)
    assert [np.frombuffer(x, "<u4").tolist() for x in got] == [reference.encode_ordinary(t) for t in texts]


def test_an_encoder_is_small(ranks):
    """What it holds and what a call adds, which each Python worker of an executor has once."""
    r = random.Random(5)
    tokens = [bytes(r.choices(b"abcdefgh", k=60)) for _ in range(12_000)]
    tracemalloc.start()
    try:
        bpe = byte_bpe.SegmentTreeBPE(ranks)
        held = tracemalloc.get_traced_memory()[0]
        tracemalloc.reset_peak()
        bpe.encode(tokens)
        assert held < 15e6 and tracemalloc.get_traced_memory()[1] - held < 30e6
    finally:
        tracemalloc.stop()


def test_counts_of_documents(documents, odd, library):
    for docs in (documents, odd):
        texts = [(r["doc_id"], r["text"] or "") for r in docs.collect()]
        want = sorted((str(i), len(t.encode()), len(library.encode(t, add_special_tokens=False).ids)) for i, t in texts)
        got = token_count.token_counts(docs).collect()
        assert sorted((str(r["doc_id"]), r["n_bytes"], r["n_tokens"]) for r in got) == want
        assert all(r["over_limit"] == (r["n_tokens"] > 512) for r in got)


def test_round_trips_of_documents(documents, odd, reference):
    for docs in (documents, odd):
        want = []
        for r in docs.collect():
            t = r["text"] or ""
            ids = reference.encode_ordinary(t)
            want.append((str(r["doc_id"]), len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()))
        got = byte_bpe.round_trip(docs).collect()
        assert sorted((str(r["doc_id"]), r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in got) == sorted(want)


def test_encode_then_decode(odd):
    back = byte_bpe.decode(byte_bpe.encode(odd)).collect()
    assert sorted((str(r["doc_id"]), bytes(r["decoded"])) for r in back) == sorted((str(r["doc_id"]), (r["text"] or "").encode()) for r in odd.collect())


def test_empty_tables(empty):
    assert token_count.token_counts(empty).count() == 0
    assert byte_bpe.round_trip(empty).count() == 0
