"""Splitting texts into pre-tokens exactly as an installed tokenizer library does.

The `regex` module knows a newer Unicode than the libraries: some code points are letters to it and unassigned
to them. A probe finds, once per worker, the code points they class differently; texts that hold one are split
through a stand-in of the library's class, and cut from the original by length.
"""

from __future__ import annotations

import functools
import unicodedata
from collections.abc import Callable

import public_tokenizers
import regex

#: A stand-in of each class: letter, number, white space, anything else.
CLASSES = {"L": "a", "N": "1", "S": "\n", "O": "!"}


def _suspects() -> list[str]:
    known = regex.compile(r"[\p{L}\p{N}\s]").match
    return [c for c in map(chr, range(0x80, 0x110000)) if not "\ud800" <= c <= "\udfff" and unicodedata.category(c) == "Cn" and known(c)]


def _by_spans(c: str) -> str:
    """The class that the tokenizers library gives a character."""
    split = _byte_level().pre_tokenize_str
    return next((k for k, x in CLASSES.items() if k != "S" and len(split(x + c)) == 1), "S")


@functools.cache
def _byte_level():
    from tokenizers import pre_tokenizers

    return pre_tokenizers.ByteLevel(add_prefix_space=False)


@functools.cache
def _probe():
    """A tiktoken encoding whose merges join a class's stand-in with any following byte."""
    import tiktoken

    ranks = {bytes([b]): b for b in range(256)}
    for x in "a1!":
        for b in range(0x80, 256):
            ranks[x.encode() + bytes([b])] = len(ranks)
    return tiktoken.Encoding("probe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def _by_merges(c: str) -> str:
    ids = _probe().encode_ordinary
    return next((k for k, x in CLASSES.items() if k != "S" and ids(x + c)[0] >= 256), "S")


@functools.cache
def splitter(library: str) -> Callable[[str], list[str]]:
    """texts -> pre-tokens, as `library` ("tokenizers" or "tiktoken") splits by public_tokenizers.PATTERN."""
    find = regex.compile(public_tokenizers.PATTERN).findall
    of = {"tokenizers": _by_spans, "tiktoken": _by_merges}[library]
    own = {k: regex.compile(p).match for k, p in (("L", r"\p{L}"), ("N", r"\p{N}"), ("S", r"\s"))}
    odd = {}
    for c in _suspects():
        if not (m := own.get(k := of(c))) or not m(c):
            odd[ord(c)] = CLASSES[k]
    if not odd:
        return find
    beyond = regex.compile(f"[{chr(min(odd))}-\U0010ffff]").search  # one range: most texts end here

    def split(text: str) -> list[str]:
        if text.isascii() or not beyond(text) or odd.keys().isdisjoint(map(ord, set(text))):
            return find(text)
        out, at = [], 0
        for t in find(text.translate(odd)):
            out.append(text[at : at + len(t)])
            at += len(t)
        return out

    return split
