"""Ids of the encoder against those of the library on whole texts."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from charprobe.llm import token_ids
from charprobe.llm.token_store import LEAST, MOST, ROLL, cut_points

PIECES = ["a", "b", "Q", "thing", " ", "  ", "\n", "\n\n", "\n \n", "\t", "\r", "'", "'s", "'ll", ".", "!?", "1", "23", "é", "ß", "×", "ż", "Ω", "ʰ", "日本", "<|endoftext|>", "Ġ", "Ċ", "\x1c", "\x85", "_", "-", "²", "٣", "😀", "́", "\xa0"]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(token_ids.default_vocabulary())


@pytest.mark.parametrize("kept", [3, 250_000])
def test_ids_are_the_librarys(library, monkeypatch, kept):
    monkeypatch.setattr(token_ids, "KEPT", kept)
    own, draw = token_ids.Encoder(token_ids.default_vocabulary()), random.Random(7)
    texts = ["", " ", "\n", "  a", "a  ", "word " * 5000, "x" * 3000, "é" * 500 + " b"]
    texts += ["".join(draw.choice(PIECES) for _ in range(draw.randrange(14))) for _ in range(6000)]
    for lo in range(0, len(texts), 50):
        part = [None, *texts[lo : lo + 50], ""]
        ids, at = own.column(pa.array(part))
        for k, text in enumerate(part):
            assert ids[at[k] : at[k + 1]].tolist() == library.encode(text or "", add_special_tokens=False).ids, text[:60]
    broken = pa.Array.from_buffers(pa.string(), 2, [None, pa.py_buffer(np.array([0, 3, 5], np.int32).tobytes()), pa.py_buffer(b"a\xffb c")])
    ids, at = own.column(broken)
    assert ids[: at[1]].tolist() == library.encode("a\ufffdb", add_special_tokens=False).ids and ids[at[1] :].tolist() == library.encode(" c", add_special_tokens=False).ids


def test_equal_hashes_are_told_apart(library, monkeypatch):
    """Every piece shares its hash with many others: the bytes decide."""
    monkeypatch.setattr(token_ids, "span_hashes", lambda values, a, b: (b - a).astype(np.uint64))
    own = token_ids.Encoder(token_ids.default_vocabulary())
    for text in ("some words of one size, even more words than sizes", "the and the one two six"):
        assert own.ids(text).tolist() == library.encode(text, add_special_tokens=False).ids


def test_every_latin_letter(library):
    own = token_ids.Encoder(token_ids.default_vocabulary())
    for c in range(0x20, 0x260):
        text = f"x a{chr(c)}b{chr(c)} {chr(c)}c\n{chr(c)}\n\nd"
        assert own.ids(text).tolist() == library.encode(text, add_special_tokens=False).ids, hex(c)


def test_rolling_hash_is_the_sum_over_the_window():
    ids = np.random.default_rng(3).integers(0, 50_257, 20_000).astype(np.uint32)
    mask, found = (1 << 64) - 1, []
    for i in range(len(ids)):
        h = sum((int(ids[i - k]) + 1) * 0x9E3779B97F4A7C15 * pow(0x5851F42D4C957F2D, k, 1 << 64) for k in range(min(ROLL, i + 1))) & mask
        if h >> 64 - 9 == 0:
            found.append(i + 1)
    ends, last = [], 0
    for e in [*found, len(ids)]:
        while e - last > MOST:
            last += MOST
            ends.append(last)
        if e == len(ids) or e - last >= LEAST:
            ends.append(e)
            last = e
    assert cut_points(ids) == ends
