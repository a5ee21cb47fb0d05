"""Tokenising, packed ids and packing against the plain library and brute force."""

from __future__ import annotations

import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from thresher.llm import packing, pfor, tokens

from .conftest import HARD

ODD = ["", " ", "a  b", "a   b ", "a \nb", "\n\n x\ty\n", " lead trail ", "don't we'll, I'M 12,345.67 x.y,z", "ΣΑΣ İstanbul", "<|endoftext|> hi", "foo...\nbar.\n", "x\x00y", "word\r\nnext", "\x1cq", "ends\n", "\nstart", "ﬁ ª º µ", "x,.", ".", "é́"]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
@settings(max_examples=150, deadline=None)
@given(text=st.one_of(st.sampled_from(ODD), st.text(st.one_of(st.sampled_from("ab .,\n\t'É1\xa0"), st.characters(codec="utf-8")), max_size=40)))
def test_ids_equal_the_library(name, text):
    t = tokens.load(name)
    assert np.frombuffer(t.encode(text), "<u4").tolist() == t.full.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_letters_and_signs_are_encoded_apart_without_the_whole_library(name, monkeypatch):
    t = tokens.WordTokenizer(name)
    whole: list[str] = []
    plain = t._whole
    monkeypatch.setattr(t, "_whole", lambda x: whole.append(x) or plain(x))
    text = " ".join(f"{w}{s}" for w in ("heat", "Été", "x", "日本") for s in ("***", ".%%%", "#", "_", "$$$,", '")', "...", "<|", "-"))
    odd = " ".join(f"{w}{s}" for w in ("a", "don", "É") for s in ("'s", "*'s", "'.", "'", ".b", "1,", "-'", ",²", "»."))
    for x in (text, odd, f"{text}\n{odd} {text}"):
        assert np.frombuffer(t.encode(x), "<u4").tolist() == t.full.encode(x, add_special_tokens=False).ids
    assert not [x for x in whole if x.strip().startswith(("heat", "Été"))]


MARKED = ["hi <|endoftext|> you", "<|endoftext|>", "a<|startoftext|>b  c", "x <|ENDOFTEXT|> y", "<|endoftext|><|endoftext|>\n\nq", "almost <|endoftext|"]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_added_tokens_are_those_of_a_fresh_library(name):
    import public_tokenizers
    from tokenizers import Tokenizer

    fresh, t = Tokenizer.from_file(public_tokenizers.path(name)), tokens.WordTokenizer(name)
    for text in [*ODD, *MARKED, *(x for _, x in HARD if x)]:
        assert np.frombuffer(t.encode(text), "<u4").tolist() == fresh.encode(text, add_special_tokens=False).ids
    assert fresh.token_to_id("<|endoftext|>") in np.frombuffer(t.encode(MARKED[0]), "<u4")


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.integers(0, 60_000), st.integers(0, 2**32 - 1)), max_size=700))
def test_blocks_round_trip(ids):
    x = np.array(ids, np.uint32)
    blob = pfor.compress(x)
    assert (pfor.decompress(blob) == x).all()
    assert (pfor.decompress(blob, 1, 2) == x[256:512]).all()


def plain(name, text, end):
    return [*tokens.load(name).full.encode(text or "", add_special_tokens=False).ids, end]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_packed_ids_of_hard_texts(hard):
    got = [tuple(r) for r in pfor.digest(pfor.write(hard, segment_ids=500).read()).collect()]
    start, want = 0, []
    for i, t in sorted(HARD, key=lambda r: (r[0] is not None, r[0] or 0)):
        ids = plain(pfor.TOKENIZER, t, pfor.END_ID)
        want.append((i, start, len(ids), crc(ids)))
        start += len(ids)
    assert sorted(got, key=lambda r: r[1]) == want


def test_packing_of_hard_texts(hard):
    packed = packing.pack(hard)
    rows = packing.digest(packed).collect()
    whole = {}
    for i, t in HARD:
        whole[i] = plain(packing.TOKENIZER, t, packing.END_ID)
    at = {}
    for r in rows:
        assert r.ids_crc32 == crc(whole[r.doc_id][r.start : r.start + r.length]) and r.doc_tokens == len(whole[r.doc_id])
        at.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for k, parts in at.items():
        end = 0
        for offset, length in sorted(parts):
            assert offset == end
            end += length
        assert end == packing.LENGTH or k == max(at)
    assert sum(r.length for r in rows) == sum(len(plain(packing.TOKENIZER, t, 0)) for _, t in HARD)
    for s in packing.sequences(packed).collect():
        n = len(s.ids) // 4
        assert n == packing.LENGTH or n == s.n_tokens and n & (n - 1) == 0


def test_empty_tables(empty):
    assert packing.digest(packing.pack(empty)).count() == 0
    assert pfor.digest(pfor.write(empty).read()).count() == 0
