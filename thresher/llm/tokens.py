"""Whole texts to token ids by the ``tokenizers`` library, one model call per distinct word.

Neither vocabulary merges across the word borders that its pre-tokenizer draws, so a text's
ids are the concatenation of its words' ids. A worker keeps the ids of the words it has seen
(bounded, emptied when full); what it has not seen goes through the library's own BPE model,
and anything but plain Latin-1 letters through the whole library pipeline. So does a text that
holds one of the vocabulary's added tokens, which the library takes out before it draws words.
"""

from __future__ import annotations

import os
import string
import struct
from collections.abc import Callable
from operator import attrgetter

#: Entries that a worker keeps, about 150 bytes each.
CACHE_WORDS = 800_000
#: Longer pieces are encoded, but not kept.
CACHE_CHARS = 48

#: White space in a row is one piece or two, by what follows: such texts go through the library as a whole.
_RUNS = ("  ", "\n\n", " \n", "\n ", "\x00")
#: Python takes these for white space, the vocabularies do not.
_NOT_BLANK = ("\x1c", "\x1d", "\x1e", "\x1f")
#: ASCII signs but the apostrophe, which may belong to letters after it.
_SIGNS = string.punctuation.replace("'", "")
_loaded: dict[str, WordTokenizer] = {}


def load(path: str) -> WordTokenizer:
    """The worker's tokenizer of that file: a name of a public vocabulary, or a path."""
    if path not in _loaded:
        _loaded[path] = WordTokenizer(path)
    return _loaded[path]


def _byte_letters() -> dict[int, str]:
    """Byte-level BPE writes each byte as a printable character: itself where it prints, else one from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(rest)}


class _OddBorder(Exception):
    """A word begins or ends with white space other than the blank before it."""


class _Known(dict):
    """Word to ids; a word that it has not seen is encoded, and kept while there is room."""

    def __init__(self, encode: Callable[[str], bytes]):
        self.encode = encode

    def __missing__(self, word: str) -> bytes:
        found = self.encode(word)
        if len(word) <= CACHE_CHARS:
            if len(self) >= CACHE_WORDS:
                self.clear()
            self[word] = found
        return found


class WordTokenizer:
    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        if not os.path.isabs(path):
            import public_tokenizers

            path = public_tokenizers.path(path)
        self.full = Tokenizer.from_file(path)
        self.model = self.full.model
        self.tokenize = self.model.tokenize
        self.letters = _byte_letters()
        self.blank = self.letters[32]
        added = self.full.get_added_tokens_decoder().values()
        #: The library looks for added tokens before it draws words, for some of them in the normalized text.
        self.added = [t.content for t in added]
        self.added_normalized = any(t.normalized for t in added) and self.full.normalizer is not None
        #: A normalizer here means: lower case, white space dropped. None: spaces belong to the words.
        self.spaced = self.full.normalizer is None
        self.known = _Known(self._ids)

    def encode(self, text: str | None) -> bytes:
        """The text's ids as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        if self._holds_added(text):
            return self._whole(text)
        if self.spaced:
            if any(x in text for x in _RUNS):
                return self._whole(text)
            words = text.replace("\n", "\x00\n\x00").replace(" ", "\x00 ").split("\x00")
        elif any(x in text for x in _NOT_BLANK):
            return self._whole(text)
        else:
            words = text.split()
        try:
            return b"".join(map(self.known.__getitem__, words))
        except _OddBorder:
            return self._whole(text)

    def _holds_added(self, text: str) -> bool:
        if any(x in text for x in self.added):
            return True
        if not self.added_normalized:
            return False
        plain = self.full.normalizer.normalize_str(text)
        return any(self.full.normalizer.normalize_str(x) in plain for x in self.added)

    def _whole(self, text: str) -> bytes:
        # The fast call gives the same ids and leaves out their places in the text.
        ids = self.full.encode_batch_fast([text], add_special_tokens=False)[0].ids
        return struct.pack(f"<{len(ids)}I", *ids)

    def _ids(self, word: str) -> bytes:
        if not word:
            return b""
        stem = word[1:] if word[0] == " " and self.spaced else word
        # Most new words are plain letters: they are asked for first.
        if stem.isalpha():
            if len(stem) <= CACHE_CHARS:
                raw = word if self.spaced else word.lower()
                if stem.isascii():
                    return _packed(self.tokenize(self.blank + stem if raw[0] == " " else raw))
                if max(stem) < "\u0100":
                    return _packed(self.tokenize(raw.encode().decode("latin-1").translate(self.letters)))
            return self._whole(word)
        if self.spaced and word != "\n" and (stem[:1].isspace() or stem[-1:].isspace()):
            raise _OddBorder
        # Letters, then signs: both vocabularies draw a border there and none between the signs.
        letters = stem.rstrip(_SIGNS)
        if letters.isalpha() and len(letters) < len(stem):
            signs = len(letters) - len(stem)
            return self.known[word[:signs]] + self.known[word[signs:]]
        return self._whole(word)


_id = attrgetter("id")
_pack = [struct.Struct(f"<{n}I").pack for n in range(4 * CACHE_CHARS + 2)]


def _packed(tokens: list) -> bytes:
    """Ids of a word that is kept: it has no more tokens than bytes."""
    return _pack[len(tokens)](*map(_id, tokens))
