"""Token ids of whole texts by a public tokenizer file, with a cache of word pieces.

Both supported vocabularies split a text into pre-tokens and encode each alone. For
texts of common Latin characters the split is done here and the ids of each distinct
pre-token, made once by the tokenizers library, are reused. Any other text goes to the
library whole, and so does one that holds the name of an added token (such as a literal
``<|endoftext|>``), which the library turns into its one id. Both ways give the ids of an
unmodified ``Tokenizer`` with ``add_special_tokens=False`` (tested against it).
"""

from __future__ import annotations

import re
import struct
import zlib
from os.path import commonprefix

import numpy as np

from tierbit.llm.common import give_back

LETTER = "A-Za-zÀ-ÖØ-öø-ÿ"
#: The same characters, tab and line feed, as bytes of ISO 8859-1.
SAFE = bytes([9, 10, *range(32, 127), *(c for c in range(0xC0, 0x100) if c not in (0xD7, 0xF7))])
#: The splitting rules of the two vocabularies, within the safe characters; what is most frequent stands first where order is free.
BYTE_SPLIT = re.compile(f" ?[{LETTER}]+| ?[0-9]+|'(?:s|t|re|ve|m|ll|d)| ?[^\\s{LETTER}0-9]+|\\s+(?!\\S)|\\s+")
WORD_SPLIT = re.compile(f"[{LETTER}]+|[0-9]|'(?:s|t|re|ve|m|ll|d)|[^\\s{LETTER}0-9]+")
#: A longer pre-token isn't kept; its text goes to the library whole.
LONGEST = 2000


class _Long(Exception):
    pass


class _Words(dict):
    """Ids of pre-tokens, made when first asked for; ``old`` holds those of the generation before."""

    def __init__(self, make, old=None):
        super().__init__()
        self.make, self.old = make, old or {}

    def __missing__(self, word: str) -> bytes:
        ids = self.old.get(word)
        if ids is None:
            if len(word) > LONGEST:
                raise _Long
            ids = self.make(word)
        self[word] = ids
        return ids


def _byte_letters() -> dict[int, str]:
    """Byte to the visible letter that byte-level vocabularies write for it (public rule)."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    return {b: chr(b) for b in plain} | {b: chr(256 + n) for n, b in enumerate(b for b in range(256) if b not in plain)}


class Encoder:
    """Ids as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str, cached: int = 200_000):
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        self.model = self.lib.model
        words = self.model.end_of_word_suffix == "</w>"
        self.split, self.lower = (WORD_SPLIT, True) if words else (BYTE_SPLIT, False)
        self.added = [t.content.lower() for t in self.lib.get_added_tokens_decoder().values()]
        self.start = commonprefix(self.added)
        if any(map(str.isalpha, self.start)):
            self.start = ""  # it may be written in capitals
        self.letters = _byte_letters()
        self.seen = _Words(self.word)
        self.cached = cached

    def word(self, word: str) -> bytes:
        """Ids of one pre-token, by the library's model."""
        tokens = self.model.tokenize(word.encode().decode("latin-1").translate(self.letters))
        return struct.pack(f"<{len(tokens)}I", *[t.id for t in tokens])

    def whole(self, text: str) -> bytes:
        return np.asarray(self.lib.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def plain(self, text: str) -> bool:
        """Whether the text can be split here: safe characters only, and no added token's name."""
        try:
            safe = not text.encode("latin-1").translate(None, SAFE)
        except UnicodeEncodeError:
            return False
        return safe and not (self.start in text and any(a in text.lower() for a in self.added))

    def encode(self, texts: list[str]) -> list[bytes]:
        out, split = [], self.split.findall
        if len(self.seen) > self.cached // 2:
            self.seen.old = {}
            self.seen = _Words(self.word, self.seen)
        ids = self.seen.__getitem__
        for t in texts:
            if self.plain(t):
                try:
                    out.append(b"".join(map(ids, split(t.lower() if self.lower else t))))
                    continue
                except _Long:
                    pass
            out.append(self.whole(t))
        return out


_OPEN: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One per worker process and file."""
    if path not in _OPEN:
        give_back()  # what earlier stages held
        _OPEN[path] = Encoder(path)
        give_back()
    return _OPEN[path]


def crc(ids: bytes) -> int:
    return zlib.crc32(ids)


def batches_of(column, most: int = 1 << 18):
    """(indices, texts) of runs of an Arrow text column that hold about ``most`` characters together; null is empty."""
    give_back()  # what earlier batches held
    run, texts, held = [], [], 0
    for i, t in enumerate(column):
        text = t.as_py() or ""
        run.append(i)
        texts.append(text)
        held += len(text)
        if held >= most:
            yield run, texts
            run, texts, held = [], [], 0
    if run:
        yield run, texts
