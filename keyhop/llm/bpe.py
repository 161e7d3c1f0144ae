"""Pre-token caches around a public BPE tokenizer, for use inside Python workers.

The tokenizer folds case, drops white space and merges inside one pre-token only, so a text's
encoding is the concatenation of its pre-tokens' encodings. That makes a pre-token the natural
cache key (with the white-space word around it kept as a unit). Texts that are not plain Latin-1, or that hold the spelling of a special token, go to the
library whole, so that its normalisation and its handling of special strings apply unchanged.
"""

from __future__ import annotations

import os
import re
import sys
from array import array

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: For lower-case Latin-1 text, where Unicode normalisation changes nothing. The letter,
#: number and space code points of Latin-1.
_LETTER = "a-zA-Z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff"
_NUMBER = "0-9\xb2\xb3\xb9\xbc-\xbe"
_SPACE = "\t-\r \x85\xa0"
PRE_TOKEN = re.compile(rf"[{_LETTER}]+|[{_NUMBER}]|'(?:[stmd]|re|ve|ll)|[^{_LETTER}{_NUMBER}{_SPACE}]+")
_INFORMATION_SEPARATORS = bytes(range(0x1C, 0x20))

_WORKER: dict = {}


def tokenizer(path: str):
    """The tokenizer at ``path``, loaded once per process."""
    from tokenizers import Tokenizer

    held = _WORKER.get(("tok", path))
    if held is None:
        held = _WORKER[("tok", path)] = Tokenizer.from_file(path)
        held.no_truncation()
        held.no_padding()
    return held


def is_plain(text: str) -> bool:
    """Whether the pre-token route gives what the library gives for the whole text.

    Latin-1 only, no start of a special token's spelling, and none of the four controls that Python
    takes for white space and the tokenizer doesn't.
    """
    try:
        raw = text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return "<|" not in text and len(raw.translate(None, _INFORMATION_SEPARATORS)) == len(raw)


def _byte_letters() -> dict[int, str]:
    """Latin-1 code point -> the letters that stand for its UTF-8 bytes in a byte-level vocabulary."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = [b for b in range(0x100) if b not in shown]
    letter = {b: chr(b) for b in shown} | {b: chr(0x100 + i) for i, b in enumerate(hidden)}
    return {c: "".join(letter[b] for b in chr(c).encode()) for c in range(0x100)}


_LETTERS = _byte_letters()


def plain_words(text: str | None) -> list[str]:
    """The words whose lengths the two tiers know: those of a plain text; other texts go to the library whole."""
    return text.lower().split() if text and is_plain(text) else []


def frequent_lengths(path: str, words: list[str]) -> dict[str, int]:
    """Token counts of the given frequent words: the first tier's table."""
    held = Lengths(path, {})
    return dict(zip(words, held.values(" ".join(words)), strict=True))


class _Tiers(dict):
    """The first tier, asked first; what it lacks is asked of the second."""

    def __init__(self, frequent: dict, second):
        super().__init__(frequent)
        self.second = second

    def __missing__(self, word: str):
        return self.second(word)


class _Cache:
    """word -> value of its pre-tokens together; no pre-token spans white space.

    ``frequent`` is the first tier. What it lacks is encoded once and kept in the second, up to
    ``limit`` words; then the second tier starts anew.
    """

    def __init__(self, path: str, frequent: dict, limit: int):
        self.tok, self.limit = tokenizer(path), limit
        self.merge = self.tok.model.tokenize
        self.known: dict = {}
        self.tiers = _Tiers(frequent, self._second)

    def of_pre_token(self, piece: str):
        raise NotImplementedError

    def joined(self, values: list):
        raise NotImplementedError

    def _second(self, word: str):
        held = self.known.get(word)
        if held is None:
            if len(self.known) >= self.limit:
                self.known = {}
            held = self.known[word] = self.joined(list(map(self.of_pre_token, PRE_TOKEN.findall(word))))
        return held

    def values(self, text: str) -> list:
        """The values of a plain text's words, in order."""
        return list(map(self.tiers.__getitem__, text.lower().split()))


class Lengths(_Cache):
    """Token counts of texts."""

    def __init__(self, path: str, frequent: dict[str, int], limit: int = 500_000):
        super().__init__(path, frequent, limit)
        self.table = frequent

    def use(self, frequent: dict[str, int]) -> None:
        self.table, self.tiers = frequent, _Tiers(frequent, self._second)

    def of_pre_token(self, piece: str) -> int:
        return len(self.merge(piece.translate(_LETTERS)))

    def joined(self, values: list) -> int:
        return sum(values)

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if is_plain(text):
            return sum(self.values(text))
        return len(self.tok.encode(text, add_special_tokens=False).ids)


def little_endian(ids) -> bytes:
    """Ids as unsigned 32-bit little-endian integers."""
    out = array("I", ids)
    if sys.byteorder == "big":
        out.byteswap()
    return out.tobytes()


class Ids(_Cache):
    """Token ids of texts, as little-endian bytes."""

    def __init__(self, path: str, limit: int = 500_000):
        super().__init__(path, {}, limit)

    def of_pre_token(self, piece: str) -> bytes:
        return little_endian([t.id for t in self.merge(piece.translate(_LETTERS))])

    def joined(self, values: list) -> bytes:
        return b"".join(values)

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if is_plain(text):
            return b"".join(self.values(text))
        return little_endian(self.tok.encode(text, add_special_tokens=False).ids)


def worker_lengths(path: str, frequent: dict[str, int]) -> Lengths:
    """This worker's length cache: it outlives the task, so that later tasks find it warm.

    Another query's table of frequent words replaces the first tier; the second stays.
    """
    held = _WORKER.get(("lengths", path))
    if held is None:
        held = _WORKER[("lengths", path)] = Lengths(path, frequent)
    elif held.table is not frequent:
        held.use(frequent)
    return held


def worker_ids(path: str) -> Ids:
    """This worker's id cache."""
    held = _WORKER.get(("ids", path))
    if held is None:
        held = _WORKER[("ids", path)] = Ids(path)
    return held
