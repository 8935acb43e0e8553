"""Encoding of text through its distinct pre-tokens.

The word-BPE file lower-cases, drops white space and cuts a text into pre-tokens before it looks at any merge, and
treats each pre-token by itself; so the library's result for a text is the concatenation of its results for the
pre-tokens, and the library is asked once per distinct one.  Latin text is cut here by the file's own pattern, and the library's model gets
the pre-tokens in the letters that its byte-level step gives for them.  A text with any
other character, or with something like a special token, is cut at ASCII white space alone and the library does the rest.
The memo is bounded and outlives a task in its worker; what it forgets costs time but never changes a result.
"""

from __future__ import annotations

import os
import re
import struct
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache

import numpy as np

#: Entries of each of a memo's two generations.
MEMO_ENTRIES = 300_000
BLOCK_CHARS = 1 << 20

#: Letters, numbers and white space among the characters that the short way handles, in lower case.
_LETTER, _NUMBER, _SPACE = "a-zªµºß-öø-žſ", "0-9²³¹¼½¾", "\t-\r \x85\xa0"
_CUT = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTER}]+|[{_NUMBER}]|[^{_SPACE}{_LETTER}{_NUMBER}]+")
_OTHER = re.compile("[^\x00-įı-ſ]")


@lru_cache(maxsize=4)
def tokenizer(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    found = Tokenizer.from_file(path)
    found.no_truncation()
    found.no_padding()
    return found


@lru_cache(maxsize=4)
def _letters(path: str) -> dict[int, str]:
    """What the library's byte-level step makes of each character that the short way handles."""
    cut = tokenizer(path).pre_tokenizer.pre_tokenize_str
    return {c: "".join(p for p, _ in cut(chr(c))) for c in range(0x180) if not chr(c).isspace()}


def blocks(text: str) -> Iterator[tuple[list[str], bool]]:
    """The parts of a text in blocks of about a million characters, and whether they are pre-tokens rather than white-space words."""
    at, end = 0, len(text)
    while at < end:
        cut = end
        if end - at > BLOCK_CHARS:
            cut = text.rfind(" ", at, at + BLOCK_CHARS)
            cut = cut if cut > at else text.find(" ", at + BLOCK_CHARS)
            cut = cut if cut > 0 else end
        block = text[at:cut]
        at = cut
        if "<|" in block or not block.isascii() and _OTHER.search(block):
            yield [w.decode("utf-8") for w in block.encode("utf-8").split()], False
        else:
            yield _CUT.findall(block.lower()), True


class Generations(dict):
    """A bounded memo: when it is full it becomes the old generation, from which what is asked for again comes back."""

    def __init__(self, entries: int = MEMO_ENTRIES) -> None:
        self.entries, self.old = entries, {}

    def missing(self, parts: Iterable) -> list:
        """Parts that are in neither generation; all others can be looked up afterwards."""
        if len(self) > self.entries:
            self.old = dict(self)
            self.clear()
        new = [p for p in set(parts) if p not in self]
        if not self.old:
            return new
        out = []
        for p in new:
            if (kept := self.old.get(p)) is None:
                out.append(p)
            else:
                self[p] = kept
        return out


class PretokenMemo(Generations):
    """Maps a part to ``make(ids)``, ids being a list; parts must be given to ``learn`` before they are looked up."""

    def __init__(self, path: str, make: Callable) -> None:
        super().__init__()
        self.lib, self.letters, self.make = tokenizer(path), _letters(path), make
        self.model = self.lib.model

    def learn(self, parts: Iterable[str], whole: bool) -> None:
        new = self.missing(parts)
        if whole:
            cut, letters, make = self.model.tokenize, self.letters, self.make
            for part in new:
                if part.isprintable():
                    self[part] = make([t.id for t in cut(part if part.isascii() else part.translate(letters))])
            new = [part for part in new if not part.isprintable()]
        if new:
            for part, found in zip(new, self.lib.encode_batch_fast(new, add_special_tokens=False), strict=True):
                self[part] = self.make(found.ids)

    def values(self, parts: list[str], whole: bool) -> list:
        """The value of every part, in order."""
        got = list(map(self.get, parts))
        if None in got:
            lost = [i for i, v in enumerate(got) if v is None]
            self.learn([parts[i] for i in lost], whole)
            for i in lost:
                got[i] = self[parts[i]]
        return got

    def values_of(self, texts: list[str]) -> list[list]:
        """The values of every text's parts; parts of several texts are looked up together."""
        cut = [(n, parts, whole) for n, text in enumerate(texts) for parts, whole in blocks(text)]
        found: list = [None] * len(cut)
        for kind in (True, False):
            own = [(i, parts) for i, (_, parts, whole) in enumerate(cut) if whole is kind]
            got, at = self.values([p for _, parts in own for p in parts], kind), 0
            for i, parts in own:
                found[i] = got[at : at + len(parts)]
                at += len(parts)
        out: list[list] = [[] for _ in texts]
        for (n, _, _), got in zip(cut, found, strict=True):
            out[n] += got
        return out


def strides(texts: Iterable[str], chars: int = 1 << 19) -> Iterator[list[str]]:
    """Groups of texts of about ``chars`` characters together; a longer text is a group of its own."""
    held, size = [], 0
    for text in texts:
        held.append(text)
        size += len(text)
        if size > chars:
            yield held
            held, size = [], 0
    if held:
        yield held


@lru_cache(maxsize=2)
def bytes_memo(path: str, kind: str) -> PretokenMemo:
    pack = {n: struct.Struct(f"<{n}{'H' if kind == '<u2' else 'I'}").pack for n in range(1, 64)}
    return PretokenMemo(path, lambda ids: pack[len(ids)](*ids) if len(ids) in pack else np.array(ids, kind).tobytes())
