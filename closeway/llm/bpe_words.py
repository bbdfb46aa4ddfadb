"""Cutting texts into segments that byte-level merges never cross, and a bounded memory of what each encodes to.

The pattern of the byte-level vocabularies always starts a piece at a blank that stands before something other than
white space. So a text without further white space after a blank is cut at its blanks, which is much cheaper than the
pattern: Arrow cuts and numbers the segments of many texts at once, only distinct ones reach Python, and a segment's
pieces are only looked for when the segment is new. Other texts are cut by the pattern.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

#: Most segments a worker remembers, and most pieces. When more are met the later half is forgotten: frequent ones are met early.
REMEMBERED = 300_000
#: Bytes of text whose segments are numbered and encoded together.
ROUND_BYTES = 8 << 20


#: Signs that end many words; after letters a run of them is one piece.
SIGNS = ".,;:!?)*&\"'-"


@lru_cache(maxsize=4)
def splitter(pattern: str) -> Callable[[str], list[str]]:
    """Pieces of a text by the pattern of the byte-level vocabularies; letters with signs after them need no search."""
    findall = regex.compile(pattern).findall

    def cut(text: str) -> list[str]:
        core = text.rstrip(SIGNS)
        if core.isalpha() or (core[:1] == " " and core[1:].isalpha()):
            return [core, text[len(core) :]] if len(core) < len(text) else [text]
        return findall(text)

    return cut


def gathered(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The runs of ``flat`` that begin at ``starts``, one after another."""
    ends = np.cumsum(lengths)
    total = int(ends[-1]) if len(ends) else 0
    small = np.int32 if max(total, len(flat)) < 1 << 31 else np.int64
    at = np.repeat((starts - (ends - lengths)).astype(small), lengths)
    at += np.arange(total, dtype=small)
    return flat[at]


class Memory:
    """Ids of segments and pieces as bytes (little-endian u32). Lives as long as the worker process, shared by its tasks."""

    def __init__(self, most: int = REMEMBERED):
        self.most = most
        #: By segment without the blank that it begins with; None: it begins with white space, so the text is loose.
        self.segments: dict[str, bytes | None] = {}
        self.pieces: dict[str, bytes] = {}

    def trim(self) -> None:
        for held in (self.segments, self.pieces):
            if len(held) > self.most:
                early = dict(islice(held.items(), self.most // 2))
                held.clear()
                held.update(early)

    def of_pieces(self, split: list[list[str]], encode: Callable[[list[str]], list[bytes]]) -> list[bytes]:
        """The ids of rows of pieces; a new piece is encoded once."""
        new = list(set().union(*split).difference(self.pieces))
        if new:
            self.pieces.update(zip(new, encode(new), strict=True))
        have = self.pieces.__getitem__
        return [have(x[0]) if len(x) == 1 else b"".join(map(have, x)) for x in split]

    def ids(self, texts: pa.Array, findall: Callable[[str], list[str]], encode: Callable[[list[str]], list[bytes]], most: int = ROUND_BYTES) -> Iterator[np.ndarray]:
        """The ids of each text (no nulls), in order; the new segments of about ``most`` bytes of text are encoded together."""
        size = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
        lo = 0
        while lo < len(texts):
            hi = max(lo + 1, int(np.searchsorted(size, (size[lo - 1] if lo else 0) + most, side="right")))
            yield from self._round(texts.slice(lo, hi - lo), findall, encode)
            self.trim()
            lo = hi

    def _round(self, texts: pa.Array, findall: Callable[[str], list[str]], encode: Callable[[list[str]], list[bytes]]) -> list[np.ndarray]:
        lists = pc.split_pattern(texts, " ")
        offsets = lists.offsets.to_numpy().astype(np.int64)
        numbered = lists.values.slice(offsets[0], offsets[-1] - offsets[0]).dictionary_encode()
        offsets -= offsets[0]
        code, keys = np.array(numbered.indices.to_numpy()), numbered.dictionary.to_numpy(zero_copy_only=False).tolist()
        first = offsets[:-1]  # a text's first segment has no blank before it
        heads = [keys[c] for c in code[first]]
        after = np.ones(len(code), bool)
        after[first] = False
        used = np.zeros(len(keys), bool)
        used[code[after]] = True
        new = [keys[c] for c in np.flatnonzero(used) if keys[c] not in self.segments]
        tight = [k for k in new if k and not k[0].isspace()]
        self.segments.update(dict.fromkeys(new))
        self.segments.update(zip(tight, self.of_pieces([findall(" " + k) for k in tight], encode), strict=True))
        have = self.segments
        forms = [have[k] if u else b"" for k, u in zip(keys, used.tolist(), strict=True)]
        loose_key = np.array([f is None for f in forms], bool)
        loose = np.zeros(len(texts), bool)
        if loose_key.any():
            loose[np.searchsorted(offsets, np.flatnonzero(loose_key[code] & after), side="right") - 1] = True
            forms = [f or b"" for f in forms]
        # Loose texts and first segments are cut by the pattern.
        forms += self.of_pieces([findall(texts[i].as_py() if slack else head) for i, (slack, head) in enumerate(zip(loose.tolist(), heads, strict=True))], encode)
        code[first] = len(keys) + np.arange(len(texts))
        if loose.any():
            keep = ~np.repeat(loose, np.diff(offsets)) | ~after
            offsets = np.concatenate(([0], np.cumsum(keep)))[offsets]
            code = code[keep]
        lengths = np.fromiter(map(len, forms), np.int64, len(forms)) // 4
        flat = np.frombuffer(b"".join(forms), "<u4")
        del forms, keys, lists, numbered
        own = lengths[code]
        every = gathered(flat, (np.cumsum(lengths) - lengths)[code], own)
        ends = np.concatenate(([0], np.cumsum(own)))[offsets]
        return np.split(every, ends[1:-1]) if len(texts) else []

    def clear(self) -> None:
        for held in (self.segments, self.pieces):
            held.clear()


_MEMORIES: dict[str, Memory] = {}


def memory(name: str, most: int = REMEMBERED) -> Memory:
    if name not in _MEMORIES:
        _MEMORIES[name] = Memory(most)
    return _MEMORIES[name]
