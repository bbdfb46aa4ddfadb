"""Byte-level BPE by replaying merges over a whole set of words at once, and decoding.

All words' bytes lie in one array of symbols linked to their neighbours. An inverted index holds, by rank, the
positions where that pair of neighbouring symbols was seen. The ranks are taken in order; each merge is applied to all
its positions that still hold, and only the pairs with touched neighbours enter the index anew. Within a word this
always merges its pair of least rank first, as the ranks ask. Should a merge make a pair of lower rank while a
further place of the same merge lies in that word, the word is encoded alone instead, one merge at a time.

The words of a run of rows are encoded together, each distinct word once per worker memory; so the index is as large
as a run's new words, never as the corpus.

Defined results: a null text is encoded as the empty text; null ids stay null; repeated rows each get a row; texts of any
length are encoded whole; of equal pairs in a word the leftmost is merged first; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import heapq
import hashlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe_words import REMEMBERED, memory, splitter
from .common import hand_back, only, steady

NONE = np.int64(1 << 40)
#: Bytes of text whose new segments are encoded together; every replay walks all ranks that occur, so few long ones are cheaper.
TOGETHER_BYTES = 16 << 20
#: Rows in a batch of results.
ROWS_OUT = 1000
#: Segments remembered, and bytes of text encoded together, where the memory is emptied after each task.
FORGOTTEN, FEW_BYTES = 40_000, 2 << 20


def parse_ranks(lines: list[str]) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in (x.split() for x in lines if x.strip())}


class Merges:
    """The vocabulary and its table from pairs of ids to the id of their joined bytes, which is the rank."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.single = np.array([ranks[bytes([c])] for c in range(256)], np.int64)
        lefts, rights, ids = [], [], []
        for whole, i in ranks.items():
            for cut in range(1, len(whole)):
                a, b = ranks.get(whole[:cut]), ranks.get(whole[cut:])
                if a is not None and b is not None:
                    lefts.append(a)
                    rights.append(b)
                    ids.append(i)
        key = np.array(lefts, np.int64) << 20 | np.array(rights, np.int64)
        order = np.argsort(key)
        self.keys, self.made = key[order], np.array(ids, np.int64)[order]

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair of ids, NONE where the vocabulary has no joined token."""
        key = left.astype(np.int64) << 20 | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.made[at], NONE)

    def alone(self, word: bytes) -> list[int]:
        """One word, one merge at a time: the leftmost pair of least rank, from a heap of pairs."""
        n = len(word)
        parts: list[bytes | None] = [word[i : i + 1] for i in range(n)]
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[int, int, bytes]] = []

        def enter(i: int) -> None:
            if i >= 0 and nxt[i] < n:
                both = parts[i] + parts[nxt[i]]
                if both in self.ranks:
                    heapq.heappush(heap, (self.ranks[both], i, both))

        for i in range(n):
            enter(i)
        while heap:
            _, i, both = heapq.heappop(heap)
            if parts[i] is None or nxt[i] >= n or parts[i] + parts[nxt[i]] != both:
                continue  # touched since
            gone = nxt[i]
            parts[i], parts[gone], nxt[i] = both, None, nxt[gone]
            if nxt[i] < n:
                prv[nxt[i]] = i
            enter(prv[i])
            enter(i)
        return [self.ranks[p] for p in parts if p is not None]

    def replay(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of each word."""
        sizes = np.array([len(w) for w in words], np.int64)
        total = int(sizes.sum())
        if not total:
            return [np.empty(0, np.int64) for _ in words]
        sym = self.single[np.frombuffer(b"".join(words), np.uint8)].astype(np.int32)
        word = np.repeat(np.arange(len(words), dtype=np.int32), sizes)
        # Links past a word's ends lead to the last place, whose symbol is in no pair.
        end = total
        sym = np.append(sym, np.int32(1 << 19))
        last = np.cumsum(sizes) - 1
        nxt = np.arange(1, total + 2, dtype=np.int32)
        nxt[last[sizes > 0]] = end
        nxt[end] = end
        prv = np.arange(-1, total, dtype=np.int32)
        prv[(last - sizes + 1)[sizes > 0]] = end
        prv = np.append(prv, np.int32(end))
        alive = np.ones(total + 1, bool)
        index: dict[int, list[np.ndarray]] = {}
        queue: list[int] = []

        def enter(at: np.ndarray) -> np.ndarray:
            """Put the pairs that start at these positions into the index; gives their ranks."""
            rank = self.rank(sym[at], sym[nxt[at]])
            some = rank < NONE
            if some.any():
                p, r = at[some], rank[some]
                order = np.argsort(r, kind="stable")
                p, r = p[order], r[order]
                cut = np.flatnonzero(r[1:] != r[:-1]) + 1
                for rr, pp in zip(r[np.concatenate(([0], cut))].tolist(), np.split(p, cut), strict=True):
                    if rr in index:
                        index[rr].append(pp)
                    else:
                        index[rr] = [pp]
                        heapq.heappush(queue, rr)
            return rank

        enter(np.arange(total))
        odd: set[int] = set()
        while queue:
            rank = heapq.heappop(queue)
            held = index.pop(rank)
            at = np.unique(np.concatenate(held)) if len(held) > 1 else np.sort(held[0])
            at = at[alive[at]]
            at = at[self.rank(sym[at], sym[nxt[at]]) == rank]
            if not len(at):
                continue
            # A place whose left part is the right part of the place before it waits its turn or is gone.
            touch = nxt[at[:-1]] == at[1:]
            if touch.any():
                keep = np.ones(len(at), bool)
                for i in np.flatnonzero(touch):
                    keep[i + 1] = not keep[i]
                at = at[keep]
            right = nxt[at]
            sym[at] = rank
            alive[right] = False
            nxt[at] = nxt[right]
            back = nxt[at]
            inner = back != end
            prv[back[inner]] = at[inner]
            before = prv[at]
            before = before[before != end]
            new = np.concatenate((at, before))
            low = enter(np.unique(new))
            if (low < rank).any():
                odd.update(word[np.unique(new)[low < rank]].tolist())
        live = np.flatnonzero(alive[:-1])
        ids, owner = sym[live], word[live]
        cut = np.searchsorted(owner, np.arange(1, len(words)))
        out = np.split(ids, cut)
        for w in odd:
            out[w] = np.array(self.alone(words[w]), np.int64)
        return out

    def decode(self, ids) -> bytes:
        return b"".join([self.bytes_of[int(i)] for i in ids])


@lru_cache(maxsize=2)
def merges_of(key: str) -> Merges:
    return Merges(_TABLES[key])


_TABLES: dict[str, dict[bytes, int]] = {}


def _ready(ranks_lines: list[str]) -> tuple[str, Merges]:
    key = hashlib.md5("\n".join(ranks_lines).encode()).hexdigest()
    if key not in _TABLES:
        _TABLES[key] = parse_ranks(ranks_lines)
    return key, merges_of(key)


def read_ranks(path: str) -> list[str]:
    with open(path) as f:
        return f.read().splitlines()


class Encoder:
    """Encodes texts; remembers each segment's ids as bytes."""

    def __init__(self, ranks: list[str], pattern: str, most: int = REMEMBERED, together_bytes: int = TOGETHER_BYTES):
        self.together_bytes = together_bytes
        key, self.merges = _ready(ranks)
        self.split, self.memory = splitter(pattern), memory(f"replay-{key}-{most}", most)
        self.bytes_of = [self.merges.bytes_of.get(i, b"") for i in range(max(self.merges.bytes_of, default=-1) + 1)]
        self.digits_of = [b"%d" % i for i in range(len(self.bytes_of))]

    def _encode(self, pieces: list[str]) -> list[bytes]:
        return [x.astype("<u4").tobytes() for x in self.merges.replay([p.encode("utf-8", "surrogatepass") for p in pieces])]

    def encode(self, texts: pa.Array) -> Iterator[np.ndarray]:
        """The ids of each text (null: none)."""
        return self.memory.ids(pc.fill_null(texts, ""), self.split, self._encode, self.together_bytes)

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def digits(self, ids: list[int]) -> bytes:
        return b",".join(map(self.digits_of.__getitem__, ids))


def together(batches: Iterator[pa.RecordBatch], most: int, column: int = 1) -> Iterator[pa.RecordBatch]:
    """The batches put together until their texts have about so many bytes."""
    held, size = [], 0
    for batch in batches:
        held.append(batch)
        size += batch.column(column).nbytes
        if size >= most:
            yield pa.concat_batches(held)
            held, size = [], 0
    if size:
        yield pa.concat_batches(held)


def encode_and_decode(docs: DataFrame, ranks: list[str], pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, forget: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256[, ids]) of every row; a null text is encoded as empty.

    ``ids`` are the token ids. ``forget`` keeps the worker small, for stages beside others: less text together, and the
    memory of segments emptied after each task. Texts are encoded whole; repeated rows each get a row.
    """
    spark = docs.sparkSession
    steady(spark)
    sent = spark.sparkContext.broadcast(ranks)  # one vocabulary file
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = None
        size = FEW_BYTES if forget else TOGETHER_BYTES
        for batch in together(batches, size):
            encoder = encoder or Encoder(sent.value, pattern, FORGOTTEN if forget else REMEMBERED, size)
            ids = encoder.encode(batch.column(1))
            for lo in range(0, batch.num_rows, ROWS_OUT):
                doc = batch.column(0).slice(lo, ROWS_OUT)
                n, a, b, every = [], [], [], []
                for one in islice(ids, len(doc)):
                    listed = one.tolist()
                    n.append(len(listed))
                    a.append(hashlib.sha256(encoder.digits(listed)).hexdigest())
                    b.append(hashlib.sha256(encoder.decode(listed)).hexdigest())
                    if with_ids:
                        every.append(one)
                cols = [doc.cast(pa.int64()), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())]
                if with_ids:
                    flat = np.concatenate(every).astype(np.int32)
                    cols.append(pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(n))), pa.int32()), pa.array(flat)))
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] + ["ids"] * with_ids)
        if forget and encoder:
            encoder.memory.clear()
        hand_back()

    return only(docs, doc_id=id_col, text=text_col).mapInArrow(run, schema)
