"""Benchmark decontamination by multi-pattern search with block shifts over words.

The symbols are whole words, so each hit is aligned with words and a skip passes over words. Patterns of one length m
form a table: for every block of words in a pattern, the least distance from the block to the pattern's end.
A block that no pattern holds lets the search move on by m - block + 1 words; a distance of 0 leads to a bucket of
patterns by the hash of that last block, split by the first word, where a direct comparison confirms or refuses.

Windows: every run of ``size`` words of an item; an item with fewer words, but not none, is one window. The patterns
are small beside the corpus; they are cut into parts of bounded bytes, each a pass over the rows that carries on what
was found. Passes are stored in between, so no worker ever holds the tables of more than one part: a larger benchmark
costs passes and not memory. A worker compiles a part's tables once for all its tasks.

Defined results: null and wordless texts and items have no words, hits or windows; an item id given twice counts
once; null item ids are left out of the list of items but their windows hit; repeated documents each get a row; with
no items nothing is hit.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from itertools import chain

import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import Stored
from .common import hand_back, only, text_rows

SIZE = 10
BLOCK = 2
#: Most bytes of pattern text in one pass.
PART_BYTES = 32 << 20

# A-Z to lower case; a-z, 0-9 and all bytes from 0x80 stay; everything else parts words.
FOLD = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 97 <= c <= 122 or 48 <= c <= 57 else 32 for c in range(256))


def words_of(text: bytes | None) -> list[bytes]:
    return text.translate(FOLD).split() if text else []


class Table:
    """Shift table and buckets of the patterns of one length."""

    def __init__(self, m: int):
        self.m, self.b = m, min(BLOCK, m)
        self.shift: dict = {}
        self.buckets: dict = {}

    def block(self, words: list[bytes], end: int):
        """The block that ends with the word at ``end``."""
        return words[end] if self.b == 1 else (words[end - 1], words[end])

    def add(self, pattern: tuple[bytes, ...], items: list[int]) -> None:
        for end in range(self.b - 1, self.m):
            key = self.block(pattern, end)
            self.shift[key] = min(self.shift.get(key, self.m), self.m - 1 - end)
        self.buckets.setdefault(self.block(pattern, self.m - 1), {}).setdefault(pattern[0], []).append((list(pattern), items))

    def search(self, words: list[bytes], spans: list, found: set) -> None:
        m, shift, buckets, get, far = self.m, self.shift, self.buckets, self.shift.get, self.m - self.b + 1
        single, end, n = self.b == 1, self.m - 1, len(words)
        while end < n:
            key = words[end] if single else (words[end - 1], words[end])
            step = get(key, far)
            if step:
                end += step
                continue
            start = end - m + 1
            for pattern, items in buckets[key].get(words[start], ()):
                if words[start : end + 1] == pattern:
                    spans.append((start, end + 1))
                    found.update(items)
            end += 1


def compile_tables(items: list[tuple[int | None, bytes | None]], size: int = SIZE) -> list[Table]:
    by_pattern: dict[tuple[bytes, ...], set] = {}
    for item, text in items:
        words = words_of(text)
        m = min(size, len(words))
        for at in range(len(words) - m + 1 if m else 0):
            by_pattern.setdefault(tuple(words[at : at + m]), set()).update([] if item is None else [item])
    tables: dict[int, Table] = {}
    for pattern, ids in sorted(by_pattern.items()):
        tables.setdefault(len(pattern), Table(len(pattern))).add(pattern, sorted(ids))
    return [tables[m] for m in sorted(tables)]


def joined(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([s, e])
    return [tuple(x) for x in out]


HITS = "doc_id long, text string, n_words long, spans array<struct<first:long,end:long>>, items array<long>"


def parts_of(benchmark: DataFrame, part_bytes: int = PART_BYTES) -> Iterator[list[tuple]]:
    """The items in runs of bounded bytes, streamed to the driver one partition at a time."""
    part, size = [], 0
    for r in benchmark.orderBy("item_id").toLocalIterator():
        part.append((r.item_id, None if r.text is None else r.text.encode()))
        size += len(r.text or "")
        if size >= part_bytes:
            yield part
            part, size = [], 0
    if part:
        yield part


#: The tables that a worker holds: those of the last part it met.
_COMPILED: dict[str, list[Table]] = {}


def tables_of(name: str, part: list[tuple], size: int) -> list[Table]:
    if name not in _COMPILED:
        _COMPILED.clear()
        _COMPILED[name] = compile_tables(part, size)
    return _COMPILED[name]


def passes(rows: DataFrame, benchmark: DataFrame, part_bytes: int, one: Callable[[DataFrame, str, Broadcast], DataFrame]) -> DataFrame:
    """``one`` applied to the rows for each part of the benchmark in turn (one empty part where there is none)."""
    held: list[Stored] = []
    some = False
    for part in chain(parts_of(benchmark, part_bytes), [None]):
        if part is None and some:
            break
        if some:
            held.append(Stored(rows, "decontaminated"))
            rows = held[-1].df
            if len(held) > 1:
                held.pop(0).drop()
        rows, some = one(rows, uuid.uuid4().hex, rows.sparkSession.sparkContext.broadcast(part or [])), True  # at most part_bytes
    return rows


def find_hits(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", part_bytes: int = PART_BYTES) -> DataFrame:
    """(doc_id, n_words, spans, items, n_hit) per document; spans are joined word ranges, items the ids found, sorted."""
    empty = F.array().cast("array<struct<first:long,end:long>>"), F.array().cast("array<long>")
    at = only(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long"), "text", F.lit(0).cast("long").alias("n_words"), empty[0].alias("spans"), empty[1].alias("items"))
    span_type = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64())]))

    def one_part(rows: DataFrame, name: str, part: Broadcast) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = tables_of(name, part.value, size)
            for batch, texts in text_rows(batches):
                n_words, spans_out, items_out = [], [], []
                for text, spans_in, items_in in zip(texts, batch.column(3).to_pylist(), batch.column(4).to_pylist(), strict=True):
                    words = words_of(text)
                    spans, found = [(s["first"], s["end"]) for s in spans_in], set(items_in)
                    for t in held:
                        t.search(words, spans, found)
                    n_words.append(len(words))
                    spans_out.append([{"first": s, "end": e} for s, e in joined(spans)])
                    items_out.append(sorted(found))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n_words, pa.int64()), pa.array(spans_out, span_type), pa.array(items_out, pa.list_(pa.int64()))], ["doc_id", "text", "n_words", "spans", "items"])
            hand_back()

        return rows.mapInArrow(run, HITS)

    bench = only(benchmark, item_id=item_col, text=item_text).withColumn("item_id", F.col("item_id").cast("long"))
    at = passes(at, bench, part_bytes, one_part)
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["first"])
    return at.select("doc_id", "n_words", "spans", "items", hit.alias("n_hit"))


def uncontaminated(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", part_bytes: int = PART_BYTES) -> DataFrame:
    """The rows, with all their columns, that hold no window of any item."""

    def one_part(rows: DataFrame, name: str, part: Broadcast) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = tables_of(name, part.value, size)
            for batch, texts in text_rows(batches, text_col):
                clean = []
                for text in texts:
                    words, spans = words_of(text), []
                    for t in held:
                        t.search(words, spans, set())
                    clean.append(not spans)
                yield batch.filter(pa.array(clean, pa.bool_()))
            hand_back()

        return rows.mapInArrow(run, docs.schema)

    return passes(docs, only(benchmark, item_id=item_col, text=item_text), part_bytes, one_part)


ORACLE = r"""
WITH dw AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
bw AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
win AS (SELECT DISTINCT item_id, m, array_to_string(w[p:p + m - 1], ' ') AS s FROM (
  SELECT item_id, w, least(10, len(w)) AS m, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS p FROM bw WHERE len(w) > 0)),
dp AS (SELECT doc_id, m, p, array_to_string(w[p:p + m - 1], ' ') AS s FROM (
  SELECT doc_id, w, m, unnest(range(1, len(w) - m + 2)) AS p FROM dw, (SELECT DISTINCT m FROM win) WHERE len(w) >= m)),
hit AS (SELECT doc_id, p, m, item_id FROM dp JOIN win USING (m, s)),
pos AS (SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + m)) AS q FROM hit) GROUP BY 1),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS l FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS i FROM hit) GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(l, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN pos USING (doc_id) LEFT JOIN its USING (doc_id)
"""
