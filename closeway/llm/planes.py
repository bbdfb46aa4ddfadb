"""Token ids in a plane-shuffled file format.

A file holds the ids of whole documents in order. Ids are cut into blocks of fixed size; a block is transposed into
byte planes (first bytes of all ids, then second bytes, ...) or bit planes, and each plane is compressed by zstandard
on its own; a plane of zeros takes no bytes. A chunk index gives every plane's place, so one block can be read alone,
and a table of documents gives ids and lengths. Layout, little-endian:

    magic (6 bytes), mode (1: byte planes, 2: bit planes), width in bytes (1),
    planes, chunk index (zstandard: u64 place, u32 length per plane), documents (zstandard: i64 id, u64 length),
    footer: u64 place and u32 length of the index, u64 place and u32 length of the documents, u64 ids, u32 ids in a
    block, u64 documents, u32 crc32 of all before the footer, magic.

Defined results: null texts are empty; null ids come first; rows that repeat an id are each a document, in the order of
a hash of their texts; texts of any length are encoded whole; an empty table gives no files and no rows.

Rows are dealt by sampled ranges of the id, sorted within each range, and each range becomes a run of files of
bounded size. The files are rows of one Parquet table in the shared folder, for only Spark reaches every store;
``export`` writes them out as plain files.
"""

from __future__ import annotations

import os
import re
import struct
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import Stored
from .bpe_words import memory, splitter
from .common import hand_back, only, steady

MAGIC = b"CWPLN1"
FOOT = struct.Struct("<QIQIQIQI6s")
BYTE_PLANES, BIT_PLANES = 1, 2
BLOCK_IDS = 1 << 16
#: A file ends with the document that brings it to so many ids.
FILE_IDS = 1 << 20
LEVEL = 3
#: Segments that a worker remembers, and pieces.
SEGMENTS = 600_000


def to_planes(block: np.ndarray, mode: int) -> np.ndarray:
    """The planes of a block of u32 ids, one per row."""
    by = block.view(np.uint8).reshape(-1, 4).T
    if mode == BYTE_PLANES:
        return np.ascontiguousarray(by)
    bits = np.unpackbits(np.ascontiguousarray(by), axis=1, bitorder="little").reshape(4, len(block), 8)
    return np.packbits(bits.transpose(0, 2, 1).reshape(32, len(block)), axis=1, bitorder="little")


def from_planes(planes: list[bytes | None], n: int, mode: int) -> np.ndarray:
    if mode == BYTE_PLANES:
        out = np.zeros((n, 4), np.uint8)
        for k, p in enumerate(planes):
            if p is not None:
                out[:, k] = np.frombuffer(p, np.uint8)
        return out.reshape(-1).view("<u4")
    bits = np.zeros((n, 32), np.uint8)
    for k, p in enumerate(planes):
        if p is not None:
            bits[:, k] = np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little")
    return np.packbits(bits, axis=1, bitorder="little").reshape(-1).view("<u4")


def pack(ids: np.ndarray, docs: list[int], lengths: list[int], mode: int = BYTE_PLANES, block_ids: int = BLOCK_IDS, level: int = LEVEL) -> bytes:
    """One file's bytes."""
    press = zstandard.ZstdCompressor(level=level).compress
    ids = np.ascontiguousarray(ids, "<u4")
    out, places, at = [MAGIC + bytes([mode, 4])], [], len(MAGIC) + 2
    for lo in range(0, len(ids), block_ids):
        for plane in to_planes(ids[lo : lo + block_ids], mode):
            data = press(plane.tobytes()) if plane.any() else b""
            places.append((at, len(data)))
            out.append(data)
            at += len(data)
    index = press(b"".join(struct.pack("<QI", *p) for p in places))
    table = press(np.array(docs, "<i8").tobytes() + np.array(lengths, "<u8").tobytes())
    body = b"".join([*out, index, table])
    return body + FOOT.pack(at, len(index), at + len(index), len(table), len(ids), block_ids, len(docs), zlib.crc32(body), MAGIC)


class PlaneFile:
    """Reads a file's bytes: whole, by document, or a single block by the index."""

    def __init__(self, data: bytes):
        if len(data) < FOOT.size or data[: len(MAGIC)] != MAGIC:
            raise ValueError("not a plane file")
        i_at, i_len, d_at, d_len, self.n_ids, self.block_ids, n_docs, crc, magic = FOOT.unpack(data[-FOOT.size :])
        if magic != MAGIC or zlib.crc32(memoryview(data)[: -FOOT.size]) != crc:
            raise ValueError("the plane file is damaged")
        self.data, self.mode = data, data[len(MAGIC)]
        self.open = zstandard.ZstdDecompressor().decompress
        self.index = list(struct.iter_unpack("<QI", self.open(data[i_at : i_at + i_len])))
        table = self.open(data[d_at : d_at + d_len])
        self.docs, self.lengths = np.frombuffer(table, "<i8", n_docs), np.frombuffer(table, "<u8", n_docs, 8 * n_docs).astype(np.int64)

    def block(self, k: int) -> np.ndarray:
        many = 4 if self.mode == BYTE_PLANES else 32
        n = min(self.block_ids, self.n_ids - k * self.block_ids)
        planes = [self.open(self.data[at : at + size]) if size else None for at, size in self.index[k * many : (k + 1) * many]]
        return from_planes(planes, n, self.mode)

    def ids(self) -> np.ndarray:
        n = -(-self.n_ids // self.block_ids)
        return np.concatenate([self.block(k) for k in range(n)]) if n else np.empty(0, "<u4")


def byte_letters() -> list[str]:
    """The byte-level alphabet by byte: printable bytes stand for themselves, the others for letters from 256 on."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(others)) for b in range(256)]


class SegmentTokenizer:
    """Encodes texts as the tokenizers library does by default, each distinct segment once.

    Pieces of letters below ``PLAIN`` go straight to the library's merges; any other piece, and a whole text that holds
    an added token of the vocabulary (which the library finds before it cuts into pieces), is encoded by the library's
    whole course.
    """

    PLAIN = "\u0250"

    def __init__(self, spec: str, pattern: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(spec)
        self.merge, self.letters = self.tokenizer.model.tokenize, byte_letters()
        added = [re.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.added = re.compile("|".join(added)).search if added else lambda text: None
        self.split, self.memory = splitter(pattern), memory(f"library-{zlib.crc32(spec.encode())}", SEGMENTS)

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _encode(self, pieces: list[str]) -> list[bytes]:
        merge, letters, plain, blank = self.merge, self.letters, self.PLAIN, self.letters[32]
        out: list = []
        for p in pieces:
            if p.isascii() and p.isprintable():
                out.append(array("I", [t.id for t in merge(p.replace(" ", blank))]).tobytes())
            elif max(p) < plain:
                out.append(array("I", [t.id for t in merge("".join([letters[b] for b in p.encode()]))]).tobytes())
            else:
                out.append(None)
        other = [i for i, x in enumerate(out) if x is None]
        for i, ids in zip(other, self._whole([pieces[i] for i in other]), strict=True):
            out[i] = ids
        return out

    def _cut(self, text: str) -> list[str]:
        """The pattern's pieces, but a text beyond ``PLAIN`` stays whole for the library to cut."""
        return self.split(text) if text.isascii() or max(text) < self.PLAIN else [text]

    def encode(self, texts: pa.Array) -> Iterator[np.ndarray]:
        """Each text's ids (null: none)."""
        texts = pc.fill_null(texts, "")
        held = np.zeros(len(texts), bool)
        for i, t in enumerate(texts):
            held[i] = self.added(t.as_py()) is not None
        plain = pc.if_else(pa.array(held), "", texts) if held.any() else texts
        for i, ids in enumerate(self.memory.ids(plain, self._cut, self._encode)):
            yield np.frombuffer(self._whole([texts[i].as_py()])[0], "<u4") if held[i] else ids


FILES = "part int, seq int, first long, n_ids long, n_docs long, content binary"


def write_files(docs: DataFrame, spec: str, pattern: str, end_id: int = 0, mode: int = BYTE_PLANES, id_col: str = "doc_id", text_col: str = "text", file_ids: int = FILE_IDS) -> Stored:
    """Encode all texts in ascending id order, each closed by ``end_id``, into a stored table of files.

    Null ids come first and are kept in the files as the least long; null texts are empty. ``first`` counts the part's
    ids before the file.
    """
    steady(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast((spec, pattern))  # one vocabulary file
    rows = only(docs, doc_id=id_col, text=text_col).select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("doc_id"), "text", F.xxhash64("text").alias("tie"))
    dealt = rows.repartitionByRange("doc_id", "tie").sortWithinPartitions("doc_id", "tie").drop("tie")
    tail = np.array([end_id], "<u4")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, part, seq, first = None, TaskContext.get().partitionId(), 0, 0
        ids: list[np.ndarray] = []
        who: list[int] = []
        lengths: list[int] = []

        def out() -> pa.RecordBatch:
            every = np.concatenate(ids)
            row = [[part], [seq], [first], [len(every)], [len(who)], [pack(every, who, lengths, mode)]]
            types = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(row, types, strict=True)], ["part", "seq", "first", "n_ids", "n_docs", "content"])

        held = 0
        for batch in batches:
            coder = coder or SegmentTokenizer(*sent.value)
            for doc, text in zip(batch.column(0).to_pylist(), coder.encode(batch.column(1)), strict=True):
                ids += [text, tail]
                who.append(doc)
                lengths.append(len(text) + 1)
                held += lengths[-1]
                if held >= file_ids:
                    yield out()
                    seq, first, held = seq + 1, first + held, 0
                    ids, who, lengths = [], [], []
        if who:
            yield out()
        hand_back()

    return Stored(dealt.mapInArrow(run, FILES), "planes")


def read_files(files: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the files; start counts all ids before it."""
    base, bases = 0, {}
    for r in files.groupBy("part").agg(F.sum("n_ids").alias("n")).orderBy("part").collect():  # one row per written part
        bases[r.part] = base
        base += r.n

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, first, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                file = PlaneFile(content.as_py())
                ids = memoryview(file.ids().tobytes())
                ends = np.cumsum(file.lengths)
                starts = ends - file.lengths
                crc = [zlib.crc32(ids[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
                doc = pa.array(file.docs, mask=file.docs == np.iinfo(np.int64).min)
                yield pa.RecordBatch.from_arrays([doc, pa.array(starts + bases[part] + first), pa.array(file.lengths), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return files.select("part", "first", "content").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def export(files: DataFrame, folder: str) -> int:
    """Write the files to a folder of this machine as part-seq.planes; gives their number."""
    os.makedirs(folder, exist_ok=True)
    n = 0
    for r in files.select("part", "seq", "content").orderBy("part", "seq").toLocalIterator():
        with open(f"{folder}/{r.part:06d}-{r.seq:06d}.planes", "wb") as f:
            f.write(r.content)
        n += 1
    return n
