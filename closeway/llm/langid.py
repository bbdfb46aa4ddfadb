"""Language identification by rank-order profiles of character n-grams.

A profile lists the most frequent n-grams (one to three letters of one word, with a blank at either end) of a
language by rank. A document's own ranks are compared with each profile: an n-gram adds the distance of its two ranks,
one that the profile lacks adds the profile's length, and the least sum wins.

An n-gram is packed into one long of up to three code points, so counting is sorting; only letters count, in lower
case. Training counts all n-grams of all training texts: summed per partition, then per (language, n-gram).

Defined results: a null text or one without a letter gets ``und`` and score 0, as does everything if nothing was
learned; ties go to the language that sorts first; texts are read whole at any length; an empty table gives no rows.
The score is 1 minus the mean distance of the best profile over the profile's length.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import Stored
from .common import hand_back, only

UNKNOWN = "und"
#: n-grams in a profile, of a language and of a document.
RANKS = 400
#: Distinct (language, n-gram) counts a partition holds before it passes them on.
HELD = 2_000_000
#: Texts whose counts are gathered before they are summed up.
GATHERED = 256
#: Salted parts a language's n-grams are ranked in before the last ranking.
PARTS = 16
#: Most languages whose profiles are sent to the executors together; more are compared in passes that carry on the best.
LANGUAGES = 256
BLANK = 32


@lru_cache(maxsize=1)
def letters() -> np.ndarray:
    """By code point: the lower-case letter, or a blank for what is no letter."""
    out = np.full(0x110000, BLANK, np.int64)
    for c in range(0x110000):
        ch = chr(c)
        if ch.isalpha():
            low = ch.lower()
            out[c] = ord(low) if len(low) == 1 else c
    return out


def grams(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(packed n-grams ascending, counts) of a whole text."""
    none = np.empty(0, np.int64), np.empty(0, np.int64)
    if not text:
        return none
    s = letters()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")]
    gap = s == BLANK
    s = s[~gap | ~np.concatenate(([True], gap[:-1]))]
    s = np.concatenate(([BLANK], s, [BLANK])) if len(s) and s[0] != BLANK else np.concatenate((s, [BLANK]))
    if len(s) > 1 and s[-2] == BLANK:
        s = s[:-1]
    if len(s) < 3:
        return none
    two = s[:-1] << 21 | s[1:]
    three = two[:-1] << 21 | s[2:]
    every = np.concatenate((s[s != BLANK], two, three[s[1:-1] != BLANK]))
    every.sort()
    first = np.flatnonzero(np.concatenate(([True], every[1:] != every[:-1])))
    return every[first], np.diff(np.append(first, len(every)))


def summed(codes: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    code, at = np.unique(np.concatenate(codes), return_inverse=True)
    return code, np.bincount(at, weights=np.concatenate(counts), minlength=len(code)).astype(np.int64)


def gram_counts(texts: DataFrame) -> DataFrame:
    """(lang, gram, n) over all rows of (lang, text), null languages left out."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, tuple[np.ndarray, np.ndarray]] = {}

        def out() -> Iterator[pa.RecordBatch]:
            for lang, (code, n) in held.items():
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(code), pa.string()), pa.array(code), pa.array(n)], ["lang", "gram", "n"])
            held.clear()

        for batch in batches:
            for lo in range(0, batch.num_rows, GATHERED):
                some = batch.slice(lo, GATHERED)
                new: dict[str, list] = defaultdict(list)
                for lang, text in zip(some.column(0).to_pylist(), some.column(1), strict=True):
                    new[lang].append(grams(text.as_py()))
                for lang, found in new.items():
                    found += [held[lang]] if lang in held else []
                    held[lang] = summed([x for x, _ in found], [x for _, x in found])
                if sum(len(x) for x, _ in held.values()) > HELD:
                    yield from out()
        yield from out()
        hand_back()

    bare = texts.where("lang is not null").select("lang", "text")
    return bare.mapInArrow(count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))


@dataclass
class Profiles:
    langs: list[str]
    grams: np.ndarray  # all profiles' n-grams, ascending
    ranks: np.ndarray  # language x n-gram: the rank, or the profile's length where absent
    size: int


def profiles_of(ranked: dict[str, list[int]], size: int) -> Profiles:
    every = np.array(sorted({g for x in ranked.values() for g in x}), np.int64)
    ranks = np.full((len(ranked), len(every)), size, np.int32)
    for i, x in enumerate(ranked.values()):
        ranks[i, np.searchsorted(every, x)] = np.arange(len(x))
    return Profiles(list(ranked), every, ranks, size)


def learn_all(texts: DataFrame, size: int = RANKS, most: int = LANGUAGES) -> Iterator[Profiles]:
    """Profiles from (lang, text), of ``most`` languages at a time in their order; the driver holds those and no more."""
    part = Window.partitionBy("lang", F.pmod(F.xxhash64("gram"), F.lit(PARTS))).orderBy(F.desc("n"), "gram")
    top = gram_counts(texts).withColumn("_r", F.row_number().over(part)).where(F.col("_r") <= size).select("lang", "gram", "n")
    ranked: dict[str, list[int]] = {}
    for lang, rows in groupby(top.orderBy("lang").toLocalIterator(), lambda r: r.lang):
        if len(ranked) == most:
            yield profiles_of(ranked, size)
            ranked = {}
        ranked[lang] = [g for _, g in sorted((-r.n, r.gram) for r in rows)[:size]]  # PARTS * size rows
    yield profiles_of(ranked, size)


def learn(texts: DataFrame, size: int = RANKS, most: int = LANGUAGES) -> Profiles | list[Profiles]:
    """Profiles from (lang, text): one set, or several where there are more than ``most`` languages."""
    every = list(learn_all(texts, size, most))
    return every[0] if len(every) == 1 else every


def judge(text: str | None, p: Profiles) -> tuple[str, float]:
    code, n = grams(text)
    if not len(code) or not p.langs:
        return UNKNOWN, 0.0
    top = code[np.argsort(-n, kind="stable")[: p.size]]
    at = np.minimum(np.searchsorted(p.grams, top), len(p.grams) - 1)
    known = p.grams[at] == top
    own = np.arange(len(top), dtype=np.int32)[known]
    far = np.abs(p.ranks[:, at[known]] - own)
    far[p.ranks[:, at[known]] == p.size] = p.size
    total = far.sum(1) + p.size * (len(top) - len(own))
    best = int(total.argmin())
    return p.langs[best], float(1 - total[best] / (p.size * len(top)))


def predict(docs: DataFrame, profiles: Profiles | list[Profiles], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) of every row; several sets of profiles are a stored pass each."""
    at = only(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long"), "text", F.lit(UNKNOWN).alias("lang_pred"), F.lit(0.0).alias("score"))

    def one(rows: DataFrame, p: Profiles) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                said = []
                for text, lang, score in zip(batch.column(1), batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                    new = judge(text.as_py(), p)
                    said.append(new if new[0] != UNKNOWN and (lang == UNKNOWN or new[1] > score) else (lang, score))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([x for x, _ in said], pa.string()), pa.array([x for _, x in said], pa.float64())], ["doc_id", "text", "lang_pred", "score"])

        return rows.mapInArrow(run, "doc_id long, text string, lang_pred string, score double")

    for i, p in enumerate(profiles if isinstance(profiles, list) else [profiles]):
        at = one(Stored(at, "languages").df if i else at, p)
    return at.drop("text")


def recognised(docs: DataFrame, profiles: Profiles | list[Profiles], text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose text has a letter: the nearest profile recognises it at any distance.

    Where nothing was learned no text is judged, and those with a letter stay as well.
    """
    place = docs.columns.index(text_col)
    profiles = profiles[0] if isinstance(profiles, list) else profiles  # any set recognises a text with a letter

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = (t.as_py() for t in batch.column(place))
            keep = [judge(t, profiles)[0] != UNKNOWN if profiles.langs else len(grams(t)[0]) > 0 for t in texts]
            yield batch.filter(pa.array(keep, pa.bool_()))
        hand_back()

    return docs.mapInArrow(run, docs.schema)
