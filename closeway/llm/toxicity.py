"""Toxicity: a linear classifier of character n-grams scaled by naive Bayes log-count ratios.

Features are the character n-grams of the lower-cased text, present or absent, hashed into buckets. Over all labelled
training rows each bucket's documents are counted per class; the log ratio of the smoothed shares scales it. The
buckets that tell most (largest log-likelihood ratio against equal shares, and at least ``TELLS``) are kept, and a logistic regression with an
L2 penalty is fitted to the scaled features on a bounded sample of labelled rows (``SAMPLE`` per class, drawn by the hash
of the id). The sample only bounds that last fit: ratios and selection count every labelled row.

Defined results: null and empty texts have no features and get the score of the intercept; rows with null labels teach
nothing; with no labels of one class the score is that of the other's prior; texts are read whole; repeated rows each
get a row.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import Stored
from .common import only

LENGTHS = (3, 4, 5)
BUCKETS = 1 << 20
FEATURES = 4096
SAMPLE = 6_000
#: A bucket needs so many labelled documents, and this log-likelihood ratio, to be a feature.
LEAST = 5
TELLS = 25.0
ALPHA = 1.0
MULT = np.uint64(0x9E3779B97F4A7C15)
MIX = np.uint64(0xD6E8FEB86659FD93)


def buckets(text: str | None) -> np.ndarray:
    """Buckets of the text's n-grams, with repeats."""
    if not text:
        return np.empty(0, np.int64)
    s = np.frombuffer((" " + text.lower() + " ").encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    out, h = [], s + np.uint64(1)
    for n in range(2, max(LENGTHS) + 1):
        if len(s) < n:
            break
        h = h[:-1] * MULT + s[n - 1 :] + np.uint64(1)
        if n in LENGTHS:
            x = (h ^ (h >> np.uint64(29))) * MIX
            out.append((x >> np.uint64(44)).astype(np.int64))
    return np.concatenate(out) if out else np.empty(0, np.int64)


def present(text: str | None) -> np.ndarray:
    mark = np.zeros(BUCKETS, bool)
    mark[buckets(text)] = True
    return np.flatnonzero(mark)


def bucket_counts(labelled: DataFrame) -> DataFrame:
    """(bucket, n0, n1): documents of each class that have the bucket, over all rows of (text, label); bucket -1 counts the documents."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, docs, some = np.zeros((2, BUCKETS), np.int64), [0, 0], False
        for batch in batches:
            for text, label in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                some = True
                docs[label] += 1
                b = buckets(text.as_py())
                b.sort()
                n[label, b[np.concatenate(([True], b[1:] != b[:-1]))] if len(b) else b] += 1
        if some:
            at = np.flatnonzero(n.sum(0))
            yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(n[0, at], docs[0])), pa.array(np.append(n[1, at], docs[1]))], ["bucket", "n0", "n1"])

    return labelled.mapInArrow(count, "bucket long, n0 long, n1 long").groupBy("bucket").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"))


@dataclass
class Model:
    where: np.ndarray  # by bucket: the feature's place, or -1
    weight: np.ndarray  # ratio times coefficient
    bias: float

    def score(self, text: str | None) -> float:
        at = self.where[buckets(text)]
        at = np.unique(at[at >= 0])
        return float(1 / (1 + np.exp(-np.clip(self.bias + self.weight[at].sum(), -60, 60))))


def fit_logistic(rows: np.ndarray, cols: np.ndarray, scale: np.ndarray, y: np.ndarray, share: float, l2: float = 1.0, rounds: int = 40) -> tuple[np.ndarray, float]:
    """Coefficients of the scaled sparse rows at the optimum, by Newton's steps with conjugate gradients; ``share`` is the positive class's true share."""
    n, m = len(y), len(scale)
    own = y.mean()
    weight = np.where(y > 0, share / own, (1 - share) / (1 - own)) / n
    value, decay = scale[cols], np.append(np.full(m, l2 / n), 1e-9)
    down = lambda t: np.bincount(rows, weights=value * t[:-1][cols], minlength=n) + t[-1]
    up = lambda r: np.append(np.bincount(cols, weights=value * r[rows], minlength=m), r.sum())
    loss = lambda z, t: float((weight * (np.logaddexp(0, z) - y * z)).sum() + 0.5 * (decay * t * t).sum())
    t = np.append(np.zeros(m), np.log(share / (1 - share)))
    z = down(t)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z, -60, 60)))
        g = up(weight * (p - y)) + decay * t
        size = float(np.linalg.norm(g))
        if size < 1e-7:
            break
        h = weight * p * (1 - p)
        diagonal = np.append(np.bincount(cols, weights=value * value * h[rows], minlength=m), h.sum()) + decay
        d, r = np.zeros(m + 1), -g
        q = r / diagonal
        s, rq = q.copy(), float(r @ q)
        for _ in range(60):
            hs = up(h * down(s)) + decay * s
            a = rq / float(s @ hs)
            d, r = d + a * s, r - a * hs
            if float(np.linalg.norm(r)) < min(0.1, size) * size:
                break
            q = r / diagonal
            rq, old = float(r @ q), rq
            s = q + rq / old * s
        before, step, dz = loss(z, t), 1.0, down(d)
        while step > 1e-4 and loss(z + step * dz, t + step * d) > before:
            step /= 2
        t, z = t + step * d, z + step * dz
    return t[:-1], float(t[-1])


def learn(labelled: DataFrame, features: int = FEATURES, sample: int = SAMPLE) -> Model:
    """Fit on rows of (id, text, label)."""
    rows = labelled.where("label in (0, 1)").select("id", F.col("label").cast("int").alias("label"), "text")
    counts = Stored(bucket_counts(rows.select("text", "label")), "buckets").df  # read twice
    docs = {r.bucket: (r.n0, r.n1) for r in counts.where("bucket = -1").collect()}.get(-1, (0, 0))
    where = np.full(BUCKETS, -1, np.int32)
    if not docs[0] or not docs[1]:
        return Model(where, np.zeros(1), 30.0 if docs[1] else -30.0)
    ratio = F.log((F.col("n1") + ALPHA) / (docs[1] + 2 * ALPHA)) - F.log((F.col("n0") + ALPHA) / (docs[0] + 2 * ALPHA))
    seen, both = F.col("n0") + F.col("n1"), docs[0] + docs[1]
    tells = 2 * sum(F.when(F.col(c) > 0, F.col(c) * F.log(F.col(c) * (both / docs[i]) / seen)).otherwise(0.0) for i, c in enumerate(("n0", "n1")))
    best = counts.where(f"bucket >= 0 and n0 + n1 >= {LEAST}").select("bucket", ratio.alias("r"), tells.alias("tells")).where(F.col("tells") >= TELLS)
    kept = best.orderBy(F.desc("tells"), "bucket").limit(features).collect()
    if not kept:
        return Model(where, np.zeros(1), float(np.log(docs[1] / docs[0])))
    where[[r.bucket for r in kept]] = np.arange(len(kept))
    scale = np.array([r.r for r in kept])

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [where[buckets(t.as_py())] for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([np.unique(x[x >= 0]).astype(np.int32) for x in found], pa.list_(pa.int32())), batch.column(2)], ["label", "at", "draw"])

    ys, ats = [], []
    draw = F.pmod(F.xxhash64("id"), F.lit(1 << 40))
    for label in (0, 1):
        # The hash bound keeps about sample * 1.1 + 100 rows before they are encoded; the limit makes the bound hard.
        share = min(1.0, (1.1 * sample + 100) / docs[label])
        drawn = rows.where((F.col("label") == label) & (draw < int(share * (1 << 40)))).select("label", "text", draw.alias("draw"))
        for r in drawn.mapInArrow(encode, "label int, at array<int>, draw long").orderBy("draw", "at").limit(sample).toLocalIterator():
            ys.append(r.label)
            ats.append(np.array(r.at, np.int32))
    row = np.repeat(np.arange(len(ats)), [len(x) for x in ats])
    coef, bias = fit_logistic(row, np.concatenate(ats), scale, np.array(ys, float), docs[1] / sum(docs))
    return Model(where, coef * scale, bias)


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score, predicted) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s = np.array([model.score(t.as_py()) for t in batch.column(1)], float)
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], ["doc_id", "score", "predicted"])

    return only(docs, doc_id=id_col, text=text_col).mapInArrow(run, "doc_id long, score double, predicted int")
