"""Near-duplicate texts by sketches of exponentially spaced, truncated minima.

A text's set holds its distinct 5-word shingles. Register i of its sketch is floor(1 - log_b(min h_i / a)), cut to
[0, q + 1], where h_i(x) is an exponential variate made from the shingle's hash; sketches of two sets merge to their
union's by the maximum of registers, and two sets share a register's value with a probability close to their
similarity.

1. Texts with equal sets form a class, stood for by its smallest id; only these go on.
2. Bands of registers are hashed; representatives with a common band value share a bucket. Buckets of one vanish.
3. A bucket's pairs are not spelled out. First each member meets the bucket's smallest id, then another leader; links
   found join components. Only buckets that still hold several components are compared in full, block by block, and
   only rows of different components that may be linked; their sets are brought together and counted at once.
4. A met pair's similarity is estimated by maximum likelihood from the numbers of registers that are greater, smaller
   and equal, given both set sizes. Pairs whose estimate lies ``SLACK`` standard errors under the bound are dropped.
5. The rest are confirmed on the full sets of both texts.

Defined results: null and wordless texts have an empty set, are linked with nothing and kept; fewer words than a
shingle make one shingle of them all; rows with a null id are linked with nothing and have a null component; rows that
repeat an id are told apart by their sets, and of a group's sets with its smallest id the smallest key's is kept.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, StructField, StructType

from ..session import Stored, cut, small
from .common import hand_back, only, text_rows
from .components import components, numbered

WORDS = 5
#: Sketch parameters: base, rate, largest value, length.
BASE, RATE, TOP = 1.001, 20.0, (1 << 16) - 2
REGISTERS = 100
#: Largest share of pairs right at the bound that may have no band in common.
MISSED = 1e-5
SLACK = 5.0
#: Members of a bucket compared in one block.
BLOCK = 1500
#: Shingles hashed at a time for one text.
CHUNK = 8192
#: Ids that are sent to the executors to find their texts; more are joined by shuffling.
SENT_IDS = 2_000_000

MIX1, MIX2, POLY = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53), np.uint64(0x9E3779B97F4A7C15)


@lru_cache(maxsize=1)
def multipliers() -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20)
    return rng.integers(0, 1 << 63, REGISTERS, dtype=np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 1 << 63, REGISTERS, dtype=np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * MIX1
    x = (x ^ (x >> np.uint64(33))) * MIX2
    return x ^ (x >> np.uint64(33))


def shingles(text: bytes | None, words: int = WORDS) -> np.ndarray:
    """Ascending 64-bit hashes of the distinct shingles of a whole text."""
    tokens = text.lower().split() if text else []
    if not tokens:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, tokens), np.uint64, len(tokens))
    n = min(words, len(h))
    x = h[: len(h) - n + 1]
    for k in range(1, n):
        x = x * POLY + h[k : len(h) - n + 1 + k]
    return np.unique(mixed(x + np.uint64(n)))


def registers(hashes: np.ndarray) -> np.ndarray:
    """The sketch of a set of hashes, as u16."""
    mul, add = multipliers()
    least = np.full(REGISTERS, np.iinfo(np.uint64).max, np.uint64)
    for lo in range(0, len(hashes), CHUNK):
        part = hashes[lo : lo + CHUNK, None] * mul
        part += add
        np.minimum(least, part.min(0), out=least)
    # The least uniform variate gives the least exponential one: the transformation is monotone.
    u = (least.astype(np.float64) + 1.0) / 2.0**64
    h = -np.log1p(-np.minimum(u, 1 - 2.0**-53)) / RATE
    return np.clip(np.floor(1 - np.log(h) / np.log(BASE)), 0, TOP + 1).astype(np.uint16)


def likeliest(na: np.ndarray, nb: np.ndarray, above: np.ndarray, below: np.ndarray, same: np.ndarray) -> np.ndarray:
    """Maximum-likelihood similarity given set sizes and the numbers of registers above, below and equal."""
    u, v = na / (na + nb), nb / (na + nb)

    def p(x: np.ndarray) -> np.ndarray:
        return -np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / np.log(BASE)

    def fit(j: np.ndarray) -> np.ndarray:
        a, b = p(u - v * j), p(v - u * j)
        return above * np.log(np.maximum(a, 1e-300)) + below * np.log(np.maximum(b, 1e-300)) + same * np.log(np.maximum(1 - a - b, 1e-300))

    lo, hi = np.zeros_like(u), np.minimum(u / v, v / u)
    for _ in range(40):  # the likelihood has one peak
        third = (hi - lo) / 3
        left = fit(lo + third) < fit(hi - third)
        lo, hi = np.where(left, lo + third, lo), np.where(left, hi, hi - third)
    return (lo + hi) / 2


def bound_of(percent: int) -> float:
    j = percent / 100
    return j - SLACK * float(np.sqrt(j * (1 - j) / REGISTERS))


def banding(percent: int) -> tuple[int, int]:
    """(bands, registers in each): the widest bands of which pairs at the bound share one but for ``MISSED``."""
    j = percent / 100
    widths = [w for w in range(1, REGISTERS + 1) if REGISTERS % w == 0 and (1 - j**w) ** (REGISTERS // w) <= MISSED]
    width = max(widths, default=1)
    return REGISTERS // width, width


SKETCH = "doc_id long, n_shingles long, key binary, regs binary"


def sketches(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, key, regs) per row of (doc_id, text); key is null for an empty set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_rows(batches):
            n, key, regs = [], [], []
            for text in texts:
                x = shingles(text)
                n.append(len(x))
                key.append(xxhash.xxh3_128_digest(x.tobytes()) if len(x) else None)
                regs.append(registers(x).tobytes() if len(x) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(key, pa.binary()), pa.array(regs, pa.binary())], ["doc_id", "n_shingles", "key", "regs"])
        hand_back()

    return docs.mapInArrow(run, SKETCH)


def bands(reps: DataFrame, percent: int) -> DataFrame:
    """(h, band, id) per band of each representative; h hashes the band's place and values."""
    many, width = banding(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                r = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint16).reshape(-1, many, width).astype(np.uint64)
                h = np.arange(1, many + 1, dtype=np.uint64)[None, :] * POLY
                for k in range(width):
                    h = mixed(h * POLY + r[:, :, k])
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64).ravel()), pa.array(np.tile(np.arange(many, dtype=np.int32), len(r))), pa.array(np.repeat(batch.column(0).to_numpy(), many))], ["h", "band", "id"])

    return reps.select("id", "regs").mapInArrow(run, "h long, band int, id long")


def likely(pairs: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose estimated similarity does not rule a link out."""
    least = bound_of(percent)
    side = lambda c: reps.select(F.col("id").alias(c), F.col("n").alias(f"n{c}"), F.col("regs").alias(f"r{c}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ra, rb = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint16).reshape(-1, REGISTERS) for c in ("ra", "rb"))
            na, nb = (batch.column(c).to_numpy().astype(float) for c in ("na", "nb"))
            j = likeliest(na, nb, (ra > rb).sum(1), (ra < rb).sum(1), (ra == rb).sum(1))
            ok = pa.array((j >= least) & (100 * np.minimum(na, nb) >= percent * np.maximum(na, nb)))
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(ok), batch.column("b").filter(ok)], ["a", "b"])

    return pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "na", "nb", "ra", "rb").mapInArrow(run, "a long, b long")


def confirmed(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets reach the bound."""
    side = lambda c: texts.select(F.col("id").alias(c), F.col("text").alias(f"t{c}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, mine = None, None
        for batch in batches:
            ok = []
            for a, ta, tb in zip(batch.column(0).to_pylist(), batch.column(2), batch.column(3), strict=True):
                if a != last:
                    last, mine = a, shingles(ta.as_py().encode())
                other = shingles(tb.as_py().encode())
                both = len(np.intersect1d(mine, other, assume_unique=True))
                ok.append(100 * both >= percent * (len(mine) + len(other) - both))
            keep = pa.array(ok, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], ["a", "b"])
        hand_back()

    return pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def _hopeful(regs: np.ndarray, n: np.ndarray, r: int, others: np.ndarray, band: int, percent: int) -> np.ndarray:
    """Of ``others`` those whose first common band with row r is this one and whose estimate reaches the bound."""
    equal = regs[others] == regs[r]
    first = equal.reshape(-1, *banding(percent)).all(2).argmax(1) == band
    others, equal = others[first], equal[first]
    same = equal.sum(1)
    some = same >= (bound_of(percent) - 0.1) * REGISTERS
    others, same = others[some], same[some]
    if not len(others):
        return others
    above = (regs[r] > regs[others]).sum(1)
    return others[likeliest(np.full(len(others), n[r]), n[others], above, REGISTERS - above - same, same) >= bound_of(percent)]


def rest(buckets: DataFrame, reps: DataFrame, texts: DataFrame, percent: int, block: int = BLOCK) -> DataFrame:
    """Links (a, b) between different components of the buckets (h, band, id, comp), block by block.

    A first pass over the sketches finds the rows of each block that some row of another component may be linked with;
    a second one brings those rows' full sets together and counts all their intersections at once. Neither writes pairs:
    the first gives rows, the second at most a spanning set of links.
    """
    parts = F.ceil(F.col("members") / block).cast("int")
    sized = buckets.join(buckets.groupBy("h").agg(F.count("*").alias("members")), "h")
    own = F.pmod(F.xxhash64("id"), parts).cast("int")
    met = (
        sized.join(reps, "id")
        .select("h", "band", "id", "comp", "n", "regs", own.alias("own"), parts.alias("parts"))
        .select("*", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("other"))
        .select("h", "band", "id", "comp", "n", "regs", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))
    )

    def take_part(pdf: pd.DataFrame) -> pd.DataFrame:
        regs = np.frombuffer(b"".join(pdf["regs"]), np.uint16).reshape(-1, REGISTERS)
        n, comp, own, band = pdf["n"].to_numpy(float), pdf["comp"].to_numpy(), pdf["own"].to_numpy(), int(pdf["band"].iloc[0])
        apart = pdf["i"].iloc[0] != pdf["j"].iloc[0]
        mark = np.zeros(len(n), bool)
        # Rows of the largest component meet only the rest, so its own square is never walked.
        most = pd.Series(comp).mode().iloc[0]
        rest_rows = np.flatnonzero(comp != most)
        for r in rest_rows:
            other = (comp != comp[r]) & (100 * np.minimum(n, n[r]) >= percent * np.maximum(n, n[r]))
            if apart:
                other &= own != own[r]
            hit = _hopeful(regs, n, r, np.flatnonzero(other), band, percent)
            if len(hit):
                mark[r] = True
                mark[hit] = True
        return pdf.loc[mark, ["h", "id", "comp", "i", "j"]]

    # The work grows with pairs and not with bytes: a fixed number of parts, which is not merged by size.
    parts_in_all = int(buckets.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = Stored(met.repartition(parts_in_all, "h", "i", "j").groupBy("h", "i", "j").applyInPandas(take_part, "h long, id long, comp long, i int, j int"), "rest-rows")
    with_sets = rows.df.join(texts, "id").repartition(parts_in_all, "h", "i", "j")

    def link(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, comp = pdf["id"].to_numpy(), pdf["comp"].to_numpy()
        sets = [shingles(t.encode()) for t in pdf["text"]]
        size = np.array([len(x) for x in sets])
        shingle, at = np.unique(np.concatenate(sets), return_inverse=True)
        row = np.repeat(np.arange(len(ids)), size)
        shared = np.bincount(at) > 1
        both = np.zeros((len(ids), len(ids)), np.float32)
        order = np.argsort(at, kind="stable")
        at, row = at[order], row[order]
        keep = shared[at]
        at, row = at[keep], row[keep]
        for lo in range(0, len(shingle), 4096):  # exact: counts stay below 2**24
            a, b = np.searchsorted(at, (lo, lo + 4096))
            if b > a:
                held = np.zeros((len(ids), 4096), np.float32)
                held[row[a:b], at[a:b] - lo] = 1
                both += held @ held.T
        union = size[:, None] + size[None, :] - both
        ok = np.triu((100 * both >= percent * union) & (comp[:, None] != comp[None, :]), 1)
        joined: dict[int, int] = {}

        def root(c: int) -> int:
            while joined.get(c, c) != c:
                c = joined[c]
            return c

        out = []
        for r, c in zip(*np.nonzero(ok), strict=True):
            x, y = root(comp[r]), root(comp[c])
            if x != y:
                joined[max(x, y)] = min(x, y)
                out.append((ids[r], ids[c]))
        return pd.DataFrame(out, columns=["a", "b"])

    return with_sets.groupBy("h", "i", "j").applyInPandas(link, "a long, b long").distinct()


def class_texts(rows: DataFrame, classes: DataFrame) -> DataFrame:
    """(id, text): each class's text by its node, from rows of (doc_id, text); of rows that repeat an id, one that has the class's set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_rows(batches):
            key = [xxhash.xxh3_128_digest(shingles(t).tobytes()) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(key, pa.binary())], ["doc_id", "text", "_k"])

    keyed = rows.select("doc_id", "text").where("text is not null").mapInArrow(run, "doc_id long, text string, _k binary")
    return keyed.join(classes, (F.col("id") == F.col("doc_id")) & (F.col("key") == F.col("_k"))).select(F.col("node").alias("id"), "text").dropDuplicates(["id"])


def with_key(docs: DataFrame, text_col: str) -> DataFrame:
    """All rows and columns, and _set_key: the text's set key, null for an empty set."""
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingles(t.encode()) if t else () for t in batch.column(place).to_pylist()]
            keys = [xxhash.xxh3_128_digest(x.tobytes()) if len(x) else None for x in sets]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(keys, pa.binary())], [*batch.schema.names, "_set_key"])

    return docs.mapInArrow(run, StructType([*docs.schema.fields, StructField("_set_key", BinaryType())]))


def _labelled(t: DataFrame, roots: DataFrame | None, column: str = "id") -> DataFrame:
    """t with the component of ``column`` so far."""
    if roots is None:
        return t.withColumn("comp", F.col(column))
    return t.join(roots.select(F.col("v").alias(column), "p"), column, "left").withColumn("comp", F.coalesce("p", column)).drop("p")


class NearDuplicates:
    """The classes of equal sets and the components of linked ones."""

    def __init__(self, docs: DataFrame, percent: int = 85, id_col: str = "doc_id", text_col: str = "text"):
        rows = only(docs, doc_id=id_col, text=text_col).withColumn("doc_id", F.col("doc_id").cast("long"))
        self.sketches = Stored(sketches(rows), "sketches")
        classes = self.sketches.df.where("key is not null and doc_id is not null").groupBy("key").agg(F.min("doc_id").alias("id"))
        self.again = cut(self.sketches.df.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select(F.col("doc_id").alias("_again")))
        self.repeats = not self.again.isEmpty()
        self.classes = Stored(numbered(classes) if self.repeats else classes.withColumn("node", F.col("id")), "classes")
        alone = self.sketches.df.select(F.col("doc_id").alias("id"), F.col("key").alias("_k"), F.col("n_shingles").alias("n"), "regs")
        picked = self.classes.df.join(alone, "id").where("key = _k").select(F.col("node").alias("id"), "n", "regs")
        banded = bands(picked, percent)
        many = banded.groupBy("h").agg(F.min("id").alias("lead"), F.max("id").alias("last"), F.min_by("id", F.xxhash64("id")).alias("second")).where("lead < last")
        buckets = Stored(banded.join(many, "h").select("h", "band", "id", "lead", "second").distinct(), "buckets")
        members = cut(buckets.df.select("id").distinct())
        reps = Stored(picked.join(small(members, SENT_IDS), "id").dropDuplicates(["id"]), "reps")
        named = members.withColumnRenamed("id", "doc_id")
        if self.repeats:
            named = cut(self.classes.df.join(members.withColumnRenamed("id", "node"), "node").select(F.col("id").alias("doc_id")).distinct())
        texts = Stored(class_texts(rows.join(small(named, SENT_IDS), "doc_id"), self.classes.df), "texts")
        links, roots, done = None, None, [buckets, reps, texts]
        for leader in ("lead", "second"):
            labelled = buckets.df.select("h", "id", F.col(leader).alias("with"))
            pairs = labelled.where("id <> with").select(F.least("id", "with").alias("a"), F.greatest("id", "with").alias("b")).distinct()
            if roots is not None:
                pairs = _labelled(_labelled(pairs, roots, "a").withColumnRenamed("comp", "ca"), roots, "b").where("ca <> comp").select("a", "b")
            hopeful = Stored(likely(pairs, reps.df, percent), "likely")
            found = Stored(confirmed(hopeful.df, texts.df, percent), "links")
            done += [hopeful, found]
            links = found.df if links is None else links.unionByName(found.df)
            roots = cut(components(links))
        left = _labelled(buckets.df.select("h", "band", "id"), roots)
        mixed_up = left.groupBy("h").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("h")
        left = cut(left.join(mixed_up, "h"))
        if not left.isEmpty():
            more = Stored(rest(left, reps.df, texts.df, percent), "rest")
            roots = cut(components(links.unionByName(more.df)))
            done.append(more)
        self.roots = roots
        for t in done:  # the components are checkpointed and need none of these any more
            t.drop()

    def marked(self) -> DataFrame:
        """(doc_id, key, n_shingles, component_id, kept) of every row."""
        named = _labelled(self.classes.df, self.roots, "node").select(F.col("key").alias("_k"), "id", "comp")
        if self.repeats:  # a node may be no id: the component has its smallest id, and that id's smallest set
            first = named.groupBy("comp").agg(F.min(F.struct("id", "_k")).alias("first"))
            named = named.join(first, "comp").select("_k", F.col("first.id").alias("comp"), ((F.col("first._k") == F.col("_k")) | (F.col("first.id") != F.col("id"))).alias("own"))
        else:
            named = named.select("_k", "comp", F.lit(True).alias("own"))
        s = self.sketches.df.select("doc_id", "n_shingles", "key")
        linked = s.join(named, F.col("key") == F.col("_k"), "left")
        component = F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "doc_id"))
        kept = F.coalesce((F.col("doc_id") == component) & F.coalesce("own", F.lit(True)), F.lit(True))
        return linked.select("doc_id", "key", "n_shingles", component.alias("component_id"), kept.alias("kept"))

    def result(self) -> DataFrame:
        """(doc_id, n_shingles, component_id, kept) of every row."""
        return self.marked().drop("key")


def deduplicated(docs: DataFrame, percent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group with all its columns: that of the group's smallest id; rows without links all stay.

    Of rows that repeat both id and set, one stays; rows that repeat an id with other sets go or stay by their own set.
    """
    found = NearDuplicates(docs, percent, id_col, text_col)
    gone = found.marked().where("not kept").select(F.col("doc_id").alias("_gone"), "key")
    own = F.col(f"`{id_col}`")
    if not found.repeats:
        return docs.join(small(gone.select("_gone").distinct(), SENT_IDS), own == F.col("_gone"), "left_anti")
    once = docs.join(found.again, own == F.col("_again"), "left_anti").join(small(gone.select("_gone").distinct(), SENT_IDS), own == F.col("_gone"), "left_anti")
    gone_sets = gone.select("_gone", F.col("key").alias("_gone_key")).distinct()
    rows = with_key(docs.join(found.again, own == F.col("_again"), "left_semi"), text_col)
    rows = rows.join(gone_sets, (own == F.col("_gone")) & (F.col("_set_key") == F.col("_gone_key")), "left_anti")
    empty, full = rows.where("_set_key is null").dropDuplicates([id_col, text_col]), rows.where("_set_key is not null").dropDuplicates([id_col, "_set_key"])
    return once.unionByName(empty.unionByName(full).drop("_set_key"))


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[p:p + least(5, len(w)) - 1], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(5, len(w)) + 2)) AS p FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
l AS (SELECT a.doc_id AS a, b.doc_id AS b FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id JOIN n x ON x.doc_id = a.doc_id JOIN n y ON y.doc_id = b.doc_id GROUP BY 1, 2, x.n, y.n HAVING 100 * count(*) >= 85 * (x.n + y.n - count(*))),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
c(doc_id, comp) USING KEY (doc_id) AS (SELECT doc_id, doc_id FROM documents
  UNION (SELECT b, m FROM (SELECT e.b, min(c.comp) AS m FROM c JOIN e ON e.a = c.doc_id GROUP BY 1) t WHERE m < (SELECT r.comp FROM recurring.c r WHERE r.doc_id = t.b)))
SELECT c.doc_id, coalesce(n, 0) AS n_shingles, comp AS component_id, c.doc_id = comp AS kept FROM c LEFT JOIN n ON n.doc_id = c.doc_id
"""
