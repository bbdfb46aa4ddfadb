"""Near-duplicate vectors by a forest of random-projection trees with spill.

Each tree halves its rows again and again along a random direction (one per tree and depth) at the median of a bounded
sample of the node's rows; rows within a margin of the cut go to both sides. A leaf's rows are compared with one
another by cosine in double precision, a pair only in the first leaf, by tree and number, that holds both; so each
link is counted once and no list of all pairs is made. Links become components within the leaf, and the leaves' links
join over the forest.

Growing is distributed: each round routes all rows through the trees so far, counts every leaf exactly, and splits the
overfull ones (``LEAF`` rows) on ``SAMPLE`` of their rows. A node whose rows mostly lie in the margin can't be split;
it is compared in blocks of ``BLOCK`` rows, each pair of blocks on its own. Only split points come to the driver and
go to the executors: about 2 rows / LEAF per tree, and never more than ``CUTS``, for leaves grow beyond that.

Defined results: rows are compared only when labels and lengths are equal and labels not null; null, empty, zero and
non-finite vectors link with nothing; equal vectors of a label are one node with a count; rows with a null id get no
links and a null component; rows that repeat an id are vectors of their own, told apart by vector and label; an empty
table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import Stored, cut, small
from .common import hand_back, only
from .components import components, numbered

TREES = 5
LEAF = 48
#: Rows of a block where a node can't be split.
BLOCK = 1000
#: Rows of a node that its split is fitted on, at most about.
SAMPLE = 16_000
#: Most split points of the forest, about: what is sent to the executors is bounded by it.
CUTS = 2_000_000
#: Half the margin, in standard deviations of a linked pair's distance along a direction.
SPILL = 0.5
DEPTH = 48
#: A split is given up if it sends more than this many rows on for each row.
WASTE = 1.25


def directions(dim: int, trees: int) -> np.ndarray:
    r = np.random.default_rng(11 + dim).standard_normal((trees, DEPTH, dim))
    return r / np.linalg.norm(r, axis=2, keepdims=True)


@dataclass
class Forest:
    """Split points by (tree, group, node); a node that is in no table is a leaf. Nodes count from 1, children 2n and 2n + 1."""

    margin: float
    trees: int
    cuts: dict[tuple[int, str], tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)
    stuck: set[tuple[int, str, int]] = field(default_factory=set)

    def add(self, found: list[tuple[int, str, int, float]]) -> None:
        new: dict[tuple[int, str], list] = {}
        for tree, group, node, at in found:
            if at is None or np.isnan(at):
                self.stuck.add((tree, group, node))
            else:
                new.setdefault((tree, group), []).append((node, at))
        for key, more in new.items():
            nodes, ats = self.cuts.get(key, (np.empty(0, np.int64), np.empty(0)))
            nodes, ats = np.append(nodes, [n for n, _ in more]), np.append(ats, [a for _, a in more])
            order = np.argsort(nodes)
            self.cuts[key] = nodes[order], ats[order]

    def route(self, tree: int, group: str, x: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf) for every leaf that a row reaches."""
        row, node = np.arange(len(x)), np.ones(len(x), np.int64)
        nodes, ats = self.cuts.get((tree, group), (np.empty(0, np.int64), np.empty(0)))
        if not len(nodes):
            return row, node
        p = x @ r[tree].T
        done_row, done_node = [], []
        for depth in range(DEPTH):
            at = np.minimum(np.searchsorted(nodes, node), len(nodes) - 1)
            inner = nodes[at] == node
            done_row.append(row[~inner])
            done_node.append(node[~inner])
            row, node, at = row[inner], node[inner], ats[at[inner]]
            if not len(row):
                break
            d = p[row, depth] - at
            left, right = d <= self.margin, d > -self.margin
            row, node = np.concatenate((row[left], row[right])), np.concatenate((2 * node[left], 2 * node[right] + 1))
        done_row.append(row)
        done_node.append(node)
        return np.concatenate(done_row), np.concatenate(done_node)


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def vectors(rows: DataFrame, kind: str) -> DataFrame:
    """(id, grp, vec) of all rows: vec holds the components' bytes, null where the row can't link; grp is label and length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            groups, out = [], []
            for i, label, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                group = data = None
                if i is not None and label is not None and v.is_valid and len(v.values) and not v.values.null_count:
                    x = v.values.to_numpy(zero_copy_only=False).astype(kind)
                    with np.errstate(over="ignore"):
                        n = float(np.linalg.norm(x.astype(float)))
                    if np.isfinite(n) and n > 0 and np.isfinite(x).all():
                        group, data = f"{label}|{len(x)}", (x + 0.0).tobytes()  # minus zero equals zero
                groups.append(group)
                out.append(data)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(groups, pa.string()), pa.array(out, pa.binary())], ["id", "grp", "vec"])

    return rows.mapInArrow(run, "id long, grp string, vec binary")


def leaves(nodes: DataFrame, forest: Forest, kind: str) -> DataFrame:
    """(tree, grp, node, id, n, vec, all) per leaf of each row; ``all`` numbers all of its leaves, tree by tree."""
    trees, sent = forest.trees, nodes.sparkSession.sparkContext.broadcast(forest)  # bounded by CUTS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = sent.value
        dirs: dict[int, np.ndarray] = {}
        for batch in batches:
            groups = np.array(batch.column(1).to_pylist(), object)
            vec = np.array([*batch.column(3).to_pylist(), None], object)[:-1]
            for g in sorted(set(groups)):
                own = np.flatnonzero(groups == g)
                x = unit(np.frombuffer(b"".join(vec[own]), kind).reshape(len(own), -1).astype(float))
                dim = x.shape[1]
                if dim not in dirs:
                    dirs[dim] = directions(dim, trees)
                rows, nodes_, tree = [], [], []
                for t in range(trees):
                    r, n = forest.route(t, g, x, dirs[dim])
                    rows.append(r)
                    nodes_.append(n)
                    tree.append(np.full(len(r), t))
                row, node, tree = np.concatenate(rows), np.concatenate(nodes_), np.concatenate(tree)
                order = np.lexsort((node, tree, row))
                row, node, tree = row[order], node[order], tree[order]
                code = node * trees + tree
                starts = np.searchsorted(row, np.arange(len(own) + 1))
                every = pa.ListArray.from_arrays(pa.array(starts, pa.int32()), pa.array(code))
                take = pa.array(row)
                at = pa.array(own[row])
                yield pa.RecordBatch.from_arrays([pa.array(tree.astype(np.int32)), batch.column(1).take(at), pa.array(node), batch.column(0).take(at), batch.column(2).take(at), batch.column(3).take(at), every.take(take)], ["tree", "grp", "node", "id", "n", "vec", "all"])

    return nodes.select("id", "grp", "n", "vec").mapInArrow(run, "tree int, grp string, node long, id long, n long, vec binary, all array<long>")


def grow(nodes: DataFrame, forest: Forest, kind: str, leaf: int, sample: int) -> dict[tuple[int, str, int], int]:
    """Split until every leaf that can be split is small enough; gives the sizes of the overfull leaves that can't be."""
    spark, margin, trees = nodes.sparkSession, forest.margin, forest.trees
    while True:
        sizes = leaves(nodes, forest, kind).groupBy("tree", "grp", "node").count().where(F.col("count") > leaf)
        over = {(r.tree, r.grp, r.node): r["count"] for r in sizes.collect()}  # fewer than rows / leaf per tree
        todo = [(t, g, n, c) for (t, g, n), c in over.items() if (t, g, n) not in forest.stuck and n < 1 << (DEPTH - 1)]
        if not todo:
            return over
        wanted = spark.createDataFrame([(t, g, n, min(1.0, sample / c), c) for t, g, n, c in todo], "tree int, grp string, node long, share double, size long")
        u = F.pmod(F.xxhash64("id", "tree"), F.lit(1 << 30)) / float(1 << 30)
        drawn = leaves(nodes, forest, kind).join(small(wanted), ["tree", "grp", "node"]).where(u < F.col("share")).select("tree", "grp", "node", "size", "vec")

        def fit(pdf: pd.DataFrame) -> pd.DataFrame:
            tree, group, top, size = int(pdf["tree"].iloc[0]), pdf["grp"].iloc[0], int(pdf["node"].iloc[0]), int(pdf["size"].iloc[0])
            x = unit(np.frombuffer(b"".join(pdf["vec"]), kind).reshape(len(pdf), -1).astype(float))
            p = x @ directions(x.shape[1], trees)[tree].T
            out, queue = [], [(top, np.arange(len(x)))]
            per = size / len(x)
            while queue:
                node, rows = queue.pop()
                depth = node.bit_length() - 1
                if len(rows) * per <= leaf or depth >= DEPTH - 1 or (node != top and len(rows) < 200 and size > len(x)):
                    continue
                at = float(np.median(p[rows, depth]))
                d = p[rows, depth] - at
                left, right = rows[d <= margin], rows[d > -margin]
                if len(left) + len(right) > WASTE * len(rows) or len(rows) < 8:
                    out.append((tree, group, node, float("nan")))
                    continue
                out.append((tree, group, node, at))
                queue += [(2 * node, left), (2 * node + 1, right)]
            return pd.DataFrame(out, columns=["tree", "grp", "node", "at"])

        found = drawn.groupBy("tree", "grp", "node").applyInPandas(fit, "tree int, grp string, node long, at double").collect()
        forest.add([(r.tree, r.grp, r.node, r.at) for r in found])
        seen = {(r.tree, r.grp, r.node) for r in found}
        forest.stuck.update((t, g, n) for t, g, n, _ in todo if (t, g, n) not in seen)


def runs(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.RecordBatch]:
    """Rows sorted by the first ``keys`` columns as one batch for each run of equal keys."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        new = np.zeros(batch.num_rows, bool)
        for c in range(keys):
            x = batch.column(c).to_numpy(zero_copy_only=False)
            new[1:] |= x[1:] != x[:-1]
        new[0] = not held or any(held[-1].column(c)[-1] != batch.column(c)[0] for c in range(keys))
        at = [*np.flatnonzero(new).tolist(), batch.num_rows]
        if held and at[0]:
            held.append(batch.slice(0, at[0]))
        for lo, hi in zip(at, at[1:], strict=False):
            if held:
                yield pa.concat_batches(held)
            held = [batch.slice(lo, hi - lo)]
    if held:
        yield pa.concat_batches(held)


def linked(group: pa.RecordBatch, least: float, kind: str, trees: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, links, roots) of the rows of one leaf that link: see ``compare``."""
    mine, node, i, j = (group.column(c)[0].as_py() for c in ("tree", "node", "i", "j"))
    ids, count, block = (group.column(c).to_numpy() for c in ("id", "n", "block"))
    x = np.frombuffer(b"".join(group.column("vec").to_pylist()), kind).reshape(len(ids), -1).astype(float)
    norm = np.linalg.norm(x, axis=1)
    hit = np.empty((len(ids), len(ids)), bool)
    for lo in range(0, len(ids), 512):
        part = slice(lo, lo + 512)
        hit[part] = (x[part] @ x.T) / (norm[part, None] * norm[None, :]) >= least
    np.fill_diagonal(hit, False)
    if i != j:
        hit &= block[:, None] != block[None, :]
    some = np.flatnonzero(hit.any(1))
    hit = hit[np.ix_(some, some)]
    label = ids[some]
    while len(some):
        least_label = np.minimum(label, np.where(hit, label[None, :], label[:, None]).min(1))
        if (least_label == label).all():
            break
        label = least_label
    # A pair counts only in the first leaf that holds both: of an earlier tree, or an earlier number in this tree.
    lists = [np.array(a) for a in group.column("all").take(pa.array(some)).to_pylist()]
    flat = np.concatenate([*lists, np.empty(0, np.int64)]).astype(np.int64)
    row = np.repeat(np.arange(len(some)), [len(a) for a in lists])
    tree = flat % trees
    before = (tree < mine) | ((tree == mine) & (flat < node * trees + mine))
    codes, at = np.unique(flat[before], return_inverse=True)
    if len(codes):
        held = np.zeros((len(some), len(codes)), np.float32)
        held[row[before], at] = 1
        hit &= (held @ held.T) == 0
    return ids[some], hit @ count[some], label


def compare(leaf_rows: DataFrame, least: float, kind: str, trees: int) -> DataFrame:
    """(id, links, root) by leaf (tree, node, grp, i, j): links first found in that leaf, weighted by copies, and the smallest id linked within it."""
    keys = ["tree", "node", "i", "j", "grp"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in runs(batches, len(keys)):
            ids, links, roots = linked(group, least, kind, trees)
            if len(ids):
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(links.astype(np.int64)), pa.array(roots)], ["id", "links", "root"])
        hand_back()

    dealt = leaf_rows.select(*keys, "id", "n", "vec", "all", "block").repartition(*keys).sortWithinPartitions(*keys)
    return dealt.mapInArrow(run, "id long, links long, root long")


def near_vectors(table: DataFrame, least: float = 0.98, trees: int = TREES, leaf: int = LEAF, sample: int = SAMPLE, block: int = BLOCK, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row."""
    rows = only(table, id=id_col, label=label_col, vec=vec_col).withColumn("id", F.col("id").cast("long"))
    kind = "<f4" if dict(rows.dtypes)["vec"] == "array<float>" else "<f8"
    if kind == "<f8":
        rows = rows.withColumn("vec", F.col("vec").cast("array<double>"))
    every = Stored(vectors(rows, kind).withColumn("key", F.sha2(F.concat(F.col("vec"), F.col("grp").cast("binary")), 256)), "vectors")
    usable = every.df.where("key is not null")
    classes = Stored(numbered(usable.groupBy("key").agg(F.min("id").alias("id"), F.count("*").alias("n"))), "vector-classes")
    bare = usable.select(F.col("id").alias("_id"), F.col("key").alias("_k"), "grp", "vec")
    met = classes.df.join(bare, (F.col("id") == F.col("_id")) & (F.col("key") == F.col("_k")))
    nodes = Stored(met.select(F.col("node").alias("id"), "grp", "n", "vec").dropDuplicates(["id"]), "vector-nodes")
    many, width = nodes.df.agg(F.count("*"), F.max(F.octet_length("vec"))).first()
    leaf = max(leaf, -(-2 * trees * many // CUTS))
    margin = SPILL * float(np.sqrt(2 - 2 * least) / np.sqrt((width or 4) / int(kind[2])))
    forest = Forest(margin, trees)
    over = grow(nodes.df, forest, kind, leaf, sample)
    spark = table.sparkSession
    blocks = spark.createDataFrame([(t, g, n, -(-c // block)) for (t, g, n), c in over.items()], "tree int, grp string, node long, parts int")
    dealt = (
        leaves(nodes.df, forest, kind)
        .join(small(blocks), ["tree", "grp", "node"], "left")
        .withColumn("parts", F.coalesce("parts", F.lit(1)))
        .withColumn("block", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        .select("tree", "grp", "node", "id", "n", "vec", "all", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))
    )
    found = Stored(compare(dealt, least, kind, trees), "vector-links")
    nodes.drop()
    links = found.df.groupBy("id").agg(F.sum("links").alias("links"))
    roots = cut(components(found.df.select(F.col("id").alias("a"), F.col("root").alias("b"))))
    done = (
        classes.df.select("key", F.col("id").alias("own"), F.col("node").alias("id"), "n")
        .join(links, "id", "left")
        .join(roots.select(F.col("v").alias("id"), "p"), "id", "left")
        .select(F.col("key").alias("_k"), (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), "own", F.coalesce("p", "id").alias("root"))
    )
    # A root may be a number that is no id: the component has its vectors' smallest id.
    first = done.groupBy("root").agg(F.min("own").alias("comp"))
    done = done.join(first, "root").drop("root")
    said = every.df.select("id", "key").join(done, F.col("key") == F.col("_k"), "left")
    component = F.coalesce("comp", "id")
    return said.select(F.col("id").alias("vec_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("id"), F.lit(True)).alias("kept"))


ORACLE = """
WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS x FROM embeddings),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND len(a.x) = len(b.x) AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.x, b.x) >= 0.98),
c(vec_id, comp) USING KEY (vec_id) AS (SELECT vec_id, vec_id FROM embeddings
  UNION (SELECT b, m FROM (SELECT l.b, min(c.comp) AS m FROM c JOIN l ON l.a = c.vec_id GROUP BY 1) t WHERE m < (SELECT r.comp FROM recurring.c r WHERE r.vec_id = t.b)))
SELECT c.vec_id, coalesce(n, 0) AS n_links, comp AS component_id, c.vec_id = comp AS kept FROM c LEFT JOIN (SELECT a, count(*) AS n FROM l GROUP BY 1) q ON q.a = c.vec_id
"""
