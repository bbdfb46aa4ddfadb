"""Road graphs: places on the network, shortest paths in two physical forms, discounted costs.

A road graph is two tables: vertices (city_id, vertex_id, x, y) and edges (city_id, edge_id, u, v, <weights>). Roads run
both ways unless ``directed``. Of equally cheap paths the one with fewer hops, then with the smaller predecessor at
each vertex is taken, so paths are unique.
"""

from __future__ import annotations

import heapq
from typing import NamedTuple

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geo import distance
from ..session import ROAD_ROWS, cut, small

#: Sources searched by one task of the local form, at least.
SOURCES = 32
#: Blocks of a city's sources for each core, at most.
WAVES = 2
#: Vertices whose distances bound the rest of a way.
LANDMARKS = 6
#: Cities with more edges than this are searched by rounds over all executors.
LOCAL_EDGES = 4_000_000


class RoadGraph(NamedTuple):
    vertices: DataFrame
    edges: DataFrame
    directed: bool = False


def arcs(g: RoadGraph, weight: str = "len_dm") -> DataFrame:
    """(city_id, a, b, edge_id, w): every way an edge can be driven."""
    out = g.edges.select("city_id", F.col("u").alias("a"), F.col("v").alias("b"), "edge_id", F.col(weight).cast("double").alias("w"))
    return out if g.directed else out.unionByName(out.select("city_id", F.col("b").alias("a"), F.col("a").alias("b"), "edge_id", "w"))


# ---------------------------------------------------------------- places on the network


def snap(points: DataFrame, vertices: DataFrame, key: str = "poi_id", cell: int = 200) -> DataFrame:
    """Adds vertex_id and snap_dist: the nearest vertex, the smaller id on a tie.

    Cells of ``cell`` metres and their neighbours are joined by equality; points without a vertex that is surely the
    nearest (within one cell) are tried again with cells twice as wide, until none is left. A point of a city without
    vertices, or without coordinates, keeps a null vertex.
    """
    inhabited = vertices.select("city_id").distinct()
    todo, done = points.where("x is not null and y is not null").join(F.broadcast(inhabited), "city_id", "left_semi"), None
    c = cell
    while True:
        near = _snap_round(todo, vertices, key, c)
        sure = near.where(F.col("snap_dist") <= c)
        done = sure if done is None else done.unionByName(sure)
        todo = cut(todo.join(sure.select("city_id", key), ["city_id", key], "left_anti"))
        if todo.isEmpty():
            break
        c *= 2
    return points.join(done, ["city_id", key], "left")


def _snap_round(points: DataFrame, vertices: DataFrame, key: str, c: int) -> DataFrame:
    at = lambda x: F.floor(F.col(x) / c).cast("long")
    around = F.sequence(F.lit(-1), F.lit(1))
    p = points.select("city_id", key, F.col("x").alias("px"), F.col("y").alias("py"), F.explode(F.transform(around, lambda i: at("x") + i)).alias("cx"), at("y").alias("_cy"))
    p = p.withColumn("cy", F.explode(F.transform(around, lambda i: F.col("_cy") + i))).drop("_cy")
    v = vertices.select("city_id", "vertex_id", F.col("x").alias("vx"), F.col("y").alias("vy"), at("x").alias("cx"), at("y").alias("cy"))
    d = distance(F.col("px"), F.col("py"), F.col("vx"), F.col("vy"))
    best = F.min(F.struct(d.alias("d"), "vertex_id"))
    return v.join(small(p, ROAD_ROWS), ["city_id", "cx", "cy"]).groupBy("city_id", key).agg(best.alias("b")).select("city_id", key, F.col("b.vertex_id").alias("vertex_id"), F.col("b.d").alias("snap_dist"))


def snap_pseudo(points: DataFrame, g: RoadGraph, key: str = "poi_id", cell: int = 400) -> tuple[RoadGraph, DataFrame]:
    """The variant that splits the nearest edge at the point's projection.

    Gives a graph with a vertex per point (id: the largest vertex id + 1 + the point's rank) and its edges cut at all
    of their points, the parts' lengths adding up to the edge's; and the points with vertex_id. Edges are put into all
    cells that their bounding boxes touch; points without an edge surely the nearest (within one cell) are tried again with
    cells twice as wide. A point of a city without edges, or without coordinates, keeps a null vertex.
    """
    vs, e = g.vertices, g.edges
    a = vs.select("city_id", F.col("vertex_id").alias("u"), F.col("x").alias("ux"), F.col("y").alias("uy"))
    b = vs.select("city_id", F.col("vertex_id").alias("v"), F.col("x").alias("wx"), F.col("y").alias("wy"))
    seg = cut(e.join(a, ["city_id", "u"]).join(b, ["city_id", "v"]))
    todo = points.where("x is not null and y is not null").join(F.broadcast(seg.select("city_id").distinct()), "city_id", "left_semi")
    best, c = None, cell
    while True:
        found = _pseudo_round(todo, seg, key, c)
        sure = cut(found.where(F.col("d") <= c))
        best = sure if best is None else best.unionByName(sure)
        todo = cut(todo.join(sure.select("city_id", key), ["city_id", key], "left_anti"))
        if todo.isEmpty():
            break
        c *= 2
    top = vs.groupBy("city_id").agg(F.max("vertex_id").alias("top"))
    rank = F.row_number().over(Window.partitionBy("city_id").orderBy(key))
    new = best.join(F.broadcast(top), "city_id").withColumn("vertex_id", (F.col("top") + rank).cast("long"))
    # Inner points of an edge in order; the last part takes what rounding leaves.
    on = Window.partitionBy("city_id", "edge_id").orderBy("t", "vertex_id")
    cuts = new.withColumn("here", F.round(F.col("t") * F.col("len_dm")).cast("long")).select("city_id", "edge_id", "u", "v", "len_dm", "vertex_id", "here", F.lag("vertex_id").over(on).alias("pv"), F.lag("here").over(on).alias("ph"), F.lead("vertex_id").over(on).alias("nv"), F.row_number().over(on).alias("k"))
    parts = cuts.select("city_id", "edge_id", (2 * F.col("k")).alias("k"), F.coalesce("pv", "u").alias("u"), F.col("vertex_id").alias("v"), (F.col("here") - F.coalesce("ph", F.lit(0))).alias("len_dm")).unionByName(
        cuts.where("nv is null").select("city_id", "edge_id", (2 * F.col("k") + 1).alias("k"), F.col("vertex_id").alias("u"), "v", (F.col("len_dm") - F.col("here")).alias("len_dm"))
    )
    most = e.groupBy("city_id").agg((F.max("edge_id") + 1).alias("base"))
    edges = e.join(cuts.select("city_id", "edge_id").distinct(), ["city_id", "edge_id"], "left_anti").select("city_id", "edge_id", "u", "v", "len_dm").unionByName(
        parts.join(F.broadcast(most), "city_id").select("city_id", (F.col("base") + F.row_number().over(Window.partitionBy("city_id").orderBy("edge_id", "k")) - 1).alias("edge_id"), "u", "v", "len_dm")
    )
    x, y = F.col("ux") + F.col("t") * (F.col("wx") - F.col("ux")), F.col("uy") + F.col("t") * (F.col("wy") - F.col("uy"))
    vertices = vs.select("city_id", "vertex_id", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y")).unionByName(new.select("city_id", "vertex_id", x.alias("x"), y.alias("y")))
    return RoadGraph(vertices, edges, g.directed), points.join(new.select("city_id", key, "vertex_id", F.col("d").alias("snap_dist"), "edge_id"), ["city_id", key], "left")


def _pseudo_round(points: DataFrame, seg: DataFrame, key: str, c: int) -> DataFrame:
    """(city_id, key, d, edge_id, t, ...): the nearest edge that touches a point's cell or one of the eight around it."""
    at = lambda x: F.floor(x / c).cast("long")
    over = lambda p, q: F.explode(F.sequence(at(F.least(p, q)), at(F.greatest(p, q))))
    around = F.sequence(F.lit(-1), F.lit(1))
    s = seg.withColumn("cx", over(F.col("ux"), F.col("wx"))).withColumn("cy", over(F.col("uy"), F.col("wy")))
    p = points.select("city_id", key, F.col("x").alias("px"), F.col("y").alias("py")).withColumn("cx", F.explode(F.transform(around, lambda i: at(F.col("px")) + i))).withColumn("cy", F.explode(F.transform(around, lambda i: at(F.col("py")) + i)))
    dx, dy = F.col("wx") - F.col("ux"), F.col("wy") - F.col("uy")
    t = F.coalesce(F.try_divide((F.col("px") - F.col("ux")) * dx + (F.col("py") - F.col("uy")) * dy, dx * dx + dy * dy).cast("double"), F.lit(0.0))
    hit = s.join(p, ["city_id", "cx", "cy"]).withColumn("t", F.greatest(F.lit(0.0), F.least(F.lit(1.0), t)))
    hit = hit.withColumn("d", F.round(distance(F.col("px"), F.col("py"), F.col("ux") + F.col("t") * dx, F.col("uy") + F.col("t") * dy), 9))
    return hit.groupBy("city_id", key).agg(F.min(F.struct("d", "edge_id", "t", "u", "v", "len_dm", "ux", "uy", "wx", "wy")).alias("b")).select("city_id", key, "b.*")


# ---------------------------------------------------------------- search, local form


class Adjacency:
    """One city's arcs by start vertex."""

    def __init__(self, pdf: pd.DataFrame):
        order = np.lexsort((pdf["edge_id"].to_numpy(), pdf["b"].to_numpy(), pdf["a"].to_numpy()))
        self.a, self.b, self.w, self.e = (pdf[c].to_numpy()[order] for c in ("a", "b", "w", "edge_id"))
        self.ids = np.unique(np.concatenate((self.a, self.b)))
        starts = np.searchsorted(self.a, self.ids)
        ends = np.searchsorted(self.a, self.ids, side="right")
        to = np.searchsorted(self.ids, self.b).tolist()
        w, e = self.w.tolist(), self.e.tolist()
        self.out = [list(zip(to[s:t], w[s:t], e[s:t], strict=True)) for s, t in zip(starts.tolist(), ends.tolist(), strict=True)]

    def place(self, v: int) -> int:
        i = int(np.searchsorted(self.ids, v))
        return i if i < len(self.ids) and self.ids[i] == v else -1

    def tree(self, source: int, targets: set[int] | None = None, bound=None) -> tuple[dict, int]:
        """Labels (cost, hops, predecessor, edge) by place, in settled order; stops when all targets are settled.

        ``bound`` gives an admissible rest of the way (goal-directed search to one target).
        """
        best = {source: (0.0, 0, -1, -1)}
        heap, settled, left = [((bound(source) if bound else 0.0), 0.0, 0, source)], {}, None if targets is None else set(targets)
        while heap:
            _, cost, hops, u = heapq.heappop(heap)
            if u in settled or (cost, hops) != best[u][:2]:
                continue
            settled[u] = best[u]
            if left is not None:
                left.discard(u)
                if not left:
                    break
            for v, w, e in self.out[u]:
                if v in settled:
                    continue
                new = (cost + w, hops + 1, u, e)
                if v not in best or new < best[v]:
                    again = v in best and new[:2] == best[v][:2]
                    best[v] = new
                    if not again:
                        heapq.heappush(heap, (new[0] + (bound(v) if bound else 0.0), new[0], new[1], v))
        return settled, len(settled)

    def walk(self, labels: dict, target: int) -> list[tuple[int, int]] | None:
        """(vertex place, edge into it) from the source to the target."""
        if target not in labels:
            return None
        out, at = [], target
        while at != -1:
            _, _, p, e = labels[at]
            out.append((at, e))
            at = p
        return out[::-1]


def _blocked(left: DataFrame, edges: DataFrame, source: str) -> tuple[DataFrame, DataFrame]:
    """Sources dealt into blocks per city, and the city's arcs once for every block of it.

    A city has no more blocks than ``WAVES`` for each core of the cluster, so copies of its arcs don't grow with the pairs.
    """
    most = WAVES * left.sparkSession.sparkContext.defaultParallelism
    counted = left.groupBy("city_id").agg(F.count_distinct(source).alias("_n")).withColumn("_parts", F.least(F.ceil(F.col("_n") / SOURCES), F.lit(most)).cast("int"))
    dealt = left.join(small(counted.select("city_id", "_parts")), "city_id").withColumn("block", F.pmod(F.xxhash64(source), F.col("_parts")).cast("int")).drop("_parts")
    every = edges.join(small(counted.select("city_id", "_parts")), "city_id").withColumn("_b", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1))).drop("_parts").withColumnRenamed("city_id", "_c")
    return dealt, every


LABELS = "city_id int, source long, v long, cost double, hops int, pred long, edge_id long"
PATHS = "city_id int, pair_id string, s long, t long, seq int, vertex_id long, edge_id long"


def tree_local(g: RoadGraph, sources: DataFrame, weight: str = "len_dm") -> DataFrame:
    """Labels (city_id, source, v, cost, hops, pred, edge_id) of everything each source of (city_id, source) reaches."""
    left, every = _blocked(sources.distinct(), arcs(g, weight), "source")

    def run(key, src: pd.DataFrame, pdf: pd.DataFrame) -> pd.DataFrame:
        adj = Adjacency(pdf)
        out = []
        for s in sorted(src["source"].unique().tolist()):
            at = adj.place(s)
            if at < 0:
                continue
            labels, _ = adj.tree(at)
            ids = adj.ids
            out += [(key[0], s, int(ids[v]), c, h, int(ids[p]) if p >= 0 else None, e if e >= 0 else None) for v, (c, h, p, e) in labels.items()]
        return pd.DataFrame(out, columns=["city_id", "source", "v", "cost", "hops", "pred", "edge_id"]).astype({"pred": "Int64", "edge_id": "Int64"})

    return left.groupBy("city_id", "block").cogroup(every.groupBy("_c", "_b")).applyInPandas(run, LABELS)


def costs_local(g: RoadGraph, pairs: DataFrame, weight: str = "len_dm") -> DataFrame:
    """(city_id, s, t, cost) of every pair (city_id, s, t) that is connected; a source's labels stay in its task."""
    left, every = _blocked(pairs.select("city_id", "s", "t").distinct(), arcs(g, weight), "s")

    def run(key, want: pd.DataFrame, pdf: pd.DataFrame) -> pd.DataFrame:
        adj, out = Adjacency(pdf), []
        for s, own in want.groupby("s", sort=True):
            at = adj.place(int(s))
            if at < 0:
                continue
            targets = {int(t): adj.place(int(t)) for t in own["t"]}
            labels, _ = adj.tree(at, {t for t in targets.values() if t >= 0})
            out += [(key[0], int(s), t, labels[to][0]) for t, to in targets.items() if to in labels]
        return pd.DataFrame(out, columns=["city_id", "s", "t", "cost"])

    return left.groupBy("city_id", "block").cogroup(every.groupBy("_c", "_b")).applyInPandas(run, "city_id int, s long, t long, cost double")


def paths_local(g: RoadGraph, pairs: DataFrame, weight: str = "len_dm", goal: str | None = None) -> DataFrame:
    """Path rows of (city_id, pair_id, s, t): one per vertex, seq 0 at s; edge_id leads into the vertex. No rows if unreachable.

    A source's search stops when all of its targets are settled. ``goal`` searches pair by pair with a lower bound on
    the rest of the way: ``line`` is m times the straight line to the target, m the least cost per metre of any arc
    (needs x and y of vertices); ``landmarks`` is the largest difference of the two vertices' distances from
    ``LANDMARKS`` vertices far apart (roads that run both ways only).
    """
    if goal == "landmarks" and g.directed:
        raise ValueError("landmark bounds need roads that run both ways")
    edges = arcs(g, weight)
    if goal == "line":
        xy = g.vertices.select("city_id", "vertex_id", "x", "y")
        edges = edges.join(xy.select("city_id", F.col("vertex_id").alias("a"), F.col("x").alias("ax"), F.col("y").alias("ay")), ["city_id", "a"]).join(xy.select("city_id", F.col("vertex_id").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by")), ["city_id", "b"])
    left, every = _blocked(pairs.select("city_id", "pair_id", "s", "t"), edges, "s")

    def run(key, want: pd.DataFrame, pdf: pd.DataFrame) -> pd.DataFrame:
        adj = Adjacency(pdf)
        bound = _line_bound(adj, pdf) if goal == "line" else _landmark_bound(adj) if goal == "landmarks" else None
        out = []
        for s, own in want.groupby("s", sort=True):
            at = adj.place(int(s))
            targets = {int(t): adj.place(int(t)) for t in own["t"].unique()}
            if at < 0:
                continue
            if bound is None:
                labels, _ = adj.tree(at, {t for t in targets.values() if t >= 0})
            for pair, t in zip(own["pair_id"], own["t"], strict=True):
                to = targets[int(t)]
                if to < 0:
                    continue
                if bound is not None:
                    labels, _ = adj.tree(at, {to}, bound(to))
                for seq, (v, e) in enumerate(adj.walk(labels, to) or []):
                    out.append((key[0], pair, int(s), int(t), seq, int(adj.ids[v]), e if e >= 0 else None))
        return pd.DataFrame(out, columns=["city_id", "pair_id", "s", "t", "seq", "vertex_id", "edge_id"]).astype({"edge_id": "Int64", "pair_id": object})

    return left.groupBy("city_id", "block").cogroup(every.groupBy("_c", "_b")).applyInPandas(run, PATHS)


def meet_in_the_middle(adj: Adjacency, s: int, t: int) -> tuple[float, int]:
    """(cost of the cheapest way between two places, places settled): searched from both ends at once; ways run both ways."""
    if s == t:
        return 0.0, 1
    sides = [({s: 0.0}, [(0.0, s)], {}), ({t: 0.0}, [(0.0, t)], {})]
    best = float("inf")
    while sides[0][1] and sides[1][1]:
        k = 0 if sides[0][1][0][0] <= sides[1][1][0][0] else 1
        near, heap, settled = sides[k]
        other = sides[1 - k][0]
        if sides[0][1][0][0] + sides[1][1][0][0] >= best:
            break
        cost, u = heapq.heappop(heap)
        if u in settled:
            continue
        settled[u] = cost
        for v, w, _ in adj.out[u]:
            if cost + w < near.get(v, float("inf")):
                near[v] = cost + w
                heapq.heappush(heap, (cost + w, v))
            if v in other:
                best = min(best, cost + w + other[v])
    return best, len(sides[0][2]) + len(sides[1][2])


def costs_both_ends(g: RoadGraph, pairs: DataFrame, weight: str = "len_dm") -> DataFrame:
    """(city_id, pair_id, cost, settled) of every pair that is connected, by search from both ends."""
    if g.directed:
        raise ValueError("search from both ends needs roads that run both ways")
    left, every = _blocked(pairs.select("city_id", "pair_id", "s", "t"), arcs(g, weight), "s")

    def run(key, want: pd.DataFrame, pdf: pd.DataFrame) -> pd.DataFrame:
        adj, out = Adjacency(pdf), []
        for pair, s, t in zip(want["pair_id"], want["s"], want["t"], strict=True):
            a, b = adj.place(int(s)), adj.place(int(t))
            if a >= 0 and b >= 0:
                cost, settled = meet_in_the_middle(adj, a, b)
                if np.isfinite(cost):
                    out.append((key[0], pair, cost, settled))
        return pd.DataFrame(out, columns=["city_id", "pair_id", "cost", "settled"]).astype({"pair_id": object})

    return left.groupBy("city_id", "block").cogroup(every.groupBy("_c", "_b")).applyInPandas(run, "city_id int, pair_id string, cost double, settled long")


def _landmark_bound(adj: Adjacency, many: int = LANDMARKS):
    """Distances from vertices chosen one after the other as far as possible from those before."""
    n, far, at = len(adj.ids), [], 0
    nearest = np.full(n, np.inf)
    for _ in range(min(many, n)):
        d = np.full(n, np.inf)
        for v, label in adj.tree(at)[0].items():
            d[v] = label[0]
        far.append(d)
        nearest = np.minimum(nearest, d)
        at = int(np.where(np.isfinite(nearest), nearest, -1).argmax())
    table = np.array(far) if far else np.zeros((0, n))

    def to(target: int):
        with np.errstate(invalid="ignore"):
            gap = np.abs(table - table[:, [target]])
        low = np.where(np.isfinite(gap), gap, 0.0).max(0, initial=0.0) * (1 - 1e-12)
        return low.tolist().__getitem__

    return to


def _line_bound(adj: Adjacency, pdf: pd.DataFrame):
    x, y = {}, {}
    for i, px, py in zip(pdf["a"], pdf["ax"], pdf["ay"], strict=True):
        x[i], y[i] = float(px), float(py)
    for i, px, py in zip(pdf["b"], pdf["bx"], pdf["by"], strict=True):
        x[i], y[i] = float(px), float(py)
    px, py = np.array([x[i] for i in adj.ids.tolist()]), np.array([y[i] for i in adj.ids.tolist()])
    d = np.hypot(pdf["ax"] - pdf["bx"], pdf["ay"] - pdf["by"]).to_numpy(float)
    m = float((pdf["w"].to_numpy(float)[d > 0] / d[d > 0]).min()) * (1 - 1e-12) if (d > 0).any() else 0.0

    def to(target: int):
        line = (m * np.hypot(px - px[target], py - py[target])).tolist()
        return line.__getitem__

    return to


# ---------------------------------------------------------------- search, distributed form


def tree_rounds(g: RoadGraph, sources: DataFrame, weight: str = "len_dm", most: float | None = None, targets: DataFrame | None = None, effort: list | None = None) -> DataFrame:
    """The same labels by rounds over all executors: relax, keep the least (cost, hops, pred), go on from what improved.

    ``most`` cuts labels above a radius; with ``targets`` (city_id, source, v) a label strictly above the dearest known
    cost of its source's targets is dropped once all of them are known. ``effort`` gets (round, rows improved).
    """
    out = arcs(g, weight).withColumnRenamed("a", "u")
    out = cut(out.repartition("city_id", "u"))
    label = F.struct("cost", "hops", "pred", "edge_id")
    start = sources.distinct().select("city_id", "source", F.col("source").alias("v"), F.lit(0.0).alias("cost"), F.lit(0).alias("hops"), F.lit(-1).cast("long").alias("pred"), F.lit(-1).cast("long").alias("edge_id"))
    labels = cut(start)
    frontier, i = labels, 0
    while True:
        i += 1
        step = frontier.select("city_id", "source", F.col("v").alias("u"), "cost", "hops").join(out, ["city_id", "u"])
        new = step.select("city_id", "source", F.col("b").alias("v"), (F.col("cost") + F.col("w")).alias("cost"), (F.col("hops") + 1).alias("hops"), F.col("u").alias("pred"), "edge_id")
        if most is not None:
            new = new.where(F.col("cost") <= most)
        if targets is not None:
            known = targets.join(labels.select("city_id", "source", "v", "cost"), ["city_id", "source", "v"], "left").groupBy("city_id", "source").agg(F.when(F.count("*") == F.count("cost"), F.max("cost")).alias("_far"))
            new = new.join(known, ["city_id", "source"], "left").where("_far is null or cost <= _far").drop("_far")
        new = new.groupBy("city_id", "source", "v").agg(F.min(label).alias("n"))
        old = labels.select("city_id", "source", "v", label.alias("o"))
        both = old.join(new, ["city_id", "source", "v"], "full_outer")
        better = F.col("o").isNull() | (F.col("n") < F.col("o"))
        both = both.select("city_id", "source", "v", F.when(better & F.col("n").isNotNull(), F.col("n")).otherwise(F.col("o")).alias("l"), (better & F.col("n").isNotNull()).alias("moved"))
        both = cut(both.select("city_id", "source", "v", "l.*", "moved"))
        labels, frontier = both.drop("moved"), both.where("moved").drop("moved")
        n = frontier.count()
        if effort is not None:
            effort.append((i, n))
        if not n:
            return labels.select("city_id", "source", "v", "cost", F.col("hops").cast("int").alias("hops"), F.when(F.col("pred") >= 0, F.col("pred")).alias("pred"), F.when(F.col("edge_id") >= 0, F.col("edge_id")).alias("edge_id"))


def trace(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """Path rows from labels: backward steps from every target at once, one join per hop."""
    step = labels.select("city_id", F.col("source").alias("s"), F.col("v").alias("at"), "hops", "pred", "edge_id")
    step = cut(step)
    now = cut(pairs.select("city_id", "pair_id", "s", "t", F.col("t").alias("at")))
    parts = []
    while True:
        here = cut(now.join(step, ["city_id", "s", "at"]))
        if here.isEmpty():
            break
        parts.append(here.select("city_id", "pair_id", "s", "t", F.col("hops").alias("seq"), F.col("at").alias("vertex_id"), "edge_id"))
        now = here.where("pred is not null").select("city_id", "pair_id", "s", "t", F.col("pred").alias("at"))
    out = parts[0] if parts else pairs.limit(0).select("city_id", "pair_id", "s", "t", F.lit(0).alias("seq"), F.col("t").alias("vertex_id"), F.lit(0).cast("long").alias("edge_id"))
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def shortest(g: RoadGraph, pairs: DataFrame, weight: str = "len_dm", strategy: str = "auto") -> DataFrame:
    """Path rows of every pair; ``auto`` searches locally unless a city's edges exceed ``LOCAL_EDGES``."""
    if strategy == "auto":
        largest = g.edges.groupBy("city_id").count().agg(F.max("count")).first()[0] or 0
        strategy = "local" if largest <= LOCAL_EDGES else "distributed"
    if strategy == "local":
        return paths_local(g, pairs, weight)
    if strategy in ("astar", "landmarks"):
        return paths_local(g, pairs, weight, "line" if strategy == "astar" else "landmarks")
    if strategy != "distributed":
        raise ValueError(f"unknown strategy {strategy}")
    sources = pairs.select("city_id", F.col("s").alias("source"))
    labels = tree_rounds(g, sources, weight, targets=pairs.select("city_id", F.col("s").alias("source"), F.col("t").alias("v")).distinct())
    return trace(labels, pairs)


# ---------------------------------------------------------------- enrichment


def close_pairs(closeness: DataFrame, snapped: DataFrame, directed: bool = False) -> DataFrame:
    """(city_id, pair_id, pi, pj, W, s, t): close pairs at their vertices; undirected ones start at the smaller vertex id."""
    a = snapped.select("city_id", F.col("poi_id").alias("pi"), F.col("vertex_id").alias("vi"))
    b = snapped.select("city_id", F.col("poi_id").alias("pj"), F.col("vertex_id").alias("vj"))
    p = closeness.join(small(a), ["city_id", "pi"]).join(small(b), ["city_id", "pj"])
    s, t = (F.col("vi"), F.col("vj")) if directed else (F.least("vi", "vj"), F.greatest("vi", "vj"))
    return p.select("city_id", F.concat_ws(">", "pi", "pj").alias("pair_id"), "pi", "pj", "W", s.alias("s"), t.alias("t"))


def unordered(pairs: DataFrame) -> DataFrame:
    """One row per pair of places whatever the order, with the larger score."""
    lo, hi = F.least("pi", "pj"), F.greatest("pi", "pj")
    return pairs.groupBy("city_id", lo.alias("pi"), hi.alias("pj"), "s", "t").agg(F.max("W").alias("W")).select("city_id", F.concat_ws(">", "pi", "pj").alias("pair_id"), "pi", "pj", "W", "s", "t")


def edge_costs(edges: DataFrame, pair_paths: DataFrame, pairs: DataFrame, alphas: list[float]) -> DataFrame:
    """(city_id, edge_id, u, v, len_dm, n_paths, cost_<alpha>...): d times the product of 1 - alpha W over the pair paths on the edge.

    All alphas in one aggregate; edges on no path keep their length. Products are taken by logarithms, zeros apart.
    """
    if any(not 0 <= a <= 1 for a in alphas):
        raise ValueError("alpha must lie in [0, 1]")
    on = pair_paths.where("edge_id is not null").select("city_id", "pair_id", "edge_id").distinct().join(pairs.select("city_id", "pair_id", "W"), ["city_id", "pair_id"])

    def product(a: float) -> Column:
        f = 1 - a * F.col("W")
        return F.when(F.min(f) <= 0, 0.0).otherwise(F.exp(F.sum(F.when(f > 0, F.log(f)))))

    names = [cost_name(a) for a in alphas]
    fac = on.groupBy("city_id", "edge_id").agg(F.count("*").alias("n_paths"), *[product(a).alias(n) for a, n in zip(alphas, names, strict=True)])
    e = edges.select("city_id", "edge_id", "u", "v", "len_dm").join(fac, ["city_id", "edge_id"], "left")
    return e.select("city_id", "edge_id", "u", "v", "len_dm", F.coalesce("n_paths", F.lit(0)).alias("n_paths"), *[(F.col("len_dm") * F.coalesce(n, F.lit(1.0))).alias(n) for n in names])


def cost_name(alpha: float) -> str:
    return f"cost_{round(100 * alpha):03d}"


def enriched(g: RoadGraph, costs: DataFrame) -> RoadGraph:
    return RoadGraph(g.vertices, costs, g.directed)
