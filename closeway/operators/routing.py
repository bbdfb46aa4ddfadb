"""The three planners: plain, enriched, and hopping over places."""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geo import distance, in_ellipse
from ..session import Stored, large, small
from .graph import RoadGraph, shortest, tree_local

UNREACHABLE = ("enriched", "widen", "null")


def trip_key() -> F.Column:
    return F.concat_ws("/", "city_id", "setting", "bracket", "trip_id")


def keyed(trips: DataFrame) -> DataFrame:
    return trips.withColumn("pair_id", trip_key())


def plain(g: RoadGraph, trips: DataFrame, strategy: str = "auto") -> DataFrame:
    """The baseline: cheapest under length. Path rows per trip."""
    return shortest(g, keyed(trips), "len_dm", strategy)


def enriched(gc: RoadGraph, trips: DataFrame, cost: str, strategy: str = "auto") -> DataFrame:
    """Cheapest under the discounted cost."""
    return shortest(gc, keyed(trips), cost, strategy)


def located(trips: DataFrame, vertices: DataFrame) -> DataFrame:
    """Trips with pair_id and the coordinates of both ends."""
    at = lambda v: vertices.select("city_id", F.col("vertex_id").alias(v), F.col("x").alias(f"{v}x"), F.col("y").alias(f"{v}y"))
    return keyed(trips).join(at("s"), ["city_id", "s"]).join(at("t"), ["city_id", "t"])


def ellipse_pois(trips_xy: DataFrame, pois: DataFrame, shape: str = "drawn", widen: float = 1.0) -> DataFrame:
    """(city_id, pair_id, poi_id, ds, dt): places in a trip's region with their distances to both ends.

    A region lies within 0.8 of the (widened) distance from the trip's middle; cells at least that wide, by powers of two, make
    an equality join of each trip's nine cells with the places, which are put into a cell of every width that occurs. The
    shape ``none`` takes all places of the city.
    """
    w = F.lit(widen)
    mx, my = (F.col("sx") + F.col("tx")) / 2, (F.col("sy") + F.col("ty")) / 2
    grow = lambda c, m: m + (F.col(c) - m) * w
    ends = [grow("sx", mx), grow("sy", my), grow("tx", mx), grow("ty", my)] if widen != 1.0 else [F.col(c) for c in ("sx", "sy", "tx", "ty")]
    p = pois.select("city_id", "poi_id", F.col("x").alias("px"), F.col("y").alias("py"), "vertex_id")
    test = in_ellipse(F.col("px"), F.col("py"), *ends, shape)
    if shape == "none":
        met = trips_xy.join(small(p), "city_id").where(test)
    else:
        reach = 0.8 * widen * distance(F.col("sx"), F.col("sy"), F.col("tx"), F.col("ty"))
        t = trips_xy.withColumn("_level", F.ceil(F.log2(F.greatest(reach, F.lit(1.0)) * 1.0001)).cast("int"))
        levels = sorted(r._level for r in t.select("_level").distinct().collect())  # fewer than 64
        cell = lambda c: F.floor(c / F.pow(F.lit(2.0), F.col("_level"))).cast("long")
        around = F.sequence(F.lit(-1), F.lit(1))
        t = t.withColumn("_cx", F.explode(F.transform(around, lambda i: cell(mx) + i))).withColumn("_cy", F.explode(F.transform(around, lambda i: cell(my) + i)))
        p = p.withColumn("_level", F.explode(F.array(*map(F.lit, levels)) if levels else F.array().cast("array<int>"))).withColumns({"_cx": cell(F.col("px")), "_cy": cell(F.col("py"))})
        met = t.join(p, ["city_id", "_level", "_cx", "_cy"]).where(test)
    return met.select("city_id", "pair_id", "poi_id", "vertex_id", distance(F.col("px"), F.col("py"), F.col("sx"), F.col("sy")).alias("ds"), distance(F.col("px"), F.col("py"), F.col("tx"), F.col("ty")).alias("dt"))


def entry_exit(nodes: DataFrame) -> DataFrame:
    """(city_id, pair_id, entry, exit): the region's places nearest to s and to t, the smaller id on a tie."""
    return nodes.groupBy("city_id", "pair_id").agg(F.min(F.struct("ds", "poi_id")).alias("a"), F.min(F.struct("dt", "poi_id")).alias("b")).select("city_id", "pair_id", F.col("a.poi_id").alias("entry"), F.col("b.poi_id").alias("exit"))


def entry_exit_network(g: RoadGraph, nodes: DataFrame, trips: DataFrame, cost: str = "len_dm") -> DataFrame:
    """Like ``entry_exit`` with the distance by road; places out of reach are no entry and no exit."""
    reach = Stored(tree_local(g, trips.select("city_id", F.col("s").alias("source")).unionByName(trips.select("city_id", F.col("t").alias("source"))), cost), "reach").df
    far = lambda end, name: reach.select("city_id", F.col("source").alias(end), F.col("v").alias("vertex_id"), F.col("cost").alias(name))
    at = nodes.select("city_id", "pair_id", "poi_id", "vertex_id").join(keyed(trips).select("city_id", "pair_id", "s", "t"), ["city_id", "pair_id"])
    return entry_exit(at.join(far("s", "ds"), ["city_id", "s", "vertex_id"]).join(far("t", "dt"), ["city_id", "t", "vertex_id"]))


def restricted_edges(nodes: DataFrame, closeness: DataFrame) -> DataFrame:
    """(city_id, pair_id, pi, pj, dist, W): closeness edges with both ends in the trip's region, both ways."""
    both = closeness.select("city_id", "pi", "pj", "dist", "W").unionByName(closeness.select("city_id", F.col("pj").alias("pi"), F.col("pi").alias("pj"), "dist", "W"))
    both = both.groupBy("city_id", "pi", "pj").agg(F.min("dist").alias("dist"), F.max("W").alias("W"))
    at = nodes.select("city_id", "pair_id", F.col("poi_id").alias("pi")).join(both, ["city_id", "pi"])
    return at.join(nodes.select("city_id", "pair_id", F.col("poi_id").alias("pj")), ["city_id", "pair_id", "pj"], "left_semi")


def hop_weight(kind: str, alpha: float) -> F.Column:
    return {"dist": F.col("dist"), "discounted": F.col("dist") * (1 - alpha * F.col("W")), "score": 1 - F.col("W")}[kind]


def poi_sequence(edges: DataFrame, ends: DataFrame, weight: F.Column | None = None) -> DataFrame:
    """(city_id, pair_id, seq, poi_id): cheapest sequence of places from entry to exit; none where they are apart.

    One small graph per trip; equal entry and exit give that place alone.
    """
    w = F.col("dist") if weight is None else weight
    left = ends.select("city_id", "pair_id", "entry", "exit")
    right = edges.select(F.col("city_id").alias("_c"), F.col("pair_id").alias("_p"), "pi", "pj", w.cast("double").alias("w"))

    def run(key, want: pd.DataFrame, pdf: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple] = []
        if len(want):
            a, b = int(want["entry"].iloc[0]), int(want["exit"].iloc[0])
            adj: dict[int, list] = {}
            for i, j, c in zip(pdf["pi"].tolist(), pdf["pj"].tolist(), pdf["w"].tolist(), strict=True):
                adj.setdefault(i, []).append((j, c))
            best, heap, done = {a: (0.0, 0, -1)}, [(0.0, 0, a)], {}
            while heap:
                cost, hops, u = heapq.heappop(heap)
                if u in done or (cost, hops) != best[u][:2]:
                    continue
                done[u] = best[u]
                if u == b:
                    break
                for v, c in adj.get(u, ()):
                    new = (cost + c, hops + 1, u)
                    if v not in done and (v not in best or new < best[v]):
                        best[v] = new
                        heapq.heappush(heap, (new[0], new[1], v))
            at = b if b in done else None
            while at is not None and at != -1:
                out.append(at)
                at = done[at][2]
        return pd.DataFrame({"city_id": [key[0]] * len(out), "pair_id": [key[1]] * len(out), "seq": range(len(out)), "poi_id": out[::-1]}).astype({"seq": "int32", "poi_id": "int64", "city_id": "int32", "pair_id": object})

    return left.groupBy("city_id", "pair_id").cogroup(right.groupBy("_c", "_p")).applyInPandas(run, "city_id int, pair_id string, seq int, poi_id long")


def stops(trips_xy: DataFrame, sequence: DataFrame, pois: DataFrame) -> DataFrame:
    """(city_id, pair_id, stop, vertex_id): start, the places' vertices, target; stops at the same vertex in a row joined."""
    n = sequence.groupBy("city_id", "pair_id").agg(F.max("seq").alias("last"))
    mid = sequence.join(small(pois.select("city_id", "poi_id", "vertex_id")), ["city_id", "poi_id"]).select("city_id", "pair_id", (F.col("seq") + 1).alias("stop"), "vertex_id")
    ends = trips_xy.join(n, ["city_id", "pair_id"])
    every = mid.unionByName(ends.select("city_id", "pair_id", F.lit(0).alias("stop"), F.col("s").alias("vertex_id"))).unionByName(ends.select("city_id", "pair_id", (F.col("last") + 2).alias("stop"), F.col("t").alias("vertex_id")))
    order = Window.partitionBy("city_id", "pair_id").orderBy("stop")
    return every.withColumn("_p", F.lag("vertex_id").over(order)).where("_p is null or _p <> vertex_id").drop("_p")


def legs_of(at: DataFrame) -> DataFrame:
    """(city_id, pair_id, leg, s, t, leg_id): the ways between consecutive stops."""
    order = Window.partitionBy("city_id", "pair_id").orderBy("stop")
    legs = at.select("city_id", "pair_id", F.row_number().over(order).alias("leg"), F.col("vertex_id").alias("s"), F.lead("vertex_id").over(order).alias("t")).where("t is not null")
    return legs.withColumn("leg_id", F.concat_ws(">", "s", "t"))


def expand(gc: RoadGraph, legs: DataFrame, cost: str, strategy: str = "auto") -> DataFrame:
    """Leg paths: each distinct (from, to) of a city is searched once."""
    return shortest(gc, legs.select("city_id", F.col("leg_id").alias("pair_id"), "s", "t").distinct(), cost, strategy)


def concat_legs(legs: DataFrame, leg_paths: DataFrame) -> DataFrame:
    """Path rows per trip from its legs in order; a joint's vertex appears once. Trips with a missing leg are dropped."""
    size = leg_paths.groupBy("city_id", F.col("pair_id").alias("leg_id")).agg(F.max("seq").alias("hops"))
    order = Window.partitionBy("city_id", "pair_id").orderBy("leg").rowsBetween(Window.unboundedPreceding, -1)
    trip = Window.partitionBy("city_id", "pair_id")
    sized = legs.join(size, ["city_id", "leg_id"], "left").withColumn("ok", F.count("hops").over(trip) == F.count("*").over(trip)).where("ok")
    placed = sized.withColumn("offset", F.coalesce(F.sum("hops").over(order), F.lit(0)))
    ends = legs.groupBy("city_id", "pair_id").agg(F.min_by("s", "leg").alias("s"), F.max_by("t", "leg").alias("t"))
    rows = placed.select("city_id", "pair_id", "leg", "leg_id", "offset").join(leg_paths.select("city_id", F.col("pair_id").alias("leg_id"), "seq", "vertex_id", "edge_id"), ["city_id", "leg_id"]).where("seq > 0 or leg = 1")
    return rows.join(ends, ["city_id", "pair_id"]).select("city_id", "pair_id", "s", "t", (F.col("offset") + F.col("seq")).cast("int").alias("seq"), "vertex_id", "edge_id")


def hop_plan(gc: RoadGraph, closeness: DataFrame, pois: DataFrame, trips: DataFrame, shape: str = "drawn", on_unreachable: str = "enriched", weight: str = "dist", alpha: float = 1.0) -> DataFrame:
    """The legs of every trip over the closeness graph inside its region; they don't depend on the roads' costs."""
    if on_unreachable not in UNREACHABLE:
        raise ValueError(f"unknown choice {on_unreachable}")
    xy = Stored(located(trips, gc.vertices), "trips").df
    todo, sequence = xy, None
    for k in range(4 if on_unreachable == "widen" else 1):
        nodes = large(Stored(ellipse_pois(todo, pois, shape, 1.25**k), "nodes").df)
        found = Stored(poi_sequence(restricted_edges(nodes, closeness), entry_exit(nodes), hop_weight(weight, alpha)), "hops").df
        sequence = found if sequence is None else sequence.unionByName(found)
        if on_unreachable == "widen":
            todo = todo.join(found.select("pair_id").distinct(), "pair_id", "left_anti")
    return Stored(legs_of(stops(xy, sequence, pois)), "legs").df


def drive(gc: RoadGraph, legs: DataFrame, trips: DataFrame, cost: str, on_unreachable: str = "enriched", strategy: str = "auto", enriched_paths: DataFrame | None = None) -> DataFrame:
    """Path rows with ``fallback`` from planned legs under ``cost``; trips that can't be driven so take the enriched route or none.

    ``enriched_paths`` are the enriched routes of all trips where they were searched before.
    """
    leg_paths = large(Stored(expand(gc, legs, cost, strategy), "leg-paths").df)
    done = Stored(concat_legs(legs, leg_paths).withColumn("fallback", F.lit(False)), "hop-routes").df
    if on_unreachable == "null":
        return done
    if enriched_paths is not None:
        return done.unionByName(enriched_paths.join(done.select("pair_id").distinct(), "pair_id", "left_anti").withColumn("fallback", F.lit(True)))
    rest = trips.withColumn("pair_id", trip_key()).join(done.select("pair_id").distinct(), "pair_id", "left_anti")
    return done.unionByName(shortest(gc, rest, cost, strategy).withColumn("fallback", F.lit(True)))


def poi_hop(gc: RoadGraph, closeness: DataFrame, pois: DataFrame, trips: DataFrame, cost: str, shape: str = "drawn", on_unreachable: str = "enriched", weight: str = "dist", alpha: float | None = None, strategy: str = "auto") -> DataFrame:
    """Path rows with ``fallback``: over the closeness graph inside the trip's region first, then by roads under ``cost``.

    Where the region holds no place, entry and exit are apart or a leg can't be driven: the enriched route
    (``enriched``), up to three regions 1.25 times as wide before that (``widen``), or no rows (``null``). The hop weight
    ``discounted`` takes the strength that ``cost`` has, unless ``alpha`` is given.
    """
    if alpha is None:
        alpha = int(cost.rsplit("_", 1)[1]) / 100 if cost.startswith("cost_") else 1.0
    legs = hop_plan(gc, closeness, pois, trips, shape, on_unreachable, weight, alpha)
    return drive(gc, legs, trips, cost, on_unreachable, strategy)


def sequence_cost(sequence: DataFrame, edges: DataFrame, weight: F.Column) -> DataFrame:
    """(city_id, pair_id, hops, cost): steps of each sequence of places and their weights' sum."""
    nxt = sequence.select("city_id", "pair_id", (F.col("seq") - 1).alias("seq"), F.col("poi_id").alias("pj"))
    step = sequence.withColumnRenamed("poi_id", "pi").join(nxt, ["city_id", "pair_id", "seq"], "left").join(edges.withColumn("w", weight), ["city_id", "pair_id", "pi", "pj"], "left")
    return step.groupBy("city_id", "pair_id").agg(F.max("seq").alias("hops"), F.coalesce(F.sum("w"), F.lit(0.0)).alias("cost"))


def describe(paths: DataFrame, pois: DataFrame) -> DataFrame:
    """(city_id, pair_id, seq, poi_id, name): the places met along a route, in order."""
    return paths.join(small(pois.select("city_id", "vertex_id", "poi_id", "name")), ["city_id", "vertex_id"]).select("city_id", "pair_id", "seq", "poi_id", "name")


def all_three(g: RoadGraph, gc: RoadGraph, closeness: DataFrame, pois: DataFrame, trips: DataFrame, cost: str, **how) -> DataFrame:
    """The ladder: path rows of the three planners with ``algo`` and ``fallback``."""
    no = F.lit(False).alias("fallback")
    a = plain(g, trips).select("*", no, F.lit("plain").alias("algo"))
    b = enriched(gc, trips, cost).select("*", no, F.lit("enriched").alias("algo"))
    return a.unionByName(b).unionByName(poi_hop(gc, closeness, pois, trips, cost, **how).withColumn("algo", F.lit("poi_hop")))
