"""Length, cost, enrichment ratio, popularity, and their comparison over trips."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geo import distance
from ..session import ROAD_ROWS, small

#: Metres within which a photo counts for a vertex.
RADIUS = 20.0


def path_costs(paths: DataFrame, costs: DataFrame, cost: str, keys: tuple[str, ...] = ("city_id", "pair_id")) -> DataFrame:
    """(keys, d, c, er, hops): length, discounted cost and their ratio per path; a path without edges has ratio null."""
    e = costs.select("city_id", "edge_id", "len_dm", F.col(cost).alias("c"))
    on = paths.join(small(e, ROAD_ROWS), ["city_id", "edge_id"], "left").groupBy(*keys).agg(F.coalesce(F.sum("len_dm"), F.lit(0)).alias("d"), F.coalesce(F.sum("c"), F.lit(0.0)).alias("c"), F.count("edge_id").alias("hops"))
    return on.withColumn("er", F.try_divide("c", F.col("d").cast("double")))


def vertex_popularity(photos: DataFrame, vertices: DataFrame, radius: float = RADIUS, nearest_only: bool = False) -> DataFrame:
    """(city_id, vertex_id, photos): photos within ``radius`` metres, the bound included; a photo counts for each such vertex.

    A grid of cells as wide as the radius turns the range join into an equality join: vertices are put into their own
    and the eight neighbouring cells, photos only into their own. Many vertices are not broadcast. ``nearest_only`` counts
    a photo once.
    """
    at = lambda x: F.floor(F.col(x) / radius).cast("long")
    near = F.sequence(F.lit(-1), F.lit(1))
    v = vertices.select("city_id", "vertex_id", F.col("x").alias("vx"), F.col("y").alias("vy"), F.explode(F.transform(near, lambda i: at("x") + i)).alias("cx"), at("y").alias("_cy")).withColumn("cy", F.explode(F.transform(near, lambda i: F.col("_cy") + i))).drop("_cy")
    p = photos.select("city_id", "photo_id", F.col("x").alias("px"), F.col("y").alias("py"), at("x").alias("cx"), at("y").alias("cy"))
    d = distance(F.col("px"), F.col("py"), F.col("vx"), F.col("vy"))
    hit = p.join(small(v, ROAD_ROWS), ["city_id", "cx", "cy"]).withColumn("d", d).where(F.col("d") <= radius)
    if nearest_only:
        hit = hit.groupBy("city_id", "photo_id").agg(F.min(F.struct("d", "vertex_id")).alias("b")).select("city_id", F.col("b.vertex_id").alias("vertex_id"))
    return hit.groupBy("city_id", "vertex_id").agg(F.count("*").alias("photos"))


def popularity(paths: DataFrame, vpop: DataFrame, keys: tuple[str, ...] = ("city_id", "pair_id")) -> DataFrame:
    """(keys, popularity): photos of every vertex position of the path, both ends included."""
    return paths.join(small(vpop, ROAD_ROWS), ["city_id", "vertex_id"], "left").groupBy(*keys).agg(F.coalesce(F.sum("photos"), F.lit(0)).alias("popularity"))


def per_path(paths: DataFrame, costs: DataFrame, cost: str, vpop: DataFrame) -> DataFrame:
    """(city_id, pair_id, algo, d, c, er, hops, popularity) in one pass over the path rows."""
    keys = ("city_id", "pair_id", "algo")
    return path_costs(paths, costs, cost, keys).join(popularity(paths, vpop, keys), list(keys))


def relative(measured: DataFrame, base: str = "plain") -> DataFrame:
    """Changes of every planner against the base planner of the same trip.

    ``er_gain`` = er_base / er - 1, ``er_drop`` = 1 - er / er_base; null where a divisor is 0.
    """
    b = measured.where(F.col("algo") == base).select("city_id", "pair_id", F.col("d").alias("d0"), F.col("er").alias("er0"), F.col("popularity").alias("p0"))
    m = measured.where(F.col("algo") != base).join(b, ["city_id", "pair_id"])
    ratio = lambda a, z: F.try_divide(F.col(a).cast("double"), F.col(z).cast("double"))
    return m.select(
        "city_id", "pair_id", "algo", "d", "d0", "er", "er0", "popularity", "p0",
        (ratio("d", "d0") - 1).alias("len_change"), (ratio("er0", "er") - 1).alias("er_gain"), (1 - ratio("er", "er0")).alias("er_drop"), (ratio("popularity", "p0") - 1).alias("pop_change"),
    )


def summarise(rel: DataFrame, keys: list[str], mode: str = "mean_of_ratios") -> DataFrame:
    """Means over trips; ``ratio_of_means`` divides the means instead. n_undefined counts trips whose base popularity is 0."""
    n = [F.count("*").alias("trips"), F.count_if(F.expr("p0 = 0")).alias("n_undefined")]
    if mode == "mean_of_ratios":
        how = [F.avg(c).alias(c) for c in ("len_change", "er_gain", "er_drop", "pop_change")]
    elif mode == "ratio_of_means":
        r = lambda a, z: F.try_divide(F.avg(a), F.avg(z))
        how = [(r("d", "d0") - 1).alias("len_change"), (r("er0", "er") - 1).alias("er_gain"), (1 - r("er", "er0")).alias("er_drop"), (r("popularity", "p0") - 1).alias("pop_change")]
    else:
        raise ValueError(f"unknown mode {mode}")
    return rel.groupBy(*keys).agg(*n, *how)


def tradeoff(summary: DataFrame) -> DataFrame:
    """Popularity gained against length paid."""
    return summary.select(*[c for c in summary.columns if c not in ("er_gain", "er_drop", "n_undefined", "trips")])


def dominance(rel: DataFrame) -> DataFrame:
    """Trips on which poi_hop is longer, has the lower ratio, is more popular than the enriched route."""
    a = rel.where("algo = 'enriched'").select("city_id", "pair_id", F.col("d").alias("de"), F.col("er").alias("ere"), F.col("popularity").alias("pe"))
    b = rel.where("algo = 'poi_hop'").select("city_id", "pair_id", F.col("d").alias("dh"), F.col("er").alias("erh"), F.col("popularity").alias("ph"))
    return a.join(b, ["city_id", "pair_id"]).agg(
        F.count("*").alias("trips"), F.count_if(F.expr("de < dh")).alias("enriched_shorter"), F.count_if(F.expr("de = dh")).alias("same_length"), F.count_if(F.expr("erh < ere")).alias("hop_lower_er"), F.count_if(F.expr("ph > pe")).alias("hop_more_popular"), F.count_if(F.expr("ph = pe")).alias("same_popularity"),
    )


def dataset_stats(photos: DataFrame, vpop: DataFrame, relations: DataFrame, vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """Per city: photos, most photos on a vertex, close pairs, their words, vertices, edges."""
    by = lambda df, *a: df.groupBy("city_id").agg(*a)
    parts = [
        by(photos, F.count("*").alias("photos")), by(vpop, F.max("photos").alias("max_photos")), by(relations, F.count_distinct(F.struct("pi", "pj")).alias("pairs"), F.sum("cnt").alias("relations")),
        by(edges, F.count("*").alias("edges")),
    ]
    out = by(vertices, F.count("*").alias("vertices"))
    for p in parts:
        out = out.join(F.broadcast(p), "city_id", "left")
    return out.select("city_id", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("photos", "max_photos", "pairs", "relations", "vertices", "edges")])


def discount_popularity_corr(costs: DataFrame, cost: str, vpop: DataFrame) -> DataFrame:
    """(city_id, corr): how an edge's discount goes with the photos at its ends; null where either doesn't vary."""
    at = lambda v: small(vpop.select("city_id", F.col("vertex_id").alias(v), F.col("photos").alias(f"p{v}")), ROAD_ROWS)
    e = costs.join(at("u"), ["city_id", "u"], "left").join(at("v"), ["city_id", "v"], "left")
    x, y = 1 - F.col(cost) / F.col("len_dm"), (F.coalesce("pu", F.lit(0)) + F.coalesce("pv", F.lit(0))).cast("double")
    return e.groupBy("city_id").agg(F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)).alias("corr"))


def overlap(paths: DataFrame, costs: DataFrame, a: str = "plain", b: str = "enriched") -> DataFrame:
    """(city_id, pair_id, overlap): length of the edges two planners share over that of those either uses."""
    e = paths.where("edge_id is not null").where(F.col("algo").isin(a, b)).select("city_id", "pair_id", "edge_id", "algo").distinct()
    used = e.groupBy("city_id", "pair_id", "edge_id").agg(F.count("*").alias("by")).join(small(costs.select("city_id", "edge_id", "len_dm"), ROAD_ROWS), ["city_id", "edge_id"])
    return used.groupBy("city_id", "pair_id").agg(F.try_divide(F.sum(F.when(F.col("by") == 2, F.col("len_dm")).otherwise(0)).cast("double"), F.sum("len_dm").cast("double")).alias("overlap"))


def search_effort(rounds: list[tuple[int, int]], spark) -> DataFrame:
    """(round, frontier_rows) of the distributed search."""
    return spark.createDataFrame(rounds or [], "round int, frontier_rows long")


def running(paths: DataFrame, costs: DataFrame, vpop: DataFrame) -> DataFrame:
    """(city_id, pair_id, seq, vertex_id, run_len, run_pop): length and popularity up to every vertex of a path."""
    order = Window.partitionBy("city_id", "pair_id").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    t = paths.join(small(costs.select("city_id", "edge_id", "len_dm"), ROAD_ROWS), ["city_id", "edge_id"], "left").join(small(vpop, ROAD_ROWS), ["city_id", "vertex_id"], "left")
    return t.select("city_id", "pair_id", "seq", "vertex_id", F.coalesce(F.sum("len_dm").over(order), F.lit(0)).alias("run_len"), F.coalesce(F.sum("photos").over(order), F.lit(0)).alias("run_pop"))
