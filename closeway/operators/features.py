"""Displacement vectors of statements: distance and direction seen from the reference place."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geo import bearing, distance
from ..session import small


def attach_coords(triplets: DataFrame, places: DataFrame) -> DataFrame:
    """Adds city_id, xi, yi, xj, yj; pairs in different cities are dropped."""
    a = places.select(F.col("poi_id").alias("pi"), "city_id", F.col("x").alias("xi"), F.col("y").alias("yi"))
    b = places.select(F.col("poi_id").alias("pj"), F.col("city_id").alias("_cj"), F.col("x").alias("xj"), F.col("y").alias("yj"))
    return triplets.join(small(a), "pi").join(small(b), "pj").where("city_id = _cj").drop("_cj")


def measured(located: DataFrame, drop_coincident: bool = True) -> DataFrame:
    """dist and theta from xi, yi (located place) and xj, yj (reference place)."""
    d = located.withColumn("dist", distance(F.col("xi"), F.col("yi"), F.col("xj"), F.col("yj"))).withColumn("theta", bearing(F.col("xj"), F.col("yj"), F.col("xi"), F.col("yi")))
    return (d.where("dist > 0") if drop_coincident else d).drop("xi", "yi", "xj", "yj")


def vectors(edges: DataFrame, places: DataFrame, drop_coincident: bool = True) -> DataFrame:
    """(city_id, rel_id, pi, pj, dist, theta, w): one row per pair and word, weighted by its statements."""
    return measured(attach_coords(edges, places), drop_coincident).select("city_id", "rel_id", "pi", "pj", "dist", "theta", F.col("cnt").cast("double").alias("w"))


def pair_vectors(edges: DataFrame, places: DataFrame) -> DataFrame:
    """(city_id, pi, pj, dist, theta): one row per ordered pair with at least one word."""
    return measured(attach_coords(edges.select("pi", "pj").distinct(), places)).select("city_id", "pi", "pj", "dist", "theta")


def recenter(vecs: DataFrame) -> DataFrame:
    """Directions turned so that each word's circular mean is pi; adds theta0, the angle taken off."""
    t0 = vecs.groupBy("rel_id").agg(F.atan2(F.sum(F.col("w") * F.sin("theta")), F.sum(F.col("w") * F.cos("theta"))).alias("theta0"))
    two = F.lit(2 * math.pi)
    return vecs.join(F.broadcast(t0), "rel_id").withColumn("theta", F.pmod(F.col("theta") - F.col("theta0") + math.pi, two))


def quantise(vecs: DataFrame, d_cell: float, o_cell: float) -> DataFrame:
    """(rel_id, dist, theta, w): weighted centres of cells, so that fitting costs follow cells and not statements."""
    cd, co = F.floor(F.col("dist") / d_cell), F.floor(F.col("theta") / o_cell)
    return vecs.groupBy("rel_id", cd.alias("cd"), co.alias("co")).agg(F.sum("w").alias("w")).select("rel_id", ((F.col("cd") + 0.5) * d_cell).alias("dist"), ((F.col("co") + 0.5) * o_cell).alias("theta"), "w")
