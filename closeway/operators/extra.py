"""Joins by time, fuzzy names, route text, sampling and recursion, beside the paper's own steps."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], time: str = "ts", value: str = "version") -> DataFrame:
    """Each left row with the value of the latest right row of its keys not after it (null if none).

    Both sides are put into one sorted run per key and the last value is carried along: one shuffle, no range join.
    """
    a = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    b = right.select(*keys, time, F.col(value).alias("_v"), F.lit(0).alias("_side"))
    run = Window.partitionBy(*keys).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("_v", F.last("_v", ignorenulls=True).over(run))
    return both.where("_side = 1").drop("_side").withColumnRenamed("_v", value)


def fuzzy_names(mentions: DataFrame, gazetteer: DataFrame, most: int = 1) -> DataFrame:
    """(name, near, edits): names outside the gazetteer with gazetteer names of the same sound at most ``most`` edits off.

    The sound and the length within ``most`` make an equality join; the edit distance is tested on its hits.
    """
    m = mentions.select("name").distinct().join(gazetteer.select("name"), "name", "left_anti")
    off = F.explode(F.sequence(F.length("name") - most, F.length("name") + most)).alias("len")
    a = m.select("name", F.soundex("name").alias("sound"), off)
    b = gazetteer.select(F.col("name").alias("near"), F.soundex("name").alias("sound"), F.length("name").alias("len")).distinct()
    return a.join(b, ["sound", "len"]).withColumn("edits", F.levenshtein("name", "near")).where(F.col("edits") <= most).select("name", "near", "edits")


def geojson(paths: DataFrame, vertices: DataFrame) -> DataFrame:
    """(city_id, pair_id, route): each path as a line-string text."""
    xy = paths.join(vertices.select("city_id", "vertex_id", "x", "y"), ["city_id", "vertex_id"])
    points = F.transform(F.array_sort(F.collect_list(F.struct("seq", "x", "y"))), lambda p: F.array(p["x"], p["y"]))
    return xy.groupBy("city_id", "pair_id").agg(points.alias("c")).select("city_id", "pair_id", F.to_json(F.struct(F.lit("LineString").alias("type"), F.col("c").alias("coordinates"))).alias("route"))


def sample_trips(trips: DataFrame, share: float, seed: int = 7) -> DataFrame:
    """The same share of every bracket's trips, drawn independently."""
    brackets = [r.bracket for r in trips.select("bracket").distinct().collect()]
    return trips.sampleBy("bracket", {b: share for b in brackets}, seed)


def reachable(edges: DataFrame, sources: DataFrame, hops: int) -> DataFrame:
    """(city_id, source, v, hops): vertices within ``hops`` steps of each source of (city_id, source); for small neighbourhoods.

    One relaxation per step; vertices met before are left out of the next.
    """
    arcs = edges.select("city_id", F.col("u").alias("v"), F.col("v").alias("to")).unionByName(edges.select("city_id", "v", F.col("u").alias("to")))
    seen = cut(sources.distinct().select("city_id", "source", F.col("source").alias("v"), F.lit(0).alias("hops")))
    last = seen
    for k in range(1, hops + 1):
        step = last.join(arcs, ["city_id", "v"]).select("city_id", "source", F.col("to").alias("v")).distinct()
        last = cut(step.join(seen, ["city_id", "source", "v"], "left_anti").withColumn("hops", F.lit(k)))
        seen = seen.unionByName(last)
    return seen
