"""Reading and writing: word lists and gazetteers, road lattices of any size, partitioned and bucketed tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import RoadGraph
from ..operators.text import Phrase

GAZETTEER = "name string, poi_id long, etype string, x double, y double"
LEXICON = "rel_id int, phrase string, kind string"


def read_gazetteer(spark: SparkSession, path: str, kind: str = "csv") -> DataFrame:
    """(name, poi_id, etype, x, y) from CSV with a header, JSON lines or Parquet, under a fixed schema; rows without a name are dropped."""
    r = spark.read.schema(GAZETTEER)
    df = {"csv": lambda: r.option("header", True).csv(path), "json": lambda: r.json(path), "parquet": lambda: r.parquet(path)}[kind]()
    return df.where("name is not null and name <> ''")


def read_lexicon(spark: SparkSession, path: str, kind: str = "json", most: int = 1000) -> tuple[Phrase, ...]:
    """The relation words as literals; a list longer than ``most`` is refused."""
    r = spark.read.schema(LEXICON)
    rows = (r.option("header", True).csv(path) if kind == "csv" else r.json(path)).where("phrase is not null").orderBy("rel_id", "phrase").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} relation words")
    return tuple(Phrase(x.rel_id, x.phrase, x.kind or "close") for x in rows)


def lattice(spark: SparkSession, width: int, height: int, city_id: int = 0) -> RoadGraph:
    """A jittered grid of width x height vertices made on the executors, for scale runs."""
    n = width * height
    jitter = lambda salt: F.pmod(F.xxhash64("id", F.lit(salt)), F.lit(21)) - 10
    v = spark.range(n).select(F.lit(city_id).alias("city_id"), F.col("id").alias("vertex_id"), (100 * (F.col("id") % width) + jitter(1)).alias("x"), (100 * F.floor(F.col("id") / width) + jitter(2)).cast("long").alias("y"))
    step = F.explode(F.array(F.struct(F.lit(0).alias("d"), F.lit(1).alias("by")), F.struct(F.lit(1).alias("d"), F.lit(width).alias("by"))))
    e = spark.range(n).select(F.col("id").alias("u"), step.alias("s")).where((F.col("u") + F.col("s.by") < n) & ((F.col("s.d") == 1) | ((F.col("u") + 1) % width != 0)))
    e = e.select(F.lit(city_id).alias("city_id"), (2 * F.col("u") + F.col("s.d")).alias("edge_id"), "u", (F.col("u") + F.col("s.by")).alias("v"), (900 + F.pmod(F.xxhash64("u", "s.d"), F.lit(300))).alias("len_dm"))
    return RoadGraph(v, e)


def write_by_city(df: DataFrame, path: str, *more: str) -> None:
    """Parquet partitioned by city (and, say, alpha), rows of a city dealt together first so that files stay few."""
    df.repartition("city_id", *more).write.mode("overwrite").partitionBy("city_id", *more).parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str = "u", buckets: int = 64) -> DataFrame:
    """A table bucketed and sorted by ``key``: joins on it shuffle only the other side."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)


def write_summary(df: DataFrame, path: str, kind: str = "csv") -> None:
    """A small result as one CSV or JSON file."""
    w = df.coalesce(1).write.mode("overwrite")
    w.option("header", True).csv(path) if kind == "csv" else w.json(path)
