"""Streams: photo counts in windows, sessions, running counts per place, late and repeated photos; texts as they come."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import text
from ..session import ROAD_ROWS, Stored, shared_dir, small

LATE = "1 hour"


def events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The photo events as a stream of Parquet files."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path if spark_is_folder(spark, path) else f"{sf_dir}/event[s].parquet")
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need a time with a zone


def spark_is_folder(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def windowed(photos: DataFrame, size: str = "1 day", slide: str | None = None, late: str = LATE) -> DataFrame:
    """(start, event_type, photos) per tumbling or sliding window; photos later than the watermark are dropped."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    t = photos.withWatermark("ts", late) if photos.isStreaming else photos
    return t.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("photos")).select(F.col("w.start").alias("start"), "event_type", "photos")


def sessions(photos: DataFrame, gap: str = "30 minutes", late: str = LATE) -> DataFrame:
    """(user_id, start, end, photos): walks, parted where a user pauses for ``gap``."""
    t = photos.withWatermark("ts", late) if photos.isStreaming else photos
    return t.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("photos")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "photos")


def distinct_photos(photos: DataFrame, key: str = "event_id", late: str = LATE) -> DataFrame:
    """Photos once each; a repeat within the watermark is dropped and forgotten after it."""
    return photos.withWatermark("ts", late).dropDuplicatesWithinWatermark([key]) if photos.isStreaming else photos.dropDuplicates([key])


def near_vertices(photos: DataFrame, vertices: DataFrame, radius: float = 20.0) -> DataFrame:
    """Stream-static join of photos (city_id, x, y) with the vertex grid: one row per photo and vertex within the radius."""
    at = lambda x: F.floor(F.col(x) / radius).cast("long")
    around = F.sequence(F.lit(-1), F.lit(1))
    v = vertices.select("city_id", "vertex_id", F.col("x").alias("vx"), F.col("y").alias("vy"), F.explode(F.transform(around, lambda i: at("x") + i)).alias("cx"), at("y").alias("_cy")).withColumn("cy", F.explode(F.transform(around, lambda i: F.col("_cy") + i))).drop("_cy")
    p = photos.withColumn("cx", at("x")).withColumn("cy", at("y"))
    d = F.sqrt(((F.col("x") - F.col("vx")) * (F.col("x") - F.col("vx")) + (F.col("y") - F.col("vy")) * (F.col("y") - F.col("vy"))).cast("double"))
    return p.join(small(v, ROAD_ROWS), ["city_id", "cx", "cy"]).where(d <= radius).drop("vx", "vy", "cx", "cy")


def running_counts(photos: DataFrame, key: str = "user_id", expire_ms: int = 86_400_000) -> DataFrame:
    """(key, seen, last): photos of each key so far; a key that pauses for ``expire_ms`` of event time starts anew."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def run(k, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, last = state.get if state.exists else (0, 0)
        for f in frames:
            n += len(f)
            last = max(last, int(f["ts"].max().timestamp() * 1000))
        state.update((n, last))
        state.setTimeoutTimestamp(max(last + expire_ms, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({key: [k[0]], "seen": [n], "last": [last]})

    return photos.withWatermark("ts", LATE).groupBy(key).applyInPandasWithState(run, f"{key} long, seen long, last long", "n long, last long", "update", GroupStateTimeout.EventTimeTimeout)


def finished(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Run a stream over what there is now into Parquet files of the shared folder and read them.

    Each micro-batch has a folder by its number, so a batch that is run again replaces its own files. ``complete`` reads
    the last batch; ``append`` and ``update`` read all (a key that several batches update has a row from each).
    """
    spark = stream.sparkSession
    path, last = f"{shared_dir(spark)}/stream-{name}", [-1]

    def batch(df: DataFrame, batch_id: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/out/batch={batch_id}")
        last[0] = max(last[0], batch_id)

    q = stream.writeStream.foreachBatch(batch).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/state").start()
    q.awaitTermination()
    if last[0] < 0:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{path}/out/batch={last[0]}" if mode == "complete" else f"{path}/out/batch=*")


def incremental_pairs(texts: DataFrame, gazetteer: DataFrame, merge: Callable[[DataFrame, int], None], **how):
    """Start extraction of newly arriving texts: the narrow steps run per micro-batch, ``merge`` gets each batch's pair counts."""
    def batch(df: DataFrame, batch_id: int) -> None:
        merge(text.relation_edges(text.extract_triplets(df, gazetteer, **how)), batch_id)

    return texts.writeStream.foreachBatch(batch)


class PairCounts:
    """Pair counts kept in the shared folder; a batch seen before is not counted twice."""

    def __init__(self):
        self.table: Stored | None = None
        self.seen: set[int] = set()

    def __call__(self, edges: DataFrame, batch_id: int) -> None:
        if batch_id in self.seen:
            return
        both = edges if self.table is None else self.table.df.unionByName(edges)
        new = Stored(both.groupBy("pi", "pj", "rel_id").agg(F.sum("cnt").alias("cnt")), "pair-counts")
        if self.table is not None:
            self.table.drop()
        self.table = new
        self.seen.add(batch_id)
