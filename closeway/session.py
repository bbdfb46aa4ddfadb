"""Session helpers: reading tables, cutting lineage, bounded broadcasts."""

from __future__ import annotations

import tempfile
import uuid
from typing import ClassVar

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a side that may be broadcast or collected after its size was checked.
BROADCAST_ROWS = 2_000_000
#: The same for sides that grow with roads and photos, of which several are joined at once; some 30 MB of the driver's memory each.
ROAD_ROWS = 250_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The shared folder the cluster names in ``spark.checkpoint.dir``; an own one only where that is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        named = tempfile.mkdtemp(prefix="closeway-shared-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage by a reliable checkpoint; for small and middle tables."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


class Stored:
    """A table written once as Parquet in the shared folder and read back; ``drop`` removes it, ``sweep`` removes all."""

    live: ClassVar[dict[str, Stored]] = {}

    def __init__(self, df: DataFrame, name: str, *partition_by: str):
        spark = df.sparkSession
        self.spark, self.path = spark, f"{shared_dir(spark)}/closeway-{name}-{uuid.uuid4().hex}"
        df.write.partitionBy(*partition_by).parquet(self.path)
        self.schema = df.schema
        Stored.live[self.path] = self

    @property
    def df(self) -> DataFrame:
        """The table, read anew each time so that it can be joined with itself."""
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        jvm = self.spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(self.path)
        p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        Stored.live.pop(self.path, None)


def sweep() -> int:
    """Remove every stored table of this process, once the results that read them have been written; gives their number."""
    every = list(Stored.live.values())
    for t in every:
        t.drop()
    return len(every)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint behind a row count; beyond the bound the join sorts and merges.

    The planner goes by the size of compressed files, times nothing for an explode, and would broadcast such a side too.
    """
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df.hint("merge")


def large(df: DataFrame, rows: int = ROAD_ROWS) -> DataFrame:
    """A table of more than so many rows, read from its files, is never broadcast unasked: its joins sort and merge.

    Its compressed files, and fewer columns of them still, look small to the planner.
    """
    return df.hint("merge") if df.count() > rows else df
