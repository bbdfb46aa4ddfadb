"""Connected components of a link table, distributed.

Each round every node hooks to its smallest neighbour below it; pointer jumping flattens the trees; the links are
relabelled by the roots and those inside one tree vanish. A root is the smallest node of its tree, so at the end it is
the smallest node of its component. Only counts come to the driver.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut


def _follow(t: DataFrame, column: str, roots: DataFrame) -> DataFrame:
    """t with ``column`` replaced by its root where it has one; the join's skew can be split."""
    r = roots.select(F.col("v").alias("_v"), F.col("p").alias("_p"))
    return t.join(r, F.col(column) == F.col("_v"), "left").withColumn(column, F.coalesce("_p", column)).drop("_v", "_p")


def components(links: DataFrame) -> DataFrame:
    """(v, p) for every node that is not the smallest of its component: p is that smallest node.

    ``links`` has columns a and b; nulls and loops are ignored, repeats are harmless.
    """
    e = cut(links.where("a <> b").select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")).distinct())
    maps: list[DataFrame] = []
    while not e.isEmpty():
        p = cut(e.groupBy(F.col("hi").alias("v")).agg(F.min("lo").alias("p")))
        while True:
            deeper = p.select(F.col("v").alias("_v"), F.col("p").alias("_p"))
            jumped = cut(p.join(deeper, F.col("p") == F.col("_v"), "left").select("v", F.coalesce("_p", "p").alias("p"), F.col("_p").isNotNull().alias("moved")))
            p = jumped.drop("moved")
            if jumped.where("moved").isEmpty():
                break
        maps.append(p)
        e = cut(_follow(_follow(e, "lo", p), "hi", p).where("lo <> hi").select(F.least("lo", "hi").alias("lo"), F.greatest("lo", "hi").alias("hi")).distinct())
    if not maps:
        return e.select(F.col("hi").alias("v"), F.col("lo").alias("p"))
    return reduce(lambda have, later: _follow(have, "p", later).select("v", "p").unionByName(later), maps[1:], maps[0])


def numbered(classes: DataFrame) -> DataFrame:
    """Classes (key, id, ...) with a ``node`` each: the id, or a number above all ids where a class of a smaller key has the id."""
    c = cut(classes)
    first = c.groupBy("id").agg(F.min("key").alias("_first"))
    again = c.join(first, "id").where("key <> _first").select(F.col("key").alias("_k"))
    if again.isEmpty():
        return c.withColumn("node", F.col("id"))
    top = c.agg(F.max("id")).first()[0]
    more = cut(again.select("_k", (F.lit(top) + 1 + F.monotonically_increasing_id()).alias("_node")))
    return c.join(more, F.col("key") == F.col("_k"), "left").select(*c.columns, F.coalesce("_node", "id").alias("node"))
