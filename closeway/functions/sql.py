"""The SQL user's surface: views, scalar functions and table functions."""

from __future__ import annotations

import re
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

# Scalar functions as SQL macros: they are inlined, so nothing leaves the JVM.
SCALARS = {
    "er_gain": ("er_base DOUBLE, er DOUBLE", "DOUBLE", "try_divide(er_base, er) - 1"),
    "er_drop": ("er_base DOUBLE, er DOUBLE", "DOUBLE", "1 - try_divide(er, er_base)"),
    "bearing": ("xr DOUBLE, yr DOUBLE, xl DOUBLE, yl DOUBLE", "DOUBLE", "pmod(atan2(yl - yr, xl - xr), 2 * pi())"),
    "line_length": ("x1 DOUBLE, y1 DOUBLE, x2 DOUBLE, y2 DOUBLE", "DOUBLE", "sqrt((x1 - x2) * (x1 - x2) + (y1 - y2) * (y1 - y2))"),
}


@udtf(returnType="sent_id int, sentence string")
class SentencesOf:
    """sentences_of(text): the parts between . ! ? and line breaks that hold more than blanks."""

    def eval(self, text: str) -> Iterator[tuple[int, str]]:
        for i, s in enumerate(re.split("[.!?\n]", text or "")):
            if s.strip(" "):
                yield i, s


@udtf(returnType="seq int, vertex_id long")
class ExpandRoute:
    """expand_route(vertices): a path kept as an array, one row per position."""

    def eval(self, vertices: list) -> Iterator[tuple[int, int]]:
        yield from enumerate(vertices or [])


def register(spark: SparkSession, **views: DataFrame) -> None:
    """Register the functions and name the given tables as views."""
    for name, (args, kind, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("sentences_of", SentencesOf)
    spark.udtf.register("expand_route", ExpandRoute)
    for name, df in views.items():
        df.createOrReplaceTempView(name)
