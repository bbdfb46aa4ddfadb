"""The paper's inputs made from the given tables: road lattice, places, gazetteer, photos, trips.

A city is a row of ``region``. All values come from integer arithmetic, md5 and square roots, so any engine derives the
same ones.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.geo import distance
from ..session import table

SEED = "42"


def whole(a, b: int):
    return F.floor(a / b).cast("long")


def road_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(city_id, vertex_id, col, row, x, y, w): a jittered lattice per city, in metres."""
    part = table(spark, sf_dir, "part").select("p_partkey", "p_size")
    city = (F.col("p_partkey") % 5).cast("int")
    widths = part.groupBy(city.alias("city_id")).agg(F.ceil(F.sqrt(F.count("*").cast("double"))).cast("long").alias("w"))
    k = whole(F.col("p_partkey"), 5)
    v = part.select(city.alias("city_id"), k.alias("vertex_id"), "p_partkey", "p_size").join(F.broadcast(widths), "city_id")  # five rows
    v = v.withColumns({"col": F.col("vertex_id") % F.col("w"), "row": F.floor(F.col("vertex_id") / F.col("w")).cast("long")})
    return v.select("city_id", "vertex_id", "col", "row", (100 * F.col("col") + (7 * F.col("p_size")).cast("long") % 21 - 10).alias("x"), (100 * F.col("row") + (13 * F.col("p_partkey")) % 21 - 10).alias("y"), "w", "p_partkey")


def road_edges(vertices: DataFrame) -> DataFrame:
    """(city_id, edge_id, u, v, len_dm): right and lower neighbours; some right ones are missing."""
    to = vertices.select("city_id", F.col("vertex_id").alias("v"), F.col("row").alias("row_v"), F.col("x").alias("xv"), F.col("y").alias("yv"))
    u = vertices.select("city_id", F.col("vertex_id").alias("u"), "row", "x", "y", "w", "p_partkey")
    side = u.withColumn("step", F.explode(F.array(F.struct(F.lit(0).cast("long").alias("down"), F.lit(1).cast("long").alias("by")), F.struct(F.lit(1).cast("long").alias("down"), F.col("w").alias("by")))))
    e = side.withColumn("v", F.col("u") + F.col("step.by")).join(to, ["city_id", "v"])
    kept = (F.col("step.down") == 1) | ((F.col("row") == F.col("row_v")) & (F.col("p_partkey") % 7 != 3))
    return e.where(kept).select("city_id", (2 * F.col("u") + F.col("step.down")).alias("edge_id"), "u", "v", F.round(10 * distance(F.col("x"), F.col("y"), F.col("xv"), F.col("yv"))).cast("long").alias("len_dm"))


def _extent(vertices: DataFrame) -> DataFrame:
    return vertices.groupBy("city_id").agg(F.max("col").alias("mc"), F.max("row").alias("mr"))


def _placed(rows: DataFrame, vertices: DataFrame) -> DataFrame:
    """x and y from (city_id, key, cents)."""
    at = rows.join(F.broadcast(_extent(vertices)), "city_id")
    return at.withColumns({"x": (7919 * F.col("key") + 31 * F.col("cents")) % (100 * F.col("mc")), "y": (104729 * F.col("key") + 17 * F.col("cents")) % (100 * F.col("mr"))}).drop("mc", "mr")


def pois(spark: SparkSession, sf_dir: str, who: str = "supplier") -> DataFrame:
    """(city_id, poi_id, name, x, y) from suppliers, or customers as the large variant."""
    p = who[0]
    cents = F.abs(F.round(100 * F.col(f"{p}_acctbal"))).cast("long")
    key = F.col("s_suppkey" if p == "s" else "c_custkey")
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias(f"{p}_nationkey"), F.col("n_regionkey").cast("int").alias("city_id"))
    rows = table(spark, sf_dir, who).join(F.broadcast(nation), f"{p}_nationkey").select("city_id", key.alias("key"), F.col(f"{p}_name").alias("name"), cents.alias("cents"))
    return _placed(rows, road_vertices(spark, sf_dir)).select("city_id", F.col("key").alias("poi_id"), "name", "x", "y")


def hex_part(text, start: int):
    """Eight hexadecimal digits of the md5 from ``start`` (1-based) as a long."""
    return F.conv(F.substring(F.md5(text), start, 8), 16, 10).cast("long")


def gazetteer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(name, poi_id, etype): names of places, taken from words of at least 4 letters in at least 3 English texts."""
    docs = table(spark, sf_dir, "documents").where("lang = 'en'").select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0))).alias("name"))
    names = docs.where(F.length("name") >= 4).groupBy("name").agg(F.count("*").alias("docs")).where("docs >= 3").select("name")
    n = table(spark, sf_dir, "supplier").agg(F.count("*").alias("n"), F.min("s_suppkey").alias("lo"))
    kinds = F.array(*[F.lit(k) for k in ("ORG", "LOC", "FAC", "GPE")])
    return names.where(hex_part(F.col("name"), 1) % 4 == 0).join(F.broadcast(n)).select("name", (hex_part(F.col("name"), 9) % F.col("n") + F.col("lo")).alias("poi_id"), F.element_at(kinds, (hex_part(F.col("name"), 17) % 4).cast("int") + 1).alias("etype"))


def heldout_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(name): recognised as places, absent from the gazetteer."""
    docs = table(spark, sf_dir, "documents").where("lang = 'en'").select(F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0))).alias("name"))
    names = docs.where(F.length("name") >= 4).groupBy("name").agg(F.count("*").alias("docs")).where("docs >= 3")
    return names.where((hex_part(F.col("name"), 1) % 4 == 1) & (hex_part(F.col("name"), 9) % 25 == 0)).select("name")


def photos(spark: SparkSession, sf_dir: str, events: DataFrame | None = None) -> DataFrame:
    """(city_id, photo_id, user_id, ts, event_type, x, y): purchases and sign-ups near the host place, others spread.

    ``events`` may be a stream of the event table's rows.
    """
    events = table(spark, sf_dir, "events") if events is None else events
    vertices = road_vertices(spark, sf_dir)
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("s_nationkey"), F.col("n_regionkey").cast("int").alias("city_id"))
    host = table(spark, sf_dir, "supplier").join(F.broadcast(nation), "s_nationkey").select("city_id", F.col("s_suppkey").alias("key"), F.abs(F.round(100 * F.col("s_acctbal"))).cast("long").alias("cents"))
    n = table(spark, sf_dir, "supplier").agg(F.count("*").alias("n"), F.min("s_suppkey").alias("lo"))
    placed = _placed(host, vertices).withColumnRenamed("x", "px").withColumnRenamed("y", "py").join(F.broadcast(_extent(vertices)), "city_id")
    e = events.select("event_id", "ts", "user_id", "event_type").join(F.broadcast(n)).withColumn("key", F.col("user_id") % F.col("n") + F.col("lo"))
    near = F.col("event_type").isin("purchase", "signup")
    i, c = F.col("event_id"), F.col("cents")
    return e.join(placed, "key").select(
        "city_id", i.alias("photo_id"), "user_id", "ts", "event_type",
        F.when(near, F.col("px") + (37 * i) % 81 - 40).otherwise((7919 * i + 31 * c) % (100 * F.col("mc"))).alias("x"),
        F.when(near, F.col("py") + (53 * i) % 81 - 40).otherwise((104729 * i + 17 * c) % (100 * F.col("mr"))).alias("y"),
    )


def extents(vertices: DataFrame, kind: str = "diagonal") -> DataFrame:
    """(city_id, extent): the bounding box's diagonal, or its longer side."""
    w, h = F.max("x") - F.min("x"), F.max("y") - F.min("y")
    return vertices.groupBy("city_id").agg((F.sqrt((w * w + h * h).cast("double")) if kind == "diagonal" else F.greatest(w, h).cast("double")).alias("extent"))


def trip_candidates(vertices: DataFrame, ends: int = 60, seed: str = SEED) -> DataFrame:
    """(city_id, s, t, sx, sy, tx, ty): pairs of drawn starts and drawn targets; ends**2 per city, however large it is."""
    def draw(tag: str, name: str) -> DataFrame:
        by = F.md5(F.concat_ws(":", F.lit(f"{seed}{tag}"), "vertex_id"))
        order = Window.partitionBy("city_id").orderBy(by, "vertex_id")
        return vertices.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= ends).select("city_id", F.col("vertex_id").alias(name), F.col("x").alias(f"{name}x"), F.col("y").alias(f"{name}y"))

    return draw("s", "s").join(draw("t", "t"), "city_id").where("s <> t")


def pick_trips(candidates: DataFrame, measure, brackets: list[tuple[str, float, float]], n: int, setting: str, seed: str = SEED) -> DataFrame:
    """(city_id, setting, bracket, trip_id, s, t): the first n by md5 per city and bracket of ``measure`` over the extent."""
    part = F.array(*[F.struct(F.lit(b).alias("bracket"), F.lit(lo).alias("lo"), F.lit(hi).alias("hi")) for b, lo, hi in brackets])
    c = candidates.withColumn("share", measure / F.col("extent")).withColumn("b", F.explode(part)).where((F.col("share") >= F.col("b.lo")) & (F.col("share") < F.col("b.hi")))
    order = Window.partitionBy("city_id", "b.bracket").orderBy(F.md5(F.concat_ws(":", F.lit(seed), "s", "t")), "s", "t")
    return c.withColumn("trip_id", F.row_number().over(order)).where(F.col("trip_id") <= n).select("city_id", F.lit(setting).alias("setting"), F.col("b.bracket").alias("bracket"), "trip_id", "s", "t")


def trips_straight(vertices: DataFrame, n: int = 100, ends: int = 60) -> DataFrame:
    """Setting i: straight line of 30 to 50 % of the extent."""
    c = trip_candidates(vertices, ends).join(F.broadcast(extents(vertices)), "city_id")
    return pick_trips(c, distance(F.col("sx"), F.col("sy"), F.col("tx"), F.col("ty")), [("30-50", 0.3, 0.5)], n, "i")


def lineitem_vectors_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(city_id, rel_id, pi, pj): suppliers of consecutive lines of an order, same city and near enough for the word."""
    p = pois(spark, sf_dir)
    v = road_vertices(spark, sf_dir).agg(F.max("col").alias("m"))
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    li = li.select(F.col("l_suppkey").alias("pi"), F.lead("l_suppkey").over(order).alias("pj"), "l_linenumber").where("pj is not null and pi <> pj")
    a, b = p.select(F.col("poi_id").alias("pi"), "city_id", F.col("x").alias("xi"), F.col("y").alias("yi")), p.select(F.col("poi_id").alias("pj"), F.col("city_id").alias("cj"), F.col("x").alias("xj"), F.col("y").alias("yj"))
    d = distance(F.col("xi"), F.col("yi"), F.col("xj"), F.col("yj"))
    return li.join(a, "pi").join(b, "pj").where("city_id = cj").join(F.broadcast(v)).where(d <= 100 * (2 + F.col("l_linenumber")) * F.greatest(F.lit(1.0), F.col("m") / 20.0)).select("city_id", (F.col("l_linenumber") % 5).cast("int").alias("rel_id"), "pi", "pj", "xi", "yi", "xj", "yj")


def planted_statements(spark: SparkSession, sf_dir: str, phrases: list[str]) -> DataFrame:
    """(doc_id, pi, pj, nth, ni, nj): every supplier beside the next of its city, with the place of one of the phrases and a name of letters each."""
    p = pois(spark, sf_dir).select("city_id", "poi_id")
    nxt = F.lead("poi_id").over(Window.partitionBy("city_id").orderBy("poi_id"))
    name = lambda c: F.concat(F.lit("p"), F.translate(F.col(c).cast("string"), "0123456789", "abcdefghij"))
    t = p.withColumn("pj", nxt).where("pj is not null").withColumnRenamed("poi_id", "pi")
    return t.select(F.col("pi").alias("doc_id"), "pi", "pj", (F.col("pi") % len(phrases)).cast("int").alias("nth"), name("pi").alias("ni"), name("pj").alias("nj"))


def planted_texts(planted: DataFrame, phrases: list[str]) -> DataFrame:
    """(doc_id, text): a sentence for each statement, and one that says nothing."""
    phrase = F.element_at(F.array(*map(F.lit, phrases)), F.col("nth") + 1)
    return planted.select("doc_id", F.concat(F.col("ni"), F.lit(" is "), phrase, F.lit(" the "), F.col("nj"), F.lit(". We saw "), F.col("ni"), F.lit(" and then "), F.col("nj"), F.lit(" later.")).alias("text"))
