"""Shards of nearly equal bytes by sampled splitters; DataFrame functions only.

Rows are ordered by (a 60-bit hash of the text, id), so equal texts lie side by side. Equal rows are counted into one
row first and dealt out again at the end, in runs of bounded length. A size-weighted sample of keys gives quantile
boundaries of many fine ranges; each row is put into its range by a binary search and ranges get their exact sizes. A
range of more than ``RANGE_ROWS`` rows is subdivided by splitters sampled within it, until none is overfull. The exact
running size within each range then gives every row's shard. The splitters thus only decide how the work is dealt,
never the result.

Law ``bytes``: the row whose preceding rows have B of T bytes goes to shard floor(n * B / T), in whole numbers; so
shards differ by less than one row's size at either end. Slots count the rows of a shard from 0 in key order.

Defined results: a null text has no bytes (size 8, crc32 of the empty text); null ids come first; equal rows
are interchangeable; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import Stored, small
from .common import only

#: Bytes added to each text's size for its end mark.
OVERHEAD = 8
#: Keys drawn for each range, about.
DRAWS = 24
#: Most rows of a range, equal rows counted once.
RANGE_ROWS = 1_000_000
#: Most parts that a range is subdivided into at once.
PARTS = 4096
#: Equal rows dealt out by one task at a time.
RUN = 100_000


def text_key(text: Column) -> Column:
    """The first 15 hexadecimal digits of the text's md5, as a long."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def drawn(rows: DataFrame, share: Column, seed: int) -> DataFrame:
    """The rows whose hash, even in (0, 1), falls below ``share``."""
    u = (F.pmod(F.xxhash64("key", "rid", F.lit(seed)), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    return rows.where(u < share)


def splitters(rows: DataFrame, ranges: int, total: int, draws: int = DRAWS) -> list[tuple[int, int]]:
    """Quantile boundaries from a sample of (key, rid), drawn by weight: about ``ranges * draws`` rows."""
    some = drawn(rows, F.lit(float(ranges * draws) / max(total, 1)) * F.col("weight"), 0).select("key", "rid").collect()
    return sorted({(r.key, r.rid) for r in some})[draws - 1 :: draws]


def search(key: Column, rid: Column, keys: Column, ids: Column, n: Column, most: int) -> Column:
    """How many of the n <= ``most`` ascending (keys, ids) are at most (key, rid): a binary search."""
    steps = [1 << k for k in range(max(most, 1).bit_length())][::-1]

    def probe(at: Column, step: Column) -> Column:
        to = at + step
        k, i = F.get(keys, to - 1), F.get(ids, to - 1)
        return F.when((to <= n) & ((k < key) | ((k == key) & (i <= rid))), to).otherwise(at)

    return F.aggregate(F.lit(steps).cast("array<int>"), F.lit(0), probe)


def range_of(key: Column, rid: Column, marks: list[tuple[int, int]]) -> Column:
    """How many splitters are at most (key, rid)."""
    if not marks:
        return F.lit(0)
    return search(key, rid, F.lit([int(k) for k, _ in marks]), F.lit([int(i) for _, i in marks]), F.lit(len(marks)), len(marks))


def subdivided(ranged: DataFrame, range_rows: int, draws: int = DRAWS) -> tuple[DataFrame, DataFrame]:
    """(rows, sizes by range) after every range of more than ``range_rows`` rows was cut by splitters drawn within it.

    Ranges stay in key order: each round multiplies a range's number and adds the part's.
    """
    seed = 1
    while True:
        sizes = Stored(ranged.groupBy("range").agg(F.sum("weight").alias("b"), F.sum("n").alias("n"), F.count("*").alias("rows")), "shard-ranges").df
        over = sizes.where(F.col("rows") > range_rows)
        if over.isEmpty():
            return ranged, sizes
        parts = F.least(F.ceil(2 * F.col("rows") / range_rows), F.lit(PARTS))
        at = drawn(ranged.join(small(over.select("range", parts.cast("int").alias("parts"), (parts * draws / F.col("rows")).alias("share"))), "range"), F.col("share"), seed)
        marks = at.groupBy("range", "parts").agg(F.array_sort(F.collect_set(F.struct("key", "rid"))).alias("m"))
        every = F.greatest(F.lit(1), F.ceil(F.size("m") / F.col("parts"))).cast("int")
        marks = marks.withColumn("every", every).select("range", F.filter("m", lambda _, i: i % F.col("every") == F.col("every") - 1).alias("m")).select("range", F.col("m.key").alias("keys"), F.col("m.rid").alias("ids"))
        marks = Stored(marks, "shard-splitters").df  # about draws rows a part were drawn, at most one a part is left
        part = search(F.col("key"), F.col("rid"), F.col("keys"), F.col("ids"), F.size("keys"), 2 * PARTS)
        columns = [c for c in ranged.columns if c != "range"]
        cut = ranged.join(small(marks, RANGE_ROWS), "range", "left").select(*columns, (F.col("range") * (2 * PARTS + 2) + F.when(F.col("keys").isNull(), 0).otherwise(part)).alias("range"))
        ranged, seed = Stored(cut, "shard-rows").df, seed + 1


def deal(rows: DataFrame, shards: int = 24, ranges_per_shard: int = 32, range_rows: int = RANGE_ROWS) -> DataFrame:
    """(id, size, text_crc32, shard, slot) for rows of (id, key, size, text_crc32)."""
    spark = rows.sparkSession
    same = rows.groupBy("id", "key", "size", "text_crc32").agg(F.count("*").alias("n"))
    same = Stored(same.select("*", F.coalesce(F.col("id").cast("long"), F.lit(-(1 << 63))).alias("rid"), (F.col("n") * F.col("size")).alias("weight")), "shard-keys").df
    total = same.agg(F.sum("weight")).first()[0] or 0
    marks = splitters(same, shards * ranges_per_shard, total)
    ranged, sizes = subdivided(same.withColumn("range", range_of(F.col("key"), F.col("rid"), marks).cast("long")), range_rows)
    before, rows_before, at = 0, 0, []
    for r in sizes.orderBy("range").toLocalIterator():  # shards * ranges_per_shard rows, and one more for about every RANGE_ROWS / 2 rows
        at.append((r["range"], before, rows_before))
        before, rows_before = before + r["b"], rows_before + r["n"]
    heads = spark.createDataFrame(at, "range long, b0 long, n0 long")
    inside = Window.partitionBy("range").orderBy("key", "rid", "size", "text_crc32").rowsBetween(Window.unboundedPreceding, -1)
    placed = (
        ranged.select("*", F.coalesce(F.sum("weight").over(inside), F.lit(0)).alias("b1"), F.coalesce(F.sum("n").over(inside), F.lit(0)).alias("n1"))
        .join(small(heads), "range")
        .select("id", "size", "text_crc32", "n", (F.col("b0") + F.col("b1")).alias("b"), (F.col("n0") + F.col("n1")).alias("nth"))
    )
    placed = Stored(placed, "shard-places").df
    once = placed.where(F.col("n") == 1).select("*", F.lit(0).cast("long").alias("copy"))
    runs = placed.where(F.col("n") > 1).select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1, F.lit(RUN).cast("long"))).alias("lo")).repartition("nth", "lo")
    copies = runs.select("*", F.explode(F.sequence("lo", F.least(F.col("lo") + RUN, F.col("n")) - 1)).alias("copy")).drop("lo")
    every = once.unionByName(copies).withColumns({"b": F.col("b") + F.col("copy") * F.col("size"), "nth": F.col("nth") + F.col("copy")})
    every = every.select("id", "size", "text_crc32", "nth", F.expr(f"cast(({int(shards)} * b) div {max(int(total), 1)} as int)").alias("shard"))
    firsts = Stored(every.groupBy("shard").agg(F.min("nth").alias("first")), "shard-firsts").df
    return every.join(F.broadcast(firsts), "shard").select("id", "size", "text_crc32", "shard", (F.col("nth") - F.col("first")).alias("slot"))  # a row per shard


def shard_by_bytes(docs: DataFrame, shards: int = 24, ranges_per_shard: int = 32, range_rows: int = RANGE_ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) for every row; grown_shard is null under this law."""
    bare = F.coalesce(F.col("text"), F.lit(""))
    keyed = only(docs, id=id_col, text=text_col).select("id", text_key(bare).alias("key"), (F.octet_length(bare) + OVERHEAD).cast("long").alias("size"), F.crc32(bare.cast("binary")).alias("text_crc32"))
    dealt = deal(keyed, shards, ranges_per_shard, range_rows)
    return dealt.select(F.col("id").alias("doc_id"), "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


# CRC-32 in SQL: the table of 256 remainders by its rule, then one step per byte. Fixed value: the polynomial 3988292384.
ORACLE = """
WITH RECURSIVE bits(k, i, c) AS (SELECT i, 0, i FROM range(256) t(i) UNION ALL SELECT k, i + 1, CASE WHEN c % 2 = 1 THEN xor(c // 2, 3988292384) ELSE c // 2 END FROM bits WHERE i < 8),
tab AS (SELECT list(c ORDER BY k) AS r FROM bits WHERE i = 8),
k AS (
  SELECT doc_id, CAST(octet_length(encode(coalesce(text, ''))) + 8 AS BIGINT) AS size, hex(encode(coalesce(text, ''))) AS h,
         CAST('0x' || substr(md5(coalesce(text, '')), 1, 15) AS BIGINT) AS key FROM documents),
o AS (SELECT *, coalesce(sum(size) OVER (ORDER BY key, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS b,
         row_number() OVER (ORDER BY key, doc_id) AS nth, sum(size) OVER () AS total FROM k),
s AS (SELECT *, CAST((24 * b) // total AS INTEGER) AS shard FROM o)
SELECT doc_id, size, xor(list_reduce(list_prepend(CAST(4294967295 AS BIGINT), list_transform(range(0, length(h) // 2), lambda p: CAST('0x' || substr(h, CAST(2 * p + 1 AS BIGINT), 2) AS BIGINT))),
         lambda c, x: xor(c // 256, r[xor(c, x) % 256 + 1])), 4294967295) AS text_crc32, 'bytes' AS law, shard,
       CAST(row_number() OVER (PARTITION BY shard ORDER BY nth) - 1 AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard
FROM s, tab
"""
