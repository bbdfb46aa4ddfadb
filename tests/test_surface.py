"""Sources, sinks, SQL functions, joins by time, fuzzy names, recursion, and streams of texts."""

import json

import pytest
from pyspark.sql import functions as F

from closeway.functions import sql
from closeway.operators import extra, graph, measures, routing, text
from closeway.plans import workloads
from closeway.sources import tables
from closeway.streaming import photos as streams


def test_gazetteer_and_lexicon_round_trip(spark, tmp_path):
    rows = spark.createDataFrame([("avonlea", 1, "GPE", 1.0, 2.0), ("", 2, "LOC", 0.0, 0.0)], tables.GAZETTEER)
    tables.write_summary(rows, str(tmp_path / "g"))
    assert [r.name for r in tables.read_gazetteer(spark, str(tmp_path / "g")).collect()] == ["avonlea"]
    (tmp_path / "lex.json").write_text("\n".join(json.dumps({"rel_id": i, "phrase": p}) for i, p in enumerate(("near", "next to"))))
    assert [p.phrase for p in tables.read_lexicon(spark, str(tmp_path / "lex.json"))] == ["near", "next to"]
    with pytest.raises(ValueError):
        tables.read_lexicon(spark, str(tmp_path / "lex.json"), most=1)


def test_lattice_and_layouts(spark, tmp_path):
    g = tables.lattice(spark, 7, 5)
    assert g.vertices.count() == 35 and g.edges.count() == 6 * 5 + 7 * 4
    tables.write_by_city(g.edges, str(tmp_path / "e"))
    assert spark.read.parquet(str(tmp_path / "e")).count() == g.edges.count()
    pair = spark.createDataFrame([(0, "p", 0, 34)], "city_id int, pair_id string, s long, t long")
    local, far = graph.shortest(g, pair, strategy="local"), graph.shortest(g, pair, strategy="distributed")
    assert local.exceptAll(far.select(local.columns)).isEmpty() and local.count() == far.count()


def test_sql_surface(spark):
    sql.register(spark)
    r = spark.sql("SELECT er_gain(1.0, 0.5) AS g, er_drop(1.0, 0.5) AS d, line_length(0, 0, 3, 4) AS l, er_gain(1.0, 0.0) AS n").first()
    assert (r.g, r.d, r.l, r.n) == (1.0, 0.5, 5.0, None)
    assert [(x.sent_id, x.sentence) for x in spark.sql("SELECT * FROM sentences_of('One. Two!')").collect()] == [(0, "One"), (1, " Two")]
    assert [x.vertex_id for x in spark.sql("SELECT * FROM expand_route(array(5L, 7L))").collect()] == [5, 7]


def test_asof_takes_the_latest_before(spark):
    a = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "k int, ts int")
    b = spark.createDataFrame([(1, 2, 10), (1, 5, 11), (1, 6, 12)], "k int, ts int, version int")
    assert sorted((r.k, r.ts, r.version or -1) for r in extra.asof_join(a, b, ["k"]).collect()) == [(1, 1, -1), (1, 5, 11), (2, 9, -1)]


def test_fuzzy_names_are_one_edit_off(spark):
    m = spark.createDataFrame([("avonlee",), ("brixton",), ("zzz",)], "name string")
    g = spark.createDataFrame([("avonlea",), ("brixton",)], "name string")
    assert [tuple(r) for r in extra.fuzzy_names(m, g).collect()] == [("avonlee", "avonlea", 1)]


def test_recursion_counts_hops(spark):
    g = tables.lattice(spark, 4, 4)
    got = {r.v: r.hops for r in extra.reachable(g.edges, spark.createDataFrame([(0, 0)], "city_id int, source long"), 3).collect()}
    assert got == {4 * y + x: x + y for x in range(4) for y in range(4) if x + y <= 3}


def test_texts_as_a_stream(spark, tmp_path):
    docs = spark.createDataFrame([(1, "Avonlea lies near Brixton."), (2, "Avonlea lies near Brixton!")], "doc_id long, text string")
    docs.repartition(2).write.parquet(str(tmp_path / "in"))
    names = spark.createDataFrame([("avonlea", 1, "GPE"), ("brixton", 2, "GPE")], "name string, poi_id long, etype string")
    counts = streams.PairCounts()
    src = spark.readStream.schema(docs.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = streams.incremental_pairs(src, names, counts, lexicon=text.TRAVEL_LEXICON).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert [tuple(r) for r in counts.table.df.collect()] == [(1, 2, 2, 2)]
    counts(counts.table.df.where(F.lit(True)), max(counts.seen))  # a batch seen before
    assert counts.table.df.first().cnt == 2


def test_html_to_text(spark):
    p = spark.createDataFrame([(1, "<p>A&nbsp;&amp; b</p><!-- x --><script>var a;</script><STYLE>p{}</STYLE> c")], "page_id long, html string")
    assert text.pages_to_text(p).first().text == "A & b c"


def test_stored_tables_can_be_swept(spark):
    from closeway.plans import catalog
    from closeway.session import Stored, sweep

    catalog.forget()  # its shared stages are stored tables too
    t = Stored(spark.range(3), "some")
    assert t.df.join(t.df, "id").count() == 3 and t.path in Stored.live
    assert sweep() >= 1 and not Stored.live
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        t.df.count()


def grid(spark, n: int):
    """(vertices, photos): n vertices 100 m apart in a row, a photo at each of the first three and two at the fourth."""
    v = spark.range(n).select(F.lit(0).alias("city_id"), F.col("id").alias("vertex_id"), (100 * F.col("id")).alias("x"), F.lit(0).cast("long").alias("y"))
    p = spark.createDataFrame([(0, i, 100 * min(i, 3), 20) for i in range(5)], "city_id int, photo_id long, x long, y long")
    return v, p


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_many_vertices_are_not_broadcast_to_photos(spark):
    v, p = grid(spark, 40_000)
    got = measures.vertex_popularity(p, v)
    assert "BroadcastHashJoin" not in plan(got)
    assert sorted((r.vertex_id, r.photos) for r in got.collect()) == [(0, 1), (1, 1), (2, 1), (3, 2)]
    assert "BroadcastHashJoin" in plan(measures.vertex_popularity(p, v.limit(10)))


def counts(spark, n: int):
    """(city_id, vertex_id, photos) of n vertices, a photo each."""
    return spark.range(n).select(F.lit(0).alias("city_id"), F.col("id").alias("vertex_id"), F.lit(1).cast("long").alias("photos"))


def test_many_counts_are_not_broadcast_to_edges(spark):
    costs = spark.createDataFrame([(0, i, i, i + 1, 10, 10.0 - i) for i in range(3)], "city_id int, edge_id long, u long, v long, len_dm long, cost_100 double")
    got = measures.discount_popularity_corr(costs, "cost_100", counts(spark, 300_000).where("vertex_id <> 1"))
    assert "BroadcastHashJoin" not in plan(got)
    assert got.first().corr == pytest.approx(0.866025, abs=1e-6)  # discounts 0, 0.1, 0.2; photos 1, 1, 2


def test_many_vertices_are_not_broadcast_to_a_stream(spark):
    v, p = grid(spark, 40_000)
    got = streams.near_vertices(p, v)
    assert "BroadcastHashJoin" not in plan(got) and sorted(r.vertex_id for r in got.collect()) == [0, 1, 2, 3, 3]


@pytest.fixture(scope="module")
def way(spark):
    """A path over three vertices with its edges' costs, of which there are many, as there are of counts."""
    paths = spark.createDataFrame([(0, "p", "plain", 0, 5, None), (0, "p", "plain", 1, 6, 5), (0, "p", "plain", 2, 7, 6)], "city_id int, pair_id string, algo string, seq int, vertex_id long, edge_id long")
    costs = spark.range(300_000).select(F.lit(0).alias("city_id"), F.col("id").alias("edge_id"), (F.col("id") % 10 + 1).alias("len_dm"), F.lit(3.0).alias("cost_100"))
    return paths, costs


def test_many_counts_are_not_broadcast_to_paths(spark, way):
    got = measures.popularity(way[0], counts(spark, 300_000))
    assert "BroadcastHashJoin" not in plan(got) and [r.popularity for r in got.collect()] == [3]


def test_many_counts_and_lengths_are_not_broadcast_to_running_sums(spark, way):
    got = measures.running(*way, counts(spark, 300_000))
    assert "BroadcastHashJoin" not in plan(got)
    assert sorted((r.seq, r.run_len, r.run_pop) for r in got.collect()) == [(0, 0, 1), (1, 6, 2), (2, 13, 3)]


def test_many_costs_are_not_broadcast_to_paths(way):
    got, same = measures.path_costs(*way, "cost_100"), measures.overlap(*way, "plain", "plain")
    assert "BroadcastHashJoin" not in plan(got) and "BroadcastHashJoin" not in plan(same)
    assert [(r.d, r.c, r.hops) for r in got.collect()] == [(13, 6.0, 2)]


def test_stored_vertices_of_many_are_not_broadcast_to_trips(spark):
    v = workloads.stored(grid(spark, 300_000)[0], "vertices")
    trips = spark.createDataFrame([(0, "i", "30-50", 1, 2, 299_999)], "city_id int, setting string, bracket string, trip_id int, s long, t long")
    got = routing.located(trips, v)
    assert "BroadcastHashJoin" not in plan(got) and [(r.sx, r.tx) for r in got.collect()] == [(200, 29_999_900)]
    few = workloads.stored(v.where("vertex_id < 10"), "vertices")
    assert "BroadcastHashJoin" in plan(routing.located(trips, few))


def test_cells_of_many_places_are_not_broadcast_to_vertices(spark):
    v, _ = grid(spark, 300_000)
    places = spark.range(40_000).select(F.lit(0).alias("city_id"), F.col("id").alias("poi_id"), (F.col("id") % 900).alias("x"), F.lit(5).alias("y"))
    got = graph._snap_round(places, v, "poi_id", 200)
    assert "BroadcastHashJoin" not in plan(got) and got.count() == 40_000
    assert got.where("poi_id = 149").first().vertex_id == 1


def test_trip_costs_are_those_of_whole_trees(spark, monkeypatch, small_dir):
    g = tables.lattice(spark, 7, 7)
    cut_off = g._replace(edges=g.edges.where("u <> 48 and v <> 48"))
    want = spark.createDataFrame([(0, s, t) for s in (0, 5, 99) for t in (3, 48, 20, 77)], "city_id int, s long, t long")
    tree = graph.tree_local(cut_off, want.select("city_id", F.col("s").alias("source"))).select("city_id", F.col("source").alias("s"), F.col("v").alias("t"), "cost")
    got = sorted(map(tuple, graph.costs_local(cut_off, want).collect()))
    assert got == sorted(map(tuple, tree.join(want, ["city_id", "s", "t"]).select("city_id", "s", "t", "cost").collect())) and len(got) == 4
    monkeypatch.setattr(graph, "tree_local", None)  # trips need no labels of whole cities
    assert workloads.World(spark, small_dir, trips=1).trips_ii.count() > 0


def test_fallback_takes_the_enriched_routes_at_hand(spark):
    g = tables.lattice(spark, 6, 6)
    trips = spark.createDataFrame([(0, "i", "b", 1, 0, 14), (0, "i", "b", 2, 3, 30)], "city_id int, setting string, bracket string, trip_id int, s long, t long")
    legs = spark.createDataFrame([(0, "0/i/b/1", 1, 0, 7, "0>7"), (0, "0/i/b/1", 2, 7, 14, "7>14")], "city_id int, pair_id string, leg int, s long, t long, leg_id string")
    known = routing.enriched(g, trips, "len_dm")
    rows = lambda df: sorted(map(tuple, df.select("pair_id", "seq", "vertex_id", F.coalesce("edge_id", F.lit(-1)), "fallback").collect()))
    got = rows(routing.drive(g, legs, trips, "len_dm", enriched_paths=known))
    assert got == rows(routing.drive(g, legs, trips, "len_dm")) and {(r[0], r[4]) for r in got} == {("0/i/b/1", False), ("0/i/b/2", True)}
