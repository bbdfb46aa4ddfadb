"""Every query with an oracle gives the oracle's rows; the others keep the laws that the method has."""

import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

from closeway.operators import graph
from closeway.plans import catalog
from closeway.plans.workloads import World

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small_dir):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{small_dir}/{t}.parquet'")
    return c


def ordered(df: pd.DataFrame) -> pd.DataFrame:
    out = df[sorted(df.columns)].copy()
    for k in out.columns:
        out[k] = out[k].astype(float).round(3) + 0.0 if out[k].dtype.kind in "fiu" else out[k].astype(str)
    return out.sort_values(list(out.columns)).reset_index(drop=True)


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_oracle(name, spark, duck, small_dir):
    got, want = catalog.queries()[name](spark, small_dir).toPandas(), duck.sql(catalog.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    a, b = ordered(got), ordered(want)
    assert len(a) == len(b)
    for k in a.columns:
        if a[k].dtype.kind == "f" and b[k].dtype.kind == "f":
            assert ((a[k] - b[k]).abs().fillna(0) <= 1.1e-3).all() and (a[k].isna() == b[k].isna()).all(), k
        else:
            assert (a[k] == b[k]).all(), k


@pytest.fixture(scope="module")
def world(spark, small_dir):
    return World(spark, small_dir, use_syntax=False, prior="corpus_frequency")


def test_scores_and_costs_keep_their_ranges(world):
    w = world.closeness.selectExpr("min(W)", "max(W)").first()
    assert w[0] is None or (w[0] >= 0 and w[1] <= 1 + 1e-9)
    bad = world.costs.where("cost_100 < 0 or cost_100 > cost_050 + 1e-9 or cost_050 > cost_020 + 1e-9 or cost_020 > len_dm + 1e-9 or (n_paths = 0 and cost_100 <> len_dm)")
    assert bad.isEmpty()


def test_planners_keep_their_laws(world):
    r = world.routes(world.trips_i, (1.0,))
    m = world.measured(r, (1.0,)).toPandas()
    assert (m["d"] >= m["d0"]).all()
    e = m[m["algo"] == "enriched"]
    assert (e["er"] <= e["er0"] + 1e-9).all()
    seqs = r.groupBy("algo", "pair_id").agg(F.max("seq").alias("m"), F.count("*").alias("n"), F.count_distinct("seq").alias("k"))
    assert seqs.where("n <> m + 1 or k <> n").isEmpty()
    joined = r.where("edge_id is not null").join(world.costs.select("city_id", "edge_id", "u", "v"), ["city_id", "edge_id"])
    assert joined.where("vertex_id <> u and vertex_id <> v").isEmpty()


def test_scaling_lengths_changes_no_path(world):
    g = world.roads
    ten = graph.RoadGraph(g.vertices, g.edges.withColumn("len_dm", F.col("len_dm") * 10))
    p = world.pairs.limit(20)
    cols = ["city_id", "pair_id", "seq", "vertex_id"]
    assert graph.shortest(g, p).select(cols).exceptAll(graph.shortest(ten, p).select(cols)).isEmpty()


def test_settings_have_all_points(spark, small_dir):
    q = catalog.queries()
    s = q["setting_alpha"](spark, small_dir).toPandas()
    assert set(s["alpha"]) == {0.2, 0.4, 0.6, 0.8, 1.0} and set(s["algo"]) == {"enriched", "poi_hop"}
    assert q["tradeoff"](spark, small_dir).count() > 0


def test_search_effort_counts_all_trip_starts(spark, small_dir):
    trips = catalog.world(spark, small_dir).trips_i
    rows = catalog.queries()["search_effort"](spark, small_dir).toPandas().sort_values("round")["frontier_rows"]
    edges = graph.arcs(catalog.world(spark, small_dir).roads).select("city_id", F.col("a").alias("s"), "b").distinct()
    assert rows.iloc[0] == trips.select("city_id", "s").distinct().join(edges, ["city_id", "s"]).count() and rows.iloc[-1] == 0


def test_streams_finish(spark, small_dir):
    q = catalog.queries()
    assert q["stream_sliding_photos"](spark, small_dir).agg(F.sum("photos")).first()[0] == 4 * spark.read.parquet(f"{small_dir}/events.parquet").count()
    assert q["stream_sessions"](spark, small_dir).count() > 0
