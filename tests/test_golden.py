"""Worked examples: features, regions, relation graph, sentences, enrichment, scores, ties, photos."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from closeway.functions.geo import bearing, distance, haversine, in_ellipse
from closeway.operators import closeness, features, graph, measures, mixture, routing, text


def test_features_of_the_figure(spark):
    rows = [(1, 1.0, 1.0, 2.0, 2.2), (2, 3.0, 5.0, 1.5, 4.2), (3, 6.5, 5.5, 7.5, 4.8), (4, 8.0, 1.0, 6.5, 3.3)]
    df = spark.createDataFrame(rows, "k int, xr double, yr double, xl double, yl double")
    got = df.select("k", distance(F.col("xl"), F.col("yl"), F.col("xr"), F.col("yr")).alias("d"), F.degrees(bearing(F.col("xr"), F.col("yr"), F.col("xl"), F.col("yl"))).alias("a")).orderBy("k").collect()
    for r, (d, a) in zip(got, [(1.562050, 50.1944), (1.7, 208.0725), (1.220656, 325.0080), (2.745906, 123.1113)], strict=True):
        assert r.d == pytest.approx(d, abs=1e-6) and r.a == pytest.approx(a, abs=1e-4)


def test_haversine_quarter_meridian(spark):
    d = spark.range(1).select(haversine(F.lit(0.0), F.lit(0.0), F.lit(0.0), F.lit(90.0))).first()[0]
    assert d == pytest.approx(math.pi / 2 * 6_371_008.8)


GREEN = [(2.7, 1.1), (3.2, -0.7), (6.3, -0.5), (5.2, 1.3), (4.6, -1.4), (2.5, -0.5), (6.1, 1.7), (7.3, -1.3), (3.4, 1.1), (5.9, -0.8)]
BLUE = [(2.4, 2.0), (2.73, -2.18), (7.5, 2.15), (6.7, -2.1)]


def test_region_of_the_figure(spark):
    df = spark.createDataFrame(GREEN + BLUE, "x double, y double")
    ends = [F.lit(v) for v in (3.0, 0.0, 7.0, 0.0)]
    got = [r[0] for r in df.select(in_ellipse(F.col("x"), F.col("y"), *ends)).collect()]
    assert got == [True] * 10 + [False] * 4
    confocal = [r[0] for r in df.select(in_ellipse(F.col("x"), F.col("y"), *ends, "confocal")).collect()]
    assert confocal[:10] == [True] * 10 and confocal[13]
    box = [r[0] for r in df.select(in_ellipse(F.col("x"), F.col("y"), *ends, "box")).collect()]
    assert sum(not b for b in box[:10]) == 3
    with pytest.raises(ValueError):
        in_ellipse(F.col("x"), F.col("y"), *ends, "circle")


def test_relation_graph_keeps_directions_apart(spark):
    pairs = [(1, 2), (1, 3), (2, 3), (3, 4), (4, 1), (4, 3)]
    t = spark.createDataFrame([(i, 0, j) for i, j in pairs] + [(1, 0, 2), (1, 1, 2)], "pi long, rel_id int, pj long")
    g = {(r.pi, r.pj): (r.n, [(x.rel_id, x.cnt) for x in r.rels]) for r in text.relation_graph(text.relation_edges(t)).collect()}
    assert set(g) == set(pairs) and g[1, 2] == (3, [(0, 2), (1, 1)]) and g[3, 4] == g[4, 3] == (1, [(0, 1)])


SAID = "Avonlea lies near Brixton. The museum of Corvale stands next to Dunmore Hall! Eastbank Trust paid 3 coins in Fairmark. Avonlea is big.\nAvonlea is near Avonlea."
NAMES = [("avonlea", 1, "GPE"), ("brixton", 2, "GPE"), ("corvale", 3, "GPE"), ("dunmore hall", 4, "FAC"), ("hall", 9, "FAC"), ("eastbank trust", 5, "ORG"), ("fairmark", 6, "GPE")]


@pytest.fixture(scope="module")
def said(spark):
    docs = spark.createDataFrame([(1, SAID), (2, None), (3, "")], "doc_id long, text string")
    return docs, spark.createDataFrame(NAMES, "name string, poi_id long, etype string")


def test_sentences_and_the_false_positive(said, spark):
    docs, names = said
    near, next_to, inside = 2, 0, 4
    key = lambda df: {(r.pi, r.rel_id, r.pj) for r in df.collect()}
    both = {(1, near, 2), (3, next_to, 4)}
    got = text.extract_triplets(docs, names, lexicon=text.TRAVEL_LEXICON, max_words=4)
    assert key(got) == both
    words = text.extract_triplets(docs, names, lexicon=text.TRAVEL_LEXICON, max_words=4, use_syntax=False)
    assert key(words) == both | {(5, inside, 6)}
    planted = spark.createDataFrame([(*t,) for t in both], "pi long, rel_id int, pj long")
    q, w = text.extraction_quality(got, planted).first(), text.extraction_quality(words, planted).first()
    assert (q.precision, q.recall) == (1, 1) and w.recall == 1 and w.precision < 1


def test_longest_name_wins(said):
    docs, names = said
    m = text.geoparse(docs, names, 4).where("name like '%hall%'").collect()
    assert [(r.name, r.poi_id) for r in m] == [("dunmore hall", 4)]


def test_keep_closeness_drops_directions(spark):
    t = spark.createDataFrame([(1, 2, 2), (1, 7, 2), (1, 9, 2)], "pi long, rel_id int, pj long")
    assert [r.rel_id for r in text.keep_closeness(t, text.TRAVEL_LEXICON).collect()] == [2]


def _road(spark):
    v = spark.createDataFrame([(0, i, x, y) for i, x, y in [(1, 0, 0), (2, 10, 0), (3, 20, 0), (4, 5, 8)]], "city_id int, vertex_id long, x long, y long")
    e = spark.createDataFrame([(0, 12, 1, 2, 100), (0, 23, 2, 3, 100), (0, 14, 1, 4, 90), (0, 43, 4, 3, 185)], "city_id int, edge_id long, u long, v long, len_dm long")
    return graph.RoadGraph(v, e)


def test_enrichment_and_trip(spark):
    g = _road(spark)
    pairs = spark.createDataFrame([(0, "a", 1, 3, 0.5, 1, 3), (0, "b", 2, 3, 0.2, 2, 3)], "city_id int, pair_id string, pi long, pj long, W double, s long, t long")
    paths = graph.shortest(g, pairs)
    c = graph.edge_costs(g.edges, paths, pairs, [0.0, 0.5, 1.0])
    got = {r.edge_id: (r.cost_000, r.cost_050, r.cost_100, r.n_paths) for r in c.collect()}
    assert got[12] == pytest.approx((100, 75, 50, 1)) and got[23] == pytest.approx((100, 67.5, 40, 2)) and got[14] == pytest.approx((90, 90, 90, 0)) and got[43] == pytest.approx((185, 185, 185, 0))
    trip = spark.createDataFrame([(0, "i", "b", 1, 4, 3)], "city_id int, setting string, bracket string, trip_id int, s long, t long")
    plain = routing.plain(g, trip)
    assert [r.vertex_id for r in plain.orderBy("seq").collect()] == [4, 3]
    gc = graph.enriched(g, c)
    full = routing.enriched(gc, trip, "cost_100")
    assert [r.vertex_id for r in full.orderBy("seq").collect()] == [4, 1, 2, 3]
    assert [r.vertex_id for r in routing.enriched(gc, trip, "cost_050").orderBy("seq").collect()] == [4, 3]
    assert [r.vertex_id for r in routing.enriched(gc, trip, "cost_000").orderBy("seq").collect()] == [4, 3]
    vpop = spark.createDataFrame([(0, 2, 3)], "city_id int, vertex_id long, photos long")
    both = plain.withColumn("algo", F.lit("plain")).unionByName(full.withColumn("algo", F.lit("enriched")))
    m = measures.relative(measures.per_path(both, c, "cost_100", vpop)).first()
    assert m.er == pytest.approx(0.620690, abs=1e-6) and m.er_gain == pytest.approx(0.611111, abs=1e-6) and m.len_change == pytest.approx(0.567568, abs=1e-6) and m.pop_change is None


def test_full_closeness_makes_an_edge_free(spark):
    g = _road(spark)
    pairs = spark.createDataFrame([(0, "a", 1, 2, 1.0, 1, 2)], "city_id int, pair_id string, pi long, pj long, W double, s long, t long")
    c = graph.edge_costs(g.edges, graph.shortest(g, pairs), pairs, [1.0])
    assert {r.edge_id: r.cost_100 for r in c.collect()}[12] == 0
    with pytest.raises(ValueError):
        graph.edge_costs(g.edges, graph.shortest(g, pairs), pairs, [1.5])


def test_scores_of_two_pairs(spark):
    lik = spark.createDataFrame([(0, 1, 2, k, math.log(p)) for k, p in ((0, 0.3), (1, 0.1))] + [(0, 3, 4, k, math.log(0.2)) for k in (0, 1)], "city_id int, pi long, pj long, rel_id int, log_lik double")
    edges = spark.createDataFrame([(0, 1, 2, 0, 2), (0, 1, 2, 1, 1), (0, 3, 4, 0, 1)], "city_id int, pi long, pj long, rel_id int, cnt long")

    def w(prior, scope="per_relation"):
        p = closeness.posteriors(lik, edges, 2, prior)
        return {r.pi: r.W for r in closeness.score(p, closeness.normalisers(p, scope), 2).collect()}, {(r.pi, r.rel_id): r.posterior for r in p.collect()}

    s, p = w("pair_frequency")
    assert p[1, 0] == pytest.approx(0.857143, abs=1e-6) and p[3, 0] == 1 and p[3, 1] == 0 and s == pytest.approx({1: 0.928571, 3: 0.5}, abs=1e-6)
    s, p = w("corpus_frequency")
    assert p[1, 0] == pytest.approx(0.9) and p[3, 1] == pytest.approx(0.25) and s == pytest.approx({1: 1.0, 3: 0.416667}, abs=1e-6)
    s, _ = w("corpus_frequency", "all_pairs")
    assert s == pytest.approx({1: 0.7, 3: 0.416667}, abs=1e-6)


def _square(spark):
    v = spark.createDataFrame([(0, i, i % 2, i // 2) for i in range(4)], "city_id int, vertex_id long, x long, y long")
    e = spark.createDataFrame([(0, 0, 0, 1, 10), (0, 1, 0, 2, 10), (0, 2, 1, 3, 10), (0, 3, 2, 3, 10)], "city_id int, edge_id long, u long, v long, len_dm long")
    return graph.RoadGraph(v, e)


@pytest.mark.parametrize("strategy", ["local", "distributed", "astar", "landmarks"])
def test_ties_take_the_smaller_predecessor(spark, strategy):
    pair = spark.createDataFrame([(0, "p", 0, 3), (0, "q", 0, 0)], "city_id int, pair_id string, s long, t long")
    rows = graph.shortest(_square(spark), pair, strategy=strategy).collect()
    assert sorted((r.seq, r.vertex_id) for r in rows if r.pair_id == "p") == [(0, 0), (1, 1), (2, 3)]
    assert [(r.seq, r.vertex_id, r.edge_id) for r in rows if r.pair_id == "q"] == [(0, 0, None)]


def test_unreachable_and_unknown_targets_give_no_rows(spark):
    g = _square(spark)
    v = g.vertices.unionByName(spark.createDataFrame([(0, 9, 5, 5)], g.vertices.schema))
    pair = spark.createDataFrame([(0, "p", 0, 9), (1, "r", 0, 1)], "city_id int, pair_id string, s long, t long")
    assert graph.shortest(graph.RoadGraph(v, g.edges), pair, strategy="local").count() == 0


def test_photos_at_the_radius(spark):
    v = spark.createDataFrame([(0, 1, 0.0, 0.0), (0, 2, 30.0, 0.0), (0, 3, -100.0, -100.0)], "city_id int, vertex_id long, x double, y double")
    p = spark.createDataFrame([(0, 1, 15.0, 0.0), (0, 2, 0.0, 20.0), (0, 3, 0.0, 20.01), (0, 4, -120.0, -100.0)], "city_id int, photo_id long, x double, y double")
    assert {r.vertex_id: r.photos for r in measures.vertex_popularity(p, v).collect()} == {1: 2, 2: 1, 3: 1}
    assert {r.vertex_id: r.photos for r in measures.vertex_popularity(p, v, nearest_only=True).collect()} == {1: 2, 3: 1}


def _hop_world(spark, places, close):
    v = spark.createDataFrame([(0, i, 10 * i, 0) for i in range(6)], "city_id int, vertex_id long, x long, y long")
    e = spark.createDataFrame([(0, i, i, i + 1, 100, 100.0) for i in range(5)], "city_id int, edge_id long, u long, v long, len_dm long, cost_100 double")
    p = spark.createDataFrame([(0, i, f"p{i}", x, y, n) for i, x, y, n in places], "city_id int, poi_id long, name string, x long, y long, vertex_id long")
    h = spark.createDataFrame([(0, a, b, 0.5, d) for a, b, d in close], "city_id int, pi long, pj long, W double, dist double")
    t = spark.createDataFrame([(0, "i", "b", 1, 0, 5)], "city_id int, setting string, bracket string, trip_id int, s long, t long")
    return graph.RoadGraph(v, e), h, p, t


@pytest.mark.parametrize(
    ("places", "close", "fallback"),
    [
        ([(1, 10, 1, 1), (2, 40, 1, 4)], [(1, 2, 30.0)], False),
        ([(1, 25, 400, 2)], [], True),
        ([(1, 20, 1, 2)], [], False),
        ([(1, 10, 1, 1), (2, 40, 1, 4)], [], True),
        ([(1, 0, 0, 0), (2, 50, 0, 5)], [(1, 2, 50.0)], False),
    ],
    ids=["chain", "empty region", "one place", "apart", "places at the ends"],
)
def test_hop_cases(spark, places, close, fallback):
    g, h, p, t = _hop_world(spark, places, close)
    rows = routing.poi_hop(g, h, p, t, "cost_100").orderBy("seq").collect()
    assert [r.vertex_id for r in rows] == list(range(6)) and [r.seq for r in rows] == list(range(6)) and {r.fallback for r in rows} == {fallback}
    left = routing.poi_hop(g, h, p, t, "cost_100", on_unreachable="null").count()
    assert left == (0 if fallback else 6)


def test_snap_prefers_the_smaller_id_and_widens(spark):
    v = spark.createDataFrame([(0, 1, 0, 0), (0, 2, 10, 0), (1, 7, 5000, 5000)], "city_id int, vertex_id long, x long, y long")
    p = spark.createDataFrame([(0, 1, 5, 0), (1, 2, 0, 0)], "city_id int, poi_id long, x long, y long")
    assert {r.poi_id: r.vertex_id for r in graph.snap(p, v).collect()} == {1: 1, 2: 7}


def test_features_drop_coincident_places(spark):
    e = spark.createDataFrame([(1, 2, 0, 1)], "pi long, pj long, rel_id int, cnt long")
    p = spark.createDataFrame([(0, 1, 3, 3), (0, 2, 3, 3)], "city_id int, poi_id long, x long, y long")
    assert features.vectors(e, p).count() == 0 and features.vectors(e, p, drop_coincident=False).count() == 1


def _mix(spark, model, n=3000):
    return mixture.sample(spark, model, n, seed=5).persist()


def test_growth_recovers_two_parts(spark):
    true = [mixture.Component(0, 0, 0.5, 10, 1, 1, 0.1, 0.04), mixture.Component(0, 1, 0.5, 30, 4, 2, 0, 0.09)]
    v = _mix(spark, true)
    grown = mixture.fit_greedy(v, 4, stop="bic")
    assert len(grown.model) == 2
    for got, want in zip(sorted(grown.model, key=lambda c: c.mu_d), true, strict=True):
        assert got.mu_d == pytest.approx(want.mu_d, abs=0.2) and got.mu_o == pytest.approx(want.mu_o, abs=0.05) and got.weight == pytest.approx(0.5, abs=0.05)
    taken = [ll for _, _, ll, _, ok in grown.trace if ok]
    assert taken == sorted(taken)


def test_em_never_loses_likelihood(spark):
    v = _mix(spark, [mixture.Component(0, 0, 0.3, 0, 0, 1, 0, 1), mixture.Component(0, 1, 0.7, 4, 2, 1, 0.3, 1)], 600)
    r = mixture.fit_fixed(v, 3, rounds=8, ridge=0.0)
    lls = [ll for _, _, ll, _ in r.trace]
    assert all(b >= a - 1e-9 * 600 for a, b in zip(lls, lls[1:], strict=False)) and sum(c.weight for c in r.model) == pytest.approx(1)
    assert all(c.s_dd * c.s_oo > c.s_do**2 for c in r.model)


@pytest.mark.parametrize("points", [[(1.0, 2.0)], [(1.0, 2.0)] * 5, [(float(i), 2.0 * i) for i in range(8)]], ids=["one", "equal", "line"])
def test_degenerate_samples_stay_finite(spark, points):
    v = spark.createDataFrame([(0, 0, 1, 2, d, o, 1.0) for d, o in points], "city_id int, rel_id int, pi long, pj long, dist double, theta double, w double")
    for c in mixture.fit_greedy(v, 3).model:
        assert all(map(math.isfinite, c)) and c.s_dd > 0 and c.s_oo > 0


def test_built_in_mixture_agrees(spark):
    from pyspark.ml.clustering import GaussianMixture
    from pyspark.ml.feature import VectorAssembler

    v = _mix(spark, [mixture.Component(0, 0, 0.5, 0, 0, 1, 0, 1), mixture.Component(0, 1, 0.5, 8, 3, 1, 0, 1)], 800)
    ours = mixture.fit_fixed(v, 2, rounds=30).loglik[0]
    theirs = GaussianMixture(k=2, seed=3, maxIter=60).fit(VectorAssembler(inputCols=["dist", "theta"], outputCol="features").transform(v)).summary.logLikelihood
    assert ours >= theirs - 0.01 * abs(theirs)


# ---------------------------------------------------------------- growth of mixtures, by hand and by both ways


def two_clouds(spark, seed=5, n=120):
    rng = np.random.default_rng(seed)
    rows = []
    for rel, centres in ((0, [(100.0, 1.0), (400.0, 4.0)]), (1, [(200.0, 2.0)]), (2, [(50.0, 0.5), (300.0, 3.0), (600.0, 5.5)])):
        for i in range(n):
            d, o = centres[i % len(centres)]
            rows.append((rel, float(d + 15 * rng.standard_normal()), float(o + 0.1 * rng.standard_normal()), float(rng.integers(1, 4))))
    return spark.createDataFrame(rows, "rel_id int, dist double, theta double, w double")


@pytest.mark.parametrize("stop", ["no_gain", "bic", "holdout"])
def test_local_growth_is_the_distributed_one(spark, stop):
    v = two_clouds(spark)
    a, b = (mixture.fit_greedy(v, 3, stop, strategy=k) for k in ("local", "distributed"))
    assert [(t[0], t[1], t[4]) for t in a.trace] == [(t[0], t[1], t[4]) for t in b.trace]
    assert [t[2] for t in a.trace] == pytest.approx([t[2] for t in b.trace], rel=1e-6)
    assert len(a.model) == len(b.model)
    for c, d in zip(a.model, b.model, strict=True):
        assert c[:2] == d[:2] and list(c[2:]) == pytest.approx(list(d[2:]), rel=1e-4, abs=1e-6)
    if stop == "bic":
        assert [sum(c.rel_id == k for c in a.model) for k in (0, 1)] == [2, 1]


def test_one_insertion_and_round_from_a_literal_start(spark):
    """The candidate taken is the best of all by plain arithmetic, and one round lifts the log likelihood."""
    v = two_clouds(spark).where("rel_id = 0")
    pdf = v.toPandas()
    start = [mixture.Component(0, 0, 1.0, 250.0, 2.5, 25000.0, 100.0, 3.0)]

    def density(c, d, o):
        s = np.array([[c.s_dd, c.s_do], [c.s_do, c.s_oo]])
        x = np.array([d - c.mu_d, o - c.mu_o])
        return math.exp(-0.5 * x @ np.linalg.inv(s) @ x) / (2 * math.pi * math.sqrt(np.linalg.det(s)))

    def loglik(model):
        return sum(w * math.log(sum(c.weight * density(c, d, o) for c in model)) for d, o, w in zip(pdf["dist"], pdf["theta"], pdf["w"], strict=True))

    values, vectors = np.linalg.eigh(np.array([[25000.0, 100.0], [100.0, 3.0]]))
    sd, axis = math.sqrt(values[1]), vectors[:, 1] * np.sign(vectors[0, 1])
    made = []
    for sign in (1, -1):
        new = mixture.Component(0, 1, 0.5, 250.0 + sign * sd * axis[0], 2.5 + sign * sd * axis[1], 12500.0, 50.0, 1.5)
        made.append([start[0]._replace(weight=0.5), new])
    best = max(made, key=loglik)
    got = mixture.insert_component(v, start)
    for c, d in zip(got, best, strict=True):
        assert list(c) == pytest.approx(list(d), rel=1e-9)
    word = mixture.Word(0, *(pdf[c].to_numpy(float) for c in ("dist", "theta", "w")), mixture.RIDGE)
    assert word.inserted(start) == got and word.loglik(got) == pytest.approx(loglik(got))
    after = mixture.from_table(mixture.em_step(v, mixture.to_table(spark, got)))
    assert loglik(after) > loglik(got)


def test_search_from_both_ends_and_network_ends(spark):
    rng = np.random.default_rng(3)
    n = 60
    edges = [(0, i, int(a), int(b), int(w)) for i, (a, b, w) in enumerate(zip(rng.integers(0, n, 150), rng.integers(0, n, 150), rng.integers(1, 50, 150), strict=True)) if a != b]
    g = graph.RoadGraph(spark.createDataFrame([(0, i, i, 0) for i in range(n)], "city_id int, vertex_id long, x long, y long"), spark.createDataFrame(edges, "city_id int, edge_id long, u long, v long, len_dm long"))
    pairs = spark.createDataFrame([(0, f"{s}>{t}", s, t) for s in range(0, 20) for t in (3, 30, 59)], "city_id int, pair_id string, s long, t long")
    got = {r.pair_id: r.cost for r in graph.costs_both_ends(g, pairs).collect()}
    tree = {(r.source, r.v): r.cost for r in graph.tree_local(g, pairs.selectExpr("city_id", "s as source")).collect()}
    assert got == {f"{s}>{t}": tree[s, t] for s in range(0, 20) for t in (3, 30, 59) if (s, t) in tree}


def test_places_without_roads_or_coordinates_keep_null_vertices(spark):
    g = graph.RoadGraph(spark.createDataFrame([(0, 0, 0, 0), (0, 1, 9000, 0)], "city_id int, vertex_id long, x long, y long"), spark.createDataFrame([(0, 0, 0, 1, 90000)], "city_id int, edge_id long, u long, v long, len_dm long"))
    points = spark.createDataFrame([(0, 1, 4500, 40), (0, 2, None, 5), (7, 3, 1, 1), (0, 4, 100, 20000)], "city_id int, poi_id long, x long, y long")
    near = {r.poi_id: (r.vertex_id, r.snap_dist) for r in graph.snap(points, g.vertices).collect()}
    assert near[2] == near[3] == (None, None) and near[1][0] == 0 and near[4][0] == 0
    split, placed = graph.snap_pseudo(points, g)
    at = {r.poi_id: (r.vertex_id, r.snap_dist) for r in placed.collect()}
    assert at[1] == (2, 40.0) and at[4][1] == 20000.0 and at[2] == at[3] == (None, None)
    assert split.edges.agg(F.sum("len_dm")).first()[0] == 90000 and split.edges.count() == 3


def test_many_names_pass_a_sieve(spark):
    gaz = spark.range(3000).selectExpr("concat('name', translate(cast(id as string), '0123456789', 'abcdefghij')) as name", "id as poi_id", "'LOC' as etype")
    rows = [(i, f"namea{'abcdefghij'[i % 10]} is near the namebc but nothing like other{i} or namezz") for i in range(200)]
    toks = text.tokens(text.split_sentences(spark.createDataFrame(rows, "doc_id long, text string")))
    a, b = (sorted(map(tuple, text.entities(toks, gaz, 2, most).collect())) for most in (10**6, 0))
    assert a == b and len(a) >= 200
    words = spark.range(20_000).selectExpr("concat('other', id) as name")
    names = gaz.select("name")
    assert text.sifted(names, names, 3000).count() == 3000 and text.sifted(words, names, 3000).count() < 20_000 / 8


def test_null_texts_and_empty_tables(spark):
    gaz = spark.createDataFrame([("rome", 1, "LOC"), ("oslo", 2, "LOC"), (None, 3, "LOC")], "name string, poi_id long, etype string")
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "Rome is near the Oslo."), (3, "Rome is near the Oslo."), (None, "rome")], "doc_id long, text string")
    assert [tuple(r) for r in text.extract_triplets(docs, gaz, lexicon=text.TRAVEL_LEXICON).select("doc_id", "pi", "rel_id", "pj").distinct().collect()] == [(3, 1, 2, 2)]
    assert text.extract_triplets(docs.where("1 = 0"), gaz).count() == 0 == text.extract_triplets(docs, gaz.where("1 = 0")).count()
    assert text.geoparse(docs, gaz).where("name = 'rome'").count() == 2  # a repeated row's mentions count once; a null id is one text
    none = spark.createDataFrame([], "rel_id int, dist double, theta double, w double")
    assert mixture.fit_greedy(none) == mixture.Grown([], []) == mixture.fit_greedy(none, strategy="distributed")
