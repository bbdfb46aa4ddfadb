"""Named queries over the given tables and the SQL that must give the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.geo import distance
from ..operators import closeness, extra, features, graph, measures, mixture, routing, text
from ..session import sweep, table
from ..sources import fixtures
from ..streaming import photos as streams
from . import oracles as O
from . import workloads
from .workloads import World, rounded

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_WORLDS: dict[tuple, World] = {}


def world(spark: SparkSession, sf_dir: str, **options) -> World:
    """The stages of one scale, shared by the queries of a session."""
    key = (spark.sparkContext.applicationId, sf_dir, *sorted(options.items()))
    if key not in _WORLDS:
        _WORLDS[key] = World(spark, sf_dir, **options)
    return _WORLDS[key]


def forget() -> None:
    """Drop the shared stages and their files; the next query makes its own."""
    _WORLDS.clear()
    sweep()


def query(final: str | None = None, *need: str, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if final is not None:
            ORACLES[name or f.__name__] = O.sql(final, *need)
        return f

    return keep


def simple(w: dict | None = None, final: str | None = None, *need: str, name: str, of: Callable[[World], DataFrame]) -> None:
    """Register a query that only reads stages of a World with options ``w``."""
    QUERIES[name] = lambda s, d: of(world(s, d, **(w or {})))
    if final is not None:
        ORACLES[name] = O.sql(final, *need)


ONE = {"single": True}

# ---------------------------------------------------------------- inputs

simple(None, "SELECT city_id, vertex_id, col, row, x, y FROM v", "v", name="road_vertices", of=lambda w: w.vertices.select("city_id", "vertex_id", "col", "row", "x", "y"))
simple(None, "SELECT * FROM e", "e", name="road_edges", of=lambda w: w.base.edges)
simple(None, "SELECT * FROM poi", "poi", name="poi_table", of=lambda w: w.pois.select("city_id", "poi_id", "x", "y"))
simple(None, "SELECT * FROM gaz", "gaz", name="gazetteer", of=lambda w: w.gazetteer)
simple(None, "SELECT city_id, photo_id, user_id, event_type, x, y FROM photo", "photo", name="photo_points", of=lambda w: w.photos.drop("ts"))
simple(None, "SELECT city_id, round(extent, 4) AS extent FROM ext", "ext", name="city_extents", of=lambda w: rounded(fixtures.extents(w.vertices)))
simple(None, "SELECT city_id, 'i' AS setting, '30-50' AS bracket, CAST(trip_id AS INTEGER) AS trip_id, s, t FROM trip", "trip", name="trips_straight", of=lambda w: w.trips_i)


@query("SELECT * FROM cust", "cust")
def customer_places(s, d):
    return fixtures.pois(s, d, "customer").select("city_id", "poi_id", "x", "y")


# ---------------------------------------------------------------- texts

simple(None, "SELECT doc_id, CAST(sent_id AS INTEGER) AS sent_id, sentence FROM sent", "sent", name="sentences", of=lambda w: text.split_sentences(w.docs))
simple(None, "SELECT doc_id, CAST(sent_id AS INTEGER) AS sent_id, CAST(len(toks) AS INTEGER) AS n, array_to_string(toks, ' ') AS toks FROM tok", "tok", name="tokens", of=lambda w: text.tokens(text.split_sentences(w.docs)).select("doc_id", "sent_id", F.size("toks").alias("n"), F.array_join("toks", " ").alias("toks")))
simple(None, f"SELECT doc_id, CAST(sent_id AS INTEGER) AS sent_id, array_to_string(list_transform(toks, lambda x: {O.TAG.format(t='x')}), '') AS tags FROM tok", "tok", name="tags", of=lambda w: text.tagged(text.tokens(text.split_sentences(w.docs))).select("doc_id", "sent_id", "tags"))
simple(None, "SELECT doc_id, CAST(sent_id AS INTEGER) AS sent_id, CAST(first AS INTEGER) AS first, name, poi_id, etype FROM ment", "ment", name="entity_mentions", of=lambda w: text.geoparse(w.docs, w.gazetteer).select("doc_id", "sent_id", "first", "name", "poi_id", "etype"))
simple(None, "SELECT doc_id, CAST(sent_id AS INTEGER) AS sent_id, unnest(regexp_extract_all(sentence, '[A-Z][a-z]+(?: [A-Z][a-z]+)*')) AS name FROM sent", "sent", name="entities_by_case", of=lambda w: text.entities_by_case(text.split_sentences(w.docs)))
simple(None, "SELECT poi.city_id, count(*) AS mentions, count(DISTINCT ment.poi_id) AS places FROM ment JOIN poi ON poi.poi_id = ment.poi_id GROUP BY 1", "ment", "poi", name="geocoded_mentions", of=lambda w: text.geocode(text.geoparse(w.docs, w.gazetteer), w.pois, "inner").groupBy("city_id").agg(F.count("*").alias("mentions"), F.count_distinct("poi_id").alias("places")))
PAIR = "doc_id, CAST(sent_id AS INTEGER) AS sent_id, CAST(at_i AS INTEGER) AS at_i, CAST(at_j AS INTEGER) AS at_j, pi, pj"


def _pairs(w: World, mode: str = "all") -> DataFrame:
    toks = text.tokens(text.split_sentences(w.docs))
    return text.entity_pairs(toks, text.entities(toks, w.gazetteer, 1), mode)


simple(None, f"SELECT {PAIR}, gap, tags FROM pair", "pair", name="entity_pairs", of=_pairs)
simple(None, f"SELECT {PAIR} FROM pair p WHERE NOT EXISTS (SELECT 1 FROM ment m WHERE m.doc_id = p.doc_id AND m.sent_id = p.sent_id AND m.first > p.at_i AND m.first < p.at_j)", "pair", "ment", name="entity_pairs_adjacent", of=lambda w: _pairs(w, "adjacent").select("doc_id", "sent_id", "at_i", "at_j", "pi", "pj"))
simple(None, f"SELECT {PAIR}, rel_id FROM tri", "tri", name="triplets", of=lambda w: w.triplets)
simple({"use_syntax": False}, f"SELECT {PAIR}, rel_id FROM said", "said", name="triplets_word_only", of=lambda w: w.triplets)
simple(None, "SELECT rel_id, count(*) AS n FROM tri WHERE rel_id IN (0, 1, 2, 3, 4) GROUP BY 1", "tri", name="closeness_triplets", of=lambda w: text.keep_closeness(w.triplets, w.lexicon).groupBy("rel_id").agg(F.count("*").alias("n")))
simple(None, "SELECT * FROM rel", "rel", name="relation_edges", of=lambda w: w.relations.select("city_id", "pi", "pj", "rel_id", "cnt"))
simple(None, "SELECT pi, pj, string_agg(rel_id || ':' || cnt, ',' ORDER BY rel_id) AS rels, CAST(sum(cnt) AS BIGINT) AS n FROM (SELECT pi, pj, rel_id, count(*) AS cnt FROM tri GROUP BY 1, 2, 3) GROUP BY 1, 2", "tri", name="relation_graph", of=lambda w: text.relation_graph(text.relation_edges(w.triplets)).select("pi", "pj", F.array_join(F.transform("rels", lambda r: F.concat_ws(":", r["rel_id"], r["cnt"])), ",").alias("rels"), "n"))


@query(f"""SELECT (SELECT count(*) FROM documents WHERE lang = 'en') AS texts, mentions, geocoded, triplets, pairs, round(geocoded / mentions, 6) AS geocode_rate, round(triplets / (SELECT count(*) FROM documents WHERE lang = 'en'), 6) AS triplets_per_text
 FROM (SELECT count(*) AS mentions, count(poi_id) AS geocoded FROM ({O.mentions('known')})), (SELECT count(*) AS triplets, count(DISTINCT (pi, pj)) AS pairs FROM tri)""", "tok", "known", "tri")
def extraction_funnel(s, d):
    w = world(s, d)
    return text.extraction_funnel(w.docs, w.gazetteer, fixtures.heldout_names(s, d))


@query(r"""SELECT page_id, trim(regexp_replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->', ' ', 'g'), '(?is)<script[^>]*>.*?</script>', ' ', 'g'), '(?is)<style[^>]*>.*?</style>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&amp;', '&'), '[ \t\r\n\x0b\f]+', ' ', 'g')) AS text FROM pages""")
def pages_to_text(s, d):
    return text.pages_to_text(table(s, d, "pages"))


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def docs_quality_semi(s, d):
    return table(s, d, "documents").join(table(s, d, "labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def docs_unlabelled_anti(s, d):
    return table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left_anti").select("doc_id")


TRAVEL = [p.phrase for p in text.TRAVEL_LEXICON]
PLANTED = "SELECT poi_id AS pi, lead(poi_id) OVER (PARTITION BY city_id ORDER BY poi_id) AS pj, CAST(poi_id % 11 AS INTEGER) AS nth FROM poi"


def _travel(s, d) -> tuple[DataFrame, DataFrame]:
    """(planted statements, statements found) on texts with all kinds of travel words."""
    planted = fixtures.planted_statements(s, d, TRAVEL)
    names = planted.select(F.col("ni").alias("name"), F.col("pi").alias("poi_id")).unionByName(planted.select("nj", "pj").toDF("name", "poi_id")).distinct().withColumn("etype", F.lit("LOC"))
    return planted, text.extract_triplets(fixtures.planted_texts(planted, TRAVEL), names, lexicon=text.TRAVEL_LEXICON)


@query(f"SELECT pi, pj, nth AS rel_id FROM ({PLANTED}) WHERE pj IS NOT NULL", "poi")
def travel_statements(s, d):
    """Statements by direction and remote words are found like those by close ones."""
    return _travel(s, d)[1].select("pi", "pj", "rel_id")


@query(f"SELECT pi, pj, nth AS rel_id FROM ({PLANTED}) WHERE pj IS NOT NULL AND nth NOT IN ({', '.join(str(p.rel_id) for p in text.TRAVEL_LEXICON if p.kind != 'close')})", "poi")
def travel_closeness_statements(s, d):
    """Only statements by close words go on to the closeness graph."""
    return text.keep_closeness(_travel(s, d)[1], text.TRAVEL_LEXICON).select("pi", "pj", "rel_id")


@query(f"SELECT count(*) AS hits, count(*) AS found, count(*) AS planted, CAST(1 AS DOUBLE) AS precision, CAST(1 AS DOUBLE) AS recall FROM ({PLANTED}) WHERE pj IS NOT NULL", "poi")
def extraction_quality(s, d):
    planted, found = _travel(s, d)
    return text.extraction_quality(found, planted.select("pi", F.col("nth").alias("rel_id"), "pj"))


# ---------------------------------------------------------------- features and mixtures

simple(None, "SELECT city_id, rel_id, pi, pj, round(dist, 4) AS dist, round(theta, 4) AS theta, w FROM vec", "vec", name="feature_vectors", of=lambda w: rounded(w.vectors))
simple(None, "SELECT city_id, pi, pj, round(dist, 4) AS dist, round(theta, 4) AS theta FROM pv", "pv", name="pair_vectors", of=lambda w: rounded(w.pair_vectors))
simple(None, "SELECT rel_id, round(atan2(sum(w * sin(theta)), sum(w * cos(theta))), 4) AS theta0 FROM vec GROUP BY 1", "vec", name="circular_means", of=lambda w: rounded(features.recenter(w.vectors).groupBy("rel_id").agg(F.first("theta0").alias("theta0"))))
simple(None, "SELECT rel_id, (floor(dist / 100) + 0.5) * 100 AS dist, round((floor(theta / 0.5) + 0.5) * 0.5, 4) AS theta, sum(w) AS w FROM vec GROUP BY 1, 2, 3", "vec", name="quantised_vectors", of=lambda w: rounded(features.quantise(w.vectors, 100.0, 0.5)))


@query(f"""SELECT i.city_id, CAST(l_linenumber % 5 AS INTEGER) AS rel_id, pi, pj, count(*) AS n, round(min({O.LINE.format(x1='i.x', x2='j.x', y1='i.y', y2='j.y')}), 4) AS dist FROM (
  SELECT l_linenumber, l_suppkey AS pi, lead(l_suppkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS pj FROM lineitem) l JOIN poi i ON i.poi_id = pi JOIN poi j ON j.poi_id = pj, (SELECT max(col) AS m FROM v) m
  WHERE pi <> pj AND i.city_id = j.city_id AND {O.LINE.format(x1='i.x', x2='j.x', y1='i.y', y2='j.y')} <= 100 * (2 + l_linenumber) * greatest(1.0, m / 20.0) GROUP BY 1, 2, 3, 4""", "poi", "v")
def lineitem_vectors(s, d):
    v = features.measured(fixtures.lineitem_vectors_source(s, d))
    return rounded(v.groupBy("city_id", "rel_id", "pi", "pj").agg(F.count("*").alias("n"), F.min("dist").alias("dist")))


MODEL = "round(mu_d, 4) AS mu_d, round(mu_o, 4) AS mu_o, round(s_dd, 4) AS s_dd, round(s_do, 4) AS s_do, round(s_oo, 4) AS s_oo"
simple(ONE, f"SELECT rel_id, {MODEL} FROM one", "one", name="single_gaussian", of=lambda w: rounded(w.model.drop("m", "weight")))


def two_components(w: World) -> DataFrame:
    """The fixed two-component start that the oracle also makes."""
    k = F.explode(F.array(F.lit(0), F.lit(1))).alias("m")
    t = mixture.fit_single(w.vectors).drop("m", "weight").select("*", k)
    side = (1 - 2 * F.col("m")) * 0.5
    return t.select("rel_id", "m", F.lit(0.5).alias("weight"), (F.col("mu_d") + side * F.sqrt("s_dd")).alias("mu_d"), (F.col("mu_o") + side * F.sqrt("s_oo")).alias("mu_o"), (0.75 * F.col("s_dd")).alias("s_dd"), (0.5 * F.col("s_do")).alias("s_do"), (0.75 * F.col("s_oo")).alias("s_oo"))


simple(ONE, "SELECT rel_id, pi, pj, round(log_p, 4) AS log_p FROM logp", "logp", name="mixture_density", of=lambda w: rounded(mixture.density(w.vectors, two_components(w)).select("rel_id", "pi", "pj", "log_p")))
simple(ONE, "SELECT rel_id, sum(w) AS n, round(sum(w * log_p), 4) AS loglik FROM logp GROUP BY 1", "logp", name="loglik", of=lambda w: rounded(mixture.loglik(w.vectors, two_components(w))))
EM = f"rel_id, m, round(weight, 4) AS weight, {MODEL}, round(loglik, 4) AS loglik"
simple(ONE, f"SELECT {EM} FROM em1", "em1", name="em_one_step", of=lambda w: rounded(mixture.em_step(w.vectors, two_components(w))))
simple(ONE, f"SELECT {EM} FROM em2", "em2", name="em_fixed_k", of=lambda w: rounded(mixture.em_step(w.vectors, workloads.stored(mixture.em_step(w.vectors, two_components(w)).drop("loglik"), "em1"))))


def _inserted(w: World) -> tuple[DataFrame, mixture.Model]:
    """The words with five statements or more, and their single Gaussians after one insertion."""
    many = w.vectors.groupBy("rel_id").agg(F.sum("w").alias("_n")).where("_n >= 5").select("rel_id")
    part = workloads.stored(w.vectors.join(F.broadcast(many), "rel_id", "left_semi"), "many")
    return part, mixture.insert_component(part, mixture.from_table(mixture.fit_single(part)))


def _inserted_em(w: World) -> DataFrame:
    part, model = _inserted(w)
    return rounded(mixture.em_step(part, mixture.to_table(w.spark, model)))


def _acceptance(w: World) -> DataFrame:
    """(rel_id, no_gain, aic, bic): whether the grown mixture, after one round, is taken under each stop rule."""
    part, model = _inserted(w)
    before = {r.rel_id: (r.n, r.loglik) for r in mixture.loglik(part, mixture.fit_single(part)).collect()}
    after = mixture.em_step(part, mixture.to_table(w.spark, model)).drop("loglik")
    rows = []
    for r in mixture.loglik(part, workloads.stored(after, "after")).collect():
        n, ll = before[r.rel_id]
        rows.append((r.rel_id, *(mixture.criterion(k, r.loglik, 2, n) - mixture.criterion(k, ll, 1, n) > 1e-9 * (1 + abs(mixture.criterion(k, ll, 1, n))) for k in ("no_gain", "aic", "bic"))))
    return w.spark.createDataFrame(rows, "rel_id int, no_gain boolean, aic boolean, bic boolean")


simple(ONE, f"SELECT rel_id, m, round(weight, 4) AS weight, {MODEL} FROM ins", "ins", name="mixture_insertion", of=lambda w: rounded(mixture.to_table(w.spark, _inserted(w)[1])))
simple(ONE, f"SELECT {EM} FROM ins1", "ins1", name="mixture_insertion_em", of=_inserted_em)
simple(ONE, """SELECT rel_id, c2 - c1 > 1e-9 * (1 + abs(c1)) AS no_gain, c2 - 11 - (c1 - 5) > 1e-9 * (1 + abs(c1 - 5)) AS aic, c2 - 5.5 * ln(greatest(n, 1)) - (c1 - 2.5 * ln(greatest(n, 1))) > 1e-9 * (1 + abs(c1 - 2.5 * ln(greatest(n, 1)))) AS bic
  FROM (SELECT o.rel_id, o.n, o.ll AS c1, b.ll AS c2 FROM one_ll o JOIN (SELECT DISTINCT rel_id, loglik AS ll FROM ins2) b ON b.rel_id = o.rel_id)""", "one_ll", "ins2", name="growth_acceptance", of=_acceptance)


@query()
def greedy_mixture(s, d):
    return world(s, d).model


@query()
def greedy_trace(s, d):
    return s.createDataFrame(world(s, d).grown.trace, "rel_id int, m int, loglik double, criterion double, accepted boolean")


def _grown(stop: str):
    return lambda s, d: mixture.to_table(s, mixture.fit_greedy(world(s, d).vectors, 3, stop).model)


for _stop in ("aic", "bic", "holdout"):
    QUERIES[f"greedy_mixture_{_stop}"] = _grown(_stop)


@query()
def fixed_mixture(s, d):
    """The baseline with a fixed number of components."""
    return mixture.to_table(s, mixture.fit_fixed(world(s, d).vectors, 2).model)


@query()
def mixture_from_cells(s, d):
    """Greedy growth on weighted cells of the line-item statements: the cost follows cells, not statements."""
    v = features.measured(fixtures.lineitem_vectors_source(s, d)).withColumn("w", F.lit(1.0))
    return mixture.to_table(s, mixture.fit_greedy(workloads.stored(features.quantise(v, 50.0, 0.25), "cells"), 3, "bic").model)


@query()
def mixture_recentred(s, d):
    return mixture.to_table(s, mixture.fit_greedy(workloads.stored(features.recenter(world(s, d).vectors).drop("theta0"), "recentred"), 3).model)


def label_vectors(s: SparkSession, d: str) -> DataFrame:
    """The first two components of the embeddings by label, as a mixture's vectors."""
    return table(s, d, "embeddings").where("label is not null").select("vec_id", F.col("label").alias("rel_id"), F.element_at("embedding", 1).cast("double").alias("dist"), F.element_at("embedding", 2).cast("double").alias("theta"), F.lit(1.0).alias("w"))


LABEL_ONE = "l AS (SELECT vec_id, label AS rel_id, CAST(embedding[1] AS DOUBLE) AS dist, CAST(embedding[2] AS DOUBLE) AS theta FROM embeddings WHERE label IS NOT NULL), g AS (SELECT rel_id, avg(dist) AS mu_d, avg(theta) AS mu_o, avg(dist * dist) - avg(dist) * avg(dist) + 1e-6 AS s_dd, avg(dist * theta) - avg(dist) * avg(theta) AS s_do, avg(theta * theta) - avg(theta) * avg(theta) + 1e-6 AS s_oo FROM l GROUP BY 1)"
ORACLES["label_gaussians"] = f"WITH {LABEL_ONE} SELECT rel_id, {MODEL} FROM g"
ORACLES["label_classified"] = f"WITH {LABEL_ONE} SELECT vec_id, max({{'p': lp, 'r': -rel_id}}).r * -1 AS said FROM (SELECT vec_id, g.rel_id, {O.log_gauss('g')} AS lp FROM l, g) GROUP BY 1"


@query()
def label_gaussians(s, d):
    return rounded(mixture.fit_single(label_vectors(s, d)).drop("m", "weight"))


@query()
def label_classified(s, d):
    """Classification of each vector to the label of largest density, where the truth is known."""
    v = label_vectors(s, d)
    lik = closeness.likelihoods(v.select(F.lit(0).alias("city_id"), F.col("vec_id").alias("pi"), F.col("vec_id").alias("pj"), "dist", "theta"), mixture.fit_single(v))
    best = F.max(F.struct("log_lik", (-F.col("rel_id")).alias("r")))
    return lik.groupBy(F.col("pi").alias("vec_id")).agg((-best["r"]).alias("said"))


# ---------------------------------------------------------------- confidences and scores


def _posterior(prior: str):
    return lambda w: closeness.posteriors(closeness.likelihoods(w.pair_vectors, w.model), w.relations, O.N_REL, prior)


def _score(prior: str, scope: str = "per_relation", combine: str = "sum"):
    def of(w: World) -> DataFrame:
        p = _posterior(prior)(w)
        return rounded(closeness.score(p, closeness.normalisers(p, scope), O.N_REL, combine))

    return of


simple(ONE, "SELECT city_id, pi, pj, rel_id, round(log_lik, 4) AS log_lik FROM lik", "lik", name="likelihoods", of=lambda w: rounded(closeness.likelihoods(w.pair_vectors, w.model)))
SCORE = "SELECT city_id, pi, pj, round(W, 4) AS W, n_words FROM ({q})"
for _prior in closeness.PRIORS:
    _post = f"post_{_prior}"
    simple(ONE, f"SELECT city_id, pi, pj, rel_id, round(posterior, 4) AS posterior, observed FROM {_post}", _post, name=f"posteriors_{_prior}", of=lambda w, p=_prior: rounded(_posterior(p)(w)))
    simple(ONE, SCORE.format(q=O.score_sql(_post)), _post, name=f"closeness_scores_{_prior}", of=_score(_prior))
for _scope in ("global", "none", "all_pairs"):
    simple(ONE, SCORE.format(q=O.score_sql("post_corpus_frequency", _scope)), "post_corpus_frequency", name=f"closeness_scope_{_scope}", of=_score("corpus_frequency", _scope))
for _how in ("max", "mean", "noisy_or"):
    simple(ONE, SCORE.format(q=O.score_sql("post_corpus_frequency", combine=_how)), "post_corpus_frequency", name=f"closeness_combine_{_how}", of=_score("corpus_frequency", combine=_how))
simple(ONE, "SELECT city_id, pi, pj, max({'p': posterior, 'r': -rel_id}).r * -1 AS rel_id, round(max(posterior), 4) AS posterior FROM post_corpus_frequency GROUP BY 1, 2, 3", "post_corpus_frequency", name="argmax_relation", of=lambda w: rounded(closeness.classify(_posterior("corpus_frequency")(w))))
simple(ONE, "SELECT clo.city_id, clo.pi, clo.pj, round(W, 4) AS W, round(dist, 4) AS dist FROM clo JOIN pv ON pv.city_id = clo.city_id AND pv.pi = clo.pi AND pv.pj = clo.pj", "clo", "pv", name="closeness_graph", of=lambda w: rounded(w.closeness))

# ---------------------------------------------------------------- roads

simple(None, "SELECT city_id, poi_id, b.v AS vertex_id, round(b.d, 4) AS snap_dist FROM snap", "snap", name="snap_nearest", of=lambda w: rounded(w.places.select("city_id", "poi_id", "vertex_id", "snap_dist")))


@query(f"""SELECT city_id, poi_id, round(min(d), 4) AS snap_dist FROM (SELECT p.city_id, p.poi_id, {O.LINE.format(x1='p.x', x2='(a.x + t * (b.x - a.x))', y1='p.y', y2='(a.y + t * (b.y - a.y))')} AS d FROM poi p JOIN e ON e.city_id = p.city_id JOIN v a ON a.city_id = e.city_id AND a.vertex_id = e.u JOIN v b ON b.city_id = e.city_id AND b.vertex_id = e.v,
  LATERAL (SELECT greatest(0.0, least(1.0, ((p.x - a.x) * (b.x - a.x) + (p.y - a.y) * (b.y - a.y)) / CAST((b.x - a.x) * (b.x - a.x) + (b.y - a.y) * (b.y - a.y) AS DOUBLE))) AS t)) GROUP BY 1, 2""", "poi", "e", "v")
def snap_pseudo(s, d):
    w = world(s, d)
    return rounded(graph.snap_pseudo(w.pois, w.base)[1].select("city_id", "poi_id", "snap_dist"))


simple(None, "SELECT city_id, s AS source, v, CAST(cost AS DOUBLE) AS cost, hops, CASE WHEN pred >= 0 THEN pred END AS pred FROM ttree", "ttree", name="shortest_trees", of=lambda w: graph.tree_local(w.roads, w.trips_i.select("city_id", F.col("s").alias("source"))).drop("edge_id"))
simple(ONE, "SELECT c.city_id, c.pair_id, CAST(t.cost AS BIGINT) AS d, t.hops FROM cp c JOIN ctree t ON t.city_id = c.city_id AND t.s = c.s AND t.v = c.t", "cp", "ctree", name="pair_shortest_paths", of=lambda w: w.pair_paths.join(w.base.edges.select("city_id", "edge_id", "len_dm"), ["city_id", "edge_id"], "left").groupBy("city_id", "pair_id").agg(F.coalesce(F.sum("len_dm"), F.lit(0)).alias("d"), F.max("seq").alias("hops")))
simple(ONE, "SELECT city_id, pair_id, seq, edge_id FROM cpath_e WHERE edge_id IS NOT NULL", "cpath_e", name="pair_path_edges", of=lambda w: w.pair_paths.where("edge_id is not null").select("city_id", "pair_id", "seq", "edge_id"))
for _a in ("020", "050", "100"):
    simple(ONE, f"SELECT city_id, edge_id, len_dm, n_paths, round(cost_{_a}, 4) AS cost FROM cost", "cost", name=f"edge_costs_alpha_{_a}", of=lambda w, a=_a: rounded(w.costs.select("city_id", "edge_id", "len_dm", "n_paths", F.col(f"cost_{a}").alias("cost"))))


@query("SELECT city_id, s AS source, v, CAST(cost AS DOUBLE) AS cost, hops, CASE WHEN pred >= 0 THEN pred END AS pred FROM ttree", "ttree")
def search_distributed(s, d):
    """Labels by rounds over all executors, from every trip start."""
    w = world(s, d)
    return graph.tree_rounds(w.roads, w.trips_i.select("city_id", F.col("s").alias("source"))).drop("edge_id")


simple(None, "SELECT t.city_id, t.pair_id, CAST(r.cost AS DOUBLE) AS cost FROM trip t JOIN ttree r ON r.city_id = t.city_id AND r.s = t.s AND r.v = t.t", "trip", "ttree", name="search_both_ends", of=lambda w: graph.costs_both_ends(w.roads, routing.keyed(w.trips_i)).drop("settled"))


@query()
def search_effort(s, d):
    """Rounds and frontier rows of the search from every trip start."""
    w, effort = world(s, d), []
    graph.tree_rounds(w.roads, w.trips_i.select("city_id", F.col("s").alias("source")), effort=effort)
    return measures.search_effort(effort, s)


# ---------------------------------------------------------------- planners

TPATH = "SELECT city_id, pair_id, seq, vertex_id FROM tpath"
simple(None, TPATH, "tpath", name="route_plain", of=lambda w: routing.plain(w.roads, w.trips_i).select("city_id", "pair_id", "seq", "vertex_id"))
simple(None, TPATH, "tpath", name="route_astar", of=lambda w: routing.plain(w.roads, w.trips_i, "astar").select("city_id", "pair_id", "seq", "vertex_id"))
simple(None, TPATH, "tpath", name="route_landmarks", of=lambda w: routing.plain(w.roads, w.trips_i, "landmarks").select("city_id", "pair_id", "seq", "vertex_id"))
simple(ONE, "SELECT t.city_id, t.pair_id, round(r.cost, 4) AS cost FROM trip t JOIN rtree r ON r.city_id = t.city_id AND r.s = t.s AND r.v = t.t", "trip", "rtree", name="route_enriched", of=lambda w: rounded(measures.path_costs(routing.enriched(w.enriched, w.trips_i, "cost_100"), w.costs, "cost_100").select("city_id", "pair_id", F.col("c").alias("cost"))))
for _shape in ("drawn", "box", "confocal"):
    simple(None, f"SELECT city_id, pair_id, poi_id, round(ds, 4) AS ds, round(dt, 4) AS dt FROM node_{_shape}", f"node_{_shape}", name="ellipse_pois" if _shape == "drawn" else f"ellipse_pois_{_shape}", of=lambda w, k=_shape: rounded(routing.ellipse_pois(routing.located(w.trips_i, w.base.vertices), w.places, k).drop("vertex_id")))
simple(None, "SELECT * FROM nends", "nends", name="entry_exit_network", of=lambda w: routing.entry_exit_network(w.base, routing.ellipse_pois(routing.located(w.trips_i, w.base.vertices), w.places), w.trips_i))
simple(None, "SELECT * FROM ends", "ends", name="entry_exit", of=lambda w: routing.entry_exit(routing.ellipse_pois(routing.located(w.trips_i, w.base.vertices), w.places)))


@query("SELECT e.city_id, e.pair_id, h.hops, round(h.cost, 4) AS dist FROM ends e JOIN hop h ON h.city_id = e.city_id AND h.pair_id = e.pair_id AND h.v = e.exit", "ends", "hop")
def poi_sequence(s, d):
    """Hops and straight-line length of each trip's sequence of places."""
    w = world(s, d, **ONE)
    nodes = workloads.stored(routing.ellipse_pois(routing.located(w.trips_i, w.base.vertices), w.places), "nodes")
    q = workloads.stored(routing.poi_sequence(routing.restricted_edges(nodes, w.closeness), routing.entry_exit(nodes)), "sequence")
    xy = w.pois.select("city_id", "poi_id", "x", "y")
    step = q.join(xy, ["city_id", "poi_id"])
    nxt = step.select("city_id", "pair_id", (F.col("seq") - 1).alias("seq"), F.col("x").alias("x2"), F.col("y").alias("y2"))
    leg = step.join(nxt, ["city_id", "pair_id", "seq"], "left")
    return rounded(leg.groupBy("city_id", "pair_id").agg(F.max("seq").alias("hops"), F.coalesce(F.sum(distance(F.col("x"), F.col("y"), F.col("x2"), F.col("y2"))), F.lit(0.0)).alias("dist")))


def _ladder(w: World) -> DataFrame:
    return w.ladder


def _hop(**how):
    return lambda s, d: routing.poi_hop(world(s, d).enriched, world(s, d).closeness, world(s, d).places, world(s, d).trips_i, "cost_100", **how)


QUERIES |= {
    "route_poi_hop": _hop(), "route_poi_hop_widen": _hop(on_unreachable="widen"), "route_poi_hop_null": _hop(on_unreachable="null"),
    "route_poi_hop_discounted": _hop(weight="discounted"), "route_poi_hop_score": _hop(weight="score"), "route_poi_hop_confocal": _hop(shape="confocal"),
    "route_ladder": lambda s, d: _ladder(world(s, d)),
    "describe_routes": lambda s, d: routing.describe(_ladder(world(s, d)).where("algo = 'poi_hop'"), world(s, d).places),
}

# ---------------------------------------------------------------- measures

simple(ONE, "SELECT p.city_id, p.pair_id, CAST(sum(c.len_dm) AS BIGINT) AS d, round(sum(c.cost_100), 4) AS c, round(sum(c.cost_100) / sum(c.len_dm), 4) AS er, count(c.edge_id) AS hops FROM tpath_e p LEFT JOIN cost c ON c.city_id = p.city_id AND c.edge_id = p.edge_id GROUP BY 1, 2", "tpath_e", "cost", name="er_per_path", of=lambda w: rounded(measures.path_costs(routing.plain(w.roads, w.trips_i), w.costs, "cost_100")))
simple(None, "SELECT * FROM vpop", "vpop", name="vertex_popularity", of=lambda w: w.vertex_photos)
simple(None, f"SELECT city_id, v AS vertex_id, count(*) AS photos FROM (SELECT p.city_id, p.photo_id, min({{'d': {O.line('p', 'v')}, 'v': v.vertex_id}}).v AS v FROM photo p JOIN v ON v.city_id = p.city_id WHERE v.x BETWEEN p.x - 20 AND p.x + 20 AND v.y BETWEEN p.y - 20 AND p.y + 20 AND {O.line('p', 'v')} <= 20 GROUP BY 1, 2) GROUP BY 1, 2", "photo", "v", name="vertex_popularity_nearest", of=lambda w: measures.vertex_popularity(w.photos, w.base.vertices, nearest_only=True))
simple(None, "SELECT p.city_id, p.pair_id, CAST(coalesce(sum(photos), 0) AS BIGINT) AS popularity FROM tpath p LEFT JOIN vpop q ON q.city_id = p.city_id AND q.vertex_id = p.vertex_id GROUP BY 1, 2", "tpath", "vpop", name="path_popularity", of=lambda w: measures.popularity(routing.plain(w.roads, w.trips_i), w.vertex_photos))
simple(None, "SELECT p.city_id, p.pair_id, p.seq, p.vertex_id, CAST(coalesce(sum(len_dm) OVER k, 0) AS BIGINT) AS run_len, CAST(coalesce(sum(photos) OVER k, 0) AS BIGINT) AS run_pop FROM tpath_e p LEFT JOIN vpop q ON q.city_id = p.city_id AND q.vertex_id = p.vertex_id WINDOW k AS (PARTITION BY p.city_id, p.pair_id ORDER BY p.seq ROWS UNBOUNDED PRECEDING)", "tpath_e", "vpop", name="running_measures", of=lambda w: measures.running(routing.plain(w.roads, w.trips_i), w.base.edges, w.vertex_photos))
simple(None, """SELECT c.city_id, coalesce(p, 0) AS photos, coalesce(mp, 0) AS max_photos, coalesce(pairs, 0) AS pairs, CAST(coalesce(rels, 0) AS BIGINT) AS relations, c.n AS vertices, coalesce(e, 0) AS edges FROM (SELECT city_id, count(*) AS n FROM v GROUP BY 1) c
  LEFT JOIN (SELECT city_id, count(*) AS p FROM photo GROUP BY 1) a ON a.city_id = c.city_id LEFT JOIN (SELECT city_id, max(photos) AS mp FROM vpop GROUP BY 1) b ON b.city_id = c.city_id
  LEFT JOIN (SELECT city_id, count(DISTINCT (pi, pj)) AS pairs, sum(cnt) AS rels FROM rel GROUP BY 1) r ON r.city_id = c.city_id LEFT JOIN (SELECT city_id, count(*) AS e FROM e GROUP BY 1) x ON x.city_id = c.city_id""", "v", "e", "photo", "vpop", "rel", name="dataset_stats", of=lambda w: measures.dataset_stats(w.photos, w.vertex_photos, w.relations, w.base.vertices, w.base.edges))  # fmt: skip
simple(None, "SELECT city_id, vertex_id, photos, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY city_id ORDER BY photos DESC, vertex_id) AS rank FROM vpop) WHERE rank <= 10", "vpop", name="top_popular_vertices", of=lambda w: w.vertex_photos.selectExpr("*", "row_number() over (partition by city_id order by photos desc, vertex_id) as rank").where("rank <= 10"))
simple(None, "SELECT city_id, CAST(hour(ts) AS INTEGER) AS hour, event_type, count(*) AS photos FROM photo GROUP BY ALL", "photo", name="hourly_photos", of=lambda w: w.photos.groupBy("city_id", F.hour("ts").alias("hour"), "event_type").agg(F.count("*").alias("photos")))
simple(None, "SELECT city_id, event_type, count(*) AS photos, CAST(grouping(city_id) * 2 + grouping(event_type) AS BIGINT) AS level FROM photo GROUP BY CUBE (city_id, event_type)", "photo", name="photo_cube", of=lambda w: w.photos.cube("city_id", "event_type").agg(F.count("*").alias("photos"), F.grouping_id().alias("level")))

QUERIES |= {
    "relative_measures": lambda s, d: rounded(workloads.compared(world(s, d))),
    "route_overlap": lambda s, d: rounded(measures.overlap(_ladder(world(s, d)), world(s, d).costs)),
    "dominance": lambda s, d: measures.dominance(workloads.compared(world(s, d))),
    "discount_popularity_corr": lambda s, d: rounded(measures.discount_popularity_corr(world(s, d).costs, "cost_100", world(s, d).vertex_photos)),
    "setting_alpha": lambda s, d: workloads.setting_alpha(world(s, d)),
    "setting_alpha_ratio_of_means": lambda s, d: workloads.setting_alpha(world(s, d), "ratio_of_means"),
    "setting_alpha_corpus_prior": lambda s, d: workloads.setting_alpha(world(s, d, prior="corpus_frequency", use_syntax=False)),
    "setting_bracket": lambda s, d: workloads.setting_bracket(world(s, d)),
    "setting_bracket_corpus_prior": lambda s, d: workloads.setting_bracket(world(s, d, prior="corpus_frequency", use_syntax=False)),
    "tradeoff": lambda s, d: workloads.tradeoff(world(s, d)),
    "summary_rollup": lambda s, d: workloads.summary_levels(world(s, d)),
    "summary_cube": lambda s, d: workloads.summary_levels(world(s, d), "cube"),
    "pivot_algorithms": lambda s, d: workloads.pivoted(world(s, d)),
    "ablation": workloads.ablation,
}

# ---------------------------------------------------------------- the experiments with all that SQL can follow: one Gaussian per word, costs on a grid

PINNED = {"single": True, "grid": O.GRID}
FULL = "alpha = CAST(1 AS DOUBLE)"
SWEPT = "alpha IN (" + ", ".join(f"CAST({a} AS DOUBLE)" for a in workloads.SWEEP) + ")"
REL = "round(er, 4) AS er, round(er0, 4) AS er0, " + ", ".join(f"round({c}, 4) AS {c}" for c in O.CHANGES)
ROWS = "SELECT city_id, algo, pair_id, CAST(seq AS INTEGER) AS seq, vertex_id, edge_id, fallback FROM xrows WHERE {}"
PATH_ROWS = ("city_id", "algo", "pair_id", "seq", "vertex_id", "edge_id", "fallback")
simple(PINNED, "SELECT city_id, edge_id, " + ", ".join(f"c{O.tag(a)} AS cost_{O.tag(a)}" for a in workloads.ALPHAS) + " FROM pcost", "pcost", name="pinned_edge_costs", of=lambda w: w.costs.drop("u", "v", "len_dm", "n_paths"))
simple(PINNED, "SELECT city_id, 'ii' AS setting, bracket, CAST(trip_id AS INTEGER) AS trip_id, s, t FROM ytrip", "ytrip", name="trips_network", of=lambda w: w.trips_ii)
simple(PINNED, ROWS.format(FULL), "xrows", name="pinned_ladder", of=lambda w: w.ladder.select(*PATH_ROWS))
simple(PINNED, ROWS.format(f"{FULL} AND algo = 'enriched'"), "xrows", name="pinned_route_enriched", of=lambda w: w.ladder.where("algo = 'enriched'").select(*PATH_ROWS))
simple(PINNED, ROWS.format(f"{FULL} AND algo = 'poi_hop'"), "xrows", name="pinned_route_poi_hop", of=lambda w: routing.poi_hop(w.enriched, w.closeness, w.places, w.trips_i, "cost_100").withColumn("algo", F.lit("poi_hop")).select(*PATH_ROWS))
simple(PINNED, ROWS.format(f"{FULL} AND algo = 'poi_hop' AND NOT fallback"), "xrows", name="pinned_route_poi_hop_null", of=lambda w: routing.poi_hop(w.enriched, w.closeness, w.places, w.trips_i, "cost_100", on_unreachable="null").withColumn("algo", F.lit("poi_hop")).select(*PATH_ROWS))
simple(PINNED, f"SELECT r.city_id, pair_id, CAST(seq AS INTEGER) AS seq, poi_id FROM xrows r JOIN snap ON snap.city_id = r.city_id AND snap.b.v = r.vertex_id WHERE {FULL} AND algo = 'poi_hop'", "xrows", "snap", name="pinned_described_routes", of=lambda w: routing.describe(w.ladder.where("algo = 'poi_hop'"), w.places).drop("name"))
simple(PINNED, f"SELECT city_id, pair_id, algo, CAST(d AS BIGINT) AS d, round(c, 4) AS c, round(er, 4) AS er, hops, CAST(popularity AS BIGINT) AS popularity FROM xm WHERE {FULL}", "xm", name="pinned_measures", of=lambda w: rounded(measures.per_path(w.ladder, w.costs, "cost_100", w.vertex_photos)))
simple(PINNED, f"SELECT city_id, pair_id, algo, alpha, bracket, d, d0, popularity, p0, {REL} FROM xrel WHERE {FULL}", "xrel", name="pinned_relative_measures", of=lambda w: rounded(workloads.compared(w)))
simple(PINNED, f"""SELECT city_id, pair_id, round(CAST(sum(CASE WHEN n = 2 THEN len_dm ELSE 0 END) AS DOUBLE) / sum(len_dm), 4) AS overlap FROM (SELECT r.city_id, pair_id, r.edge_id, any_value(len_dm) AS len_dm, count(DISTINCT algo) AS n FROM xrows r JOIN pcost e ON e.city_id = r.city_id AND e.edge_id = r.edge_id
  WHERE {FULL} AND algo <> 'poi_hop' GROUP BY 1, 2, 3) GROUP BY 1, 2""", "xrows", "pcost", name="pinned_overlap", of=lambda w: rounded(measures.overlap(w.ladder, w.costs)))  # fmt: skip
simple(PINNED, f"""SELECT count(*) AS trips, count(*) FILTER (a.d < b.d) AS enriched_shorter, count(*) FILTER (a.d = b.d) AS same_length, count(*) FILTER (b.er < a.er) AS hop_lower_er, count(*) FILTER (b.popularity > a.popularity) AS hop_more_popular, count(*) FILTER (b.popularity = a.popularity) AS same_popularity
  FROM xrel a JOIN xrel b ON a.pair_id = b.pair_id AND a.alpha = b.alpha AND a.algo = 'enriched' AND b.algo = 'poi_hop' WHERE a.{FULL}""", "xrel", name="pinned_dominance", of=lambda w: measures.dominance(workloads.compared(w)))  # fmt: skip
simple(PINNED, "SELECT e.city_id, round(CASE WHEN stddev_pop(1 - c100 / len_dm) > 0 AND stddev_pop(coalesce(a.photos, 0) + coalesce(b.photos, 0)) > 0 THEN corr(1 - c100 / len_dm, coalesce(a.photos, 0) + coalesce(b.photos, 0)) END, 4) AS corr FROM pcost e LEFT JOIN vpop a ON a.city_id = e.city_id AND a.vertex_id = e.u LEFT JOIN vpop b ON b.city_id = e.city_id AND b.vertex_id = e.v GROUP BY 1", "pcost", "vpop", name="pinned_discount_popularity_corr", of=lambda w: rounded(measures.discount_popularity_corr(w.costs, "cost_100", w.vertex_photos)))
simple(PINNED, O.summary("xrel", "city_id, algo, alpha", SWEPT), "xrel", name="pinned_setting_alpha", of=workloads.setting_alpha)
simple(PINNED, O.summary("xrel", "city_id, algo, alpha", SWEPT, "ratio_of_means"), "xrel", name="pinned_setting_alpha_ratio_of_means", of=lambda w: workloads.setting_alpha(w, "ratio_of_means"))
simple(PINNED, O.summary("yrel", "city_id, algo, bracket", FULL), "yrel", name="pinned_setting_bracket", of=workloads.setting_bracket)
simple(PINNED, "SELECT setting, algo, alpha, bracket, round(avg(len_change), 4) AS len_change, round(avg(pop_change), 4) AS pop_change FROM (SELECT 'i' AS setting, * FROM xrel WHERE alpha = CAST(0.5 AS DOUBLE) UNION ALL SELECT 'ii', * FROM yrel) GROUP BY ALL", "xrel", "yrel", name="pinned_tradeoff", of=workloads.tradeoff)
for _how, _sets in (("rollup", "ROLLUP"), ("cube", "CUBE")):
    simple(PINNED, f"SELECT city_id, algo, CAST(grouping(city_id) * 2 + grouping(algo) AS BIGINT) AS level, count(*) AS trips, round(avg(len_change), 4) AS len_change, round(avg(er_gain), 4) AS er_gain, round(avg(pop_change), 4) AS pop_change FROM xrel WHERE {FULL} GROUP BY {_sets} (city_id, algo)", "xrel", name=f"pinned_summary_{_how}", of=lambda w, h=_how: workloads.summary_levels(w, h))
simple(PINNED, f"SELECT city_id, round(avg(len_change) FILTER (algo = 'enriched'), 4) AS enriched, round(avg(len_change) FILTER (algo = 'poi_hop'), 4) AS poi_hop FROM xrel WHERE {FULL} GROUP BY 1", "xrel", name="pinned_pivot", of=workloads.pivoted)


def _sequence_cost(kind: str):
    def of(w: World) -> DataFrame:
        nodes = workloads.stored(routing.ellipse_pois(routing.located(w.trips_i, w.base.vertices), w.places), "nodes")
        edges = workloads.stored(routing.restricted_edges(nodes, w.closeness), "hop-edges")
        weight = routing.hop_weight(kind, 1.0)
        found = workloads.stored(routing.poi_sequence(edges, routing.entry_exit(nodes), weight), "sequence")
        return rounded(routing.sequence_cost(found, edges, weight).select("city_id", "pair_id", "cost"))

    return of


for _kind, _block in (("discounted", "xhopd"), ("score", "xhopw")):
    simple(PINNED, f"SELECT e.city_id, e.pair_id, round(h.cost, 4) AS cost FROM xends e JOIN {_block} h ON h.city_id = e.city_id AND h.pair_id = e.pair_id AND h.v = e.exit", "xends", _block, name=f"pinned_poi_sequence_{_kind}", of=_sequence_cost(_kind))

# ---------------------------------------------------------------- streams


def _streamed(make: Callable[[DataFrame], DataFrame], mode: str = "complete"):
    return lambda s, d: streams.finished(make(streams.events(s, d)), f"closeway_{uuid.uuid4().hex}", mode)


DAILY = "SELECT CAST(ts AS DATE) AS day, event_type, count(*) AS photos FROM events GROUP BY 1, 2"


@query(DAILY)
def stream_daily_photos(s, d):
    done = _streamed(lambda e: streams.windowed(e))(s, d)
    return done.select(F.to_date("start").alias("day"), "event_type", "photos")


CLOCK = "yyyy-MM-dd HH:mm:ss.SSSSSS"
STRF = "'%Y-%m-%d %H:%M:%S.%f'"


@query(f"SELECT strftime(w, {STRF}) AS start, event_type, count(*) AS photos FROM (SELECT event_type, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - to_hours(6 * k) AS w FROM events, (VALUES (0), (1), (2), (3)) v(k)) GROUP BY 1, 2")
def stream_sliding_photos(s, d):
    done = _streamed(lambda e: streams.windowed(e, "1 day", "6 hours"))(s, d)
    return done.select(F.date_format("start", CLOCK).alias("start"), "event_type", "photos")


SESSIONS = """SELECT user_id, count(*) AS photos, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS stop FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (
  SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, k"""


@query(f"SELECT user_id, photos, strftime(start, {STRF}) AS start, strftime(stop, {STRF}) AS stop FROM ({SESSIONS})")
def stream_sessions(s, d):
    done = _streamed(lambda e: streams.sessions(e))(s, d)
    return done.select("user_id", "photos", F.date_format("start", CLOCK).alias("start"), F.date_format("end", CLOCK).alias("stop"))


@query("SELECT user_id, count(*) AS seen FROM events GROUP BY 1")
def stream_running_counts(s, d):
    """Photos of each user so far, the last row of each."""
    return _streamed(streams.running_counts, "update")(s, d).groupBy("user_id").agg(F.max("seen").alias("seen"))


@query("SELECT * FROM vpop", "vpop")
def stream_vertex_photos(s, d):
    """Photos of each vertex so far: a stream-static join with the vertex grid."""
    w = world(s, d)
    return _streamed(lambda e: streams.near_vertices(fixtures.photos(s, d, e), w.base.vertices).groupBy("city_id", "vertex_id").agg(F.count("*").alias("photos")))(s, d)


@query(DAILY)
def stream_distinct_photos(s, d):
    """Daily counts of a stream in which every photo comes twice; the repeat is dropped within the watermark."""
    twice = lambda e: e.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    done = _streamed(lambda e: streams.distinct_photos(twice(e)), "append")(s, d)
    return streams.windowed(done).select(F.to_date("start").alias("day"), "event_type", "photos")


@query(DAILY)
def daily_photos(s, d):
    return streams.windowed(table(s, d, "events")).select(F.to_date("start").alias("day"), "event_type", "photos")


@query(f"SELECT user_id, photos, start FROM ({SESSIONS})")
def photo_sessions(s, d):
    return streams.sessions(table(s, d, "events")).select("user_id", "photos", "start")


# ---------------------------------------------------------------- around the paper's steps

VERSIONS = "SELECT city_id, CAST(DATE '2024-01-01' + CAST(5 * k AS INTEGER) AS TIMESTAMP) AS ts, k AS version FROM (SELECT DISTINCT city_id FROM v), (SELECT unnest(range(0, 6)) AS k)"


@query(f"SELECT p.city_id, p.photo_id, m.version FROM photo p ASOF LEFT JOIN ({VERSIONS}) m ON m.city_id = p.city_id AND m.ts <= p.ts", "photo", "v")
def photo_asof_model(s, d):
    """Each photo with the latest version of its city's relation model before it (a version every five days)."""
    w = world(s, d)
    versions = w.vertices.select("city_id").distinct().select("city_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(5).cast("long"))).alias("version"))
    versions = versions.select("city_id", F.expr("cast(date'2024-01-01' + cast(5 * version as int) as timestamp_ntz)").alias("ts"), "version")
    return extra.asof_join(w.photos.select("city_id", "photo_id", "ts"), versions, ["city_id"]).select("city_id", "photo_id", "version")


@query("SELECT city_id, s AS source, v, hops FROM around", "around")
def reachable(s, d):
    """Vertices within six steps of every trip start."""
    w = world(s, d)
    return extra.reachable(w.base.edges, w.trips_i.select("city_id", F.col("s").alias("source")), 6)


@query()
def fuzzy_names(s, d):
    w = world(s, d)
    return extra.fuzzy_names(fixtures.heldout_names(s, d), w.gazetteer)


@query("""SELECT p.city_id, pair_id, '{"type":"LineString","coordinates":[' || string_agg('[' || x || ',' || y || ']', ',' ORDER BY seq) || ']}' AS route FROM tpath p JOIN v ON v.city_id = p.city_id AND v.vertex_id = p.vertex_id GROUP BY 1, 2""", "tpath", "v")
def route_geojson(s, d):
    w = world(s, d)
    return extra.geojson(routing.plain(w.roads, w.trips_i), w.vertices)


@query()
def sampled_trips(s, d):
    return extra.sample_trips(world(s, d).trips_i, 0.25)


@query("SELECT city_id, bracket, count(*) AS trips, CAST(grouping(city_id) * 2 + grouping(bracket) AS BIGINT) AS level FROM (SELECT city_id, '30-50' AS bracket FROM trip) GROUP BY GROUPING SETS ((city_id), (bracket), ())", "trip")
def trips_grouping_sets(s, d):
    world(s, d).trips_i.createOrReplaceTempView("closeway_trips")
    return s.sql("SELECT city_id, bracket, count(*) AS trips, CAST(grouping_id() AS BIGINT) AS level FROM closeway_trips GROUP BY city_id, bracket GROUPING SETS ((city_id), (bracket), ())")


@query("SELECT photo_id, city_id, json_extract_string(props, '$.k') AS k FROM photo JOIN events ON event_id = photo_id", "photo")
def photo_props(s, d):
    props = table(s, d, "events").select(F.col("event_id").alias("photo_id"), F.from_json("props", "k string")["k"].alias("k"))
    return world(s, d).photos.select("photo_id", "city_id").join(props, "photo_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return {k: v for k, v in ORACLES.items() if k in QUERIES}
