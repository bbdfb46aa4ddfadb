"""The paper's experiments on the given tables: one city per region, all stages stored once and shared."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import closeness, features, graph, measures, mixture, routing, text
from ..session import Stored, large, table
from ..sources import fixtures

ALPHAS = (0.2, 0.4, 0.5, 0.6, 0.8, 1.0)
SWEEP = (0.2, 0.4, 0.6, 0.8, 1.0)
BRACKETS = (("10-20", 0.1, 0.2), ("20-30", 0.2, 0.3), ("30-40", 0.3, 0.4), ("40-50", 0.4, 0.5), ("50-60", 0.5, 0.6))
#: Trips per city and bracket; ten where a city has fewer vertices than this.
TRIPS, FEW_TRIPS, FEW_VERTICES = 100, 10, 100


def stored(df: DataFrame, name: str) -> DataFrame:
    return large(Stored(df, name).df)


class World:
    """All stages of one scale, each made when first asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str, prior: str = "pair_frequency", scope: str = "per_relation", use_syntax: bool = True, pairs: str = "ordered", shape: str = "drawn", pseudo: bool = False, max_components: int = 3, combine: str = "sum", single: bool = False, grid: int = 0, trips: int | None = None):
        self.spark, self.sf_dir, self.prior, self.scope, self.use_syntax = spark, sf_dir, prior, scope, use_syntax
        self.pair_mode, self.shape, self.pseudo, self.max_components, self.combine = pairs, shape, pseudo, max_components, combine
        self.single = single  # one Gaussian per word in closed form instead of a grown mixture
        self.grid = grid  # discounted costs rounded to so many parts of a decimetre: sums are then exact and paths unique in any engine
        self.trips = trips  # per city and bracket; None: by the size of the smallest city
        self.lexicon = text.TABLE_LEXICON

    @property
    def docs(self) -> DataFrame:
        return table(self.spark, self.sf_dir, "documents").where("lang = 'en'").select("doc_id", "text")

    @cached_property
    def gazetteer(self) -> DataFrame:
        return stored(fixtures.gazetteer(self.spark, self.sf_dir), "gazetteer")

    @cached_property
    def pois(self) -> DataFrame:
        return stored(fixtures.pois(self.spark, self.sf_dir), "pois")

    @cached_property
    def triplets(self) -> DataFrame:
        return stored(text.extract_triplets(self.docs, self.gazetteer, lexicon=self.lexicon, use_syntax=self.use_syntax), "triplets")

    @cached_property
    def relations(self) -> DataFrame:
        """(city_id, pi, pj, rel_id, cnt) within cities."""
        close = text.keep_closeness(self.triplets, self.lexicon)
        return stored(text.in_city(text.relation_edges(close), self.pois), "relations")

    @cached_property
    def vectors(self) -> DataFrame:
        return stored(features.vectors(self.relations.drop("city_id"), self.pois), "vectors")

    @cached_property
    def pair_vectors(self) -> DataFrame:
        return stored(features.pair_vectors(self.relations, self.pois), "pair-vectors")

    @cached_property
    def grown(self) -> mixture.Grown:
        return mixture.fit_greedy(self.vectors, self.max_components)

    @cached_property
    def model(self) -> DataFrame:
        if self.single:
            return stored(mixture.fit_single(self.vectors), "single")
        return mixture.to_table(self.spark, self.grown.model)

    @cached_property
    def closeness(self) -> DataFrame:
        return stored(closeness.closeness_graph(self.relations, self.pair_vectors, self.model, len(self.lexicon), self.prior, self.scope, self.combine), "closeness")

    @cached_property
    def vertices(self) -> DataFrame:
        return stored(fixtures.road_vertices(self.spark, self.sf_dir), "vertices")

    @cached_property
    def base(self) -> graph.RoadGraph:
        return graph.RoadGraph(self.vertices.select("city_id", "vertex_id", "x", "y"), stored(fixtures.road_edges(self.vertices), "edges"))

    @cached_property
    def roads_and_places(self) -> tuple[graph.RoadGraph, DataFrame]:
        if self.pseudo:
            g, p = graph.snap_pseudo(self.pois, self.base)
            return graph.RoadGraph(stored(g.vertices, "pseudo-v"), stored(g.edges, "pseudo-e")), stored(p, "pseudo-p")
        return self.base, stored(graph.snap(self.pois, self.base.vertices), "snapped")

    @property
    def roads(self) -> graph.RoadGraph:
        return self.roads_and_places[0]

    @property
    def places(self) -> DataFrame:
        return self.roads_and_places[1]

    @cached_property
    def pairs(self) -> DataFrame:
        p = graph.close_pairs(self.closeness, self.places)
        return stored(graph.unordered(p) if self.pair_mode == "unordered" else p, "pairs")

    @cached_property
    def pair_paths(self) -> DataFrame:
        return stored(graph.shortest(self.roads, self.pairs), "pair-paths")

    @cached_property
    def costs(self) -> DataFrame:
        c = graph.edge_costs(self.roads.edges, self.pair_paths, self.pairs, list(ALPHAS))
        if self.grid:
            c = c.withColumns({k: F.round(F.col(k) * self.grid) / self.grid for k in map(graph.cost_name, ALPHAS)})
        return stored(c, "costs")

    @cached_property
    def enriched(self) -> graph.RoadGraph:
        return graph.enriched(self.roads, self.costs)

    @cached_property
    def photos(self) -> DataFrame:
        return stored(fixtures.photos(self.spark, self.sf_dir), "photos")

    @cached_property
    def vertex_photos(self) -> DataFrame:
        return stored(measures.vertex_popularity(self.photos, self.roads.vertices), "vertex-photos")

    @cached_property
    def n_trips(self) -> int:
        if self.trips is not None:
            return self.trips
        least = self.vertices.groupBy("city_id").count().agg(F.min("count")).first()[0] or 0
        return TRIPS if least >= FEW_VERTICES else FEW_TRIPS

    @cached_property
    def trips_i(self) -> DataFrame:
        return stored(fixtures.trips_straight(self.vertices, self.n_trips), "trips-i")

    @cached_property
    def trips_ii(self) -> DataFrame:
        """Brackets of network length over the extent (in decimetres)."""
        c = stored(fixtures.trip_candidates(self.vertices), "candidates")
        c = c.join(graph.costs_local(self.base, c), ["city_id", "s", "t"]).join(F.broadcast(fixtures.extents(self.vertices)), "city_id")
        return stored(fixtures.pick_trips(c, F.col("cost") / 10, list(BRACKETS), self.n_trips, "ii"), "trips-ii")

    def routes(self, trips: DataFrame, alphas: tuple[float, ...]) -> DataFrame:
        """(alpha, algo, path rows): the plain route once, the other two per alpha."""
        no = F.lit(False).alias("fallback")
        plain = stored(routing.plain(self.roads, trips), "plain")
        plan = routing.hop_plan(self.enriched, self.closeness, self.places, trips, self.shape)
        out = None
        for a in alphas:
            cost = graph.cost_name(a)
            e = stored(routing.enriched(self.enriched, trips, cost), "enriched")
            h = routing.drive(self.enriched, plan, trips, cost, enriched_paths=e).withColumn("algo", F.lit("poi_hop"))
            part = plain.select("*", no, F.lit("plain").alias("algo")).unionByName(e.select("*", no, F.lit("enriched").alias("algo"))).unionByName(h).withColumn("alpha", F.lit(a))
            out = part if out is None else out.unionByName(part)
        return stored(out, "routes")

    @cached_property
    def ladder(self) -> DataFrame:
        """The three planners on the trips of setting i at full strength."""
        return self.routes(self.trips_i, (1.0,))

    def measured(self, routes: DataFrame, alphas: tuple[float, ...]) -> DataFrame:
        """(alpha, per-trip changes against the plain route)."""
        out = None
        for a in alphas:
            m = measures.per_path(routes.where(F.col("alpha") == a), self.costs, graph.cost_name(a), self.vertex_photos)
            r = measures.relative(stored(m, "measured")).withColumn("alpha", F.lit(a))
            out = r if out is None else out.unionByName(r)
        return out.withColumn("bracket", F.element_at(F.split("pair_id", "/"), 3))


def rounded(df: DataFrame, digits: int = 4) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" and c != "alpha" else F.col(c) for c, t in df.dtypes])


def setting_alpha(w: World, mode: str = "mean_of_ratios") -> DataFrame:
    """Setting i: the discount's strength varies, trips of 30 to 50 % of the extent."""
    r = w.measured(w.routes(w.trips_i, SWEEP), SWEEP)
    return rounded(measures.summarise(r, ["city_id", "algo", "alpha"], mode))


def setting_bracket(w: World, mode: str = "mean_of_ratios") -> DataFrame:
    """Setting ii: full discount, trips by network length."""
    r = w.measured(w.routes(w.trips_ii, (1.0,)), (1.0,))
    return rounded(measures.summarise(r, ["city_id", "algo", "bracket"], mode))


def compared(w: World) -> DataFrame:
    """Changes per trip of setting i at full strength."""
    return w.measured(w.ladder, (1.0,))


def tradeoff(w: World) -> DataFrame:
    """Popularity against length: alpha 0.5 for both settings, and 1 for setting ii."""
    i = w.measured(w.routes(w.trips_i, (0.5,)), (0.5,)).withColumn("setting", F.lit("i"))
    ii = w.measured(w.routes(w.trips_ii, (0.5, 1.0)), (0.5, 1.0)).withColumn("setting", F.lit("ii"))
    return rounded(measures.tradeoff(measures.summarise(i.unionByName(ii), ["setting", "algo", "alpha", "bracket"])))


def summary_levels(w: World, how: str = "rollup") -> DataFrame:
    """Mean changes by city and planner with totals: ``rollup`` or ``cube``."""
    r = compared(w)
    g = r.rollup("city_id", "algo") if how == "rollup" else r.cube("city_id", "algo")
    return rounded(g.agg(F.grouping_id().alias("level"), F.count("*").alias("trips"), F.avg("len_change").alias("len_change"), F.avg("er_gain").alias("er_gain"), F.avg("pop_change").alias("pop_change")))


def pivoted(w: World) -> DataFrame:
    """Length change with a column per planner."""
    r = compared(w)
    return rounded(r.groupBy("city_id").pivot("algo", ["enriched", "poi_hop"]).agg(F.avg("len_change")))


def ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per variant: what the prior, normaliser, region, syntax test, pair order, snapping, combination and the grown mixture change."""
    variants = {
        "default": {}, "prior=pair_uniform": {"prior": "pair_uniform"}, "prior=corpus_frequency": {"prior": "corpus_frequency"}, "prior=corpus_uniform": {"prior": "corpus_uniform"},
        "scope=global": {"scope": "global"}, "scope=none": {"scope": "none"}, "syntax=off": {"use_syntax": False}, "pairs=unordered": {"pairs": "unordered"},
        "shape=confocal": {"shape": "confocal"}, "shape=none": {"shape": "none"}, "snap=pseudo": {"pseudo": True}, "combine=noisy_or": {"combine": "noisy_or"}, "model=single": {"single": True},
    }
    # Stages that a variant leaves alone are made once.
    first = World(spark, sf_dir)
    roads = ("gazetteer", "pois", "vertices", "base", "photos", "n_trips", "trips_i")
    words = ("triplets", "relations", "vectors", "pair_vectors", "model")
    for stage in roads + words:
        getattr(first, stage)
    out = None
    for name, options in variants.items():
        w = World(spark, sf_dir, **options)
        own = {"model"} if "single" in options else set()
        w.__dict__.update({k: first.__dict__[k] for k in roads + words * ("use_syntax" not in options) if k not in own})
        r = w.measured(w.routes(w.trips_i, (1.0,)), (1.0,))
        s = measures.summarise(r, ["algo"]).withColumn("variant", F.lit(name))
        out = s if out is None else out.unionByName(s)
    return rounded(out)
