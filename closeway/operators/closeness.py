"""Bayesian confidences of (pair, word) and their condensation into one closeness score per ordered pair."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .mixture import log_gauss

PRIORS = ("pair_frequency", "pair_uniform", "corpus_frequency", "corpus_uniform")
SCOPES = ("per_relation", "global", "none", "all_pairs")
COMBINES = ("sum", "max", "mean", "noisy_or")


def likelihoods(pairs: DataFrame, model: DataFrame) -> DataFrame:
    """(city_id, pi, pj, rel_id, log_lik): every pair's vector under every word; the model is broadcast, no shuffle."""
    array = model.groupBy("rel_id").agg(F.array_sort(F.collect_list(F.struct("m", "weight", "mu_d", "mu_o", "s_dd", "s_do", "s_oo"))).alias("c"))
    terms = F.transform("c", lambda c: F.log(c["weight"]) + log_gauss(F.col("dist"), F.col("theta"), c))
    t = pairs.select("city_id", "pi", "pj", "dist", "theta").join(F.broadcast(array)).withColumn("_t", terms).withColumn("_top", F.array_max("_t"))
    return t.select("city_id", "pi", "pj", "rel_id", (F.col("_top") + F.log(F.aggregate("_t", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("_top"))))).alias("log_lik"))


def priors(edges: DataFrame, n_rel: int, prior: str = "pair_frequency") -> DataFrame:
    """(city_id, pi, pj, rel_id, prior) where it is positive and differs by pair, or (city_id, rel_id, prior) for the corpus variants."""
    if prior == "pair_frequency":
        return edges.select("city_id", "pi", "pj", "rel_id", (F.col("cnt") / F.sum("cnt").over(Window.partitionBy("city_id", "pi", "pj"))).alias("prior"))
    if prior == "pair_uniform":
        return edges.select("city_id", "pi", "pj", "rel_id", (F.lit(1.0) / F.count("*").over(Window.partitionBy("city_id", "pi", "pj"))).alias("prior"))
    words = edges.groupBy("city_id", "rel_id").agg(F.sum("cnt").alias("c"))
    if prior == "corpus_frequency":
        total = words.groupBy("city_id").agg(F.sum("c").alias("all"))
        return words.join(F.broadcast(total), "city_id").select("city_id", "rel_id", (F.col("c") / F.col("all")).alias("prior"))
    if prior == "corpus_uniform":
        ids = words.select("rel_id").distinct()
        return words.select("city_id").distinct().join(F.broadcast(ids)).select("city_id", "rel_id", F.lit(1.0 / n_rel).alias("prior"))
    raise ValueError(f"unknown prior {prior}")


def posteriors(lik: DataFrame, edges: DataFrame, n_rel: int, prior: str = "pair_frequency") -> DataFrame:
    """(city_id, pi, pj, rel_id, posterior, observed) over all words; a pair without support gets 0 everywhere.

    Likelihoods are shifted by the pair's largest before they are exponentiated.
    """
    p = priors(edges, n_rel, prior)
    keys = ["city_id", "pi", "pj", "rel_id"] if prior.startswith("pair") else ["city_id", "rel_id"]
    t = lik.join(p if prior.startswith("pair") else F.broadcast(p), keys, "left").withColumn("prior", F.coalesce("prior", F.lit(0.0)))
    t = t.join(edges.select("city_id", "pi", "pj", "rel_id", F.lit(True).alias("observed")), ["city_id", "pi", "pj", "rel_id"], "left")
    pair = Window.partitionBy("city_id", "pi", "pj")
    top = F.max(F.when(F.col("prior") > 0, F.col("log_lik"))).over(pair)
    t = t.withColumn("_m", F.when(F.col("prior") > 0, F.exp(F.col("log_lik") - top) * F.col("prior")).otherwise(0.0))
    post = F.coalesce(F.try_divide("_m", F.sum("_m").over(pair)), F.lit(0.0))
    return t.select("city_id", "pi", "pj", "rel_id", post.alias("posterior"), F.coalesce("observed", F.lit(False)).alias("observed"))


def classify(post: DataFrame) -> DataFrame:
    """The baseline: each pair's word of largest posterior, the smaller id on a tie."""
    best = F.max(F.struct("posterior", (-F.col("rel_id")).alias("neg")))
    return post.groupBy("city_id", "pi", "pj").agg(best.alias("b")).select("city_id", "pi", "pj", (-F.col("b.neg")).alias("rel_id"), F.col("b.posterior").alias("posterior"))


def normalisers(post: DataFrame, scope: str = "per_relation") -> DataFrame:
    """(city_id, rel_id, top): the largest posterior of each word over the pairs that have it (``all_pairs``: over all)."""
    seen = post if scope == "all_pairs" else post.where("observed")
    top = seen.groupBy("city_id", "rel_id").agg(F.max("posterior").alias("top"))
    if scope == "global":
        return top.withColumn("top", F.max("top").over(Window.partitionBy("city_id")))
    if scope == "none":
        return top.withColumn("top", F.lit(1.0))
    if scope not in SCOPES:
        raise ValueError(f"unknown scope {scope}")
    return top


def score(post: DataFrame, norm: DataFrame, n_rel: int, combine: str = "sum") -> DataFrame:
    """(city_id, pi, pj, W, n_words): the pair's observed words' normalised posteriors, added up over all words' number."""
    share = F.coalesce(F.try_divide("posterior", "top"), F.lit(0.0))
    t = post.where("observed").join(F.broadcast(norm), ["city_id", "rel_id"]).withColumn("share", share)
    how = {
        "sum": F.sum("share") / n_rel,
        "max": F.max("share"),
        "mean": F.avg("share"),
        "noisy_or": 1 - F.product(1 - F.col("share")),
    }[combine]
    return t.groupBy("city_id", "pi", "pj").agg(how.alias("W"), F.count("*").alias("n_words"))


def graph(scores: DataFrame, pair_vecs: DataFrame) -> DataFrame:
    """(city_id, pi, pj, W, dist): the closeness graph's edges with their straight-line length."""
    return scores.join(pair_vecs.select("city_id", "pi", "pj", "dist"), ["city_id", "pi", "pj"]).select("city_id", "pi", "pj", "W", "dist")


def closeness_graph(edges: DataFrame, pair_vecs: DataFrame, model: DataFrame, n_rel: int, prior: str = "pair_frequency", scope: str = "per_relation", combine: str = "sum") -> DataFrame:
    post = posteriors(likelihoods(pair_vecs, model), edges, n_rel, prior)
    return graph(score(post, normalisers(post, scope), n_rel, combine), pair_vecs)
