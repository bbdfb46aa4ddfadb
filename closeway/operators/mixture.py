"""Two-dimensional Gaussian mixtures, one per relation word, fitted for all words in the same jobs.

A model is a list of ``Component`` rows on the driver (words times components), sent down as literals. Every round is
one aggregate: nine weighted sums per component give the next model and the log likelihood of the last.
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Iterable
from typing import NamedTuple

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

RIDGE = 1e-6
#: A component with less weight than this share of a word's samples is dropped.
LEAST_SHARE = 1e-6


class Component(NamedTuple):
    rel_id: int
    m: int
    weight: float
    mu_d: float
    mu_o: float
    s_dd: float
    s_do: float
    s_oo: float


Model = list[Component]
SCHEMA = "rel_id int, m int, weight double, mu_d double, mu_o double, s_dd double, s_do double, s_oo double"


def to_table(spark: SparkSession, model: Model) -> DataFrame:
    return spark.createDataFrame([(c.rel_id, c.m, *map(float, c[2:])) for c in model], SCHEMA)


def from_table(df: DataFrame) -> Model:
    return [Component(*r) for r in df.select("rel_id", "m", "weight", "mu_d", "mu_o", "s_dd", "s_do", "s_oo").orderBy("rel_id", "m").collect()]


def log_gauss(d: Column, o: Column, c) -> Column:
    """Log density of a component given as columns or numbers, by the closed 2x2 inverse."""
    det = c["s_dd"] * c["s_oo"] - c["s_do"] * c["s_do"]
    u, v = d - c["mu_d"], o - c["mu_o"]
    q = (c["s_oo"] * u * u - 2 * c["s_do"] * u * v + c["s_dd"] * v * v) / det
    return -math.log(2 * math.pi) - 0.5 * F.log(det) - 0.5 * q


def joined(vecs: DataFrame, model: DataFrame) -> DataFrame:
    """Each vector with each component of its word, and ``lp``: log of weight times density. The model is broadcast."""
    c = {k: F.col(k) for k in ("mu_d", "mu_o", "s_dd", "s_do", "s_oo")}
    return vecs.join(F.broadcast(model), "rel_id").withColumn("lp", F.log("weight") + log_gauss(F.col("dist"), F.col("theta"), c))


def fit_single(vecs: DataFrame, ridge: float = RIDGE) -> DataFrame:
    """One component per word, in closed form: weighted means and covariances."""
    w = F.col("w")
    n = F.sum("w")
    g = vecs.groupBy("rel_id").agg(n.alias("n"), *[F.sum(w * e).alias(k) for k, e in {"d": F.col("dist"), "o": F.col("theta"), "dd": F.col("dist") * F.col("dist"), "do": F.col("dist") * F.col("theta"), "oo": F.col("theta") * F.col("theta")}.items()])
    md, mo = F.col("d") / F.col("n"), F.col("o") / F.col("n")
    return g.select(
        "rel_id", F.lit(0).alias("m"), F.lit(1.0).alias("weight"), md.alias("mu_d"), mo.alias("mu_o"),
        (F.greatest(F.col("dd") / F.col("n") - md * md, F.lit(0.0)) + ridge).alias("s_dd"), (F.col("do") / F.col("n") - md * mo).alias("s_do"), (F.greatest(F.col("oo") / F.col("n") - mo * mo, F.lit(0.0)) + ridge).alias("s_oo"),
    )


def density(vecs: DataFrame, model: DataFrame) -> DataFrame:
    """(keys, log_p): log mixture density of each vector under its own word; the sum is shifted by its largest term."""
    array = model.groupBy("rel_id").agg(F.array_sort(F.collect_list(F.struct("m", "weight", "mu_d", "mu_o", "s_dd", "s_do", "s_oo"))).alias("c"))
    terms = F.transform("c", lambda c: F.log(c["weight"]) + log_gauss(F.col("dist"), F.col("theta"), c))
    t = vecs.join(F.broadcast(array), "rel_id").withColumn("_t", terms).withColumn("_top", F.array_max("_t"))
    return t.withColumn("log_p", F.col("_top") + F.log(F.aggregate("_t", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("_top"))))).drop("c", "_t", "_top")


def loglik(vecs: DataFrame, model: DataFrame) -> DataFrame:
    """(rel_id, n, loglik) of a model."""
    return density(vecs, model).groupBy("rel_id").agg(F.sum("w").alias("n"), F.sum(F.col("w") * F.col("log_p")).alias("loglik"))


def em_sums(vecs: DataFrame, model: DataFrame) -> DataFrame:
    """(rel_id, m, n, d, o, dd, do, oo, ll): responsibility sums of every component; ll is the word's log likelihood.

    Without a row number the vectors keep their components in one row: an array of terms, its log-sum, and an exploded
    share per component, so there is no shuffle but that of the sums.
    """
    array = model.groupBy("rel_id").agg(F.array_sort(F.collect_list(F.struct("m", "weight", "mu_d", "mu_o", "s_dd", "s_do", "s_oo"))).alias("c"))
    terms = F.transform("c", lambda c: F.log(c["weight"]) + log_gauss(F.col("dist"), F.col("theta"), c))
    t = vecs.select("rel_id", "dist", "theta", "w").join(F.broadcast(array), "rel_id").withColumn("_t", terms).withColumn("_top", F.array_max("_t"))
    t = t.withColumn("lp", F.col("_top") + F.log(F.aggregate("_t", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("_top")))))
    t = t.select("rel_id", "dist", "theta", "w", "lp", F.posexplode("_t").alias("i", "term"), F.col("c")).select("rel_id", "dist", "theta", "w", "lp", F.element_at("c", F.col("i") + 1)["m"].alias("m"), "i", F.exp(F.col("term") - F.col("lp")).alias("r"))
    r = F.col("w") * F.col("r")
    d, o = F.col("dist"), F.col("theta")
    return t.groupBy("rel_id", "m").agg(F.sum(r).alias("n"), F.sum(r * d).alias("d"), F.sum(r * o).alias("o"), F.sum(r * d * d).alias("dd"), F.sum(r * d * o).alias("do"), F.sum(r * o * o).alias("oo"), F.sum(F.col("w") * F.col("lp")).alias("ll"), F.sum("w").alias("a"))


def em_step(vecs: DataFrame, model: DataFrame, ridge: float = RIDGE) -> DataFrame:
    """The next model and, as ``loglik``, the log likelihood of the one given."""
    s = em_sums(vecs, model)
    md, mo = F.col("d") / F.col("n"), F.col("o") / F.col("n")
    return s.select(
        "rel_id", "m", (F.col("n") / F.col("a")).alias("weight"), md.alias("mu_d"), mo.alias("mu_o"),
        (F.greatest(F.col("dd") / F.col("n") - md * md, F.lit(0.0)) + ridge).alias("s_dd"), (F.col("do") / F.col("n") - md * mo).alias("s_do"), (F.greatest(F.col("oo") / F.col("n") - mo * mo, F.lit(0.0)) + ridge).alias("s_oo"), F.col("ll").alias("loglik"),
    )


def guarded(rows: Iterable, ridge: float) -> tuple[Model, int]:
    """Components with too little weight dropped, covariances made positive definite, weights adding up to one; and the number of repairs."""
    by: dict[int, list[Component]] = defaultdict(list)
    repairs = 0
    for r in rows:
        c = Component(*(r[k] for k in Component._fields))
        if not all(map(math.isfinite, c[2:])) or c.weight < LEAST_SHARE:
            repairs += 1
            continue
        room = c.s_dd * c.s_oo
        if c.s_do * c.s_do >= room * (1 - 1e-9):
            repairs += 1
            c = c._replace(s_do=math.copysign(math.sqrt(room) * (1 - 1e-6), c.s_do), s_dd=c.s_dd + ridge, s_oo=c.s_oo + ridge)
        by[c.rel_id].append(c)
    out = []
    for rel, cs in sorted(by.items()):
        total = sum(c.weight for c in cs)
        out += [c._replace(weight=c.weight / total, m=i) for i, c in enumerate(sorted(cs, key=lambda c: c.m))]
    return out, repairs


class EmResult(NamedTuple):
    model: Model
    loglik: dict[int, float]
    trace: list[tuple[int, int, float, float]]
    repairs: int


def fit_em(vecs: DataFrame, start: Model, tol: float = 1e-6, max_iter: int = 60, stop: str = "loglik", ridge: float = RIDGE) -> EmResult:
    """Rounds until every word's relative gain in log likelihood, or its parameters' largest change, is below ``tol``.

    Words that have settled leave the job. The trace lists (word, round, log likelihood, gain).
    """
    spark, model = vecs.sparkSession, start
    active, last, trace, repairs = {c.rel_id for c in start}, {}, [], 0
    for i in range(max_iter + 1):
        if not active:
            break
        now = [c for c in model if c.rel_id in active]
        rows = em_step(vecs.where(F.col("rel_id").isin(sorted(active))), to_table(spark, now), ridge).collect()
        ll = {r.rel_id: r.loglik for r in rows}
        new, fixed = guarded(rows, ridge)
        repairs += fixed
        grown = {c.rel_id: c for c in new}
        for rel in sorted(active):
            gain = ll[rel] - last[rel] if rel in last else math.inf
            trace.append((rel, i, ll[rel], gain))
            mine, old = [c for c in new if c.rel_id == rel], [c for c in now if c.rel_id == rel]
            if stop == "params":
                far = max((abs(a - b) / (1 + abs(b)) for c, o in zip(mine, old, strict=False) for a, b in zip(c[2:], o[2:], strict=True)), default=0.0) if len(mine) == len(old) else math.inf
            else:
                far = abs(gain) / (1 + abs(ll[rel]))
            last[rel] = ll[rel]
            if far < tol or rel not in grown or i == max_iter:
                active.discard(rel)
            else:
                model = [c for c in model if c.rel_id != rel] + mine
    return EmResult(sorted(model), last, trace, repairs)


def _axis(c: Component) -> tuple[float, float, float]:
    """Largest standard deviation of a component and its direction."""
    half, diff = (c.s_dd + c.s_oo) / 2, (c.s_dd - c.s_oo) / 2
    root = math.hypot(diff, c.s_do)
    top = half + root
    vx, vy = (c.s_do, top - c.s_dd) if abs(c.s_do) > 1e-12 else ((1.0, 0.0) if c.s_dd >= c.s_oo else (0.0, 1.0))
    n = math.hypot(vx, vy)
    return math.sqrt(max(top, 0.0)), vx / n, vy / n


def candidates(model: Model, shrink: float = 0.5) -> list[tuple[int, Component]]:
    """Two new components per component: its mean one largest standard deviation to either side, covariance shrunk."""
    out = []
    for c in model:
        sd, vx, vy = _axis(c)
        for k, sign in enumerate((1, -1)):
            out.append((2 * c.m + k, Component(c.rel_id, c.m, 0.5 * c.weight, c.mu_d + sign * sd * vx, c.mu_o + sign * sd * vy, c.s_dd * shrink, c.s_do * shrink, c.s_oo * shrink)))
    return out


def insert_component(vecs: DataFrame, model: Model) -> Model:
    """Per word the candidate that gives the best log likelihood, half its parent's weight moved to it; all scored in one pass."""
    spark = vecs.sparkSession
    cand = candidates(model)
    by: dict[int, list[Component]] = defaultdict(list)
    for c in model:
        by[c.rel_id].append(c)
    trial, grown = [], {}
    for k, new in cand:
        mix = [c._replace(weight=c.weight / 2) if c.m == new.m else c for c in by[new.rel_id]] + [new._replace(m=len(by[new.rel_id]))]
        grown[new.rel_id, k] = mix
        trial += [(new.rel_id, k, *c[1:]) for c in mix]
    table = spark.createDataFrame(trial, "rel_id int, k int, m int, weight double, mu_d double, mu_o double, s_dd double, s_do double, s_oo double")
    array = table.groupBy("rel_id", "k").agg(F.collect_list(F.struct("m", "weight", "mu_d", "mu_o", "s_dd", "s_do", "s_oo")).alias("c"))
    terms = F.transform("c", lambda c: F.log(c["weight"]) + log_gauss(F.col("dist"), F.col("theta"), c))
    t = vecs.select("rel_id", "dist", "theta", "w").join(F.broadcast(array), "rel_id").withColumn("_t", terms).withColumn("_top", F.array_max("_t"))
    lp = F.col("_top") + F.log(F.aggregate("_t", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("_top"))))
    scored = t.groupBy("rel_id", "k").agg(F.sum(F.col("w") * lp).alias("ll")).collect()
    best: dict[int, tuple[float, int]] = {}
    for r in scored:
        if r.rel_id not in best or (-r.ll, r.k) < best[r.rel_id]:
            best[r.rel_id] = (-r.ll, r.k)
    return [c for rel in sorted(by) for c in (grown[rel, best[rel][1]] if rel in best else by[rel])]


def criterion(stop: str, ll: float, m: int, n: float) -> float:
    """What growth must raise: the log likelihood, or it less a charge for 6m - 1 parameters."""
    if stop == "aic":
        return ll - (6 * m - 1)
    if stop == "bic":
        return ll - 0.5 * (6 * m - 1) * math.log(max(n, 1.0))
    return ll


class Grown(NamedTuple):
    model: Model
    trace: list[tuple[int, int, float, float, bool]]


#: Vectors (or weighted cells) of all words that are grown one word to a task; more are grown by aggregates over all executors.
LOCAL_VECTORS = 1_000_000


def fit_greedy(vecs: DataFrame, max_components: int = 4, stop: str = "no_gain", tol: float = 1e-6, max_iter: int = 40, least_gain: float = 1e-9, holdout: float = 0.25, ridge: float = RIDGE, strategy: str = "auto") -> Grown:
    """Grow every word's mixture; ``local`` by one task per word, ``distributed`` by an aggregate per round over all words.

    ``auto`` grows locally up to ``LOCAL_VECTORS`` vectors in all. Both follow the rules of ``grow_distributed``.
    """
    if strategy == "auto":
        strategy = "local" if vecs.limit(LOCAL_VECTORS + 1).count() <= LOCAL_VECTORS else "distributed"
    if strategy == "distributed":
        return grow_distributed(vecs, max_components, stop, tol, max_iter, least_gain, holdout, ridge)
    if strategy != "local":
        raise ValueError(f"unknown strategy {strategy}")
    out = F.pmod(F.xxhash64("dist", "theta"), F.lit(1000)) < int(1000 * holdout) if stop == "holdout" else F.lit(False)
    rules = (max_components, stop, tol, max_iter, least_gain, ridge)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        model, trace = grow_word(int(pdf["rel_id"].iloc[0]), *(pdf[c].to_numpy(float) for c in ("dist", "theta", "w")), pdf["out"].to_numpy(bool), *rules)
        rows = [(c.rel_id, c.m, *c[2:], None, None, None, None) for c in model] + [(k, m, *[None] * 6, ll, crit, ok, "trace") for k, m, ll, crit, ok in trace]
        return pd.DataFrame(rows, columns=["rel_id", "m", "weight", "mu_d", "mu_o", "s_dd", "s_do", "s_oo", "ll", "crit", "accepted", "kind"]).astype({"accepted": object, "kind": object})

    grown = vecs.select("rel_id", "dist", "theta", "w", out.alias("out")).groupBy("rel_id").applyInPandas(run, SCHEMA + ", ll double, crit double, accepted boolean, kind string").collect()
    model = sorted(Component(*r[:8]) for r in grown if r.kind is None)
    return Grown(model, sorted((r.rel_id, r.m, r.ll, float("nan") if r.crit is None else r.crit, r.accepted) for r in grown if r.kind))


def grow_distributed(vecs: DataFrame, max_components: int = 4, stop: str = "no_gain", tol: float = 1e-6, max_iter: int = 40, least_gain: float = 1e-9, holdout: float = 0.25, ridge: float = RIDGE) -> Grown:
    """Grow every word's mixture from one component, one at a time, until the cap or the criterion stops it.

    ``no_gain``: the log likelihood; ``aic``, ``bic``: it less a charge; ``holdout``: that of a quarter of the pairs
    kept out of the fit. A step that does not raise the criterion is taken back: the previous mixture is kept. The
    trace lists (word, components, log likelihood, criterion, accepted). Vectors are scaled per word for the fit and the
    model is scaled back.
    """
    spark = vecs.sparkSession
    scale = {r.rel_id: (r.md or 0.0, max(r.sd or 0.0, 1e-9), r.mo or 0.0, max(r.so or 0.0, 1e-9)) for r in _scales(vecs).collect()}
    if not scale:
        return Grown([], [])
    s = spark.createDataFrame([(k, *v) for k, v in scale.items()], "rel_id int, md double, sd double, mo double, so double")
    z = vecs.join(F.broadcast(s), "rel_id").select("rel_id", ((F.col("dist") - F.col("md")) / F.col("sd")).alias("dist"), ((F.col("theta") - F.col("mo")) / F.col("so")).alias("theta"), "w", F.col("dist").alias("_d"), F.col("theta").alias("_o"))
    out = F.lit(False)
    if stop == "holdout":
        out = F.pmod(F.xxhash64("_d", "_o"), F.lit(1000)) < int(1000 * holdout)
    z = z.withColumn("_out", out).drop("_d", "_o").persist()
    try:
        train, test = z.where("not _out"), z.where("_out")
        sizes = {r.rel_id: r.n for r in train.groupBy("rel_id").agg(F.sum("w").alias("n")).collect()}

        def judge(fit: EmResult) -> dict[int, float]:
            if stop == "holdout":
                return {r.rel_id: r.loglik for r in loglik(test, to_table(spark, fit.model)).collect()}
            return {k: criterion(stop, v, sum(c.rel_id == k for c in fit.model), sizes[k]) for k, v in fit.loglik.items()}

        first, _ = guarded(fit_single(train, ridge).collect(), ridge)
        best = EmResult(first, {r.rel_id: r.loglik for r in loglik(train, to_table(spark, first)).collect()}, [], 0)
        score = judge(best)
        trace = [(k, 1, v, score.get(k, v), True) for k, v in sorted(best.loglik.items())]
        active = {k for k, n in sizes.items() if n >= 2}
        model = best.model
        for m in range(2, max_components + 1):
            if not active:
                break
            part = train.where(F.col("rel_id").isin(sorted(active)))
            fit = fit_em(part, insert_component(part, [c for c in model if c.rel_id in active]), tol, max_iter, ridge=ridge)
            got = judge(fit)
            for k in sorted(active):
                better = got.get(k, -math.inf) - score.get(k, -math.inf) > least_gain * (1 + abs(score.get(k, 0.0))) and sum(c.rel_id == k for c in fit.model) == m
                trace.append((k, m, fit.loglik[k], got.get(k, float("nan")), better))
                if better:
                    model = [c for c in model if c.rel_id != k] + [c for c in fit.model if c.rel_id == k]
                    score[k] = got[k]
                else:
                    active.discard(k)
    finally:
        z.unpersist()
    back = []
    for c in sorted(model):
        md, sd, mo, so = scale[c.rel_id]
        back.append(Component(c.rel_id, c.m, c.weight, c.mu_d * sd + md, c.mu_o * so + mo, c.s_dd * sd * sd, c.s_do * sd * so, c.s_oo * so * so))
    return Grown(back, sorted(trace))


class Word:
    """One word's vectors in a task, with the same steps as the aggregates."""

    def __init__(self, rel_id: int, d: np.ndarray, o: np.ndarray, w: np.ndarray, ridge: float):
        self.rel_id, self.d, self.o, self.w, self.ridge, self.n = rel_id, d, o, w, ridge, float(w.sum())

    def terms(self, model: Model) -> tuple[np.ndarray, np.ndarray]:
        """(log of weight times density of each vector under each component, their log sums)."""
        t = np.empty((len(self.d), len(model)))
        for k, c in enumerate(model):
            det = c.s_dd * c.s_oo - c.s_do * c.s_do
            u, v = self.d - c.mu_d, self.o - c.mu_o
            t[:, k] = math.log(c.weight) - math.log(2 * math.pi) - 0.5 * math.log(det) - 0.5 * (c.s_oo * u * u - 2 * c.s_do * u * v + c.s_dd * v * v) / det
        top = t.max(1)
        return t, top + np.log(np.exp(t - top[:, None]).sum(1))

    def loglik(self, model: Model) -> float:
        return float((self.w * self.terms(model)[1]).sum())

    def fitted(self, share: np.ndarray, m: list[int]) -> list[dict]:
        out = []
        for k, name in enumerate(m):
            r = self.w * share[:, k]
            n = r.sum()
            md, mo = (r * self.d).sum() / n, (r * self.o).sum() / n
            out.append({"rel_id": self.rel_id, "m": name, "weight": n / self.n, "mu_d": md, "mu_o": mo, "s_dd": max((r * self.d * self.d).sum() / n - md * md, 0.0) + self.ridge, "s_do": (r * self.d * self.o).sum() / n - md * mo, "s_oo": max((r * self.o * self.o).sum() / n - mo * mo, 0.0) + self.ridge})
        return out

    def em(self, start: Model, tol: float, max_iter: int) -> tuple[Model, float]:
        model, last = start, None
        for i in range(max_iter + 1):
            t, lp = self.terms(model)
            ll = float((self.w * lp).sum())
            with np.errstate(invalid="ignore", divide="ignore"):
                new, _ = guarded(self.fitted(np.exp(t - lp[:, None]), [c.m for c in model]), self.ridge)
            gain = math.inf if last is None else ll - last
            last = ll
            if abs(gain) / (1 + abs(ll)) < tol or not new or i == max_iter:
                break
            model = new
        return model, last

    def inserted(self, model: Model) -> Model:
        best = None
        for k, new in candidates(model):
            mix = [c._replace(weight=c.weight / 2) if c.m == new.m else c for c in model] + [new._replace(m=len(model))]
            key = (-self.loglik(mix), k)
            if best is None or key < best[0]:
                best = key, mix
        return best[1]


def grow_word(rel_id: int, d: np.ndarray, o: np.ndarray, w: np.ndarray, out: np.ndarray, max_components: int, stop: str, tol: float, max_iter: int, least_gain: float, ridge: float) -> tuple[Model, list[tuple]]:
    """Greedy growth of one word's mixture: (model, trace)."""
    n = w.sum()
    md, mo = (w * d).sum() / n, (w * o).sum() / n
    sd, so = max(math.sqrt((w * (d - md) ** 2).sum() / n), 1e-9), max(math.sqrt((w * (o - mo) ** 2).sum() / n), 1e-9)
    z = (d - md) / sd, (o - mo) / so
    if out.all():
        return [], []
    train, test = (Word(rel_id, z[0][part], z[1][part], w[part], ridge) for part in (~out, out))

    def judge(model: Model, ll: float) -> float | None:
        if stop == "holdout":
            return test.loglik(model) if len(test.d) else None
        return criterion(stop, ll, len(model), train.n)

    model, _ = guarded(train.fitted(np.ones((len(train.d), 1)), [0]), ridge)
    ll = train.loglik(model)
    score = judge(model, ll)
    trace = [(rel_id, 1, ll, ll if score is None else score, True)]
    score = -math.inf if score is None else score
    for m in range(2, max_components + 1 if train.n >= 2 else 2):
        new, ll = train.em(train.inserted(model), tol, max_iter)
        got = judge(new, ll)
        better = (-math.inf if got is None else got) - score > least_gain * (1 + abs(score)) and len(new) == m
        trace.append((rel_id, m, ll, got, bool(better)))
        if not better:
            break
        model, score = new, got
    return [Component(rel_id, c.m, c.weight, c.mu_d * sd + md, c.mu_o * so + mo, c.s_dd * sd * sd, c.s_do * sd * so, c.s_oo * so * so) for c in model], trace


def _scales(vecs: DataFrame) -> DataFrame:
    """Weighted means and deviations per word; deviations from the mean in a second step, which loses no digits."""
    n, w = F.sum("w"), F.col("w")
    mean = vecs.groupBy("rel_id").agg((F.sum(w * F.col("dist")) / n).alias("md"), (F.sum(w * F.col("theta")) / n).alias("mo"))
    dev = lambda c, m: F.sqrt(F.sum(w * (F.col(c) - F.col(m)) * (F.col(c) - F.col(m))) / n)
    return vecs.join(F.broadcast(mean), "rel_id").groupBy("rel_id").agg(F.first("md").alias("md"), dev("dist", "md").alias("sd"), F.first("mo").alias("mo"), dev("theta", "mo").alias("so"))


def fit_fixed(vecs: DataFrame, k: int, rounds: int = 20, ridge: float = RIDGE) -> EmResult:
    """The baseline with a fixed number of components: split the single Gaussian k - 1 times, then EM."""
    model, _ = guarded(fit_single(vecs, ridge).collect(), ridge)
    for _ in range(k - 1):
        model = insert_component(vecs, model)
    return fit_em(vecs, model, max_iter=rounds, ridge=ridge)


def sample(spark: SparkSession, model: Model, n: int, seed: int = 1) -> DataFrame:
    """(rel_id, dist, theta, w): n draws per word, by the components' weights and a 2x2 Cholesky factor."""
    cut: dict[int, float] = defaultdict(float)
    rows = []
    for c in sorted(model):
        lo = cut[c.rel_id]
        cut[c.rel_id] += c.weight
        a = math.sqrt(c.s_dd)
        b = c.s_do / a
        rows.append((c.rel_id, *map(float, (lo, cut[c.rel_id], c.mu_d, c.mu_o, a, b, math.sqrt(max(c.s_oo - b * b, 0.0))))))
    comps = spark.createDataFrame(rows, "rel_id int, lo double, hi double, md double, mo double, a double, b double, c double")
    words = spark.createDataFrame([(k,) for k in sorted(cut)], "rel_id int")
    draws = spark.range(n).join(F.broadcast(words)).select("rel_id", F.rand(seed).alias("u"), F.randn(seed + 1).alias("g"), F.randn(seed + 2).alias("h"))
    hit = (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi"))
    return draws.join(F.broadcast(comps), "rel_id").where(hit).select("rel_id", (F.col("md") + F.col("a") * F.col("g")).alias("dist"), (F.col("mo") + F.col("b") * F.col("g") + F.col("c") * F.col("h")).alias("theta"), F.lit(1.0).alias("w"))
