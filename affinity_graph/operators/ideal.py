"""Idealized profiles: discrete degree laws, exponential clustering, their realisation, and fits of their parameters."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


from ..functions import rng
from ..functions.rng import uniform


@dataclass(frozen=True)
class IdealSpec:
    """A law ("dpl": gamma; "dgln": alpha, delta) up to a largest degree, and the clustering curve's c_max and xi."""

    kind: str
    dmax: int
    gamma: float = 0.0
    alpha: float = 0.0
    delta: float = 0.0
    c_max: float = 0.5
    xi: float = 0.0


def proportion(spec: IdealSpec, d: Column | None = None) -> Column:
    """What a degree's probability is proportional to."""
    d = F.col("degree").cast("double") if d is None else d
    if spec.kind == "dpl":
        return F.pow(d, F.lit(-spec.gamma))
    if spec.kind == "dgln":
        return F.exp(-F.pow(F.log(d) / F.lit(spec.alpha), F.lit(spec.delta)))
    raise ValueError(f"unknown law: {spec.kind}")


def discretise(spark: SparkSession, f: Column, dmax: int) -> DataFrame:
    """(degree, p) on 1..dmax from any proportionality in ``degree``."""
    rows = spark.range(1, dmax + 1).withColumnRenamed("id", "degree").select("degree", f.alias("f"))
    total = rows.agg(F.sum("f").alias("total"))
    return rows.join(F.broadcast(total)).select("degree", (F.col("f") / F.col("total")).alias("p"))  # one row


def ideal_degrees(spark: SparkSession, spec: IdealSpec) -> DataFrame:
    return discretise(spark, proportion(spec), spec.dmax)


def ideal_moments(dist: DataFrame) -> DataFrame:
    """(davg, p_top): the mean degree and the probability of the largest degree."""
    return dist.agg(F.sum(F.col("degree") * F.col("p")).alias("davg"), F.max_by("p", "degree").alias("p_top"))


def check_ideal(dist: DataFrame, davg: float, nodes: int, tolerance: float = 0.01) -> DataFrame:
    """Whether the mean is right to ``tolerance`` and a node of the largest degree is improbable (n p_top below 1)."""
    return ideal_moments(dist).select("davg", "p_top", (F.abs(F.col("davg") - davg) <= tolerance * davg).alias("mean_fits"), (F.col("p_top") * nodes < 1).alias("tail_fits"))


def _shape(kind: str, dmax: int) -> Callable[[np.ndarray], tuple[float, float]]:
    """Mean degree and log probability of the top degree for parameters, on a log-spaced grid of exact sums.

    Degrees below 4096 are summed one by one, the rest by the midpoint rule on 20,000 geometric steps; the error is far below the
    tolerances of the fits.
    """
    low = np.arange(1.0, min(dmax, 4096) + 1)
    if dmax > 4096:
        edges = np.unique(np.floor(np.geomspace(4097, dmax + 1, 20_000)))
        x, width = (edges[:-1] + edges[1:] - 1) / 2, np.diff(edges)
    else:
        x, width = np.zeros(0), np.zeros(0)
    d, m = np.concatenate([low, x]), np.concatenate([np.ones(len(low)), width])

    def value(p: np.ndarray) -> tuple[float, float]:
        with np.errstate(over="ignore", invalid="ignore", divide="ignore"):
            def log_f(t: np.ndarray) -> np.ndarray:
                return -p[0] * np.log(t) if kind == "dpl" else -((np.log(t) / p[0]) ** p[1])

            f = np.exp(log_f(d)) * m
            total = f.sum()
            return float((f * d).sum() / total), float(log_f(np.array([float(dmax)]))[0] - math.log(total))

    return value


def _simplex(loss: Callable[[np.ndarray], float], start: np.ndarray, steps: int = 400) -> np.ndarray:
    """Derivative-free descent with a simplex: the worst corner is moved across, out, in, or all shrink to the best."""
    n = len(start)
    corners = [start, *(start * (1 + 0.15 * np.eye(n)[i]) for i in range(n))]
    points = sorted(((loss(c), tuple(c)) for c in corners))
    for _ in range(steps):
        best, worst = points[0], points[-1]
        if worst[0] - best[0] < 1e-15 and np.ptp([p[1] for p in points], axis=0).max() < 1e-9:
            break
        middle = np.mean([p[1] for p in points[:-1]], axis=0)
        away = middle - np.array(worst[1])
        trial = [(loss(middle + k * away), tuple(middle + k * away)) for k in (1.0,)]
        if trial[0][0] < best[0]:
            trial.append((loss(middle + 2 * away), tuple(middle + 2 * away)))
        elif trial[0][0] >= points[-2][0]:
            trial.append((loss(middle - 0.5 * away), tuple(middle - 0.5 * away)))
        new = min(trial)
        if new[0] < points[-2][0] or new[0] < worst[0]:
            points[-1] = new
        else:
            points = [best, *((loss(c), tuple(c)) for c in ((np.array(p[1]) + np.array(best[1])) / 2 for p in points[1:]))]
        points.sort()
    return np.array(points[0][1])


def fit_degrees(kind: str, davg: float, dmax: int, p_max: float | None = None, tolerance: float = 1e-10) -> IdealSpec:
    """Parameters for a mean degree and, with ``p_max``, the probability of the largest degree; without, only a penalty above ``tolerance``."""
    value = _shape(kind, dmax)

    def loss(p: np.ndarray) -> float:
        if (p <= 0.05).any() or (p > 60).any():
            return 1e9 + float(np.abs(p).sum())
        mean, top = value(p)
        if not math.isfinite(mean):
            return 1e9
        out = (math.log(mean) - math.log(davg)) ** 2
        if p_max is not None:
            return out + ((top - math.log(p_max)) / 10) ** 2
        return out + max(0.0, top - math.log(tolerance)) ** 2 * (kind == "dgln")

    best = min((_simplex(loss, s) for s in ([np.array([1.5]), np.array([2.2])] if kind == "dpl" else [np.array([2.0, 2.0]), np.array([1.0, 1.3]), np.array([3.0, 3.0])])), key=loss)
    if kind == "dpl":
        return IdealSpec("dpl", dmax, gamma=float(best[0]))
    return IdealSpec("dgln", dmax, alpha=float(best[0]), delta=float(best[1]))


def fit_grid(spark: SparkSession, kind: str, davg: float, dmax: int, candidates: DataFrame) -> DataFrame:
    """The fit as one job: the loss of each candidate (columns of the law's parameters), best first. The candidates are a parameter."""
    d = spark.range(1, dmax + 1).select(F.col("id").cast("double").alias("d"))
    f = F.pow("d", -F.col("gamma")) if kind == "dpl" else F.exp(-F.pow(F.log("d") / F.col("alpha"), F.col("delta")))
    names = candidates.columns
    by = d.join(F.broadcast(candidates)).groupBy(*names).agg((F.sum(f * F.col("d")) / F.sum(f)).alias("davg"), (F.max_by(f, "d") / F.sum(f)).alias("p_top"))
    return by.select(*names, F.round("davg", 6).alias("davg"), F.round(F.abs(F.log(F.col("davg") / davg)), 6).alias("loss"))


def realise(dist: DataFrame, nodes: int, how: str = "rounded", seed: int = 1, kind: str = "fast") -> DataFrame:
    """(degree, n) for ``nodes`` nodes: largest remainders of the expected counts, or independent draws (``multinomial``)."""
    if how == "rounded":
        x = dist.withColumn("x", F.col("p") * nodes).withColumn("base", F.floor("x"))
        short = nodes - (x.agg(F.sum("base")).head()[0] or 0)
        top = x.where("p > 0").orderBy(F.desc(F.round(F.col("x") - F.col("base"), 9)), "degree").limit(short).select("degree", F.lit(1).alias("more"))
        return x.join(F.broadcast(top), "degree", "left").select("degree", (F.col("base") + F.coalesce("more", F.lit(0))).cast("bigint").alias("n")).where("n > 0")
    from .discrete import cumulative, draw
    from .generate import edge_ids

    scaled = dist.withColumn("w", F.col("p") * 1e12)
    ids = edge_ids(dist.sparkSession, nodes)
    return draw(ids, uniform(seed, "edge_id", rng.TRIAL, kind), cumulative(scaled, "degree", "w")).groupBy(F.col("bin").alias("degree")).agg(F.count(F.lit(1)).alias("n"))


def ideal_clustering(hist: DataFrame, c_max: float, xi: float, noise: bool = False, seed: int = 1, kind: str = "fast") -> DataFrame:
    """``hist`` with c = c_max exp(-(d - 1) xi) from degree 2 on; with noise, normal about it with deviation min(0.01, c / 2), in [0, 1]."""
    mean = F.when(F.col("degree") >= 2, F.lit(c_max) * F.exp(-(F.col("degree") - 1) * F.lit(xi))).otherwise(F.lit(0.0))
    if noise:
        u1, u2 = uniform(seed, "degree", rng.NOISE_1, kind), uniform(seed, "degree", rng.NOISE_2, kind)
        normal = F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - u1)) * F.cos(F.lit(2 * math.pi) * u2)
        mean = F.when(F.col("degree") >= 2, F.least(F.lit(1.0), F.greatest(F.lit(0.0), mean + F.least(F.lit(0.01), mean / 2) * normal))).otherwise(F.lit(0.0))
    return hist.withColumn("c", mean)


def fit_xi(hist: DataFrame, c_max: float, gcc: float) -> float:
    """The decay for a global clustering, by bisection over the collected distinct degrees."""
    rows = hist.where("degree >= 2").select("degree", "n").collect()
    if not rows:
        return 0.0
    d = np.array([r["degree"] for r in rows], float)
    w = np.array([r["n"] for r in rows], float) * d * (d - 1)

    def value(xi: float) -> float:
        return c_max * float((w * np.exp(-(d - 1) * xi)).sum() / w.sum())

    lo, hi = 0.0, 1.0
    while value(hi) > gcc and hi < 1e6:
        hi *= 2
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if value(mid) > gcc else (lo, mid)
    return (lo + hi) / 2


def fit_xi_grid(hist: DataFrame, c_max: float, gcc: float, candidates: DataFrame) -> DataFrame:
    """(xi, gcc, loss) of each candidate decay, the fit as one job. The candidates (xi) are a parameter."""
    w = F.col("n") * (F.col("degree") * (F.col("degree") - 1) / 2)
    rows = hist.where("degree >= 2").join(F.broadcast(candidates))  # a parameter's rows
    by = rows.groupBy("xi").agg((F.lit(c_max) * F.sum(w * F.exp(-(F.col("degree") - 1) * F.col("xi"))) / F.sum(w)).alias("gcc"))
    return by.select("xi", F.round("gcc", 6).alias("gcc"), F.round(F.abs(F.col("gcc") - gcc), 6).alias("loss"))


def ideal_profile(spark: SparkSession, spec: IdealSpec, nodes: int, how: str = "rounded", noise: bool = False, seed: int = 1, kind: str = "fast", graph: str = "ideal") -> DataFrame:
    hist = realise(ideal_degrees(spark, spec), nodes, how, seed, kind)
    return ideal_clustering(hist, spec.c_max, spec.xi, noise, seed, kind).select(F.lit(graph).alias("graph"), "degree", "n", "c")


def benchmark_graph(spark: SparkSession, nodes: int, davg: float, dmax: int, c_max: float, gcc: float | None = None, xi: float | None = None, spec: IdealSpec | None = None, beta: float = 1.0, seed: int = 1, kind: str = "fast", how: str = "rounded") -> tuple[DataFrame, DataFrame]:
    """A graph from targets alone: fit the degree law, realise it, fit the clustering, plan, generate, drop repeats. Returns (profile, edges)."""
    from ..plans.block_plan import build_plan
    from ..sources.tables import stored
    from .generate import dedup, generate

    spec = spec or fit_degrees("dgln", davg, dmax, 0.001 / nodes)
    hist = stored(realise(ideal_degrees(spark, spec), nodes, how, seed, kind), "hist")
    xi = xi if xi is not None else fit_xi(hist, c_max, gcc or 0.0)
    profile = ideal_clustering(hist, c_max, xi).select(F.lit("benchmark").alias("graph"), "degree", "n", "c")
    return profile, dedup(generate(build_plan(profile, beta), seed, kind=kind))


def scaling_series(base_nodes: int, base_dmax: int, steps: int) -> list[tuple[int, int]]:
    """(nodes, dmax) doubling the nodes, dmax growing as their root."""
    return [(base_nodes << k, round(base_dmax * 2 ** (k / 2))) for k in range(steps)]


def dgln_study(spark: SparkSession, nodes: int = 10_000_000, dmax: int = 1_000_000, alphas: tuple[float, ...] = (1.5, 2.0, 2.5), deltas: tuple[float, ...] = (1.5, 2.0, 2.5)) -> DataFrame:
    """(alpha, delta, degree, n): expected counts with one parameter at 2 and the other varied, at degrees 1, 2, 4, ..."""
    grid = sorted({(2.0, d) for d in deltas} | {(a, 2.0) for a in alphas})
    params = spark.createDataFrame(grid, "alpha double, delta double")
    rows = spark.range(1, dmax + 1).select(F.col("id").alias("degree")).join(F.broadcast(params))
    f = F.exp(-F.pow(F.log(F.col("degree").cast("double")) / F.col("alpha"), F.col("delta")))
    rows = rows.select("alpha", "delta", "degree", f.alias("f"))
    total = rows.groupBy("alpha", "delta").agg(F.sum("f").alias("total"))
    some = rows.where(F.expr("(degree & (degree - 1)) = 0"))
    return some.join(F.broadcast(total), ["alpha", "delta"]).select("alpha", "delta", "degree", F.round(F.col("f") / F.col("total") * nodes, 6).alias("n"))
