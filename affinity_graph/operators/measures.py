"""Cost and accuracy measures: what the tables and plots of an evaluation are made of."""

from __future__ import annotations

import math
import time

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..functions import rng
from ..functions.rng import below, uniform
from .discrete import locate
from .generate import pair_columns
from .profile import degrees, triangles, wedges


def profile_series(a: DataFrame, b: DataFrame) -> DataFrame:
    """(degree, n_a, n_b, c_a, c_b) of two profiles side by side; a missing degree has 0 nodes."""
    x = a.select("degree", F.col("n").alias("n_a"), F.col("c").alias("c_a"))
    y = b.select("degree", F.col("n").alias("n_b"), F.col("c").alias("c_b"))
    return x.join(y, "degree", "full").select("degree", F.coalesce("n_a", F.lit(0)).alias("n_a"), F.coalesce("n_b", F.lit(0)).alias("n_b"), F.coalesce("c_a", F.lit(0.0)).alias("c_a"), F.coalesce("c_b", F.lit(0.0)).alias("c_b"))


def log_bin_starts(omega: float = 1.5, upto: int = 1 << 20) -> list[int]:
    """First degrees of bins that grow by ``omega``, empty ones left out."""
    out, k = [], 1
    while True:
        start = math.ceil(round((omega ** (k - 1) - 1) / (omega - 1), 9)) + 1
        if start > upto:
            return out
        if not out or start > out[-1]:
            out.append(start)
        k += 1


def log_bins(spark: SparkSession, omega: float = 1.5, upto: int = 1 << 20) -> DataFrame:
    """(k, lo, hi)."""
    s = log_bin_starts(omega, math.ceil(upto * omega) + 3)
    s, e = s[:-1], s[1:]
    s, e = [a for a in s if a <= upto], e[: sum(a <= upto for a in s)]
    return spark.createDataFrame([(k + 1, a, b - 1) for k, (a, b) in enumerate(zip(s, e, strict=True))], "k int, lo long, hi long")


def log_binned(series: DataFrame, omega: float = 1.5, upto: int = 1 << 24, how: dict[str, str] | None = None) -> DataFrame:
    """Series by degree in log bins: counts summed, clustering averaged. The bins are a few dozen rows, hence broadcast."""
    how = how or {"n": "sum", "c": "avg"}
    bins = log_bins(series.sparkSession, omega, upto)
    hit = series.join(F.broadcast(bins), (F.col("degree") >= F.col("lo")) & (F.col("degree") <= F.col("hi")))
    return hit.groupBy("k", "lo", "hi").agg(*[getattr(F, f)(c).alias(c) for c, f in how.items()])


def cumulative_degrees(hist: DataFrame, normalise: bool = True) -> DataFrame:
    """(degree, cum_le, cum_ge): nodes up to and from each degree on. Windows over distinct degrees."""
    le = F.sum("n").over(Window.orderBy("degree").rowsBetween(Window.unboundedPreceding, 0))
    ge = F.sum("n").over(Window.orderBy("degree").rowsBetween(0, Window.unboundedFollowing))
    total = F.sum("n").over(Window.partitionBy())
    if normalise:
        return hist.select("degree", (le / total).alias("cum_le"), (ge / total).alias("cum_ge"))
    return hist.select("degree", le.alias("cum_le"), ge.alias("cum_ge"))


def repeat_ratio(gen: DataFrame) -> DataFrame:
    """(phase, generated, unique, ratio) by phase and in total (phase 0); loops count as generated only."""
    pairs = gen.select("phase", *pair_columns(gen), (F.col("a") != F.col("b")).alias("proper"))
    each = pairs.groupBy("phase", "lo", "hi", "proper").agg(F.count(F.lit(1)).alias("times"))
    by = each.groupBy("phase").agg(F.sum("times").alias("generated"), F.sum(F.col("proper").cast("bigint")).alias("unique"))
    whole = each.groupBy("lo", "hi", "proper").agg(F.sum("times").alias("times")).agg(F.coalesce(F.sum("times"), F.lit(0)).alias("generated"), F.coalesce(F.sum(F.col("proper").cast("bigint")), F.lit(0)).alias("unique"))
    out = by.select(F.col("phase").cast("int").alias("phase"), "generated", "unique").unionByName(whole.select(F.lit(0).alias("phase"), "generated", "unique"))
    return out.withColumn("ratio", F.round(F.try_divide(F.col("generated").cast("double"), F.col("unique").cast("double")), 6))


def timed(workload: str, graph: str, stage: str, df: DataFrame) -> tuple[str, str, str, float, int]:
    """Run a stage into the noop sink and return (workload, graph, stage, seconds, rows_out)."""
    seen = F.count(F.lit(1))
    o = Observation()
    began = time.perf_counter()
    df.observe(o, seen.alias("rows")).write.format("noop").mode("overwrite").save()
    return workload, graph, stage, time.perf_counter() - began, o.get["rows"]


def poisson_cdf(mean: float) -> list[float]:
    """P(number <= k) for k = 0, 1, ... up to twelve deviations above the mean."""
    out, p, s = [], math.exp(-mean), 0.0
    for k in range(int(mean + 12 * math.sqrt(mean) + 20)):
        s += p
        out.append(min(s, 1.0))
        p *= mean / (k + 1)
    return out


def coupon_trials(spark: SparkSession, n_b: int = 10, rho: float = 0.5, trials: int | DataFrame = 10_000, seed: int = 1, kind: str = "fast", fixed: bool = False) -> DataFrame:
    """(unique, trials): distinct pairs seen among a Poisson number (or, ``fixed``, the rounded mean) of draws from a block's pairs.

    ``trials`` is their number, or their ids (trial).
    """
    pairs = n_b * (n_b - 1) // 2
    mean = -pairs * math.log1p(-rho)
    t = spark.range(trials).withColumnRenamed("id", "trial") if isinstance(trials, int) else trials
    if fixed:
        t = t.withColumn("number", F.lit(round(mean)))
    else:
        u = uniform(seed, "trial", rng.TRIAL, kind)
        t = t.withColumn("u", u).withColumn("number", F.size(F.filter(F.array(*map(F.lit, poisson_cdf(mean))), lambda x: x <= F.col("u"))))
    drawn = t.where("number > 0").select("trial", F.explode(F.sequence(F.lit(1), F.col("number"))).alias("s"))
    code = below(uniform(seed, F.col("trial") * 1000 + F.col("s"), rng.FIRST, kind), F.lit(pairs))
    some = drawn.withColumn("code", code).groupBy("trial").agg(F.count_distinct("code").alias("unique"))
    return t.select("trial").join(some, "trial", "left").groupBy(F.coalesce("unique", F.lit(0)).alias("unique")).agg(F.count(F.lit(1)).alias("trials"))


def degree_one_loss(plan, edges: DataFrame) -> DataFrame:
    """(pool, unused, once, more): what became of the degree-1 pool's ids."""
    one = plan.degree.where("degree = 1").select("first_node", "n_fill")
    hit = degrees(edges).join(F.broadcast(one), (F.col("v") >= F.col("first_node")) & (F.col("v") < F.col("first_node") + F.col("n_fill")))  # one row
    counts = hit.agg(F.count(F.lit(1)).alias("used"), F.count_if(F.col("degree") == 1).alias("once"))
    return one.join(F.broadcast(counts)).select(F.col("n_fill").alias("pool"), (F.col("n_fill") - F.col("used")).alias("unused"), "once", (F.col("used") - F.col("once")).alias("more"))


def degree_dispersion(profile: DataFrame, seeds: int = 20, kind: str = "fast") -> DataFrame:
    """(degree, mean, variance) of the degrees that Chung-Lu gives to nodes meant to have ``degree``, repeats kept, over seeds."""
    from .baselines import _classes, chung_lu

    classes = _classes(profile, 1.0).select("degree", "first_node", "pool")
    runs = None
    for seed in range(seeds):
        ends = chung_lu(profile, 1.0, seed, kind).select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("got"))
        runs = ends if runs is None else runs.unionByName(ends)
    by = locate(runs, "v", classes.withColumn("end", F.col("first_node") + F.col("pool")), "first_node", "end")
    sums = by.groupBy("degree", "pool").agg(F.sum("got").alias("s1"), F.sum(F.col("got") * F.col("got")).alias("s2"))
    n = F.col("pool") * seeds
    return sums.select("degree", (F.col("s1") / n).alias("mean"), (F.col("s2") / n - (F.col("s1") / n) * (F.col("s1") / n)).alias("variance"))


def ks_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """(ks): largest distance of two cumulative degree distributions."""
    s = a.select("degree", F.col("n").alias("x"), F.lit(0).cast("bigint").alias("y")).unionByName(b.select("degree", F.lit(0).cast("bigint").alias("x"), F.col("n").alias("y")))
    s = s.groupBy("degree").agg(F.sum("x").alias("x"), F.sum("y").alias("y"))
    run = Window.orderBy("degree").rowsBetween(Window.unboundedPreceding, 0)
    every = Window.partitionBy()
    gap = F.abs(F.sum("x").over(run) / F.sum("x").over(every) - F.sum("y").over(run) / F.sum("y").over(every))
    return s.select(gap.alias("gap")).agg(F.round(F.coalesce(F.max("gap"), F.lit(0.0)), 6).alias("ks"))


def clustering_gap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(gap_n, gap_wedge): mean distance of c by degree, weighted by the first profile's nodes of degree 2 and more, and by its wedges."""
    s = profile_series(a, b).where("degree >= 2 AND n_a > 0")
    gap, w = F.abs(F.col("c_a") - F.col("c_b")), F.col("n_a") * wedges("degree")
    return s.agg(F.round(F.try_divide(F.sum(gap * F.col("n_a")), F.sum("n_a").cast("double")), 6).alias("gap_n"), F.round(F.try_divide(F.sum(gap * w), F.sum(w).cast("double")), 6).alias("gap_wedge"))


def binned_gap(a: DataFrame, b: DataFrame, omega: float = 1.5) -> DataFrame:
    """(gap_binned): mean relative distance of the counts in log bins."""
    x = log_binned(a, omega).select("k", F.col("n").alias("x"))
    y = log_binned(b, omega).select("k", F.col("n").alias("y"))
    both = x.join(y, "k", "full").select(F.coalesce("x", F.lit(0)).alias("x"), F.coalesce("y", F.lit(0)).alias("y"))
    return both.agg(F.round(F.avg(F.abs(F.col("x") - F.col("y")) / F.greatest("x", "y")), 6).alias("gap_binned"))


def compare_all(own: DataFrame, models: DataFrame, omega: float = 1.5, upto: int = 1 << 24) -> DataFrame:
    """(model, ks, gap_n, gap_wedge, gap_binned, gcc_rel) of profiles (model, degree, n, c) against the one of ``own``, in one pass.

    ``own`` is repeated for each model (a handful of names), both are summed by (model, degree), and every measure is an
    aggregate or a window over distinct degrees of a model.
    """
    none = F.lit(0).cast("bigint")
    names = models.select("model").distinct()
    mine = own.join(F.broadcast(names)).select("model", "degree", F.col("n").alias("x"), none.alias("y"), F.col("c").alias("cx"), F.lit(0.0).alias("cy"))  # one row a model
    theirs = models.select("model", "degree", none.alias("x"), F.col("n").alias("y"), F.lit(0.0).alias("cx"), F.col("c").alias("cy"))
    by = mine.unionByName(theirs).groupBy("model", "degree").agg(*[F.sum(c).alias(c) for c in ("x", "y", "cx", "cy")])
    run, every = Window.partitionBy("model").orderBy("degree").rowsBetween(Window.unboundedPreceding, 0), Window.partitionBy("model")
    by = by.withColumn("far", F.abs(F.sum("x").over(run) / F.sum("x").over(every) - F.sum("y").over(run) / F.sum("y").over(every)))
    both = (F.col("degree") >= 2) & (F.col("x") > 0)
    gap, w = F.abs(F.col("cx") - F.col("cy")), wedges("degree")

    def share(of: Column, weight: Column, where: Column) -> Column:
        return F.try_divide(F.sum(F.when(where, of * weight)), F.sum(F.when(where, weight)).cast("double"))

    gx, gy = (F.coalesce(share(F.col(c), F.col(n) * w, F.lit(True)), F.lit(0.0)) for c, n in (("cx", "x"), ("cy", "y")))
    out = by.groupBy("model").agg(
        F.round(F.max("far"), 6).alias("ks"), F.round(share(gap, F.col("x"), both), 6).alias("gap_n"), F.round(share(gap, F.col("x") * w, both), 6).alias("gap_wedge"),
        F.round(F.coalesce(F.try_divide(F.abs(gx - gy), gx), F.lit(0.0)), 6).alias("gcc_rel"),
    )
    bins = log_bins(own.sparkSession, omega, upto)
    hit = by.join(F.broadcast(bins), (F.col("degree") >= F.col("lo")) & (F.col("degree") <= F.col("hi"))).groupBy("model", "k").agg(F.sum("x").alias("x"), F.sum("y").alias("y"))
    binned = hit.groupBy("model").agg(F.round(F.avg(F.abs(F.col("x") - F.col("y")) / F.greatest("x", "y")), 6).alias("gap_binned"))
    return out.join(F.broadcast(binned), "model").select("model", "ks", "gap_n", "gap_wedge", "gap_binned", "gcc_rel")


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: ks, gap_n, gap_wedge, gap_binned and the relative gap of the profiles' global clustering."""
    return compare_all(a.select("degree", "n", "c"), b.select(F.lit("").alias("model"), "degree", "n", "c")).drop("model")


def spectrum_gap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(gap): summed distance of two spectra by rank, relative to the first."""
    both = a.select("rank", F.abs("value").alias("x")).join(b.select("rank", F.abs("value").alias("y")), "rank", "left")
    return both.agg(F.try_divide(F.sum(F.abs(F.col("x") - F.coalesce("y", F.lit(0.0)))), F.sum("x")).alias("gap"))


def roughness(hist: DataFrame) -> DataFrame:
    """(degree, second_difference) of log counts over neighbouring distinct degrees: jumps of a distribution."""
    w = Window.orderBy("degree")
    x = F.log(F.col("n").cast("double"))
    return hist.select("degree", (F.lag(x).over(w) - 2 * x + F.lead(x).over(w)).alias("second_difference")).where("second_difference IS NOT NULL")


def triangle_provenance(gen: DataFrame) -> DataFrame:
    """(local_edges, triangles): triangles by how many of their edges came from the local phase."""
    e = gen.where("a <> b").select(*pair_columns(gen), "phase").groupBy("lo", "hi").agg(F.min("phase").alias("phase"))
    t = triangles(e.select("lo", "hi"))

    def local(t: DataFrame, x: str, y: str, name: str) -> DataFrame:
        tagged = e.select(F.col("lo").alias("l_"), F.col("hi").alias("h_"), (F.col("phase") == 1).cast("int").alias(name))
        return t.join(tagged, (F.least(x, y) == F.col("l_")) & (F.greatest(x, y) == F.col("h_"))).drop("l_", "h_")

    t = local(local(local(t, "a", "b", "p1"), "a", "c", "p2"), "b", "c", "p3")
    return t.groupBy((F.col("p1") + F.col("p2") + F.col("p3")).alias("local_edges")).agg(F.count(F.lit(1)).alias("triangles"))

