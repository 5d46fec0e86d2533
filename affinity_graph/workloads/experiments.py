"""The experiments, each with a scale argument and DataFrames as results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, generate, ideal, measures, profile, spectrum
from ..plans.block_plan import build_plan
from ..sources.graphs import BUILDERS
from ..sources.tables import stored

BENCH = "workload string, graph string, stage string, seconds double, rows_out long"


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def small_comparison(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("doc_line", "user_next"), beta: float = 10.0, initiator: tuple[float, float, float, float] = baselines.INITIATOR, k: int = 50, seed: int = 1) -> dict[str, DataFrame]:
    """Block model, Chung-Lu with blow-up and Kronecker against the original: summaries, series and the ``k`` leading eigenvalues (none with 0)."""
    summaries, series, spectra = [], [], []
    for g in graphs:
        own = stored(BUILDERS[g](spark, sf_dir), "edges")
        p = stored(profile.measure_profile(own, g), "profile")
        n, stubs = p.agg(F.sum("n"), F.sum(F.col("n") * F.col("degree"))).head()
        made = {
            "original": own,
            "block model": generate.dedup(generate.generate(build_plan(p, beta), seed)),
            "chung-lu": generate.dedup(baselines.chung_lu(p, beta, seed)),
            "kronecker": generate.dedup(baselines.kronecker(spark, max(1, (n - 1).bit_length()), stubs // 2, initiator, seed)),
        }
        for model, e in made.items():
            e = e if model == "original" else stored(e, "edges")
            summaries.append(profile.summary(e, g, model))
            series.append(profile.measure_profile(e, g).withColumn("model", F.lit(model)))
            if k:
                spectra.append(spectrum.leading_eigenvalues(e, k).select(F.lit(g).alias("graph"), F.lit(model).alias("model"), "rank", "value"))
    out = {"summary": _union(summaries), "series": _union(series)}
    return out | ({"spectrum": _union(spectra)} if k else {})


def large_clones(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("doc_line", "part_basket", "cust_day", "page_href", "host_href"), beta: float = 1.0, k: int = 2000, seed: int = 1) -> dict[str, DataFrame]:
    """Clones by the block model and by Chung-Lu from a profile with sampled clustering, with sizes, sampled global clustering, and the
    seconds of generation and of dropping repeats."""
    rows, sizes = [], []
    for g in graphs:
        own = stored(BUILDERS[g](spark, sf_dir), "edges")
        p = stored(profile.measure_profile(own, g, "sampled", k, seed), "profile")
        plan = build_plan(p, beta)
        rows.append(measures.timed("clones", g, "generate", generate.generate(plan, seed)))
        gen = stored(generate.generate(plan, seed), "gen")
        rows.append(measures.timed("clones", g, "dedup", generate.dedup(gen)))
        made = {"original": p}
        for model, x in (("block model", gen), ("chung-lu", baselines.chung_lu(p, beta, seed))):
            made[model] = stored(profile.measure_profile(stored(generate.dedup(x), "edges"), g, "sampled", k, seed), "profile")
        sizes += [_sized(x, g, model) for model, x in made.items()]
    return {"summary": _union(sizes), "bench": spark.createDataFrame(rows, BENCH)}


def _sized(p: DataFrame, graph: str, model: str) -> DataFrame:
    """One row: sizes and global clustering that a profile implies."""
    w = F.col("n") * profile.wedges("degree")
    stubs, n = F.sum(F.col("degree") * F.col("n")), F.sum("n")
    gcc = F.coalesce(F.try_divide(F.sum(F.col("c") * w), F.sum(w).cast("double")), F.lit(0.0))
    return p.agg(F.lit(graph).alias("graph"), F.lit(model).alias("model"), n.alias("nodes"), (stubs / 2).cast("bigint").alias("edges"), F.max("degree").alias("dmax"), (stubs / n).alias("davg"), gcc.alias("gcc"))


def degree_fit_cases(spark: SparkSession, nodes: int = 10_000_000) -> DataFrame:
    """Both targets by both laws: parameters, mean degree and probability of the largest degree."""
    out = []
    for case, davg, dmax, tail in (("A", 16.0, 10**6, 4.14e-26), ("B", 64.0, 10**5, 8.35e-12)):
        for kind in ("dpl", "dgln"):
            s = ideal.fit_degrees(kind, davg, dmax, None if kind == "dpl" else tail)
            m = ideal.ideal_moments(ideal.ideal_degrees(spark, s))
            out.append(m.select(F.lit(case).alias("case"), F.lit(kind).alias("law"), F.lit(s.gamma).alias("gamma"), F.lit(s.alpha).alias("alpha"), F.lit(s.delta).alias("delta"), "davg", "p_top", (F.col("p_top") * nodes < 1).alias("tail_fits")))
    return _union(out)


def example_graphs(spark: SparkSession, nodes: int = 10_000, seed: int = 1, k: int = 2000) -> dict[str, DataFrame]:
    """The two example graphs at any size: target and realised summaries, and seconds."""
    rows, summaries = [], []
    for name, spec in (("EX-A", ideal.IdealSpec("dgln", 100_000, alpha=2.14, delta=1.83, c_max=0.9, xi=3.59e-4)), ("EX-B", ideal.IdealSpec("dgln", 10_000, alpha=1.98, delta=2.08, c_max=0.5, xi=0.01))):
        p = stored(ideal.ideal_profile(spark, spec, nodes, "multinomial", seed=seed, graph=name), "profile")
        plan = build_plan(p)
        rows.append(measures.timed("examples", name, "generate", generate.generate(plan, seed)))
        gen = stored(generate.generate(plan, seed), "gen")
        rows.append(measures.timed("examples", name, "dedup", generate.dedup(gen)))
        made = stored(profile.sample_clustering(stored(generate.dedup(gen), "edges"), k, seed), "profile")
        summaries += [_sized(x, name, model) for model, x in (("target", p), ("model", made))]
    return {"summary": _union(summaries), "bench": spark.createDataFrame(rows, BENCH)}


def weak_scaling(spark: SparkSession, base_nodes: int = 10_000, base_dmax: int = 500, steps: int = 7, edges_per_task: int = 250_000, seed: int = 1) -> DataFrame:
    """Graphs of doubling size with a fixed number of edges a task: generated, unique, and seconds of both stages."""
    rows = []
    for nodes, dmax in ideal.scaling_series(base_nodes, base_dmax, steps):
        spec = ideal.fit_degrees("dgln", 32, dmax, 0.001 / nodes)
        hist = stored(ideal.realise(ideal.ideal_degrees(spark, spec), nodes), "hist")
        p = ideal.ideal_clustering(hist, 0.5, ideal.fit_xi(hist, 0.5, 0.15)).select(F.lit(str(nodes)).alias("graph"), "degree", "n", "c")
        plan = build_plan(p)
        rows.append(measures.timed("weak scaling", str(nodes), "generate", generate.generate(plan, seed, edges_per_task=edges_per_task)))
        gen = stored(generate.generate(plan, seed, edges_per_task=edges_per_task), "gen")
        rows.append(measures.timed("weak scaling", str(nodes), "dedup", generate.dedup(gen)))
    return spark.createDataFrame(rows, BENCH)


def coupon_experiment(spark: SparkSession) -> DataFrame:
    return measures.coupon_trials(spark, 10, 0.5, 10_000)


def replot(series: DataFrame) -> tuple[DataFrame, DataFrame]:
    """A profile's series in log bins, and its cumulative degrees."""
    return measures.log_binned(series), measures.cumulative_degrees(series.select("degree", "n"))


def largest_series(spark: SparkSession, nodes: int = 640_000, dmax: int = 4000, seed: int = 1, k: int = 2000) -> DataFrame:
    """Target against realised degrees and clustering of the largest scaling graph, in log bins."""
    spec = ideal.fit_degrees("dgln", 32, dmax, 0.001 / nodes)
    target, edges = ideal.benchmark_graph(spark, nodes, 32, dmax, 0.5, gcc=0.15, spec=spec, seed=seed)
    made = profile.sample_clustering(stored(edges, "edges"), k, seed)
    a = measures.log_binned(target).select("k", "lo", "hi", F.col("n").alias("n_target"), F.col("c").alias("c_target"))
    return a.join(measures.log_binned(made).select("k", F.col("n").alias("n_model"), F.col("c").alias("c_model")), "k", "full")


def ablations(spark: SparkSession, sf_dir: str, graph: str = "doc_line", seed: int = 1) -> DataFrame:
    """One option changed at a time: distance of each clone's profile from the original's."""
    own = stored(BUILDERS[graph](spark, sf_dir), "edges")
    p = stored(profile.measure_profile(own, graph), "profile")
    base = build_plan(p)
    runs = {f"weight={w}": generate.generate(build_plan(p, weight=w), seed) for w in ("log", "harmonic", "plain")}
    runs |= {f"beta={b:g}": generate.generate(build_plan(p, b), seed) for b in (2.0, 10.0)}
    runs |= {f"mode={m}": generate.generate(base, seed, m) for m in ("bulk", "poisson", "skip", "realised")}
    runs["density by degree"] = generate.generate(build_plan(p, rho=F.lit(0.9) * F.exp(-F.lit(0.01) * F.col("degree"))), seed)
    every = [profile.measure_profile(stored(generate.dedup(gen), "edges"), graph).select(F.lit(name).alias("model"), "degree", "n", "c") for name, gen in runs.items()]
    return measures.compare_all(p, stored(_union(every), "profiles")).withColumnRenamed("model", "variant")
