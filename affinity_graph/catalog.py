"""Named queries over the given tables, and their DuckDB equivalents. Floats are rounded to six places on both sides."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from . import oracles as O
from .functions.rng import uniform
from .operators import baselines, baskets, discrete, families, generate, ideal, measures, profile, relational, spectrum
from .plans import block_plan
from .sources import graphs
from .sources.tables import stored, table
from .streaming import stream
from .workloads import experiments

Query = Callable[[SparkSession, str], DataFrame]
FLAGSHIP, SEED, BETA = "doc_line", 1, 10.0
LINKS = "page_href"
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def rounded(df: DataFrame, places: int = 6) -> DataFrame:
    return df.select(*[F.round(c, places).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def edges(g: str) -> Query:
    return lambda s, d: graphs.BUILDERS[g](s, d)


def stored_edges(s: SparkSession, d: str, g: str) -> DataFrame:
    """Edges written once where a query looks at them several times."""
    return stored(graphs.BUILDERS[g](s, d), "edges")


def hist(s: SparkSession, d: str, g: str) -> DataFrame:
    if g in graphs.MEMBERS:
        return families.degree_hist(family(s, d, g))
    return profile.degree_hist(profile.degrees(graphs.BUILDERS[g](s, d)))


def sized(s: SparkSession, d: str) -> Row:
    """Nodes and mean degree of the page graph, which ideal laws are held against."""
    return profile.size_from_hist(hist(s, d, LINKS)).head()


def family(s: SparkSession, d: str, g: str) -> DataFrame:
    """Families of nodes of a graph that ties the members of groups."""
    members, keys = graphs.MEMBERS[g]
    return families.families(members(s, d), *keys)


def by_degree(s: SparkSession, d: str, g: str) -> DataFrame:
    if g in graphs.BASKETS:
        return profile.clustered(profile.shared_closed(baskets.closed_at_nodes(graphs.BASKETS[g](s, d))))
    return families.clustering_by_degree(family(s, d, g)) if g in graphs.MEMBERS else profile.clustering_by_degree(stored_edges(s, d, g))


def profiled(s: SparkSession, d: str, g: str) -> DataFrame:
    return by_degree(s, d, g).select(F.lit(g).alias("graph"), "degree", "n", "c")


def _both(s: SparkSession, d: str, together: Callable[[DataFrame, DataFrame], DataFrame]) -> DataFrame:
    """An operation on user_next and those edges of user_window that can meet one of its edges; the others, far more, are not made."""
    a = stored(graphs.user_next(s, d), "edges")
    return together(a, families.among(a, graphs.user_window_members(s, d), "w0"))


def measured(s: SparkSession, d: str, g: str) -> DataFrame:
    return stored(profiled(s, d, g) if g in graphs.BASKETS else profile.measure_profile(stored_edges(s, d, g), g), "profile")


def planned(s: SparkSession, d: str, g: str, beta: float = 1.0, **options) -> block_plan.Plan:
    return block_plan.build_plan(graphs.fixture73(s) if g == "fixture73" else measured(s, d, g), beta, **options)


def made(s: SparkSession, d: str, beta: float = BETA, **options) -> DataFrame:
    return generate.generate(planned(s, d, FLAGSHIP, beta), SEED, kind="portable", **options)


def clone(s: SparkSession, d: str, strategy: str = "exchange", **options) -> DataFrame:
    return generate.dedup(made(s, d, **options), strategy)


def _loop(g: str, f: Callable[[SparkSession, str, str], DataFrame]) -> Query:
    return lambda s, d: f(s, d, g)


# graphs
for g in graphs.BUILDERS:
    add(f"edges_{g}", edges(g), O.EDGES[g])
    add(f"degree_hist_{g}", _loop(g, hist), O.degree_hist(g))
add("interval_users", lambda s, d: graphs.users_within(s, d), O.EDGES["users_within"])

# measures
for g in ("doc_line", "user_next", "cust_order", "page_href"):
    add(f"degrees_{g}", _loop(g, lambda s, d, g: profile.degrees(graphs.BUILDERS[g](s, d))), O.degrees(g))
    add(f"cumulative_degrees_{g}", _loop(g, lambda s, d, g: measures.cumulative_degrees(hist(s, d, g), False)), O.cumulative(g))
    add(f"size_from_hist_{g}", _loop(g, lambda s, d, g: rounded(profile.size_from_hist(hist(s, d, g)))), O.size_from_hist(g))
    add(f"wedge_counts_{g}", _loop(g, lambda s, d, g: profile.wedge_counts(hist(s, d, g))), O.wedge_counts(g))
for g in ("doc_line", "part_basket", "cust_day", "user_next", "user_props", "page_href", "host_href", "cust_order", "turn_chain", "vec_knn"):
    add(f"summary_{g}", _loop(g, lambda s, d, g: profile.summed(by_degree(s, d, g), g, "original")), O.summary(g))
for g in ("doc_line", "user_next", "cust_day", "user_props"):
    add(f"clustering_by_degree_{g}", _loop(g, lambda s, d, g: rounded(by_degree(s, d, g))), O.clustering(g))
    add(f"profile_gcc_{g}", _loop(g, lambda s, d, g: rounded(profile.profile_gcc(profiled(s, d, g)))), O.gcc(g))
    add(f"log_binned_{g}", _loop(g, lambda s, d, g: rounded(measures.log_binned(profiled(s, d, g)))), O.binned(g))
for g in ("doc_line", "user_next"):
    add(f"local_clustering_{g}", _loop(g, lambda s, d, g: rounded(profile.local_clustering(stored_edges(s, d, g)))), O.local(g))
    add(f"roughness_{g}", _loop(g, lambda s, d, g: rounded(measures.roughness(hist(s, d, g)))), O.roughness(g))
    add(f"canonical_order_{g}", _loop(g, lambda s, d, g: profile.canonical_order(profile.degrees(graphs.BUILDERS[g](s, d)))), O.order(g))
add("triangles_doc_line", lambda s, d: profile.triangles(stored_edges(s, d, FLAGSHIP)).select(F.array_sort(F.array("a", "b", "c")).alias("t")).select(F.col("t")[0].alias("a"), F.col("t")[1].alias("b"), F.col("t")[2].alias("c")), O.triangle_rows(FLAGSHIP))
add("log_bins", lambda s, d: measures.log_bins(s, 1.5, 3000), O.bins())
add("sampled_clustering_doc_line", lambda s, d: rounded(profile.sample_clustering(stored_edges(s, d, FLAGSHIP), 2000, SEED, "portable")), O.sampled_clustering(FLAGSHIP, 2000, SEED))
for g in ("part_basket", "user_next"):
    add(f"sampled_clustering_{g}", _loop(g, lambda s, d, g: rounded(profile.sample_clustering(stored_edges(s, d, g), 2000, SEED, "portable"))), O.sampled_clustering(g, 2000, SEED))
add("sampled_clustering_exact_below", lambda s, d: rounded(profile.sample_clustering(stored_edges(s, d, FLAGSHIP), 2000, SEED, "portable", exact_below=2000)), O.sampled_clustering(FLAGSHIP, 2000, SEED, 2000))
add("sampled_gcc_doc_line", lambda s, d: rounded(profile.sample_gcc(stored_edges(s, d, FLAGSHIP), 2000, SEED, "portable")), O.sampled_gcc(FLAGSHIP, 2000, SEED))
add("sampling_error_doc_line", lambda s, d: rounded(profile.sampling_error(stored_edges(s, d, FLAGSHIP), 2000, SEED, "portable")), O.sampling_error(FLAGSHIP, 2000, SEED))
add("eigenvalues_doc_line", lambda s, d: rounded(spectrum.leading_eigenvalues(stored_edges(s, d, FLAGSHIP))))

# plan
for g in ("fixture73", "doc_line", "part_basket", "page_href", "user_next", "cust_order"):
    add(f"plan_degree_{g}", _loop(g, lambda s, d, g: rounded(planned(s, d, g).degree)), O.plan_degree(g))
    add(f"plan_group_{g}", _loop(g, lambda s, d, g: rounded(planned(s, d, g).group)), O.plan_group(g))
add("index_ranges_doc_line", lambda s, d: block_plan.index_ranges(measured(s, d, FLAGSHIP)).select("degree", "n", "first_node", "n_above"), O.plan_ranges(FLAGSHIP))
add("expected_edges_doc_line", lambda s, d: rounded(planned(s, d, FLAGSHIP).expected_edges()), O.expected_edges(FLAGSHIP))
add("plan_cells_doc_line", lambda s, d: planned(s, d, FLAGSHIP).cells(), O.plan_cells(FLAGSHIP))
add("nodes_fixture73", lambda s, d: block_plan.expand_nodes(planned(s, d, "fixture73")), O.expanded_nodes())
add("blocks_fixture73", lambda s, d: block_plan.expand_blocks(planned(s, d, FLAGSHIP)), O.expanded_blocks(FLAGSHIP))  # the name is kept, the plan is the flagship's
for w in ("harmonic", "plain"):
    add(f"plan_group_{w}", (lambda w: lambda s, d: rounded(planned(s, d, FLAGSHIP, weight=w).group))(w), O.plan_group(FLAGSHIP, w))
add("plan_density_by_degree", lambda s, d: rounded(block_plan.build_plan(measured(s, d, FLAGSHIP), rho=F.lit(0.9) * F.exp(-F.lit(0.01) * F.col("degree"))).group), O.plan_by_degree(FLAGSHIP, 0.9, 0.01))

# draws
_N = 20_000
for m in ("scan", "guide", "search", "array"):
    add(f"draw_{m}", (lambda m: lambda s, d: discrete.draw(generate.edge_ids(s, _N), uniform(SEED, "edge_id", 5, "portable"), discrete.cumulative(hist(s, d, FLAGSHIP).withColumn("w", F.col("degree") * F.col("n").cast("double")), "degree", "w"), m))(m), O.draw_rows(FLAGSHIP, SEED, _N))
add("draw_alias", lambda s, d: discrete.draw(generate.edge_ids(s, _N), uniform(SEED, "edge_id", 5, "portable"), discrete.cumulative(hist(s, d, FLAGSHIP).withColumn("w", F.col("degree") * F.col("n").cast("double")), "degree", "w"), "alias"))
add("phase_coin", lambda s, d: generate.phase_coin(generate.edge_ids(s, _N), 0.7, SEED, "portable"), O.coin_rows(0.7, SEED, _N))

# generation
add("local_edges_doc_line", lambda s, d: made(s, d).where("phase = 1"), O.gen_rows(FLAGSHIP, BETA, SEED, 1))
add("global_edges_doc_line", lambda s, d: made(s, d).where("phase = 2"), O.gen_rows(FLAGSHIP, BETA, SEED, 2))
add("generated_doc_line", lambda s, d: clone(s, d), O.gen_edges(FLAGSHIP, BETA, SEED))
add("generated_bulk", lambda s, d: clone(s, d, mode="bulk"), O.gen_edges(FLAGSHIP, BETA, SEED, "bulk"))
for m in ("poisson", "skip", "realised"):
    add(f"generated_{m}", (lambda m: lambda s, d: clone(s, d, mode=m))(m), O.gen_edges(FLAGSHIP, BETA, SEED, m))
for k in ("sort", "endpoint"):
    add(f"dedup_{k}", (lambda k: lambda s, d: clone(s, d, k))(k), O.gen_edges(FLAGSHIP, BETA, SEED))


def _tiled(s: SparkSession, d: str) -> DataFrame:
    plan = planned(s, d, FLAGSHIP, BETA)
    return generate.dedup(stored(generate.generate(plan, SEED, "skip", "portable"), "gen"), "tile", plan, unique_local=True)


add("dedup_tile", _tiled, O.gen_edges(FLAGSHIP, BETA, SEED, "skip"))
add("dedup_count", lambda s, d: clone(s, d, "count"), O.gen_count(FLAGSHIP, BETA, SEED))
add("clone_summary_doc_line", lambda s, d: profile.summary(stored(clone(s, d), "clone"), FLAGSHIP, "model"), O.clone_summary(FLAGSHIP, BETA, SEED))
add("clone_profile_doc_line", lambda s, d: rounded(profile.measure_profile(stored(clone(s, d), "clone"), FLAGSHIP)), O.clone_profile(FLAGSHIP, BETA, SEED))
add("repeat_ratio_rollup", lambda s, d: measures.repeat_ratio(stored(made(s, d), "gen")), O.repeat_ratio(FLAGSHIP, BETA, SEED))


def _blowup(beta: float) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        plan = planned(s, d, FLAGSHIP, beta)
        return measures.degree_one_loss(plan, stored(generate.dedup(generate.generate(plan, SEED, kind="portable")), "clone"))

    return run


add("blowup_isolated", _blowup(BETA), O.blowup(FLAGSHIP, BETA, SEED))
add("blowup_isolated_beta_1", _blowup(1.0), O.blowup(FLAGSHIP, 1.0, SEED))
add("triangle_provenance", lambda s, d: measures.triangle_provenance(stored(made(s, d), "gen")), O.triangle_provenance(FLAGSHIP, BETA, SEED))
add("draws_per_edge", lambda s, d: generate.draws_per_edge(planned(s, d, FLAGSHIP)), "SELECT 1::INTEGER AS phase, 1::INTEGER AS discrete, 3::INTEGER AS uniforms UNION ALL SELECT 2, 2, 4")

# baselines
add("chung_lu", lambda s, d: generate.dedup(baselines.chung_lu(hist(s, d, FLAGSHIP), 1.0, SEED, "portable")), O.chung_lu(FLAGSHIP, 1.0, SEED))
add("chung_lu_blowup", lambda s, d: generate.dedup(baselines.chung_lu(hist(s, d, FLAGSHIP), BETA, SEED, "portable")), O.chung_lu(FLAGSHIP, BETA, SEED))
add("chung_lu_pairs", lambda s, d: baselines.chung_lu_pairs(stored(profile.degrees(graphs.BUILDERS[FLAGSHIP](s, d)), "nodes"), SEED, "portable"), O.chung_lu_pairs(FLAGSHIP, SEED))
add("chung_lu_expected", lambda s, d: baselines.chung_lu_expected(hist(s, d, FLAGSHIP)), O.chung_lu_expected(FLAGSHIP))
add("degree_dispersion", lambda s, d: rounded(measures.degree_dispersion(measured(s, d, FLAGSHIP), 5, "portable")), O.degree_dispersion(FLAGSHIP, 5))
add("kronecker", lambda s, d: generate.dedup(baselines.kronecker(s, 9, 4000, seed=SEED, kind="portable")), O.kronecker(9, 4000, baselines.INITIATOR, SEED))
add("kronecker_noisy", lambda s, d: generate.dedup(baselines.kronecker(s, 9, 4000, seed=SEED, noise=0.05, kind="portable")), O.kronecker(9, 4000, baselines.INITIATOR, SEED, 0.05))
_days = lambda s, d: table(s, d, "orders").select(F.to_date("o_orderdate")).distinct().count()
add("erdos_renyi_pairs", lambda s, d: baselines.erdos_renyi(s, _days(s, d), 0.05, "pairs", SEED, "portable"), O.erdos_renyi_pairs(0.05, SEED))
add("erdos_renyi_skip", lambda s, d: baselines.erdos_renyi(s, _days(s, d), 0.002, "skip", SEED, "portable"), O.erdos_renyi_skip(0.002, SEED))

# idealized profiles
_DPL, _DGLN = (1.911,), (1.98, 2.08)
_SPEC = ideal.IdealSpec("dgln", 1000, alpha=1.98, delta=2.08, c_max=0.5, xi=0.01)
add("ideal_dpl", lambda s, d: rounded(ideal.ideal_degrees(s, ideal.IdealSpec("dpl", 1000, gamma=1.911)), 9), O.ideal("dpl", _DPL, 1000))
add("ideal_dgln", lambda s, d: rounded(ideal.ideal_degrees(s, _SPEC), 9), O.ideal("dgln", _DGLN, 1000))
for name, spec, p in (("fit_a_dpl", ideal.IdealSpec("dpl", 10**6, gamma=1.911), (1.911,)), ("fit_a_dgln", ideal.IdealSpec("dgln", 10**6, alpha=1.988, delta=2.079), (1.988, 2.079)), ("fit_b_dpl", ideal.IdealSpec("dpl", 10**5, gamma=1.668), (1.668,)), ("fit_b_dgln", ideal.IdealSpec("dgln", 10**5, alpha=2.171, delta=1.877), (2.171, 1.877))):
    add(f"ideal_moments_{name}", (lambda spec: lambda s, d: ideal.ideal_moments(ideal.ideal_degrees(s, spec)).select(F.round("davg", 6).alias("davg"), F.round(F.log("p_top"), 6).alias("log_p_top")))(spec), O.ideal_moments(spec.kind, p, spec.dmax))
_A, _B = [(round(1.9 + k / 20, 2), round(1.9 + j / 20, 2)) for k in range(4) for j in range(4)], [(round(1.7 + k / 20, 2),) for k in range(8)]
add("fit_grid_dgln", lambda s, d: ideal.fit_grid(s, "dgln", sized(s, d).davg, 10_000, s.createDataFrame(_A, "alpha double, delta double")), O.fit_grid("dgln", ["alpha", "delta"], _A, LINKS, 10_000))
add("fit_grid_dpl", lambda s, d: ideal.fit_grid(s, "dpl", sized(s, d).davg, 10_000, s.createDataFrame(_B, "gamma double")), O.fit_grid("dpl", ["gamma"], _B, LINKS, 10_000))
add("ideal_clustering", lambda s, d: rounded(ideal.ideal_clustering(hist(s, d, FLAGSHIP), 0.5, 0.01)), O.ideal_clustering(FLAGSHIP, 0.5, 0.01))
_XIS = [0.002 * 2**k for k in range(8)]
add("fit_xi_grid", lambda s, d: ideal.fit_xi_grid(hist(s, d, FLAGSHIP), 0.9, 0.4, s.createDataFrame([(x,) for x in _XIS], "xi double")), O.xi_grid(FLAGSHIP, 0.9, 0.4, _XIS))
add("ideal_clustering_noisy", lambda s, d: rounded(ideal.ideal_clustering(hist(s, d, FLAGSHIP), 0.5, 0.01, True, SEED, "portable")), O.ideal_noisy(FLAGSHIP, 0.5, 0.01, SEED))
add("ideal_profile_gcc", lambda s, d: rounded(profile.profile_gcc(ideal.ideal_clustering(hist(s, d, FLAGSHIP), 0.5, 0.01).withColumn("graph", F.lit("ideal")))), O.ideal_gcc(FLAGSHIP, 0.5, 0.01))
add("ideal_check", lambda s, d: rounded(ideal.check_ideal(ideal.ideal_degrees(s, _SPEC), sized(s, d).davg, sized(s, d).nodes), 4), O.ideal_check("dgln", _DGLN, 1000, LINKS))
add("dgln_study", lambda s, d: ideal.dgln_study(s, sized(s, d).nodes), O.dgln_study(LINKS, 1_000_000))
add("realised_rounded", lambda s, d: ideal.realise(ideal.ideal_degrees(s, _SPEC), 10_000), O.realised_rounded("dgln", _DGLN, 1000, 10_000))
add("realised_multinomial", lambda s, d: ideal.realise(ideal.ideal_degrees(s, _SPEC), 10_000, "multinomial", SEED, "portable"), O.realised_multinomial("dgln", _DGLN, 1000, 10_000, SEED))
add("benchmark_summary", lambda s, d: profile.summary(stored(ideal.benchmark_graph(s, 10_000, 16, 1000, 0.5, gcc=0.1, spec=_SPEC)[1], "bench"), "benchmark", "model"))

# the coupon experiment: pairs of the orders' lines, trials by customer
def _line_pairs(s: SparkSession, d: str) -> DataFrame:
    """(u): distinct numbers of pairs of lines that orders have."""
    lines = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
    return lines.select(profile.wedges("n").alias("u")).where("u > 0").distinct()


_LINE_PAIRS = "(SELECT DISTINCT n * (n - 1) // 2 AS u FROM (SELECT count(*)::BIGINT AS n FROM lineitem GROUP BY l_orderkey) WHERE n > 1)"
_trials = lambda s, d: table(s, d, "customer").select(F.col("c_custkey").alias("trial"))
add("coupon_weight", lambda s, d: _line_pairs(s, d).select("u", F.round(F.col("u") * -F.log1p(F.lit(-0.5)), 6).alias("draws"), (F.col("u") / 2).alias("target")), f"SELECT u::BIGINT AS u, round(u * ln(2::DOUBLE), 6) AS draws, u / 2::DOUBLE AS target FROM {_LINE_PAIRS}")
add("coupon_harmonic", lambda s, d: _line_pairs(s, d).withColumn("seen", F.ceil(F.col("u") / 2)).select("u", F.round(F.col("u") * F.aggregate(F.sequence(F.col("u") - F.col("seen") + 1, F.col("u")), F.lit(0.0), lambda a, x: a + F.lit(1.0) / x), 6).alias("draws")), f"SELECT u::BIGINT AS u, round(u * sum(1::DOUBLE / k), 6) AS draws FROM {_LINE_PAIRS}, LATERAL (SELECT unnest(range(u // 2 + 1, u + 1)) AS k) GROUP BY u")
add("coupon_trials", lambda s, d: measures.coupon_trials(s, 10, 0.5, _trials(s, d), SEED, "portable"), O.coupon_poisson("(SELECT c_custkey FROM customer)", SEED, measures.poisson_cdf(-45 * math.log1p(-0.5))))
add("coupon_trials_fixed", lambda s, d: measures.coupon_trials(s, 10, 0.5, _trials(s, d), SEED, "portable", True), O.coupon_fixed("(SELECT c_custkey FROM customer)", SEED))


# comparisons
def _models(s: SparkSession, d: str) -> dict[str, DataFrame]:
    """Profiles of the original and of every model of the flagship graph."""
    own = measured(s, d, FLAGSHIP)
    n, m = own.agg(F.sum("n"), F.sum(F.col("n") * F.col("degree"))).head()
    models = {f"model_{b:g}": generate.generate(block_plan.build_plan(own, b), SEED, kind="portable") for b in (1.0, BETA)}
    models |= {"chung_lu": baselines.chung_lu(own, BETA, SEED, "portable"), "kronecker": baselines.kronecker(s, max(1, (n - 1).bit_length()), m // 2, seed=SEED, kind="portable")}
    return {"original": own} | {k: profile.measure_profile(stored(generate.dedup(x), "edges"), k) for k, x in models.items()}


def compare_models(s: SparkSession, d: str) -> DataFrame:
    p = _models(s, d)
    every = None
    for k, x in p.items():
        rows = x.select(F.lit(k).alias("model"), "degree", "n", "c")
        every = rows if every is None else every.unionByName(rows)
    return measures.compare_all(p["original"], stored(every, "profiles"))


def _clone_hist(s: SparkSession, d: str) -> DataFrame:
    return profile.degree_hist(profile.degrees(clone(s, d)))


add("compare_models_doc_line", compare_models, O.compare_models(FLAGSHIP, (1.0, BETA), BETA, baselines.INITIATOR, SEED))
add("ks_distance", lambda s, d: measures.ks_distance(hist(s, d, FLAGSHIP), _clone_hist(s, d)), O.compared(FLAGSHIP, BETA, SEED))
add("profile_series_doc_line", lambda s, d: rounded(measures.profile_series(measured(s, d, FLAGSHIP), profile.measure_profile(stored(clone(s, d), "clone"), FLAGSHIP))), O.profile_series(FLAGSHIP, BETA, SEED))
add("clustering_gap", lambda s, d: measures.clustering_gap(measured(s, d, FLAGSHIP), profile.measure_profile(stored(clone(s, d), "clone"), FLAGSHIP)), O.clustering_gap(FLAGSHIP, BETA, SEED))

# relational surroundings
_nodes = lambda s, d, g=FLAGSHIP: profile.degrees(graphs.BUILDERS[g](s, d))
_WITH = f"WITH {O._base(FLAGSHIP)}"
add("topk_hubs", lambda s, d: relational.top_hubs(_nodes(s, d)), f"{_WITH} SELECT v, degree FROM nd ORDER BY degree DESC, v LIMIT 10")
add("topk_per_class", lambda s, d: relational.top_per_class(_nodes(s, d)), f"{_WITH} SELECT v, degree, rank::INTEGER AS rank FROM (SELECT *, row_number() OVER (PARTITION BY degree ORDER BY v) AS rank FROM nd) WHERE rank <= 3")
add("degree_ranks", lambda s, d: relational.degree_ranks(_nodes(s, d)), f"{_WITH} SELECT degree, n, dense_rank() OVER w::INTEGER AS dense_rank, round(percent_rank() OVER w, 6) AS percent_rank, round(cume_dist() OVER w, 6) AS cume_dist, ntile(4) OVER w::INTEGER AS quartile FROM h WINDOW w AS (ORDER BY degree)")
add("hist_jumps", lambda s, d: relational.hist_jumps(hist(s, d, FLAGSHIP)), f"{_WITH} SELECT degree, n, n - lag(n) OVER w AS step, lead(n) OVER w AS next_n, round(avg(n) OVER (ORDER BY degree ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) AS moving FROM h WINDOW w AS (ORDER BY degree)")
add("asof_prev_order", relational.previous_order, "SELECT o_custkey, o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS previous FROM orders")
add("anti_missing_edges", lambda s, d: relational.missing_edges(graphs.user_next(s, d), graphs.user_window(s, d)), f"SELECT * FROM ({O.EDGES['user_next']}) EXCEPT SELECT * FROM ({O.EDGES['user_window']})")
add("intersect_realisations", lambda s, d: _both(s, d, relational.shared_edges), f"SELECT * FROM ({O.EDGES['user_next']}) INTERSECT SELECT * FROM ({O.EDGES['user_window']})")
add("isolated_customers", lambda s, d: relational.isolated_customers(s, d, families.touched(graphs.cust_day_members(s, d), "day")), f"SELECT c_custkey, c_nationkey FROM customer WHERE c_custkey NOT IN (SELECT lo FROM ({O.EDGES['cust_day']}) UNION SELECT hi FROM ({O.EDGES['cust_day']}))")
add("nation_edges", lambda s, d: relational.nation_edges(s, d, family(s, d, "cust_day")), f"SELECT least(x.c_nationkey, y.c_nationkey) AS nation_a, greatest(x.c_nationkey, y.c_nationkey) AS nation_b, count(*)::BIGINT AS edges FROM ({O.EDGES['cust_day']}) e JOIN customer x ON x.c_custkey = lo JOIN customer y ON y.c_custkey = hi GROUP BY 1, 2")
add("hashed_sample", lambda s, d: relational.hashed_sample(graphs.cust_day(s, d)), f"SELECT lo, hi FROM ({O.EDGES['cust_day']}) WHERE CAST('0x' || substr(md5('s|' || lo || '|' || hi), 1, 8) AS BIGINT) % 1000 < 100")
add("json_keys", relational.json_keys, "SELECT (props->>'k')::INTEGER AS k, count(*)::BIGINT AS events, count(DISTINCT user_id)::BIGINT AS users FROM events GROUP BY 1")
add("array_hist_map", lambda s, d: relational.hist_map(hist(s, d, FLAGSHIP)), f"{_WITH} SELECT degree, n, round(n::DOUBLE / (SELECT sum(n) FROM h), 6) AS share FROM h")
add("assortativity", lambda s, d: relational.assortativity(graphs.user_next(s, d), _nodes(s, d, "user_next")), f"WITH {O._base('user_next')}, x AS (SELECT a.degree::DOUBLE AS p, b.degree::DOUBLE AS q FROM e JOIN nd a ON a.v = lo JOIN nd b ON b.v = hi), y AS (SELECT p, q FROM x UNION ALL SELECT q, p FROM x) SELECT round(corr(p, q), 6) AS r FROM y")
add("degree_moments", lambda s, d: relational.degree_moments(_nodes(s, d)), f"{_WITH} SELECT round(avg(degree), 6) AS mean, round(stddev_pop(degree), 6) AS deviation, quantile_cont(degree, 0.5)::DOUBLE AS median FROM nd")
add("quality_by_degree", lambda s, d: relational.quality_by_degree(s, d, _nodes(s, d)), f"{_WITH} SELECT degree, count(*)::BIGINT AS labelled, count(*) FILTER (quality = 1)::BIGINT AS good FROM nd JOIN labels ON doc_id = v GROUP BY degree")
add("cube_phase_class", lambda s, d: relational.class_cube(graphs.user_next(s, d), _nodes(s, d, "user_next")), f"WITH {O._base('user_next')}, c AS (SELECT v, floor(log2(degree) + 1e-9)::INTEGER AS cls FROM nd), x AS (SELECT a.cls AS class_lo, b.cls AS class_hi FROM e JOIN c a ON a.v = lo JOIN c b ON b.v = hi) SELECT class_lo, class_hi, count(*)::BIGINT AS edges, grouping(class_lo, class_hi)::BIGINT AS level FROM x GROUP BY CUBE (class_lo, class_hi)")
add("sketches", lambda s, d: relational.sketches(graphs.user_next(s, d), _nodes(s, d, "user_next")))


def _rollup(s: SparkSession, d: str) -> DataFrame:
    plan = planned(s, d, FLAGSHIP, BETA)
    return relational.phase_rollup(generate.generate(plan, SEED, kind="portable"), plan)


add("rollup_phase", _rollup, O.phase_rollup(FLAGSHIP, BETA, SEED))
add("pivot_summary", lambda s, d: relational.pivoted(profile.summary(stored_edges(s, d, FLAGSHIP), FLAGSHIP, "original").unionByName(profile.summary(stored(clone(s, d), "clone"), FLAGSHIP, "model"))), O.pivoted(FLAGSHIP, BETA, SEED))

# streams: the batch result of the finished query
_WINDOW = "SELECT w AS start, w + INTERVAL {n} MINUTE AS \"end\", user_id, count(*)::BIGINT AS events FROM ({src}) GROUP BY ALL"


def _finished(kind: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        out = stream.finished(stream.window_members(stream.event_stream(s, d), kind), f"windows-{kind}", "complete")
        return out.select(F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), "user_id", "events")

    return run


add("window_edges_tumbling", _finished("tumbling"), _WINDOW.format(n=5, src="SELECT time_bucket(INTERVAL 5 MINUTE, ts) AS w, user_id FROM events"))
add("window_edges_sliding", _finished("sliding"), _WINDOW.format(n=15, src="SELECT time_bucket(INTERVAL 5 MINUTE, ts) - INTERVAL (5 * k) MINUTE AS w, user_id FROM events, range(3) t(k)"))
add("window_edges_session", _finished("session"), O.SESSIONS)


def _running(s: SparkSession, d: str) -> DataFrame:
    e = stream.event_stream(s, d).select((F.col("user_id") * 2).alias("lo"), (F.col("event_id") * 2 + 1).alias("hi"))
    return stream.finished(stream.running_degrees(e), "running", "complete")


add("running_degrees", _running, "SELECT v, count(*)::BIGINT AS degree FROM (SELECT user_id * 2 AS v FROM events UNION ALL SELECT event_id * 2 + 1 FROM events) GROUP BY v")


add("stream_generate", lambda s, d: generate.dedup(stream.generated_by_stream(planned(s, d, FLAGSHIP, BETA), round(sum(planned(s, d, FLAGSHIP, BETA).totals())), SEED, "portable")), O.gen_edges(FLAGSHIP, BETA, SEED))
add("stream_static_nation", lambda s, d: stream.finished(stream.by_nation(stream.event_stream(s, d), s, d), "nation", "complete"), "SELECT c_nationkey, count(*)::BIGINT AS events FROM events JOIN customer ON c_custkey = user_id GROUP BY 1")
add("stream_followed_within", lambda s, d: stream.finished(stream.followed_within(stream.event_stream(s, d), stream.event_stream(s, d)), "followed"), "SELECT a.user_id, a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE")


def _stateful(s: SparkSession, d: str) -> DataFrame:
    ends = stream.event_stream(s, d).select((F.col("user_id") * 2).alias("lo"), (F.col("event_id") * 2 + 1).alias("hi"))
    with stream.column_families(s):
        return stream.finished(stream.stateful_degrees(ends), "stateful", "update")


add("stream_stateful_degrees", _stateful, "SELECT v, count(*)::BIGINT AS degree FROM (SELECT user_id * 2 AS v FROM events UNION ALL SELECT event_id * 2 + 1 FROM events) GROUP BY v")

# more of the relational surroundings
add("edges_by_degree", lambda s, d: relational.edges_by_degree(graphs.BUILDERS[FLAGSHIP](s, d), _nodes(s, d)), f"{_WITH} SELECT degree, count(*)::BIGINT AS edges FROM e JOIN nd ON v = lo GROUP BY degree")
add("lateral_blocks", lambda s, d: relational.lateral_blocks(planned(s, d, "fixture73")), f"SELECT g, block, first_node FROM ({O.expanded_blocks()})")
add("decimal_gcc", lambda s, d: relational.decimal_gcc(profile.clustering_by_degree(stored_edges(s, d, FLAGSHIP))), f"WITH {O._clustered(FLAGSHIP)} SELECT round(sum(closed)::DOUBLE / sum(wedges)::DOUBLE, 9) AS gcc FROM cd")
add("multiset_difference", lambda s, d: _both(s, d, relational.multiset_difference), f"SELECT * FROM ({O.EDGES['user_next']})")
add("degree_shape", lambda s, d: relational.degree_shape(_nodes(s, d)), f"{_WITH}, m AS (SELECT avg(degree) AS a FROM nd), c AS (SELECT avg((degree - a) ** 2) AS m2, avg((degree - a) ** 3) AS m3, avg((degree - a) ** 4) AS m4 FROM nd, m) SELECT round(m3 / m2 ** 1.5, 6) AS skewness, round(m4 / m2 ** 2 - 3, 6) AS kurtosis FROM c")
add("near_degrees", lambda s, d: relational.near_degrees(hist(s, d, FLAGSHIP)), f"{_WITH} SELECT degree, (sum(n) OVER (ORDER BY degree RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING))::BIGINT AS near FROM h")
add("hist_json", lambda s, d: relational.hist_json(hist(s, d, FLAGSHIP)), f"{_WITH} SELECT degree, '{{\"degree\":' || degree || ',\"n\":' || n || '}}' AS said FROM h")
add("recursive_bins", lambda s, d: relational.recursive_bins(s), f"WITH {O._BINS} SELECT lo FROM bn WHERE lo <= 3000")
add("stratified_sample", lambda s, d: relational.stratified(_nodes(s, d), 0.5, SEED))

# the experiments; seconds are left to the bench
add("w1_summary", lambda s, d: rounded(experiments.small_comparison(s, d, (FLAGSHIP,), k=0)["summary"]))
add("w2_large_clones", lambda s, d: rounded(experiments.large_clones(s, d, (FLAGSHIP, "part_basket", "page_href"))["summary"]))
add("w3_degree_fits", lambda s, d: rounded(experiments.degree_fit_cases(s), 4))
add("w4_example_graphs", lambda s, d: rounded(experiments.example_graphs(s)["summary"]))
add("w5_weak_scaling", lambda s, d: experiments.weak_scaling(s, steps=3).drop("seconds"))
add("w7_largest_series", lambda s, d: rounded(experiments.largest_series(s, 40_000, 1000)))
add("w8_replot_binned", lambda s, d: rounded(experiments.replot(measured(s, d, FLAGSHIP))[0]), O.binned(FLAGSHIP))
add("w8_replot_cumulative", lambda s, d: rounded(experiments.replot(measured(s, d, FLAGSHIP))[1]), O.cumulative_shares(FLAGSHIP))
add("w10_ablations", lambda s, d: experiments.ablations(s, d))


def flagship(s: SparkSession, d: str) -> DataFrame:
    """The original graph and its clone, one summary row each."""
    own = stored_edges(s, d, FLAGSHIP)
    made_ = stored(generate.clone_graph(own, FLAGSHIP, BETA, seed=SEED, kind="portable"), "clone")
    return profile.summary(own, FLAGSHIP, "original").unionByName(profile.summary(made_, FLAGSHIP, "model"))


add("flagship", flagship, O.flagship(FLAGSHIP, BETA, SEED))
