import numpy as np
import pytest
from pyspark.sql import functions as F

from affinity_graph import catalog
from affinity_graph.functions.rng import uniform
from affinity_graph.operators import baselines, discrete, generate, measures, profile, relational, spectrum
from affinity_graph.plans import block_plan as bp
from affinity_graph.sources import edge_source, graphs, tables
from affinity_graph.streaming import stream


def edges(spark, pairs):
    return graphs.to_simple(spark.createDataFrame(pairs, "src long, dst long"))


@pytest.fixture(scope="module")
def lines(spark, data):
    return tables.stored(graphs.doc_line(spark, data), "edges")


@pytest.fixture(scope="module")
def plan(spark, lines):
    return bp.build_plan(profile.measure_profile(lines, "doc_line"), 10.0)


def test_dirty_pairs(spark):
    assert sorted(map(tuple, edges(spark, [(1, 1), (1, 2), (2, 1), (2, 3), (2, 3), (None, 3)]).collect())) == [(1, 2), (2, 3)]


def test_toy_graph(spark):
    e = edges(spark, [(1, 2), (1, 3), (2, 3), (3, 4), (4, 5)])
    s = profile.summary(e, "toy", "original").head()
    assert (s.nodes, s.edges, s.dmax, s.wedges, s.triangles, s.gcc) == (5, 5, 3, 6, 1, 0.5)
    assert {r.v: round(r.c, 6) for r in profile.local_clustering(e).collect()} == {1: 1.0, 2: 1.0, 3: 0.333333, 4: 0.0, 5: 0.0}
    assert {r.degree: (round(r.c, 6), round(r.c_mean, 6)) for r in profile.clustering_by_degree(e).collect()} == {1: (0.0, 0.0), 2: (0.666667, 0.666667), 3: (0.333333, 0.333333)}
    assert {r.v: r.position for r in profile.canonical_order(profile.degrees(e)).collect()} == {1: 1, 2: 2, 4: 3, 3: 4, 5: 5}


def test_clique_and_star(spark):
    clique = edges(spark, [(i, j) for i in range(5) for j in range(i)])
    assert {r.c for r in profile.local_clustering(clique).collect()} == {1.0}
    p = bp.build_plan(profile.measure_profile(clique, "clique"))
    assert p.group.count() == 1 and np.isfinite(p.totals()[0])
    star = edges(spark, [(0, i) for i in range(1, 6)])
    assert bp.build_plan(profile.measure_profile(star, "star")).expected_edges().head().edges == pytest.approx(5)


def test_empty_graph(spark):
    e = spark.createDataFrame([], "lo long, hi long")
    s = profile.summary(e, "none", "original").head()
    assert (s.nodes, s.edges, s.gcc) == (0, 0, 0.0)
    assert spectrum.leading_eigenvalues(e).count() == 0


def test_sampling_within_error(spark, lines):
    assert profile.samples_for(0.05, 0.001) == 1521
    assert profile.sampling_error(lines, 2000, 3).agg(F.max("gap")).head()[0] <= 0.05
    s = profile.sampled_wedges(lines, 50, 2)
    assert s.where("a = b OR center = a OR center = b").count() == 0


def test_draws_agree(spark, lines):
    hist = profile.degree_hist(profile.degrees(lines)).withColumn("w", F.col("degree") * F.col("n").cast("double"))
    dist, ids = discrete.cumulative(hist, "degree", "w"), generate.edge_ids(spark, 20_000)
    got = {m: sorted(map(tuple, discrete.draw(ids, uniform(7, "edge_id", 3), dist, m).select("edge_id", "bin").collect())) for m in ("scan", "guide", "search", "array", "alias")}
    assert got["scan"] == got["guide"] == got["search"] == got["array"] and len(got["alias"]) == 20_000
    share = {r.bin: r.hi - r.lo for r in dist.collect()}
    for m in ("guide", "alias"):
        n = {b: 0 for b in share}
        for _, b in got[m]:
            n[b] += 1
        chi = sum((n[b] - 20_000 * p) ** 2 / (20_000 * p) for b, p in share.items())
        assert chi < len(share) + 6 * np.sqrt(2 * len(share))


def test_rows_do_not_depend_on_partitions(plan):
    want = None
    for per_task in (10**9, 1000, 77):
        got = sorted(map(tuple, generate.generate(plan, 5, edges_per_task=per_task).collect()))
        want = want or got
        assert got == want


def test_local_edges_stay_in_their_block(plan):
    local = generate.generate(plan, 2).where("phase = 1")
    both = bp.block_of(bp.block_of(local, plan, "a").withColumnRenamed("g", "ga").withColumnRenamed("block", "ba"), plan, "b")
    assert both.where("a = b OR ga <> g OR ba <> block OR g IS NULL").count() == 0


def test_dedup_strategies_agree(plan):
    gen = tables.stored(generate.generate(plan, 3), "gen")
    sets = {k: sorted((r.lo, r.hi) for r in generate.dedup(gen, k).collect()) for k in ("exchange", "sort", "endpoint", "count")}
    sets["tile"] = sorted((r.lo, r.hi) for r in generate.dedup(gen, "tile", plan).collect())
    assert len({tuple(s) for s in sets.values()}) == 1 and len(set(sets["sort"])) == len(sets["sort"])
    with pytest.raises(ValueError):
        generate.dedup(gen, "other")


@pytest.mark.parametrize("mode", ["independent", "bulk", "poisson", "skip", "realised"])
def test_modes_keep_the_size(plan, lines, mode):
    m = lines.count()
    assert abs(generate.dedup(generate.generate(plan, 1, mode)).count() - m) < 0.12 * m


def test_skip_has_no_local_repeats(plan):
    local = generate.skip_local(plan, 4)
    assert local.count() == local.select(F.least("a", "b"), F.greatest("a", "b")).distinct().count()
    gen = tables.stored(generate.generate(plan, 4, "skip"), "gen")
    assert sorted(map(tuple, generate.dedup(gen, "tile", plan, True).collect())) == sorted(map(tuple, generate.dedup(gen).collect()))


@pytest.mark.parametrize("mode", ["skip", "poisson"])
def test_local_modes_spread_over_tasks_without_exchange(spark, mode):
    """Many groups, one of them huge: rows come from all tasks, the plan has no exchange but those of its group table, and each
    density's pairs are kept as often as its law says."""
    p = bp.build_plan(spark.createDataFrame([("g", 40, 40_000, 0.36), ("g", 900, 9_010, 0.0009), ("g", 3000, 3_001, 0.0004)], "graph string, degree long, n long, c double"))
    local = {"skip": generate.skip_local, "poisson": generate.poisson_local}[mode](p, 7)
    rows = local.withColumn("task", F.spark_partition_id()).groupBy("task").count().collect()
    assert len(rows) > 1 and max(r["count"] for r in rows) < 0.7 * sum(r["count"] for r in rows)
    found = {r.g: r.n for r in bp.block_of(local, p, "a").groupBy("g").agg(F.count_distinct(F.least("a", "b"), F.greatest("a", "b")).alias("n")).collect()}
    for g in p.group.collect():
        pairs = g.blocks * g.block_size * (g.block_size - 1) / 2
        assert abs(found[g.g] - pairs * g.rho) < 5 * (pairs * g.rho * (1 - g.rho)) ** 0.5, g
    text = local._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in text and "BroadcastNestedLoopJoin" not in text and "Exchange hashpartitioning" not in text


def test_numbering_and_lookup_plans(spark, lines, plan):
    """No window over all nodes, no nested loop: numbers come from range partitions, blocks from slots."""
    ids = lines.select(F.xxhash64("lo").alias("lo"), F.xxhash64("hi").alias("hi")).select(F.least("lo", "hi").alias("lo"), F.greatest("lo", "hi").alias("hi"))
    nodes = profile.degrees(ids)
    got = profile.canonical_order(nodes).orderBy("position").collect()
    assert [r.position for r in got] == list(range(1, len(got) + 1))
    assert [(r.degree, r.v) for r in got] == sorted(((r.degree, r.v) for r in nodes.collect()), key=lambda x: (x[0] == 1, x))
    for df in (profile.sampled_wedges(ids, 20, 1), bp.block_of(generate.generate(plan, 1), plan, "a")):
        text = df._jdf.queryExecution().executedPlan().toString()
        assert "BroadcastNestedLoopJoin" not in text and "CartesianProduct" not in text


def test_plan_shape_of_generation(plan):
    text = generate.dedup(generate.generate(plan, 1, edges_per_task=100))._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" not in text and "CartesianProduct" not in text and "BroadcastHashJoin" in text
    assert text.count("Exchange hashpartitioning(lo") + text.count("Exchange hashpartitioning(hi") == 1


def test_models_in_the_reported_order(spark, data):
    """On a union of cliques the block model keeps clustering, Chung-Lu and Kronecker do not."""
    d = data.replace("sf0.001", "sf0.01")
    own = tables.stored(profile.measure_profile(tables.stored(graphs.doc_line(spark, d), "e"), "g"), "p")
    models = {"block": generate.generate(bp.build_plan(own, 10.0), 1), "chung_lu": baselines.chung_lu(own, 10.0, 1), "kronecker": baselines.kronecker(spark, 9, 3260)}
    gap = {k: measures.compare(own, profile.measure_profile(tables.stored(generate.dedup(x), "c"), k)).head() for k, x in models.items()}
    assert gap["block"].ks <= 0.10 and gap["block"].gap_n < 0.4 * min(gap["chung_lu"].gap_n, gap["kronecker"].gap_n)


def test_repeats_and_degree_one_loss(spark, lines, plan):
    gen = generate.generate(plan, 1)
    rows = {r.phase: r for r in measures.repeat_ratio(gen).collect()}
    assert rows[0].generated == rows[1].generated + rows[2].generated and rows[0].unique <= rows[1].unique + rows[2].unique
    assert rows[0].unique == generate.dedup(gen).count()
    one = spark.createDataFrame([("g", 1, 20_000, 0.0)], "graph string, degree long, n long, c double")
    p = bp.build_plan(one)
    loss = measures.degree_one_loss(p, generate.dedup(generate.generate(p, 1))).head()
    assert loss.unused / loss.pool == pytest.approx(0.368, abs=0.02) and loss.more / loss.pool == pytest.approx(0.264, abs=0.02)


def test_coupon_mean(spark):
    rows = measures.coupon_trials(spark, 10, 0.5, 10_000, 1).collect()
    assert sum(r.trials for r in rows) == 10_000
    assert sum(r.unique * r.trials for r in rows) / 10_000 == pytest.approx(22.5, abs=0.12)


def test_eigenvalues(spark, lines):
    at, rows = {}, lines.collect()
    for r in rows:
        at.setdefault(r.lo, len(at)), at.setdefault(r.hi, len(at))
    a = np.zeros((len(at), len(at)))
    for r in rows:
        a[at[r.lo], at[r.hi]] = a[at[r.hi], at[r.lo]] = 1
    want = np.sort(np.abs(np.linalg.eigvalsh(a)))[::-1][:6]
    got = [abs(r.value) for r in spectrum.leading_eigenvalues(lines, 6, 12, 1e-7, 12).orderBy("rank").collect()]
    assert got == pytest.approx(list(want), rel=1e-3)


def test_erdos_renyi(spark):
    for method in ("pairs", "skip"):
        e = baselines.erdos_renyi(spark, 400, 0.05, method)
        n = e.count()
        assert abs(n - 3990) < 5 * 62 and e.distinct().count() == n and e.where("lo >= hi OR lo < 1 OR hi > 400").count() == 0


def test_edge_source(spark, plan):
    edge_source.register(spark)
    df = spark.read.format("affinity_edges").option("plan", edge_source.plan_json(plan)).option("edges_per_task", 300).option("seed", 4).load()
    assert df.rdd.getNumPartitions() > 1 and df.count() == round(sum(plan.totals()))
    assert sorted(map(tuple, df.collect())) == sorted(map(tuple, df.collect()))
    assert abs(df.where("phase = 1").count() / df.count() - plan.totals()[0] / sum(plan.totals())) < 0.08


def test_edge_lists_and_sinks(spark, lines, tmp_path):
    tables.write_edges(lines, f"{tmp_path}/e", tiles=4)
    assert spark.read.parquet(f"{tmp_path}/e").select("lo", "hi").exceptAll(lines).count() == 0
    for fmt in ("csv", "json", "orc"):
        tables.export(lines.withColumnsRenamed({"lo": "src", "hi": "dst"}), f"{tmp_path}/{fmt}", fmt)
        back = tables.read_edge_list(spark, f"{tmp_path}/{fmt}", fmt, **({"header": "true"} if fmt == "csv" else {}))
        assert graphs.to_simple(back).count() == lines.count()
    (tmp_path / "pairs.txt").write_text("# comment\n1 2\n2\t1\nx y\n")
    assert graphs.to_simple(tables.read_edge_list(spark, f"{tmp_path}/pairs.txt", "text")).count() == 1


def test_stream_repeats_the_batch(spark, plan):
    s = stream.generate_stream(plan, 100, 5)
    assert s.isStreaming and s.columns == ["edge_id", "phase", "a", "b"]
    total = round(sum(plan.totals()))
    got = stream.generated_by_stream(plan, total, 5)
    assert got.count() == total and got.exceptAll(generate.generate(plan, 5)).count() == 0


def test_stateful_degrees(spark, data):
    e = stream.event_stream(spark, data).select((F.col("user_id") * 2).alias("lo"), (F.col("event_id") * 2 + 1).alias("hi"), "ts")
    got = stream.finished(stream.unique_within_watermark(e), "unique")
    assert got.count() <= 1000
    with stream.column_families(spark):
        ends = stream.finished(stream.stateful_degrees(e.select("lo", "hi")), "stateful", "update")
    batch = spark.read.parquet(f"{data}/events.parquet").select((F.col("user_id") * 2).alias("lo"), (F.col("event_id") * 2 + 1).alias("hi"))
    assert sorted(map(tuple, ends.collect())) == sorted(map(tuple, stream.running_degrees(batch).collect()))


def test_late_rows_are_counted(spark, tmp_path):
    """A second file with events before the watermark: they are dropped, and counted."""
    for k, stamps in enumerate((["2024-01-01 10:00:00", "2024-01-01 12:00:00"], ["2024-01-01 12:01:00"], ["2024-01-01 08:00:00", "2024-01-01 08:21:00", "2024-01-01 12:05:00"])):
        rows = spark.createDataFrame([(x,) for x in stamps], "ts string").select(F.col("ts").cast("timestamp").alias("ts"))
        rows.coalesce(1).write.parquet(f"{tmp_path}/in/k={k}")
    events = spark.readStream.schema("ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*").withWatermark("ts", "10 minutes")
    assert stream.late_rows(events.groupBy(F.window("ts", "5 minutes")).count()) == 2


def test_sql_face(spark, lines):
    relational.register_sql(spark, {"edges_view": lines})
    assert spark.sql("SELECT count(*) FROM edges_view").head()[0] == lines.count()
    rows = spark.sql("SELECT * FROM block_plan(TABLE(SELECT 'g' AS graph, 3L AS degree, 8L AS n, 0.25D AS c, 1L AS first_node, 0L AS n_above) PARTITION BY (graph) ORDER BY (degree), 1.0D, 'log', true, 'split')").collect()
    assert {r.kind for r in rows} == {"group", "degree"}


def test_registered_eigenvalues(spark, data):
    e = [(r.lo, r.hi) for r in graphs.doc_line(spark, data).collect()]
    at = {v: i for i, v in enumerate(sorted({x for r in e for x in r}))}
    a = np.zeros((len(at), len(at)))
    for x, y in e:
        a[at[x], at[y]] = a[at[y], at[x]] = 1
    want = sorted(np.abs(np.linalg.eigvalsh(a)), reverse=True)[:50]
    got = sorted(catalog.QUERIES["eigenvalues_doc_line"](spark, data).collect(), key=lambda r: r.rank)
    assert len(got) == 50 and np.allclose(np.abs([r.value for r in got]), want, atol=1e-3)
