from affinity_graph.workloads import experiments as ex


def test_small_comparison(spark, data):
    out = ex.small_comparison(spark, data, ("doc_line",), k=2)
    s = {r.model: r for r in out["summary"].collect()}
    assert set(s) == {"original", "block model", "chung-lu", "kronecker"} and s["block model"].gcc > s["chung-lu"].gcc
    assert out["spectrum"].count() == 8


def test_clones_and_scaling(spark, data):
    out = ex.large_clones(spark, data, ("doc_line",), k=200)
    assert out["bench"].count() == 2
    s = {r.model: r for r in out["summary"].collect()}
    assert set(s) == {"original", "block model", "chung-lu"} and abs(s["original"].gcc - s["block model"].gcc) < 0.1 < s["original"].gcc - s["chung-lu"].gcc
    rows = ex.weak_scaling(spark, 1000, 100, 2).collect()
    made = {(r.graph, r.stage): r.rows_out for r in rows}
    assert 1.6 < made["2000", "generate"] / made["1000", "generate"] < 2.6
    assert made["1000", "dedup"] < made["1000", "generate"]


def test_fits_examples_and_ablations(spark, data):
    rows = {(r.case, r.law): r for r in ex.degree_fit_cases(spark).collect()}
    assert abs(rows["A", "dgln"].davg - 16) < 0.2 and rows["A", "dgln"].p_top < 1e-20 < rows["A", "dpl"].p_top
    s = {(r.graph, r.model): r for r in ex.example_graphs(spark, 2000)["summary"].collect()}
    assert s["EX-B", "model"].davg > 8
    a = {r.variant: r for r in ex.ablations(spark, data).collect()}
    assert a["weight=plain"].gcc_rel > a["weight=log"].gcc_rel
    assert ex.coupon_experiment(spark).count() > 5


def test_largest_series_and_replots(spark, data):
    rows = ex.largest_series(spark, 4000, 316, k=300).collect()
    whole = [r for r in rows if (r.n_target or 0) > 100]
    assert len(rows) > 5 and all(abs(r.n_model - r.n_target) < 0.5 * r.n_target for r in whole)
    p = spark.createDataFrame([("g", d, 100 // d, 0.1) for d in range(1, 50)], "graph string, degree long, n long, c double")
    binned, cumulative = ex.replot(p)
    assert binned.agg({"n": "sum"}).head()[0] == sum(100 // d for d in range(1, 50)) and cumulative.orderBy("degree").head().cum_ge == 1.0
