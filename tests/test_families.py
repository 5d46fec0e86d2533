"""Graphs of groups: large groups without their pairs, triangles without exchanged wedges, and equal results to brute force."""

import itertools
import random
from math import comb

import pytest
from pyspark.sql import functions as F

from affinity_graph import catalog
from affinity_graph.operators import families, profile

MANY = 20_000  # one group of so many nodes has 2e8 pairs and 1.3e12 triangles


@pytest.fixture(scope="module")
def crowd(spark, tmp_path_factory):
    """A day, and an hour with equal properties, that MANY have in common; node 0 also meets node MANY, and MANY + 1 is alone."""
    d = str(tmp_path_factory.mktemp("crowd"))
    rows = spark.range(MANY).select("id", F.lit(1).alias("day")).unionByName(spark.createDataFrame([(0, 2), (MANY, 2), (MANY + 1, 3)], "id long, day int"))
    at = F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_interval(0, 0, 0, day)")
    rows.select(F.monotonically_increasing_id().alias("o_orderkey"), F.col("id").alias("o_custkey"), at.alias("o_orderdate")).write.parquet(f"{d}/orders.parquet")
    rows.select(F.monotonically_increasing_id().alias("event_id"), at.alias("ts"), F.col("id").alias("user_id"), F.lit("view").alias("event_type"), F.lit(1.0).alias("value"), F.lit('{"k": 1}').alias("props")).write.parquet(f"{d}/events.parquet")
    spark.range(MANY + 3).select(F.col("id").alias("c_custkey"), (F.col("id") % 2).cast("int").alias("c_nationkey")).write.parquet(f"{d}/customer.parquet")
    return d


def ask(name, spark, d):
    return [tuple(r) for r in catalog.QUERIES[name](spark, d).collect()]


def by_degree():
    c = comb(MANY - 1, 2)
    share = round(c / comb(MANY, 2), 6)
    return [(1, 1, 0, 0, 0.0, 0.0), (MANY - 1, MANY - 1, (MANY - 1) * c, (MANY - 1) * c, 1.0, 1.0), (MANY, 1, c, comb(MANY, 2), share, share)]


@pytest.mark.parametrize("g", ["cust_day", "user_props"])
def test_clustering_of_a_crowd(g, spark, crowd):
    assert sorted(ask(f"clustering_by_degree_{g}", spark, crowd)) == by_degree()


@pytest.mark.parametrize("weighted", [False, True])
def test_closed_wedges_equal_brute_force(weighted, spark):
    r = random.Random(3)
    pairs = {tuple(sorted(r.sample(range(0, 400, 7), 2))) for _ in range(700)} | {(0, v) for v in range(7, 400, 7)}
    size = {v: r.choice([1, 2, 300]) if weighted else 1 for v in range(0, 400, 7)}
    near = {v: {a + b - v for a, b in pairs if v in (a, b)} for v in size}
    want = {v: sum(size[a] * size[b] for a, b in itertools.combinations(sorted(near[v]), 2) if b in near[a]) for v in size}
    nodes = spark.createDataFrame([(v, len(near[v]), size[v]) for v in size], "v long, degree long, weight long")
    for ranges in (1, 2, 9):
        got = profile.closed_wedges(spark.createDataFrame(sorted(pairs), "lo long, hi long"), nodes if weighted else nodes.drop("weight"), ranges).collect()
        assert {x.v: x.closed for x in got} == {v: n for v, n in want.items() if n}


def test_families_equal_brute_force(spark):
    r = random.Random(5)
    rows = [(k, v) for v in range(90) for k in [r.choice([("a", 1), ("a", 2), ("b", 3), ("b", None)])] + ([("c", r.randrange(9))] if v % 4 == 0 else [])] + [(("a", 1), None), (("z", 0), 200)]
    members = spark.createDataFrame([(*k, v) for k, v in rows], "k string, h int, v long")
    groups = {}
    for k, v in rows:
        if v is not None and k[1] is not None:
            groups.setdefault(k, set()).add(v)
    want = {p for g in groups.values() for p in itertools.combinations(sorted(g), 2)}
    fam = families.families(members, "k", "h")
    got = [tuple(x) for x in families.pairs(fam).collect()]
    assert len(got) == len(set(got)) and set(got) == want
    edges = spark.createDataFrame(sorted(want), "lo long, hi long")
    assert sorted(families.degree_hist(fam).collect()) == sorted(profile.degree_hist(profile.degrees(edges)).collect())
    assert [tuple(x)[:5] for x in sorted(families.clustering_by_degree(fam).collect())] == [tuple(x)[:5] for x in sorted(profile.clustering_by_degree(edges).collect())]


@pytest.mark.parametrize("g", ["cust_day", "user_props"])
def test_summary_of_a_crowd(g, spark, crowd):
    edges, nodes = comb(MANY, 2) + 1, MANY + 1
    wedges = (MANY - 1) * comb(MANY - 1, 2) + comb(MANY, 2)
    assert ask(f"summary_{g}", spark, crowd) == [(g, "original", nodes, edges, MANY, round(2 * edges / nodes, 6), wedges, comb(MANY, 3), round(3 * comb(MANY, 3) / wedges, 6))]


@pytest.mark.parametrize("g", ["cust_day", "user_props"])
def test_log_bins_of_a_crowd(g, spark, crowd):
    first, *rest = sorted(ask(f"log_binned_{g}", spark, crowd))
    assert first[3:] == (1, 0.0) and [r[3] for r in rest] == [MANY]
    assert rest[0][4] == pytest.approx((1 + comb(MANY - 1, 2) / comb(MANY, 2)) / 2, abs=1e-6)


@pytest.mark.parametrize("g", ["cust_day", "user_props"])
def test_gcc_of_a_crowd(g, spark, crowd):
    wedges = (MANY - 1) * comb(MANY - 1, 2) + comb(MANY, 2)
    assert ask(f"profile_gcc_{g}", spark, crowd) == [(g, round(3 * comb(MANY, 3) / wedges, 6))]


@pytest.mark.parametrize("g", ["cust_day", "user_props"])
def test_degrees_of_a_crowd(g, spark, crowd):
    assert sorted(ask(f"degree_hist_{g}", spark, crowd)) == [(1, 1), (MANY - 1, MANY - 1), (MANY, 1)]


def test_isolated_beside_a_crowd(spark, crowd):
    assert sorted(ask("isolated_customers", spark, crowd)) == [(MANY + 1, 1), (MANY + 2, 0)]


def test_nations_of_a_crowd(spark, crowd):
    half = MANY // 2
    assert sorted(ask("nation_edges", spark, crowd)) == [(0, 0, comb(half, 2) + 1), (0, 1, half * half), (1, 1, comb(half, 2))]


def test_pairs_need_no_exchange_of_pairs(spark, crowd):
    assert catalog.QUERIES["edges_cust_day"](spark, crowd).where("hi >= 10000 AND lo < 5").count() == 5 * (MANY - 10_000) + 1


def test_sample_of_pairs_needs_no_exchange_of_pairs(spark, crowd):
    from affinity_graph.sources import graphs

    plan = catalog.QUERIES["hashed_sample"](spark, crowd)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate explode" in plan and "Aggregate" not in plan
    assert graphs.cust_day(spark, crowd).where("hi = 20000").collect() == [(0, MANY)]


def test_given_edges_in_a_crowd(spark, crowd):
    from affinity_graph.sources import graphs

    given = spark.createDataFrame([(0, MANY), (5, MANY - 1), (5, MANY), (0, MANY + 1)], "lo long, hi long")
    got = families.among(given, graphs.user_props_members(spark, crowd), "event_type", "props", "hour")
    assert sorted(map(tuple, got.collect())) == [(0, MANY), (5, MANY - 1)]


@pytest.mark.parametrize("name", ["coupon_weight", "coupon_harmonic", "coupon_trials", "coupon_trials_fixed", "erdos_renyi_pairs", "erdos_renyi_skip", "fit_grid_dgln", "fit_grid_dpl", "ideal_check", "dgln_study", "draws_per_edge", "blocks_fixture73"])
def test_moved_queries_read_tables(name, spark, data, same, monkeypatch):
    read = []
    from affinity_graph.sources import graphs

    for module in (catalog, graphs):
        monkeypatch.setattr(module, "table", lambda s, d, t, real=module.table: read.append(t) or real(s, d, t))
    df = catalog.QUERIES[name](spark, data)
    assert read
    same(df, catalog.ORACLES[name])


@pytest.mark.parametrize("name", ["plan_degree_part_basket", "plan_group_part_basket", "summary_part_basket"])
def test_baskets_exchange_no_wedges(name, spark, data, monkeypatch):
    def wedges(edges):
        raise AssertionError("wedges were joined")

    monkeypatch.setattr(profile, "triangles", wedges)
    assert catalog.QUERIES[name](spark, data).count() > 0
