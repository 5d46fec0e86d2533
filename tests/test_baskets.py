"""Graphs of baskets: packed pairs give the counts of brute force, and no table of edges is made."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from affinity_graph import catalog
from affinity_graph.operators import baskets, profile
from affinity_graph.sources import graphs


@pytest.mark.parametrize("ranges", [1, 2, 9])
def test_baskets_equal_brute_force(ranges, spark):
    """Hubs, repeated rows, groups of one, nulls, ids at both ends of bigint, and blocks far smaller than a group's pairs."""
    r = random.Random(7)
    far = [-(1 << 63), (1 << 63) - 1]
    rows = [(k, r.choice(far + list(range(-40, 300, 7)))) for k in far + list(range(150)) for _ in range(r.randrange(1, 6))] + [(k, 5) for k in range(0, 150, 2)]
    rows += [(1000, v) for v in range(0, 400, 3)] + [(7, None), (None, 7), (None, 14), (2000, 9999)] + [(1000, 3)] * 3
    groups = {}
    for k, v in rows:
        if None not in (k, v):
            groups.setdefault(k, set()).add(v)
    pairs = {p for g in groups.values() for p in itertools.combinations(sorted(g), 2)}
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    want = sorted((len(n), sum(b in near[a] for a, b in itertools.combinations(n, 2))) for n in near.values())
    got = baskets.closed_at_nodes(spark.createDataFrame(rows, "key long, v long").repartition(3), ranges, most=50).collect()
    assert len({x.v for x in got}) == len(got) and sorted((x.degree, x.closed) for x in got) == want


def test_baskets_without_edges(spark):
    for rows in ([], [(1, 1), (1, 1), (2, 3), (None, 1)]):
        assert baskets.closed_at_nodes(spark.createDataFrame(rows, "key long, v long")).collect() == []


@pytest.mark.parametrize("name", ["plan_degree_part_basket", "plan_group_part_basket", "summary_part_basket"])
def test_baskets_make_no_table_of_edges(name, spark, data, same, monkeypatch):
    def made(*a):
        raise AssertionError("edges were made")

    monkeypatch.setitem(graphs.BUILDERS, "part_basket", made)
    same(catalog.QUERIES[name](spark, data), catalog.ORACLES[name])


def test_baskets_and_edges_agree(spark, data):
    d = data.replace("sf0.001", "sf0.01")
    by = profile.clustered(profile.shared_closed(baskets.closed_at_nodes(graphs.part_basket_members(spark, d), 5)))
    other = profile.clustering_by_degree(graphs.part_basket(spark, d))
    cols = ["degree", "n", "closed", "wedges", "c", F.round("c_mean", 9)]
    assert sorted(by.select(cols).collect()) == sorted(other.select(cols).collect())


def _exchanged(spark, df):
    """Bytes that a query's exchanges write."""
    sc, jvm = spark.sparkContext, spark.sparkContext._jvm

    def total():
        sc._jsc.sc().listenerBus().waitUntilEmpty()
        stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
        return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))

    before = total()
    df.collect()
    return total() - before


def test_lists_are_written_once_whatever_the_ranges(spark):
    """Members drawn at random, so that a list has heads in all ranges: many ranges write less than twice what few do (before: five times)."""
    r = random.Random(3)
    rows = spark.createDataFrame([(k, v) for k in range(20_000) for v in r.sample(range(4000), 5)], "key long, v long").localCheckpoint()
    few, many = (_exchanged(spark, baskets.closed_at_nodes(rows, n)) for n in (2, 16))
    assert many < 2 * few
    plan = baskets.closed_at_nodes(rows, 16)
    plan.collect()
    shown = plan._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    assert "ReusedExchange" in shown and "CartesianProduct" in shown
    assert shown.count("MapInArrow") == 6  # one for the lists, though both sides of the product read them
