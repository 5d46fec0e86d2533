"""Graphs of days looked at slice by slice: equal results to brute force, and no pair of families joined."""

import datetime
import itertools
import random
from collections import Counter

import pytest

from affinity_graph import catalog
from affinity_graph.operators import families, profile, slices

DAYS = [datetime.date(1995, 1, 1) + datetime.timedelta(n) for n in (0, 1, 5, 40, 41, 42, 900, 20_000)]


def crowd(alone: bool):
    """Nodes with days, some of them with equal sets; without many equal ones if ``alone``."""
    r = random.Random(11)
    sets = [sorted(r.sample(DAYS, r.randint(1, 5))) for _ in range(150 if alone else 12)]
    return {v * 3 - 50: sets[v] if alone else r.choice(sets) for v in range(150)} | {1000: [datetime.date(2001, 1, 1)]}


@pytest.mark.parametrize("small", [False, True])
@pytest.mark.parametrize("alone", [False, True])
def test_days_equal_brute_force(spark, monkeypatch, small, alone):
    if small:
        monkeypatch.setattr(slices, "LEAST", 40)
        monkeypatch.setattr(slices, "MOST", 100)
        monkeypatch.setattr(slices, "EXCESS", 50)
        monkeypatch.setattr(slices, "RUN", 7)
        monkeypatch.setattr(families, "PIECE", 4)
    monkeypatch.setattr(families, "links", lambda fam: pytest.fail("pairs of families were joined"))
    has = crowd(alone)
    members = spark.createDataFrame([(d, v) for v, ds in has.items() for d in ds] + [(None, 3), (DAYS[0], None)], "day date, v long")
    want = {(x, y) for x, y in itertools.combinations(sorted(has), 2) if set(has[x]) & set(has[y])}
    fam = families.families(members, "day")
    got = [tuple(x) for x in families.pairs(fam).collect()]
    assert len(got) == len(set(got)) and set(got) == want
    edges = spark.createDataFrame(sorted(want), "lo long, hi long")
    assert sorted(families.degree_hist(fam).collect()) == sorted(profile.degree_hist(profile.degrees(edges)).collect())
    by = sorted(families.clustering_by_degree(fam).collect())
    assert [tuple(x)[:5] for x in by] == [tuple(x)[:5] for x in sorted(profile.clustering_by_degree(edges).collect())]
    label = {v: None if v % 7 == 0 else v % 4 - 1 for v in has if v % 11}
    attribute = spark.createDataFrame(list(label.items()), "v long, x int")
    count = Counter(tuple(sorted((label[a], label[b]), key=lambda c: (c is None, c))) for a, b in want if a in label and b in label)
    got = families.count_by(fam, attribute, "x", "a", "b").collect()
    # least and greatest pass over nulls: a pair with one null has the other value twice
    folded = Counter()
    for (a, b), n in count.items():
        folded[(a, a) if b is None else (a, b)] += n
    assert {(x.a, x.b): x.edges for x in got} == dict(folded) and len(got) == len(folded)


@pytest.mark.parametrize("name", ["degree_hist_cust_day", "edges_cust_day", "hashed_sample", "nation_edges", "clustering_by_degree_cust_day", "log_binned_cust_day", "profile_gcc_cust_day", "summary_cust_day"])
def test_no_pair_of_families_is_joined(name, spark, data, same, monkeypatch):
    monkeypatch.setattr(families, "links", lambda fam: pytest.fail("pairs of families were joined"))
    same(catalog.QUERIES[name](spark, data), catalog.ORACLES[name])
