import math

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from affinity_graph.operators import generate, ideal, measures
from affinity_graph.plans import block_plan as bp
from affinity_graph.sources.graphs import FIXTURE73, fixture73


def scanned(profile, beta=1.0, weight="log", last="split"):
    """The scan without Spark: degree rows and group rows."""
    scan, rows = bp.BlockPlanScan(), []
    order = sorted(profile, key=lambda r: (r[0] == 1, r[0]))
    first = 1
    for d, n, c in order:
        above = sum(m for e, m, _ in profile if e > d)
        rows += scan.eval({"graph": "g", "degree": d, "n": n, "c": c, "n_above": above, "first_node": first}, beta, weight, True, last)
        first += n
    return [r for r in rows if r[1] == "degree"], [r for r in rows if r[1] == "group"]


profiles = st.dictionaries(st.integers(1, 12), st.tuples(st.integers(1, 30), st.floats(0, 1)), min_size=1, max_size=8).map(lambda d: [(k, n, c if k > 1 else 0.0) for k, (n, c) in d.items()])


def test_golden_plan(spark):
    plan = bp.build_plan(fixture73(spark))
    got = {r.degree: (r.first_node, r.n_fill, r.n - r.n_fill, round(r.w_fill, 4), round(r.w_bulk, 4)) for r in plan.degree.collect()}
    assert got == {
        2: (1, 0, 20, 0, 1.9517), 3: (21, 1, 9, 0.5976, 1.9115), 4: (31, 3, 3, 2.1372, 1.1008), 5: (37, 2, 2, 1.7338, 1.1164),
        6: (41, 3, 0, 3.1746, 0), 7: (44, 1, 1, 1.5582, 2.7972), 8: (46, 1, 0, 3.2972, 0), 9: (47, 1, 0, 3.7972, 0), 1: (48, 26, 0, 13, 0),
    }
    groups = [(r.g, r.degree, r.first_node, r.blocks, r.block_size, round(r.w, 4)) for r in plan.group.orderBy("g").collect()]
    assert groups == [(1, 2, 1, 7, 3, 48.8678), (2, 3, 22, 3, 4, 35.186), (3, 4, 34, 1, 5, 16.9575), (4, 5, 39, 1, 6, 22.4897), (5, 7, 45, 1, 3, 3.6401)]
    assert plan.expected_edges().head().edges == pytest.approx(sum(d * n for d, n in FIXTURE73.items()) / 2)


@settings(max_examples=200, deadline=None)
@given(profiles)
def test_invariants(profile):
    degrees, groups = scanned(profile)
    high = sum(n for d, n, _ in profile if d > 1)
    covered = sorted(v for g in groups for v in range(g[3], g[3] + g[9] * g[10]))
    assert covered == list(range(1, high + 1))  # every node of degree 2 and more, once
    assert all(r[6] >= -1e-9 and r[7] >= -1e-9 and 0 <= r[5] <= r[4] for r in degrees)
    local = sum(g[9] * g[11] * g[10] * (g[10] - 1) / 2 for g in groups)
    far = sum(r[6] + r[7] for r in degrees)
    assert local + far == pytest.approx(sum(d * n for d, n, _ in profile) / 2)
    assert all(math.isfinite(g[12]) for g in groups)


@settings(max_examples=100, deadline=None)
@given(profiles)
def test_scan_equals_node_by_node(profile):
    excess, blocks = bp.naive_plan(profile)
    degrees, groups = scanned(profile)
    assert [(g[3] + k * g[10], g[10], g[2]) for g in groups for k in range(g[9])] == blocks
    assert {r[2]: r[6] + r[7] for r in degrees} == pytest.approx({d: x[1] for d, x in excess.items()})


def test_last_group_policies():
    profile = [(6, 37, 0.1)]
    with pytest.raises(ValueError):
        scanned(profile, last="strict")
    _, groups = scanned(profile)
    assert [(g[9], g[10]) for g in groups] == [(5, 7), (1, 2)]


def test_weights():
    assert bp.log_weight(45, 0.5) == pytest.approx(31.1916, abs=1e-4)
    for u in (10, 100, 10_000, 1_000_000):
        for rho in (0.1, 0.5, 0.9):
            assert abs(bp.harmonic_weight(u, rho) - bp.log_weight(u, rho)) < 5
    assert bp.harmonic_weight(45, 1.0) < 250


def test_blow_up_leaves_weights():
    one, ten = scanned([(1, 9, 0.0), (3, 5, 0.2)], 1.0), scanned([(1, 9, 0.0), (3, 5, 0.2)], 2.5)
    assert one[1] == ten[1] and [r[6] for r in one[0]] == [r[6] for r in ten[0]]
    assert [r[5] for r in ten[0] if r[2] == 1] == [23]


def test_empty_and_degree_one_only(spark):
    empty = bp.build_plan(spark.createDataFrame([], "graph string, degree long, n long, c double"))
    assert empty.totals() == (0.0, 0.0) and generate.dedup(generate.generate(empty)).count() == 0
    lone = bp.build_plan(spark.createDataFrame([("g", 1, 10, 0.0)], "graph string, degree long, n long, c double"))
    assert lone.totals() == (0.0, 5.0)


def test_log_bins():
    assert measures.log_bin_starts(1.5, 2955) == [1, 2, 4, 6, 10, 15, 22, 34, 51, 76, 115, 172, 259, 389, 583, 875, 1313, 1970, 2955]


@pytest.mark.parametrize(("kind", "davg", "dmax", "p", "want"), [("dpl", 16, 10**6, None, (1.911,)), ("dpl", 64, 10**5, None, (1.668,)), ("dgln", 16, 10**6, 4.14e-26, (1.988, 2.079)), ("dgln", 64, 10**5, 8.35e-12, (2.171, 1.877))])
def test_fits(kind, davg, dmax, p, want):
    s = ideal.fit_degrees(kind, davg, dmax, p)
    assert ((s.gamma,) if kind == "dpl" else (s.alpha, s.delta)) == pytest.approx(want, rel=2e-3)


def test_scaling_series():
    assert ideal.scaling_series(1_000_000, 50_000, 3) == [(1_000_000, 50_000), (2_000_000, 70_711), (4_000_000, 100_000)]
