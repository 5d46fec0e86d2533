"""Many md5 at once, and the coins of all pairs that are tossed with them."""

import hashlib
import random

import numpy as np
import pytest

from affinity_graph.functions import md5
from affinity_graph.functions.rng import TRIAL
from affinity_graph.operators import baselines


@pytest.mark.parametrize("start", ["", "1|0-", "12345|", "1|12-", "1|-9223372036854775808-"])
@pytest.mark.parametrize("length", [1, 4, 7, 23])
def test_first_words(start, length):
    r = random.Random(length)
    ends = [bytes(r.choices(b"0123456789|", k=length)) for _ in range(50)]
    got = md5.Tails(ends).first_words(start.encode(), 3, 47, [np.empty(60, np.uint32) for _ in range(7)])
    assert got.tolist() == [int(hashlib.md5(start.encode() + e).hexdigest()[:8], 16) for e in ends[3:47]]


def test_long_messages_are_refused():
    with pytest.raises(ValueError):
        md5.Tails([b"0" * 30]).first_words(b"0" * 26, 0, 1, [np.empty(1, np.uint32) for _ in range(7)])


@pytest.mark.parametrize("targets", [40, 32_768])
def test_coins_of_all_pairs(targets, spark, monkeypatch):
    """Ids of all lengths and signs, certain pairs, several blocks; no pair is made for its coin."""

    def made(*a):
        raise AssertionError("pairs were made")

    monkeypatch.setattr(baselines, "_pairs", made)
    monkeypatch.setattr(baselines, "TARGETS", targets)
    r = random.Random(2)
    v = [-(1 << 63), (1 << 63) - 1, -7, 10**18] + r.sample(range(-2000, 120_000), 140)
    nodes = {x: r.choice([1, 2, 30, 90]) for x in v}
    stubs = sum(nodes.values())
    coin = lambda x, y: int(hashlib.md5(f"3|{x}-{y}|{TRIAL}".encode()).hexdigest()[:13], 16) / 2.0**52
    want = sorted((x, y) for x in nodes for y in nodes if x < y and coin(x, y) < min(1.0, nodes[x] * nodes[y] / stubs))
    got = baselines.chung_lu_pairs(spark.createDataFrame(list(nodes.items()), "v long, degree long"), 3, "portable")
    assert sorted(map(tuple, got.collect())) == want and len(want) > 100


def test_no_nodes_no_pairs(spark):
    assert baselines.chung_lu_pairs(spark.createDataFrame([], "v long, degree long"), 3, "portable").collect() == []
