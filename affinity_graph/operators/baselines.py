"""Models to compare with: Chung-Lu (fast, blown up, all pairs), stochastic Kronecker (plain, noisy), Erdos-Renyi."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..functions import rng
from ..functions.rng import below, uniform
from .discrete import cumulative, draw
from .generate import EDGES_PER_TASK, HITS, STEPS, edge_ids, edge_total
from .profile import numbered

INITIATOR = (0.57, 0.19, 0.19, 0.05)


def _classes(profile: DataFrame, beta: float) -> DataFrame:
    """(degree, pool, first_node, w): a degree's nodes, the pool of degree 1 blown up and numbered last, and its weight."""
    pool = F.when(F.col("degree") == 1, F.floor(F.col("n") * beta + 0.5)).otherwise(F.col("n"))
    order = F.when(F.col("degree") == 1, F.lit(1 << 62)).otherwise(F.col("degree"))
    rows = profile.where("degree >= 1 AND n > 0").select("degree", pool.cast("bigint").alias("pool"), order.alias("position"), (F.col("degree").cast("double") * F.col("n")).alias("w"))
    before = Window.orderBy("position").rowsBetween(Window.unboundedPreceding, -1)
    return rows.withColumn("first_node", F.coalesce(F.sum("pool").over(before), F.lit(0)) + 1)


def chung_lu(profile: DataFrame, beta: float = 1.0, seed: int = 1, kind: str = "fast", method: str = "guide", edges_per_task: int = EDGES_PER_TASK) -> DataFrame:
    """m edges with both ends drawn in proportion to degree (degrees need not be whole): degree class, then a member of its pool."""
    classes = _classes(profile, beta)
    m = edge_total((classes.agg(F.sum("w")).head()[0] or 0.0) / 2)
    dist = cumulative(classes, "degree", "w", ("first_node", "pool"))
    out = edge_ids(profile.sparkSession, m, edges_per_task)
    for name, one, two in (("a", rng.DEGREE_A, rng.MEMBER_A), ("b", rng.DEGREE_B, rng.MEMBER_B)):
        keep = out.columns
        out = draw(out, uniform(seed, "edge_id", one, kind), dist, method)
        out = out.select(*keep, (F.col("first_node") + below(uniform(seed, "edge_id", two, kind), F.col("pool"))).alias(name))
    return out.select("edge_id", F.lit(2).cast("tinyint").alias("phase"), "a", "b")


def _pairs(n: int, spark: SparkSession) -> DataFrame:
    """All pairs a < b of 0..n-1 as codes, unranked arithmetically; for graphs whose n (n - 1) / 2 pairs can be looked at."""
    total = n * (n - 1) // 2
    codes = spark.range(0, total, 1, max(1, math.ceil(total / EDGES_PER_TASK)))
    return _unranked(codes.withColumnRenamed("id", "code"))


def _unranked(codes: DataFrame) -> DataFrame:
    hi = F.floor((F.sqrt(F.lit(8.0) * F.col("code") + 1) + 1) / 2)
    codes = codes.withColumn("h0", hi)
    hi = F.when(F.expr("h0 * (h0 - 1) div 2 > code"), F.col("h0") - 1).when(F.expr("(h0 + 1) * h0 div 2 <= code"), F.col("h0") + 1).otherwise(F.col("h0"))
    return codes.withColumn("hi", hi).withColumn("lo", F.expr("code - hi * (hi - 1) div 2")).select("code", "lo", "hi")


TARGETS = 32_768


def _likely(seed: int, stubs: float):
    """Blocks of nodes x and of nodes y to the pairs x < y whose uniform may be below their probability, judged by 32 of its 52 bits."""

    def toss(batches):
        import numpy as np
        import pyarrow as pa

        from ..functions.md5 import Tails

        room = [np.empty(TARGETS, np.uint32) for _ in range(7)]
        for batch in batches:
            for row in batch.to_pylist():
                y, dy = np.array(row["ys"], np.int64), np.array(row["dys"], np.int64)
                texts = [str(v) for v in row["ys"]]
                length = np.array([len(t) for t in texts])
                same = []
                for n in np.unique(length):
                    of = np.flatnonzero(length == n)
                    of = of[np.argsort(y[of])]
                    same.append((y[of], dy[of], dy[of].astype(np.float64), Tails([f"{texts[k]}|{rng.TRIAL}".encode() for k in of])))
                for x, dx in zip(row["xs"], row["dxs"]):
                    for v, d, real, tails in same:
                        i = int(np.searchsorted(v, x, "right"))
                        for i in range(i, len(v), TARGETS):
                            j = min(i + TARGETS, len(v))
                            first = tails.first_words(f"{seed}|{x}-".encode(), i, j, room)
                            hit = i + np.flatnonzero(first <= real[i:j] * (dx * (1 + 1e-9) * 2.0**32 / stubs))
                            if len(hit):
                                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(hit), x)), pa.array(np.full(len(hit), dx)), pa.array(v[hit]), pa.array(d[hit])], ["x", "dx", "y", "dy"])

    return toss


def _likely_pairs(ranked: DataFrame, n: int, stubs: float, seed: int) -> DataFrame:
    """(x, dx, y, dy) by ``_likely``: a task for a block of x and one of y; ``ranked`` has places from 0 in the order of v."""
    width = ranked.sparkSession.sparkContext.defaultParallelism * 16
    span = max(64, min(TARGETS, n * n // (width * TARGETS)))  # x of a task
    here, there = F.expr(f"at div {span}"), F.expr(f"at div {TARGETS}")
    block = lambda by, c: ranked.groupBy(by.alias(c)).agg(F.sort_array(F.collect_list(F.struct("v", "degree"))).alias("m")).select(c, F.col("m.v").alias(f"{c}s"), F.col("m.degree").alias(f"d{c}s"))
    # The first y that an x can meet is in its own block of y.
    xs = block(here, "x").withColumn("y", F.explode(F.sequence(F.expr(f"x * {span} div {TARGETS}"), F.lit((n - 1) // TARGETS).cast("bigint"))))
    tasks = (-(-n // span)) * (-(-n // TARGETS))
    units = xs.join(block(there, "y"), "y").withColumn("unit", (F.col("x") * (-(-n // TARGETS)) + F.col("y")).cast("int"))
    return units.repartitionById(max(1, min(tasks, 100_000)), F.pmod("unit", F.lit(100_000))).select("xs", "dxs", "ys", "dys").mapInArrow(_likely(seed, stubs), "x long, dx long, y long, dy long")


def chung_lu_pairs(nodes: DataFrame, seed: int = 1, kind: str = "fast") -> DataFrame:
    """A coin for every pair with probability d_i d_j / 2m, at most 1. Quadratic by definition: nodes are numbered and pairs coded.

    Portable coins are tossed by blocks, many md5 at a time up to their first word; the few pairs that this leaves get the whole coin.
    """
    n, stubs = nodes.agg(F.count(F.lit(1)), F.sum("degree")).head()
    if kind == "portable" and n:
        pairs = _likely_pairs(numbered(nodes.select("v", "degree"), "v").select("v", "degree", (F.col("position") - 1).alias("at")), n, float(stubs), seed)
    else:
        ranked = nodes.select("v", "degree", (F.row_number().over(Window.orderBy("v")) - 1).cast("bigint").alias("at"))
        pairs = _pairs(n, nodes.sparkSession)
        pairs = pairs.join(ranked.select(F.col("at").alias("lo"), F.col("v").alias("x"), F.col("degree").alias("dx")), "lo").join(ranked.select(F.col("at").alias("hi"), F.col("v").alias("y"), F.col("degree").alias("dy")), "hi")
    p = F.least(F.lit(1.0), F.col("dx") * F.col("dy") / F.lit(float(stubs or 1)))
    id_ = F.concat_ws("-", "x", "y")
    return pairs.where(uniform(seed, id_, rng.TRIAL, kind) < p).select(F.col("x").alias("lo"), F.col("y").alias("hi"))


def chung_lu_expected(profile: DataFrame) -> DataFrame:
    """(degree_a, degree_b, expected): expected edges between degree classes, as m draws of pairs give them.

    A row per pair of distinct degrees, which is the result's own size; give degrees in log bins where there are many.
    """
    p = profile.select(F.col("degree").alias("degree_a"), F.col("n").alias("na"))
    q = profile.select(F.col("degree").alias("degree_b"), F.col("n").alias("nb"))
    stubs = profile.agg(F.sum(F.col("degree") * F.col("n")).cast("double").alias("stubs"))
    both = p.join(q, F.col("degree_a") <= F.col("degree_b")).join(F.broadcast(stubs))  # distinct degrees only
    share = F.col("degree_a") * F.col("na") * F.col("degree_b") * F.col("nb") / F.col("stubs") / 2
    return both.select("degree_a", "degree_b", F.round(F.when(F.col("degree_a") == F.col("degree_b"), share).otherwise(share * 2), 6).alias("expected"))


def quadrants(initiator: tuple[float, ...], noise: float, seed: int, level: int) -> list[float]:
    """Shares of the four quadrants on one level."""
    p = [x / sum(initiator) for x in initiator]
    if noise:
        shift = noise * (2 * ((seed * 2654435761 + level * 40503) % 65536) / 65536 - 1)
        spread = p[0] + p[3]
        p = [p[0] - 2 * shift * p[0] / spread, p[1] + shift, p[2] + shift, p[3] - 2 * shift * p[3] / spread]
    return p


def kronecker(spark: SparkSession, levels: int, edges: int, initiator: tuple[float, float, float, float] = INITIATOR, seed: int = 1, noise: float = 0.0, kind: str = "fast", edges_per_task: int = EDGES_PER_TASK) -> DataFrame:
    """``edges`` draws of a quadrant on each of ``levels`` levels; ``noise`` perturbs the initiator level by level, which evens degrees out."""
    a = b = F.lit(0).cast("bigint")
    for level in range(levels):
        p = quadrants(initiator, noise, seed, level)
        u = uniform(seed, "edge_id", rng.LEVEL + level, kind)
        down = u >= F.lit(p[0] + p[1])
        right = ((u >= F.lit(p[0])) & ~down) | (u >= F.lit(p[0] + p[1] + p[2]))
        a, b = a * 2 + down.cast("bigint"), b * 2 + right.cast("bigint")
    return edge_ids(spark, edges, edges_per_task).select("edge_id", F.lit(2).cast("tinyint").alias("phase"), a.alias("a"), b.alias("b"))


def erdos_renyi(spark: SparkSession, n: int, rho: float, method: str = "skip", seed: int = 1, kind: str = "fast") -> DataFrame:
    """Each pair of 1..n with probability ``rho``: a coin per pair, or geometric gaps inside tiles of pair codes for sparse graphs."""
    if method == "pairs":
        p = _pairs(n, spark)
        return p.where(uniform(seed, "code", rng.TRIAL, kind) < F.lit(rho)).select((F.col("lo") + 1).alias("lo"), (F.col("hi") + 1).alias("hi"))
    total, keep = n * (n - 1) // 2, F.lit(min(rho, 1 - 1e-12))
    span = math.ceil(HITS / rho) if rho > 0 else max(1, total)
    tiles = spark.range(0, -(-total // span), 1, max(spark.sparkContext.defaultParallelism, math.ceil(total * rho / EDGES_PER_TASK))).withColumnRenamed("id", "t")

    def step(acc: Column, s: Column) -> Column:
        gap = F.floor(F.log(F.lit(1.0) - uniform(seed, F.concat_ws("-", "t", s), rng.SKIP, kind)) / F.log(F.lit(1.0) - keep)) + 1
        at = acc["at"] + gap
        return F.struct(at.alias("at"), F.when(at < span, F.array_append(acc["codes"], at)).otherwise(acc["codes"]).alias("codes"))

    zero = F.struct(F.lit(-1).cast("bigint").alias("at"), F.array().cast("array<bigint>").alias("codes"))
    codes = tiles.select("t", F.explode(F.aggregate(F.sequence(F.lit(1), F.lit(STEPS)), zero, step, lambda acc: acc["codes"])).alias("at"))
    codes = codes.select((F.col("t") * span + F.col("at")).alias("code")).where(F.col("code") < total)
    return _unranked(codes).select((F.col("lo") + 1).alias("lo"), (F.col("hi") + 1).alias("hi"))
