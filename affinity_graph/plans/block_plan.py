"""The block plan: a profile condensed to a few numbers per distinct degree and per group of equal blocks.

Nodes are numbered by degree, degree 1 last. Blocks are runs of consecutive nodes: one of lowest degree d has d + 1 of them. A
degree's nodes first fill the block left open by lower degrees (fillers), the others (bulk) open a group of blocks of their own.
Degrees are passed once in ascending order, with the slots still open and the local degree in them as only state, which a
table function carries per graph; many graphs are planned side by side. Only distinct degrees are kept.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window
from pyspark.sql.functions import udtf

from ..sources.tables import stored

SCAN_SCHEMA = (
    "graph string, kind string, degree bigint, first_node bigint, n bigint, n_fill bigint, w_fill double, w_bulk double,"
    " g int, blocks bigint, block_size bigint, rho double, weight double"
)


def log_weight(pairs: float, rho: float) -> float:
    """Draws from ``pairs`` equally likely ones after which a share ``rho`` has been seen, in the limit."""
    return -pairs * math.log1p(-rho) if rho < 1 else math.inf


def harmonic_weight(pairs: int, rho: float) -> float:
    """The same expectation exactly, as a sum of waiting times; finite at a share of 1."""
    seen = round(pairs * rho)
    return pairs * (_harmonic(pairs) - _harmonic(pairs - seen))


def _harmonic(n: int) -> float:
    if n < 256:
        return sum(1.0 / i for i in range(1, n + 1))
    return math.log(n) + 0.5772156649015329 + 1 / (2 * n) - 1 / (12 * n**2) + 1 / (120 * n**4)


def _density(c: float, pairs: int, cap: bool) -> float:
    rho = math.sqrt(min(1.0, max(0.0, c)))
    if pairs < 1:
        return 0.0
    return 1 - 1 / (2 * pairs) if cap and rho >= 1 else rho  # a complete block would take infinitely many draws


_WEIGHTS = {"log": log_weight, "harmonic": harmonic_weight, "plain": lambda pairs, rho: pairs * rho}


class BlockPlanScan:
    """Table function over one graph's (degree, n, c, n_above, first_node) in ascending order of degree, degree 1 last."""

    def __init__(self) -> None:
        self.slots, self.local, self.groups = 0, 0.0, 0

    def eval(self, row, beta: float, weight: str, rho_cap: bool, last_group: str) -> Iterator[tuple]:
        graph, d, n, c, above, first = row["graph"], row["degree"], row["n"], row["c"], row["n_above"], row["first_node"]
        if d < 2:
            if n:
                yield graph, "degree", d, first, n, math.floor(beta * n + 0.5), n / 2, 0.0, None, None, None, None, None
            return
        fill = min(self.slots, n)
        w_fill = fill * (d - self.local) / 2
        self.slots -= fill
        bulk, w_bulk = n - fill, 0.0
        at = first + fill
        for members, blocks, size in self._shapes(d, bulk, bulk + above, last_group):
            pairs = size * (size - 1) // 2
            rho = _density(c, pairs, rho_cap)
            self.local = (size - 1) * rho
            self.slots = blocks * size - members
            self.groups += 1
            w_bulk += members * (d - self.local) / 2
            yield graph, "group", d, at, None, None, None, None, self.groups, blocks, size, rho, blocks * _WEIGHTS[weight](pairs, rho) if pairs else 0.0
            at += blocks * size
        yield graph, "degree", d, first, n, fill, w_fill, w_bulk, None, None, None, None, None

    @staticmethod
    def _shapes(d: int, bulk: int, left: int, last_group: str) -> list[tuple[int, int, int]]:
        """Groups that ``bulk`` nodes of degree ``d`` open, ``left`` nodes being left in all: (own members, blocks, size)."""
        if not bulk:
            return []
        size = d + 1
        blocks = -(-bulk // size)
        if blocks * size <= left:
            return [(bulk, blocks, size)]
        if blocks == 1:
            return [(bulk, 1, left)]
        if last_group == "strict":
            raise ValueError(f"the last group needs {blocks} blocks of {size} nodes, and {left} nodes are left")
        whole = bulk // size
        shapes = [(whole * size, whole, size)]
        if bulk > whole * size:
            shapes.append((bulk - whole * size, 1, left - whole * size))
        return shapes


@dataclass(frozen=True)
class Plan:
    """``degree`` (graph, degree, first_node, n, n_fill, w_fill, w_bulk, w, r) and ``group`` (graph, g, degree, first_node, blocks, block_size, rho, w)."""

    degree: DataFrame
    group: DataFrame

    def totals(self) -> tuple[float, float]:
        """Weights of the local and the global phase: the only numbers that the driver reads."""
        one = self.group.agg(F.sum("w")).head()[0] or 0.0
        two = self.degree.agg(F.sum("w")).head()[0] or 0.0
        return one, two

    def cells(self) -> DataFrame:
        """Stored values: five a degree and four a group, against the bound of ten per possible degree."""
        return self.degree.agg((F.count(F.lit(1)) * 5).alias("degree_cells"), (F.coalesce(F.max("degree"), F.lit(0)) * 10).alias("bound")).join(F.broadcast(self.group.agg((F.count(F.lit(1)) * 4).alias("group_cells")))).select("degree_cells", "group_cells", "bound")

    def expected_edges(self) -> DataFrame:
        """(local, global, edges) expected after repeats have gone, without generating anything."""
        local = self.group.agg(F.coalesce(F.sum(F.col("blocks") * F.col("block_size") * (F.col("block_size") - 1) / 2 * F.col("rho")), F.lit(0.0)).alias("local"))
        far = self.degree.agg(F.coalesce(F.sum("w"), F.lit(0.0)).alias("global"))
        return local.join(F.broadcast(far)).select("local", "global", (F.col("local") + F.col("global")).alias("edges"))


def index_ranges(profile: DataFrame) -> DataFrame:
    """``profile`` with first_node (from 1; degree 1 last) and n_above (nodes of higher degree). A window per graph over its distinct degrees."""
    order = F.when(F.col("degree") == 1, F.lit((1 << 62))).otherwise(F.col("degree"))
    before = Window.partitionBy("graph").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    above = Window.partitionBy("graph").orderBy("degree").rowsBetween(1, Window.unboundedFollowing)
    out = profile.where("degree >= 1 AND n > 0")
    return out.select("*", (F.coalesce(F.sum("n").over(before), F.lit(0)) + 1).alias("first_node"), F.coalesce(F.sum("n").over(above), F.lit(0)).alias("n_above"))


def register(spark: SparkSession) -> None:
    """``block_plan(TABLE(...) PARTITION BY graph ORDER BY position, beta, weight, rho_cap, last_group)`` in SQL."""
    spark.udtf.register("block_plan", udtf(BlockPlanScan, returnType=SCAN_SCHEMA))


def build_plan(profile: DataFrame, beta: float = 1.0, rho: Column | None = None, weight: str = "log", rho_cap: bool = True, last_group: str = "split") -> Plan:
    """Plan of every graph in ``profile`` (graph, degree, n, c). ``rho``: densities by a formula of degree instead of the clustering."""
    if beta < 1:
        raise ValueError("beta is at least 1")
    if weight not in _WEIGHTS or last_group not in ("strict", "split"):
        raise ValueError(f"unknown option: {weight}, {last_group}")
    spark = profile.sparkSession
    register(spark)
    c = F.col("c").cast("double") if rho is None else rho * rho
    rows = index_ranges(profile.select("graph", F.col("degree").cast("bigint").alias("degree"), F.col("n").cast("bigint").alias("n"), c.alias("c"))).withColumn("position", F.when(F.col("degree") == 1, F.lit(1 << 62)).otherwise(F.col("degree")))
    scan = spark.sql(f"SELECT * FROM block_plan(TABLE({{rows}}) PARTITION BY (graph) ORDER BY (position), {float(beta)!r}D, '{weight}', {bool(rho_cap)}, '{last_group}')", rows=rows)
    scan = stored(scan, "plan")
    w = F.col("w_fill") + F.col("w_bulk")
    degree = scan.where("kind = 'degree'").select("graph", "degree", "first_node", "n", "n_fill", "w_fill", "w_bulk", w.alias("w"), F.when(w > 0, F.col("w_fill") / w).otherwise(0.0).alias("r"))
    group = scan.where("kind = 'group'").select("graph", "g", "degree", "first_node", "blocks", "block_size", "rho", F.col("weight").alias("w"))
    return Plan(degree, group)


def expand_nodes(plan: Plan) -> DataFrame:
    """(graph, v, degree, filler) of every node; for tests and small graphs."""
    at = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("n") - 1)).alias("k")
    return plan.degree.select("graph", "degree", "first_node", "n_fill", at).select("graph", (F.col("first_node") + F.col("k")).alias("v"), "degree", (F.col("k") < F.col("n_fill")).alias("filler"))


def expand_blocks(plan: Plan) -> DataFrame:
    """(graph, g, block, first_node, last_node, degree) of every block; for tests and small graphs."""
    b = plan.group.select("graph", "g", "degree", "first_node", "block_size", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("blocks") - 1)).alias("k"))
    first = F.col("first_node") + F.col("k") * F.col("block_size")
    return b.select("graph", "g", F.col("k").alias("block"), first.alias("first_node"), (first + F.col("block_size") - 1).alias("last_node"), "degree")


def block_of(nodes: DataFrame, plan: Plan, v: str = "v") -> DataFrame:
    """``nodes`` with g and block (null outside all blocks)."""
    from ..operators.discrete import locate

    g = plan.group.select("g", F.col("first_node").alias("f0"), (F.col("first_node") + F.col("blocks") * F.col("block_size")).alias("f1"), "block_size")
    hit = locate(nodes, v, g, "f0", "f1", "left")
    return hit.select(*nodes.columns, "g", F.expr(f"({v} - f0) div block_size").alias("block"))


def naive_plan(profile: list[tuple[int, int, float]], beta: float = 1.0) -> tuple[dict[int, list], list[tuple[int, int, int]]]:
    """Blocks node by node, as a check: ({degree: [fillers, excess]}, [(first node, size, lowest degree)]). Small graphs only."""
    nodes = [d for d, n, _ in sorted(profile) if d > 1 for _ in range(n)]
    c = {d: x for d, _, x in profile}
    excess: dict[int, list] = {d: [0, 0.0] for d, _, _ in profile}
    blocks, i = [], 0
    while i < len(nodes):
        size = min(nodes[i] + 1, len(nodes) - i)
        rho = _density(c[nodes[i]], size * (size - 1) // 2, True)
        for d in nodes[i : i + size]:
            excess[d][0] += d != nodes[i]
            excess[d][1] += (d - (size - 1) * rho) / 2
        blocks.append((i + 1, size, nodes[i]))
        i += size
    for d, n, _ in profile:
        if d == 1:
            excess[1] = [math.floor(beta * n + 0.5), n / 2]
    return excess, blocks
