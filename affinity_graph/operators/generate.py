"""Generating edges from a block plan: each edge is drawn by itself from its id, without exchange of data.

Rows: gen_edge (edge_id, phase, a, b); phase 1 is local (inside a block), 2 global. Rows depend on the plan, the seed and the id only:
any range of ids can be made again, anywhere, with the same result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.rng import below, uniform
from ..plans.block_plan import Plan, block_of
from ..sources.tables import stored
from .discrete import _small, cumulative, draw, locate

EDGES_PER_TASK = 10_000_000


def edge_ids(spark, total: int, edges_per_task: int = EDGES_PER_TASK, start: int = 0) -> DataFrame:
    parts = max(1, math.ceil((total - start) / edges_per_task))
    return spark.range(start, total, 1, parts).withColumnRenamed("id", "edge_id")


def edge_total(weight: float, how: str = "round") -> int:
    return {"round": math.floor(weight + 0.5), "ceil": math.ceil(weight)}[how]


def group_dist(plan: Plan) -> DataFrame:
    return cumulative(plan.group.withColumn("g", F.col("g").cast("bigint")), "g", "w", ("first_node", "blocks", "block_size"))


def degree_dist(plan: Plan) -> DataFrame:
    """Degrees by their excess weight; n_fill counts the degree-1 pool with its blow-up."""
    return cumulative(plan.degree.withColumn("n_bulk", F.greatest(F.col("n") - F.col("n_fill"), F.lit(0))), "degree", "w", ("first_node", "n_fill", "n_bulk", "r"))


def local_edges(ids: DataFrame, plan: Plan, seed: int, kind: str = "fast", method: str = "guide") -> DataFrame:
    """Group by weight, block and two distinct members uniformly: the second is drawn among the others and shifted past the first."""
    u = lambda stream: uniform(seed, "edge_id", stream, kind)
    hit = draw(ids.select("edge_id"), u(rng.GROUP), group_dist(plan), method)
    base = F.col("first_node") + below(u(rng.BLOCK), F.col("blocks")) * F.col("block_size")
    hit = hit.select("edge_id", base.alias("base"), below(u(rng.FIRST), F.col("block_size")).alias("i"), below(u(rng.SECOND), F.col("block_size") - 1).alias("j"))
    return hit.select("edge_id", F.lit(1).cast("tinyint").alias("phase"), (F.col("base") + F.col("i")).alias("a"), (F.col("base") + F.col("j") + (F.col("j") >= F.col("i")).cast("bigint")).alias("b"))


def _endpoint(df: DataFrame, dist: DataFrame, seed: int, streams: tuple[int, int, int], name: str, kind: str, method: str) -> DataFrame:
    columns = df.columns
    hit = draw(df, uniform(seed, "edge_id", streams[0], kind), dist, method)
    filler = uniform(seed, "edge_id", streams[1], kind) < F.col("r")
    member = uniform(seed, "edge_id", streams[2], kind)
    node = F.col("first_node") + F.when(filler, below(member, F.col("n_fill"))).otherwise(F.col("n_fill") + below(member, F.col("n_bulk")))
    return hit.select(*columns, node.alias(name))


def global_edges(ids: DataFrame, plan: Plan, seed: int, kind: str = "fast", method: str = "guide") -> DataFrame:
    """Two independent ends: degree by excess weight, filler or bulk by a coin, member uniformly."""
    dist = degree_dist(plan)
    one = _endpoint(ids.select("edge_id"), dist, seed, (rng.DEGREE_A, rng.FILL_A, rng.MEMBER_A), "a", kind, method)
    both = _endpoint(one, dist, seed, (rng.DEGREE_B, rng.FILL_B, rng.MEMBER_B), "b", kind, method)
    return both.select("edge_id", F.lit(2).cast("tinyint").alias("phase"), "a", "b")


def phase_coin(ids: DataFrame, share: float, seed: int, kind: str = "fast") -> DataFrame:
    return ids.withColumn("local", uniform(seed, "edge_id", rng.PHASE, kind) < F.lit(share))


def generate(plan: Plan, seed: int = 1, mode: str = "independent", kind: str = "fast", method: str = "guide", total: str = "round", edges_per_task: int = EDGES_PER_TASK) -> DataFrame:
    """All edges, repeats and loops included.

    ``independent``: each edge tosses its phase. ``bulk``: the phases' numbers are fixed first. ``poisson``: each group
    draws its own Poisson number. ``skip``: local pairs are kept with their density by geometric gaps, without
    repeats, in tiles of bounded size. ``realised``: the global phase makes up for the local degrees that came about.
    """
    spark = plan.degree.sparkSession
    one, two = plan.totals()
    if mode == "independent":
        ids = phase_coin(edge_ids(spark, edge_total(one + two, total), edges_per_task), one / (one + two) if one + two else 0.0, seed, kind)
        local = local_edges(ids.where("local"), plan, seed, kind, method)
        return local.unionByName(global_edges(ids.where("NOT local"), plan, seed, kind, method))
    n_local, n_global = edge_total(one, total), edge_total(two, total)
    far = edge_ids(spark, n_local + n_global, edges_per_task, n_local)
    if mode == "bulk":
        return local_edges(edge_ids(spark, n_local, edges_per_task), plan, seed, kind, method).unionByName(global_edges(far, plan, seed, kind, method))
    if mode == "poisson":
        return poisson_local(plan, seed, kind, edges_per_task).unionByName(global_edges(far, plan, seed, kind, method))
    if mode == "skip":
        return skip_local(plan, seed, kind, edges_per_task).unionByName(global_edges(far, plan, seed, kind, method))
    if mode == "realised":
        local = skip_local(plan, seed, kind, edges_per_task)
        return local.unionByName(realised_global(local, plan, seed, kind, method, edges_per_task))
    raise ValueError(f"unknown mode: {mode}")


TILE, DRAWS, HITS, STEPS = 1 << 16, 4096, 64, 160


def _id(kind: str, *names: str) -> Column:
    """What a uniform of several whole numbers is drawn for."""
    return F.concat_ws("-", *names) if kind == "portable" else F.xxhash64(*names)


def _tiles(plan: Plan, which: Column, span: Column, edges_per_task: int) -> DataFrame:
    """Pair spaces of the groups ``which``, blocks end to end, in tiles of ``span`` codes: (g, tile, lo, hi, codes, pairs, ...).

    Tiles are numbered through all groups, and their numbers come from a range that is spread over tasks; each finds its group by
    ``locate``. So neither a large group nor the plan's one file ties tiles to a task, and there is no exchange.
    """
    pairs = F.expr("block_size * (block_size - 1) div 2")
    g = plan.group.withColumn("pairs", pairs).where((F.col("pairs") > 0) & which).withColumn("codes", F.col("blocks") * F.col("pairs")).withColumn("span", span.cast("bigint"))
    g = g.withColumn("tiles", F.expr("(codes - 1) div span + 1"))
    g = g.withColumn("t1", F.sum("tiles").over(Window.orderBy("g").rowsBetween(Window.unboundedPreceding, 0))).withColumn("t0", F.col("t1") - F.col("tiles"))
    spark = plan.group.sparkSession
    total, draws = g.agg(F.coalesce(F.sum("tiles"), F.lit(0)), F.coalesce(F.sum("w"), F.lit(0.0))).head()
    parts = min(max(1, total), max(math.ceil(draws / edges_per_task), spark.sparkContext.defaultParallelism))
    t = locate(spark.range(0, total, 1, parts).withColumnRenamed("id", "t"), "t", g, "t0", "t1").withColumn("tile", F.col("t") - F.col("t0"))
    return t.withColumn("lo", F.col("tile") * F.col("span")).withColumn("hi", F.least(F.col("codes"), (F.col("tile") + 1) * F.col("span")))


def _unranked(df: DataFrame, code: str = "code") -> DataFrame:
    """Pair codes of a group to nodes: block, then the pair j < i with i (i - 1) / 2 + j."""
    df = df.withColumn("block", F.expr(f"{code} div pairs")).withColumn("q", F.expr(f"{code} % pairs"))
    i0 = F.floor((F.sqrt(F.lit(8.0) * F.col("q") + 1) + 1) / 2)
    df = df.withColumn("i0", i0)
    i = F.when(F.expr("i0 * (i0 - 1) div 2 > q"), F.col("i0") - 1).when(F.expr("(i0 + 1) * i0 div 2 <= q"), F.col("i0") + 1).otherwise(F.col("i0"))
    df = df.withColumn("i", i).withColumn("j", F.expr("q - i * (i - 1) div 2"))
    base = F.col("first_node") + F.col("block") * F.col("block_size")
    return df.withColumn("a", base + F.col("j")).withColumn("b", base + F.col("i"))


def skip_local(plan: Plan, seed: int, kind: str = "fast", edges_per_task: int = EDGES_PER_TASK) -> DataFrame:
    """Every pair of a block kept with its density, so that there are no repeats. No exchange; a tile is one row until it is opened.

    Above a density of 0.1 each pair tosses a coin. Below, geometric gaps lead from one kept pair to the next in tiles in which
    ``HITS`` are expected; ``STEPS`` gaps leave a tile unfinished with a probability below 1e-20.
    """
    dense = F.col("rho") > 0.1
    coin = _tiles(plan, dense, F.lit(TILE), edges_per_task).withColumn("code", F.explode(F.sequence(F.col("lo"), F.col("hi") - 1)))
    coin = coin.where(uniform(seed, _id(kind, "g", "code"), rng.SKIP, kind) < F.col("rho"))
    sparse = _tiles(plan, ~dense & (F.col("rho") > 0), F.ceil(F.lit(float(HITS)) / F.col("rho")), edges_per_task)

    def step(acc: Column, s: Column) -> Column:
        id_ = F.concat_ws("-", "g", "tile", s) if kind == "portable" else F.xxhash64("g", "tile", s)
        gap = F.floor(F.log(F.lit(1.0) - uniform(seed, id_, rng.SKIP, kind)) / F.log(F.lit(1.0) - F.col("rho"))) + 1
        at = acc["at"] + gap
        return F.struct(at.alias("at"), F.when(at < F.col("hi"), F.array_append(acc["codes"], at)).otherwise(acc["codes"]).alias("codes"))

    zero = F.struct((F.col("lo") - 1).alias("at"), F.array().cast("array<bigint>").alias("codes"))
    sparse = sparse.withColumn("code", F.explode(F.aggregate(F.sequence(F.lit(1), F.lit(STEPS)), zero, step, lambda acc: acc["codes"])))
    keep = ("g", "first_node", "block_size", "pairs", "code")
    out = _unranked(coin.select(*keep).unionByName(sparse.select(*keep)))
    return out.select(F.xxhash64("g", "code").alias("edge_id"), F.lit(1).cast("tinyint").alias("phase"), "a", "b")


def poisson_local(plan: Plan, seed: int, kind: str = "fast", edges_per_task: int = EDGES_PER_TASK) -> DataFrame:
    """Each tile of a group's pair space draws a Poisson number of pairs, uniformly with replacement. No exchange.

    Splitting a Poisson number over tiles leaves it Poisson, so tiles of about ``DRAWS`` draws spread any group over tasks. A number is drawn by inversion
    for small means and by the normal limit for large ones.
    """
    span = F.greatest(F.lit(1), F.ceil(F.lit(float(DRAWS)) * F.col("codes") / F.col("w")))
    t = _tiles(plan, F.col("w") > 0, span, edges_per_task).withColumn("mean", F.col("w") * (F.col("hi") - F.col("lo")) / F.col("codes"))
    u1, u2 = (uniform(seed, _id(kind, "g", "tile"), stream, kind) for stream in (rng.NOISE_1, rng.NOISE_2))
    normal = F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - u1)) * F.cos(F.lit(2 * math.pi) * u2)
    zero = F.struct(F.lit(0).alias("k"), F.exp(-F.col("mean")).alias("p"), F.exp(-F.col("mean")).alias("s"))
    inverse = F.aggregate(F.sequence(F.lit(1), F.lit(120)), zero, lambda acc, k: F.when(acc["s"] > F.col("u1"), acc).otherwise(F.struct(k.alias("k"), (acc["p"] * F.col("mean") / k).alias("p"), (acc["s"] + acc["p"] * F.col("mean") / k).alias("s"))), lambda acc: acc["k"])
    t = t.withColumn("u1", u1).withColumn("number", F.when(F.col("mean") < 30, inverse).otherwise(F.greatest(F.lit(0), F.round(F.col("mean") + F.sqrt("mean") * normal).cast("int"))))
    t = t.where("number > 0").withColumn("s", F.explode(F.sequence(F.lit(1), F.col("number"))))
    id_ = _id(kind, "g", "tile", "s")
    code = F.col("lo") + below(uniform(seed, id_, rng.FIRST, kind), F.col("hi") - F.col("lo"))
    out = _unranked(t.withColumn("code", code))
    return out.select(F.xxhash64("g", "tile", "s").alias("edge_id"), F.lit(1).cast("tinyint").alias("phase"), "a", "b")


def realised_global(local: DataFrame, plan: Plan, seed: int, kind: str = "fast", method: str = "guide", edges_per_task: int = EDGES_PER_TASK) -> DataFrame:
    """Chung-Lu on what the local phase left of each node's degree: one shuffle of the local edges more than the expected excess.

    Node ids are a range; each finds its wanted degree among the plan's id ranges. Nodes are drawn by class (what is left of the
    degree), a table of checked size, and inside a class by place.
    """
    from .profile import degrees, numbered

    spark = local.sparkSession
    have = degrees(local.select(*pair_columns(local)).distinct())
    ranges = plan.degree.select("degree", F.col("first_node").alias("f0"), (F.col("first_node") + F.col("n")).alias("f1"))
    top = ranges.agg(F.max("f1")).head()[0] or 1
    ids = spark.range(1, top, 1, max(spark.sparkContext.defaultParallelism, math.ceil(top / edges_per_task))).withColumnRenamed("id", "v")
    nodes = locate(ids, "v", ranges, "f0", "f1").select("v", "degree").join(have.withColumnRenamed("degree", "has"), "v", "left")
    left = F.greatest(F.col("degree") - F.coalesce("has", F.lit(0)), F.lit(0))
    ranked = numbered(nodes.select("v", left.alias("left")).where("left > 0"), "left", "v")
    classes = ranked.groupBy("left").agg(F.count(F.lit(1)).alias("members"), F.min("position").alias("start")).withColumn("w", F.col("left") * F.col("members"))
    weight = (classes.agg(F.sum("w")).head()[0] or 0) / 2
    dist = cumulative(classes, "left", "w", ("members", "start"))
    out = edge_ids(spark, edge_total(weight), edges_per_task)
    for name, streams in (("a", (rng.DEGREE_A, rng.MEMBER_A)), ("b", (rng.DEGREE_B, rng.MEMBER_B))):
        out = draw(out, uniform(seed, "edge_id", streams[0], kind), dist, method).withColumn("position", F.col("start") + below(uniform(seed, "edge_id", streams[1], kind), F.col("members")))
        out = out.join(ranked.select("position", F.col("v").alias(name)), "position").drop("position", "start", "members", "bin")
    return out.select("edge_id", F.lit(2).cast("tinyint").alias("phase"), "a", "b")


def pair_columns(gen: DataFrame) -> tuple[Column, Column]:
    return F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")


def dedup(gen: DataFrame, strategy: str = "exchange", plan: Plan | None = None, unique_local: bool = False) -> DataFrame:
    """Simple edges of generated ones; loops go.

    ``exchange`` aggregates by the pair, partly before the shuffle. ``sort`` compares neighbours of a sorted partition. ``count``
    keeps each pair's multiplicity, ``none`` all pairs. ``endpoint`` deals by one end only (an ablation: hubs make it
    uneven). ``tile`` exchanges global edges only: those with both ends in one block of ``plan`` are looked for among the local
    edges, which are taken as unique with ``unique_local`` (as ``mode="skip"`` makes them) and exchanged by themselves otherwise.
    """
    pairs = gen.where("a <> b").select(*pair_columns(gen))
    if strategy == "exchange":
        return pairs.distinct()
    if strategy == "none":
        return pairs
    if strategy == "count":
        return pairs.groupBy("lo", "hi").agg(F.count(F.lit(1)).alias("times"))
    if strategy in ("sort", "endpoint"):

        width = int(gen.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        dealt = pairs.repartition(width, "lo", "hi") if strategy == "sort" else pairs.repartition(width, "lo")
        order = Window.partitionBy("lo", "hi").orderBy("hi") if strategy == "sort" else Window.partitionBy("lo").orderBy("hi")
        return dealt.withColumn("before", F.lag("hi").over(order)).where("before IS NULL OR before <> hi").select("lo", "hi")
    if strategy == "tile":
        if plan is None:
            raise ValueError("tile needs the plan")
        local = gen.where("phase = 1 AND a <> b").select(*pair_columns(gen))
        local = local if unique_local else local.distinct()
        far = stored(gen.where("phase = 2 AND a <> b").select(*pair_columns(gen)).distinct(), "far")
        ends = block_of(block_of(far, plan, "lo").withColumnsRenamed({"g": "g_lo", "block": "block_lo"}), plan, "hi")
        inside = ends.where("g_lo = g AND block_lo = block").select("lo", "hi")
        again = local.join(_small(inside, inside.count()), ["lo", "hi"], "left_semi")
        return local.unionByName(far.join(again, ["lo", "hi"], "left_anti"))
    raise ValueError(f"unknown strategy: {strategy}")


def clone_graph(edges: DataFrame, graph: str = "graph", beta: float = 1.0, clustering: str = "exact", seed: int = 1, kind: str = "fast", mode: str = "independent") -> DataFrame:
    """Measure, plan, generate and drop repeats."""
    from ..plans.block_plan import build_plan
    from .profile import measure_profile

    return dedup(generate(build_plan(measure_profile(edges, graph, clustering), beta), seed, mode, kind))


def draws_per_edge(plan: Plan) -> DataFrame:
    """(phase, discrete, uniforms) drawn for one edge, the phase's own coin apart."""
    return plan.degree.sparkSession.createDataFrame([(1, 1, 3), (2, 2, 4)], "phase int, discrete int, uniforms int")
