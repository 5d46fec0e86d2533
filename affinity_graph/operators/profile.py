"""Measuring a graph: degrees, triangles, clustering, profile. Input: edges (lo, hi), simple and undirected."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..functions import rng
from ..sources.tables import stored


def degrees(edges: DataFrame) -> DataFrame:
    """(v, degree) of every node with an edge."""
    return edges.select(F.explode(F.array("lo", "hi")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("degree"))


def degree_hist(nodes: DataFrame) -> DataFrame:
    """(degree, n), distinct degrees only."""
    return nodes.groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


def wedges(degree: Column | str) -> Column:
    """Wedges at a node: pairs of its neighbours."""
    degree = F.col(degree) if isinstance(degree, str) else degree
    return (degree * (degree - 1) / 2).cast("bigint")


def size_from_hist(hist: DataFrame) -> DataFrame:
    """Nodes, edges, largest and mean degree from a degree distribution alone."""
    n, stubs = F.sum("n"), F.sum(F.col("degree") * F.col("n"))
    return hist.agg(n.alias("nodes"), (stubs / 2).cast("bigint").alias("edges"), F.max("degree").alias("dmax"), (stubs / n).alias("davg"))


def wedge_counts(hist: DataFrame) -> DataFrame:
    """(degree, n, wedges) from a degree distribution."""
    return hist.select("degree", "n", (F.col("n") * wedges("degree")).alias("wedges"))


def oriented(edges: DataFrame) -> DataFrame:
    """Edges from the end of lower (degree, id) to the other: out-degrees are at most sqrt(2m), hubs included."""
    d = degrees(edges)
    e = edges.join(d.select(F.col("v").alias("lo"), F.col("degree").alias("dl")), "lo").join(d.select(F.col("v").alias("hi"), F.col("degree").alias("dh")), "hi")
    up = F.col("dl") <= F.col("dh")
    return e.select(F.when(up, F.col("lo")).otherwise(F.col("hi")).alias("tail"), F.when(up, F.col("hi")).otherwise(F.col("lo")).alias("head"))


def triangles(edges: DataFrame) -> DataFrame:
    """(a, b, c), each triangle once: wedges at the low end, closed by an equi-join."""
    o = oriented(edges)
    pairs = o.select("tail", F.col("head").alias("x")).join(o.select("tail", F.col("head").alias("y")), "tail").where("x < y")
    return pairs.join(edges.select(F.col("lo").alias("x"), F.col("hi").alias("y")), ["x", "y"]).select(F.col("tail").alias("a"), F.col("x").alias("b"), F.col("y").alias("c"))


RANGE_EDGES = 2_000_000


def _packed(a) -> bytes:
    """Whole numbers >= 0 in the narrowest width that holds them."""
    import numpy as np

    top = int(a.max()) if len(a) else 0
    width = 1 if top < 1 << 8 else 2 if top < 1 << 16 else 4 if top < 1 << 32 else 8
    return bytes([width]) + a.astype(f"<u{width}").tobytes()


def _unpacked(b: bytes):
    import numpy as np

    return np.frombuffer(b, f"<u{b[0]}", offset=1).astype(np.int64)


def _dealt(bounds: list[int]):
    """Lists of heads to the range of ids that holds the tail (kind 0) and to every other that holds a head (kind 1)."""

    def deal(batches):
        import numpy as np
        import pyarrow as pa

        cuts = np.array(bounds, np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            heads, weights = batch.column("heads"), batch.column("weights")
            flat, at = heads.flatten().to_numpy(), np.concatenate([[0], np.cumsum(heads.value_lengths().to_numpy())])
            w = weights.flatten().to_numpy()
            row = np.repeat(np.arange(batch.num_rows), np.diff(at))
            own = np.searchsorted(cuts, batch.column("tail").to_numpy(), "right")
            width = len(cuts) + 1
            sent = np.unique(np.concatenate([np.arange(batch.num_rows) * width + own, row * width + np.searchsorted(cuts, flat, "right")]))
            to, rows = sent % width, sent // width
            first = flat[at[:-1]]
            steps = np.diff(flat, prepend=flat[:1])
            steps[at[:-1]] = 0
            lists = pa.array([_packed(steps[i:j]) for i, j in zip(at, at[1:])], pa.binary())
            sizes = pa.array([_packed(w[i:j] if w[i:j].max() > 1 else w[i:i]) for i, j in zip(at, at[1:])], pa.binary())
            kept = pa.array(rows)
            yield pa.RecordBatch.from_arrays([pa.array(to.astype(np.int32)), pa.array((to != own[rows]).astype(np.int32)), batch.column("tail").take(kept), batch.column("weight").take(kept), pa.array(first).take(kept), lists.take(kept), sizes.take(kept)], ["r", "kind", "tail", "weight", "first", "steps", "sizes"])

    return deal


def _close(batches):
    """Closed wedges of each range: its own lists (kind 0) are kept, and every list is looked up against those of its heads."""
    import numpy as np
    import pyarrow as pa

    def listed(first, steps, sizes):
        heads = first + np.cumsum(_unpacked(steps))
        return heads, (_unpacked(sizes) if len(sizes) > 1 else np.ones(len(heads), np.int64))

    def rows():
        for batch in batches:
            yield from zip(*(batch.column(c).to_pylist() for c in ("r", "kind", "tail", "weight", "first", "steps", "sizes")))

    def out(v, closed):
        hit = np.flatnonzero(closed)
        return pa.RecordBatch.from_arrays([pa.array(v[hit]), pa.array(closed[hit])], ["v", "closed"])

    class Range:
        def __init__(self, own):
            own.sort(key=lambda o: o[0])
            self.tails = np.array([o[0] for o in own], np.int64)
            lengths = np.array([len(o[2]) for o in own], np.int64)
            self.start = np.concatenate([[0], np.cumsum(lengths)])
            flat = np.concatenate([o[2] for o in own]) if own else np.zeros(0, np.int64)
            sizes = np.concatenate([o[3] for o in own]) if own else np.zeros(0, np.int64)
            self.cols, where, self.near = np.unique(flat, return_index=True, return_inverse=True)
            self.sizes = sizes[where]
            self.plain = bool((self.sizes == 1).all())
            self.mark = np.zeros(len(self.cols), bool)
            self.at_tail, self.at_col = np.zeros(len(own), np.int64), np.zeros(len(self.cols), np.int64)

        def look(self, weight, heads, sizes):
            """The tail's own count; those of its heads are added up."""
            if len(heads) < 2 or not len(self.tails):
                return 0
            lo, hi = np.searchsorted(self.tails, heads[0]), np.searchsorted(self.tails, heads[-1], "right")
            if lo == hi:
                return 0
            x = np.searchsorted(self.tails, heads)
            x[x == len(self.tails)] = 0
            mine = self.tails[x] == heads
            x, wx = x[mine], sizes[mine]
            n = self.start[x + 1] - self.start[x]
            if not len(x):
                return 0
            ends = np.cumsum(n)
            y = self.near[np.arange(ends[-1]) + np.repeat(self.start[x] - ends + n, n)]
            mark = np.searchsorted(self.cols, heads)
            mark[mark == len(self.cols)] = 0
            mark = mark[self.cols[mark] == heads]
            self.mark[mark] = True
            hit = np.flatnonzero(self.mark[y])
            self.mark[mark] = False
            if not len(hit):
                return 0
            y, of = y[hit], np.searchsorted(ends, hit, "right")
            by_x = np.bincount(of, minlength=len(x)) if self.plain else np.diff(np.concatenate([[0], np.cumsum(self.sizes[y])])[np.searchsorted(of, np.arange(len(x) + 1))])
            self.at_tail[x] += weight * by_x
            np.add.at(self.at_col, y, weight * wx[of])
            return int((wx * by_x).sum())

    current, now, own, tails, closed = None, None, [], [], []

    def finish():
        if now is not None:
            yield out(now.tails, now.at_tail)
            yield out(now.cols, now.at_col)
        if tails:
            yield out(np.array(tails, np.int64), np.array(closed, np.int64))

    def looked(tail, weight, heads, sizes):
        n = now.look(weight, heads, sizes)
        if n:
            tails.append(tail)
            closed.append(n)

    def opened():
        nonlocal now, own
        if now is None:
            now = Range(own)
            for tail, weight, heads, sizes in own:
                looked(tail, weight, heads, sizes)
            own = []

    for r, kind, tail, weight, first, steps, sizes in rows():
        if r != current:
            if current is not None:
                opened()
                yield from finish()
            current, now, own, tails, closed = r, None, [], [], []
        heads, weights = listed(first, steps, sizes)
        if kind == 0:
            own.append((tail, weight, heads, weights))
        else:
            opened()
            looked(tail, weight, heads, weights)
    if current is not None:
        opened()
        yield from finish()


def closed_wedges(edges: DataFrame, nodes: DataFrame, ranges: int | None = None) -> DataFrame:
    """(v, closed): the closed wedges at each node, nodes given with their degree and, where a row stands for several, their weight.

    Lists of heads go, packed, to the ranges of ids that hold their heads; wedges are made and closed there in memory, one list at
    a time, and never exchanged. A triangle counts at each corner by the weights of the other two.
    """
    weighted = "weight" in nodes.columns
    side = lambda v, n: nodes.select(F.col("v").alias(v), F.struct("degree", F.col("v").alias("id"), *(["weight"] if weighted else [])).alias(n))
    e = edges.join(side("lo", "l"), "lo").join(side("hi", "h"), "hi")
    up = F.struct("l.degree", "l.id") < F.struct("h.degree", "h.id")
    tail, head = F.when(up, F.col("l")).otherwise(F.col("h")), F.when(up, F.col("h")).otherwise(F.col("l"))
    arcs = e.select(tail.alias("t"), head.alias("h")).select(F.col("t.id").alias("tail"), F.col("h.id").alias("head"), *([F.col("t.weight").alias("weight"), F.col("h.weight").alias("size")] if weighted else []))
    if weighted:
        lists = arcs.groupBy("tail").agg(F.first("weight").alias("weight"), F.sort_array(F.collect_list(F.struct("head", "size"))).alias("x"))
        lists = lists.select("tail", "weight", F.col("x.head").alias("heads"), F.col("x.size").alias("weights"))
    else:
        one = F.lit(1).cast("bigint")
        lists = arcs.groupBy("tail").agg(F.sort_array(F.collect_list("head")).alias("heads"))
        lists = lists.select("tail", one.alias("weight"), "heads", F.array_repeat(one, F.size("heads")).alias("weights"))
    if ranges is None:
        n = edges.count()
        ranges = max(1, min(math.ceil(n / 50_000), max(edges.sparkSession.sparkContext.defaultParallelism, math.ceil(n / RANGE_EDGES))))
    bounds = sorted({int(x) for x in edges.approxQuantile("lo", [k / ranges for k in range(1, ranges)], 0.2 / ranges)}) if ranges > 1 else []
    dealt = lists.mapInArrow(_dealt(bounds), "r int, kind int, tail long, weight long, first long, steps binary, sizes binary")
    dealt = dealt.repartitionById(ranges, "r").sortWithinPartitions("r", "kind")
    return dealt.mapInArrow(_close, "v long, closed long").groupBy("v").agg(F.sum("closed").alias("closed"))


def local_clustering(edges: DataFrame) -> DataFrame:
    """(v, degree, closed, c): closed wedges at each node and their share, 0 below degree 2."""
    nodes = degrees(edges)
    return shared_closed(nodes.join(closed_wedges(edges, nodes), "v", "left").withColumn("closed", F.coalesce("closed", F.lit(0).cast("bigint"))))


def shared_closed(nodes: DataFrame) -> DataFrame:
    """(v, degree, closed) with the share c of closed wedges."""
    return nodes.select("v", "degree", "closed", F.coalesce(F.try_divide(F.col("closed").cast("double"), wedges("degree").cast("double")), F.lit(0.0)).alias("c"))


def clustering_by_degree(edges: DataFrame) -> DataFrame:
    """(degree, n, closed, wedges, c, c_mean): c as closed over all wedges and as the mean over nodes, which agree."""
    return clustered(local_clustering(edges))


def clustered(nodes: DataFrame) -> DataFrame:
    """``clustering_by_degree`` from (v, degree, closed, c)."""
    by = nodes.groupBy("degree").agg(F.count(F.lit(1)).alias("n"), F.sum("closed").alias("closed"), F.avg("c").alias("c_mean"))
    by = by.withColumn("wedges", F.col("n") * wedges("degree"))
    return by.select("degree", "n", "closed", "wedges", F.coalesce(F.try_divide(F.col("closed").cast("double"), F.col("wedges").cast("double")), F.lit(0.0)).alias("c"), "c_mean")


def measure_profile(edges: DataFrame, graph: str, clustering: str = "exact", k: int = 2000, seed: int = 1) -> DataFrame:
    """The model's input: (graph, degree, n, c)."""
    if clustering == "exact":
        by = clustering_by_degree(edges)
    elif clustering == "sampled":
        by = sample_clustering(edges, k, seed).select("degree", "n", "c")
    else:
        raise ValueError(f"unknown clustering: {clustering}")
    return by.select(F.lit(graph).alias("graph"), "degree", "n", "c")


def profile_gcc(profile: DataFrame) -> DataFrame:
    """(graph, gcc): the global clustering that a profile implies."""
    w = F.col("n") * wedges("degree")
    return profile.groupBy("graph").agg(F.coalesce(F.try_divide(F.sum(F.col("c") * w), F.sum(w).cast("double")), F.lit(0.0)).alias("gcc"))


def summary(edges: DataFrame, graph: str, model: str) -> DataFrame:
    """One row: nodes, edges, dmax, davg, wedges, triangles and global clustering (three triangles over wedges)."""
    return summed(clustering_by_degree(edges), graph, model)


def summed(by: DataFrame, graph: str, model: str) -> DataFrame:
    """The summary of a graph from its counts by degree."""
    n, stubs, w, closed = F.sum("n"), F.sum(F.col("degree") * F.col("n")), F.sum("wedges"), F.sum("closed")
    return by.agg(
        F.lit(graph).alias("graph"), F.lit(model).alias("model"), F.coalesce(n, F.lit(0)).alias("nodes"), F.coalesce((stubs / 2).cast("bigint"), F.lit(0)).alias("edges"), F.coalesce(F.max("degree"), F.lit(0)).alias("dmax"),
        F.round(F.coalesce(stubs / n, F.lit(0.0)), 6).alias("davg"), F.coalesce(w, F.lit(0)).alias("wedges"), F.coalesce((closed / 3).cast("bigint"), F.lit(0)).alias("triangles"),
        F.round(F.coalesce(F.try_divide(closed.cast("double"), w.cast("double")), F.lit(0.0)), 6).alias("gcc"),
    )


def canonical_order(nodes: DataFrame) -> DataFrame:
    """(v, degree, position) by degree, degree 1 last, ties by id."""
    n = nodes.withColumn("cls", F.when(F.col("degree") == 1, F.lit(1 << 62)).otherwise(F.col("degree")))
    return numbered(n, "cls", "v").select("v", "degree", "position")


def numbered(rows: DataFrame, *order: str) -> DataFrame:
    """``rows`` with ``position`` from 1 in an order without ties.

    Range partitions, cut by sampled values of the whole order and so of even size whatever the ids or classes, are sorted and
    written with each row's place; a place is moved by the sizes of the partitions before, one row per shuffle partition.
    """
    width = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    id_ = F.monotonically_increasing_id()  # partition in the upper bits, place in the lower 33
    dealt = rows.repartitionByRange(width, *order).sortWithinPartitions(*order)
    placed = stored(dealt.select("*", F.shiftright(id_, 33).alias("part_"), id_.bitwiseAND(F.lit((1 << 33) - 1)).alias("at_")), "numbered")
    sizes = placed.groupBy("part_").agg(F.count(F.lit(1)).alias("k_"))
    before = F.coalesce(F.sum("k_").over(Window.orderBy("part_").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return placed.join(F.broadcast(sizes.select("part_", before.alias("before_"))), "part_").select(*rows.columns, (F.col("before_") + F.col("at_") + 1).alias("position"))


# --- wedge sampling ----------------------------------------------------------------------------------------------


def samples_for(eps: float, delta: float) -> int:
    """Wedges per degree so that a sampled share is off by more than ``eps`` with probability ``delta`` at most (Hoeffding)."""
    return math.ceil(math.log(2 / delta) / (2 * eps * eps))


def _arcs(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("lo").alias("center"), F.col("hi").alias("w")).unionByName(edges.select(F.col("hi").alias("center"), F.col("lo").alias("w")))


def sampled_wedges(edges: DataFrame, k: int, seed: int, kind: str = "fast", least: int = 0) -> DataFrame:
    """(degree, n, k, center, a, b, closed): ``k`` uniform wedges for every degree of at least 2 with more than ``least`` wedges in all.

    Every node of a degree class has as many wedges, so a uniform node and two distinct uniform neighbours are a uniform wedge.
    Nodes are numbered by (degree, id) and the arcs at drawn centres by (centre, neighbour), both in even range partitions, so
    that neither a class nor a hub is one task's; drawn ranks meet them in equi-joins. Closure is an equi-join of k wedges a
    degree with the edges.
    """
    ranked = numbered(degrees(edges).where("degree >= 2"), "degree", "v")
    hist = ranked.groupBy("degree").agg(F.count(F.lit(1)).alias("n"), F.min("position").alias("first")).where(F.col("n") * wedges("degree") > least)
    draws = hist.select("degree", "n", "first", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(k - 1).cast("bigint"))).alias("k"))
    id_ = F.col("degree") * F.lit(1 << 20) + F.col("k")
    rank = rng.below(rng.uniform(seed, id_, rng.CENTER, kind), F.col("n"))
    i, j = rng.below(rng.uniform(seed, id_, rng.NEIGHBOUR_1, kind), F.col("degree")), rng.below(rng.uniform(seed, id_, rng.NEIGHBOUR_2, kind), F.col("degree") - 1)
    draws = draws.select("degree", "n", "k", (F.col("first") + rank).alias("position"), i.alias("i"), j.alias("j"))
    picked = stored(draws.join(ranked.select("position", F.col("v").alias("center")), "position").drop("position"), "picked")
    near = numbered(_arcs(edges).join(picked.select("center").distinct(), "center", "left_semi"), "center", "w")
    starts = near.groupBy("center").agg(F.min("position").alias("start"))
    shifted = F.when(F.col("j") >= F.col("i"), F.col("j") + 1).otherwise(F.col("j"))
    w = picked.join(starts, "center").select("degree", "n", "k", "center", (F.col("start") + F.col("i")).alias("at_a"), (F.col("start") + shifted).alias("at_b"))
    for name in ("a", "b"):
        w = w.join(near.select(F.col("position").alias(f"at_{name}"), F.col("w").alias(name)), f"at_{name}")
    w = w.select("degree", "n", "k", "center", "a", "b", F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi"))
    return w.join(edges.select("lo", "hi", F.lit(True).alias("closed")), ["lo", "hi"], "left").select("degree", "n", "k", "center", "a", "b", F.coalesce("closed", F.lit(False)).alias("closed"))


def exact_small(edges: DataFrame, most: int) -> DataFrame:
    """(degree, n, c) of the degrees with at most ``most`` wedges in all: only those wedges are made and closed."""
    nodes = degrees(edges).where("degree >= 2")
    small = degree_hist(nodes).withColumn("wedges", F.col("n") * wedges("degree")).where(F.col("wedges") <= most)
    near = _arcs(edges).join(nodes.join(small.select("degree"), "degree").select(F.col("v").alias("center"), "degree"), "center")
    pairs = near.select("center", "degree", F.col("w").alias("lo")).join(near.select("center", F.col("w").alias("hi")), "center").where("lo < hi")
    closed = pairs.join(edges, ["lo", "hi"]).groupBy("degree").agg(F.count(F.lit(1)).alias("closed"))
    share = F.coalesce("closed", F.lit(0)).cast("double") / F.col("wedges").cast("double")
    return small.join(closed, "degree", "left").select("degree", "n", share.alias("c"))


def sample_clustering(edges: DataFrame, k: int = 2000, seed: int = 1, kind: str = "fast", exact_below: int = 0) -> DataFrame:
    """(degree, n, c) from sampled wedges; degrees with at most ``exact_below`` wedges in all are counted exactly."""
    out = sampled_wedges(edges, k, seed, kind, exact_below).groupBy("degree").agg(F.first("n").alias("n"), F.avg(F.col("closed").cast("double")).alias("c"))
    if exact_below:
        out = out.unionByName(exact_small(edges, exact_below))
    return out.unionByName(degree_hist(degrees(edges)).where("degree = 1").select("degree", "n", F.lit(0.0).alias("c")))


def sample_gcc(edges: DataFrame, k: int = 2000, seed: int = 1, kind: str = "fast") -> DataFrame:
    """Global clustering from sampled shares, each degree weighted by its wedges."""
    return profile_gcc(sample_clustering(edges, k, seed, kind).select(F.lit("sampled").alias("graph"), "degree", "n", "c"))


def sampling_error(edges: DataFrame, k: int = 2000, seed: int = 1, kind: str = "fast") -> DataFrame:
    """(degree, exact, sampled, gap)."""
    exact = clustering_by_degree(edges).select("degree", F.col("c").alias("exact"))
    sampled = sample_clustering(edges, k, seed, kind).select("degree", F.col("c").alias("sampled"))
    return exact.join(sampled, "degree").withColumn("gap", F.abs(F.col("exact") - F.col("sampled")))
