"""Ties of group graphs looked at in memory, slice by slice, so that no pair of nodes is exchanged or written.

Nodes (or families, or pieces of such) with sets of numbered keys are cut into slices by range and packed. A task has one slice of its
own and reads the packed slices of all: for each of its nodes it puts the lists of that node's keys together and makes them distinct.
What a task gives are counts, or the lists of a node's neighbours. Memory is that of some slices (``MOST`` keys of nodes), not of pairs.
Only clustering holds the keys of all nodes at once; what exceeds one common key of a pair is read in runs.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .baskets import _packed, _starts, _unpacked

SLICE, LEAST, MOST = 500_000, 2_000, 12_000_000  # keys of nodes in a slice, at most and at least, and looked at together
OUT, RUN = 1 << 20, 1 << 16  # neighbours in a batch and in a row
EXCESS = 6_000_000  # pairs with several common keys held together
FIELDS = ("s", "m", "n", "block", "head", "nn", "nodes")
SLICES = "s int, m long, n long, block binary, head binary, nn long, nodes binary"


def _pack(batches) -> Iterator:
    """One row for the nodes of a partition: places with keys, weights with labels, places with the nodes of families."""
    import numpy as np
    import pyarrow as pa

    held = [b for b in batches if b.num_rows]
    if not held:
        return
    t = pa.Table.from_batches(held).combine_chunks()

    def flat(name):
        lists = t.column(name).combine_chunks()
        lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
        at = np.repeat(np.arange(t.num_rows), np.diff(lists.offsets.to_numpy()))
        return at, lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)

    keys, nodes = flat("keys"), flat("nodes")
    block, names = _packed(*keys), _packed(*nodes)
    head = _packed(t.column("weight").to_numpy(), t.column("label").to_numpy())
    row = t.column("s")[0].as_py(), t.num_rows, len(keys[0]), block, head, len(nodes[0]), names
    types = (pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.binary())
    yield pa.RecordBatch.from_arrays([pa.array([c], k) for c, k in zip(row, types)], list(FIELDS))


def packed(nodes: DataFrame, *order: str) -> tuple[DataFrame, int]:
    """Slices of (order, weight, label, keys, nodes) by range of ``order``, and their number at most."""
    n = nodes.agg(F.sum(F.size("keys"))).head()[0] or 0
    slices = max(1, min(math.ceil(n / LEAST), max(8 * nodes.sparkSession.sparkContext.defaultParallelism, math.ceil(n / SLICE))))
    rows = nodes.repartitionByRange(slices, *order).sortWithinPartitions(*order)
    return rows.select(F.spark_partition_id().alias("s"), "weight", "label", "keys", "nodes").mapInArrow(_pack, SLICES), slices


def _met(slices: DataFrame, count: int, half: bool) -> DataFrame:
    """Each slice (columns own_) with all slices, or with itself and those after it; no row is exchanged but a slice to its own task."""
    own = slices.select(*[F.col(c).alias(f"own_{c}") for c in FIELDS]).repartitionById(count, "own_s")
    every = slices.select(*FIELDS).coalesce(1)
    return own.join(every.hint("shuffle_replicate_nl"), F.col("s") >= F.col("own_s") if half else F.lit(True))


class _Slice:
    """Nodes and their keys."""

    def __init__(self, s, m, n, block, head, nn, nodes):
        import numpy as np

        self.s, self.m = s, m
        self.place, self.key = _unpacked(block, n)
        self.start = np.searchsorted(self.place, np.arange(m + 1))
        self.weight, self.label = _unpacked(head, m)
        at, self.nodes = _unpacked(nodes, nn)
        self.first = np.searchsorted(at, np.arange(m + 1))


class _Block:
    """Nodes of several slices by key."""

    def __init__(self, slices: list[_Slice], own: _Slice):
        import numpy as np

        self.slices = sorted(slices, key=lambda x: x.s)
        self.base = np.append(0, np.cumsum([x.m for x in self.slices])).astype(np.int64)
        self.of = {x.s: int(b) for x, b in zip(self.slices, self.base)}
        place = np.concatenate([x.place + b for x, b in zip(self.slices, self.base)])
        key = np.concatenate([x.key for x in self.slices])
        self.width = int(self.base[-1])
        self.weight = np.concatenate([x.weight for x in self.slices])
        self.label = np.concatenate([x.label for x in self.slices])
        self.even = bool((self.weight == 1).all())
        self.keys, code = _coded(key)
        by = np.argsort(code, kind="stable")
        self.member = place[by]  # eight bytes each, as they index
        self.start = np.append(0, np.cumsum(np.bincount(code, minlength=len(self.keys))))
        self.tag = np.zeros(self.width, np.int32)
        self.count = np.arange(1 << 16, dtype=np.int32)
        self.node_at = np.append(0, np.cumsum(np.concatenate([np.diff(x.first) for x in self.slices])))
        self.nodes = np.concatenate([x.nodes for x in self.slices])
        if own.s in self.of:
            first = sum(len(x.key) for x in self.slices if x.s < own.s)
            mine = np.flatnonzero((by >= first) & (by < first + len(own.key)))
            self.own_at = np.empty(len(mine), np.int64)  # where its nodes are in the lists of their keys
            self.own_at[by[mine] - first] = mine
        self.code, self.key_at = code, np.append(0, np.cumsum(np.concatenate([np.diff(x.start) for x in self.slices])))

    def lists(self, own: _Slice, after: bool = False):
        """Where the list of each key of a slice's nodes begins and ends, for its own nodes from ``after`` the node itself."""
        import numpy as np

        at = np.minimum(np.searchsorted(self.keys, own.key), len(self.keys) - 1)
        there = self.keys[at] == own.key
        lo = np.where(there, self.start[at], 0)
        if after and own.s in self.of:
            lo = self.own_at + 1
        return lo.tolist(), np.where(there, self.start[at + 1], 0).tolist()

    def held(self, lists, i: int, j: int):
        """Nodes with any of a node's keys, once for each common key."""
        import numpy as np

        return np.concatenate([self.member[x:y] for x, y in zip(lists[0][i:j], lists[1][i:j])])

    def near(self, lists, i: int, j: int):
        """The same, and which of these entries is the one that stands for its node."""
        import numpy as np

        at = self.held(lists, i, j)
        if len(at) > len(self.count):
            self.count = np.arange(2 * len(at), dtype=np.int32)
        n = self.count[: len(at)]
        self.tag[at] = n
        return at, self.tag[at] == n

    def flat(self, starts, at):
        """Places of the entries of some nodes in a flat list, one node's after the other's."""
        import numpy as np

        lo, n = starts[at], starts[at + 1] - starts[at]
        ends = np.cumsum(n)
        return np.arange(ends[-1] if len(ends) else 0) + np.repeat(lo - ends + n, n)


def _coded(key):
    """Distinct numbers in order and each one's place among them, small for a fast sort."""
    import numpy as np

    lo, span = int(key.min()), int(key.max()) - int(key.min()) + 1
    if span <= 4 * len(key) + 1024:
        there = np.bincount(key - lo, minlength=span) > 0
        keys, code = np.flatnonzero(there) + lo, (np.cumsum(there) - 1)[key - lo]
    else:
        keys, code = np.unique(key, return_inverse=True)
    return keys, code.astype(np.uint16 if len(keys) < 1 << 16 else np.int32)


def _looked(look: Callable) -> Callable:
    """``look(own, block)`` for each slice and the others, of about MOST keys together."""
    most = MOST

    def run(batches):
        own, held, n = None, [], 0
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1).to_pydict()
                if own is None or own.s != row["own_s"][0]:
                    if held:
                        yield from look(own, _Block(held, own))
                    own, held, n = _Slice(*(row[f"own_{c}"][0] for c in FIELDS)), [], 0
                held.append(_Slice(*(row[c][0] for c in FIELDS)))
                n += row["n"][0]
                if n >= most:
                    yield from look(own, _Block(held, own))
                    held, n = [], 0
        if held:
            yield from look(own, _Block(held, own))

    return run


def _batch(names: str, *columns):
    import pyarrow as pa

    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names.split())


def _degrees(own: _Slice, block: _Block):
    """(s, place, weight, near): nodes of the block tied to each node, itself included."""
    import numpy as np

    lists, out, there = block.lists(own), np.zeros(own.m, np.int64), np.zeros(block.width, bool)
    for v in range(own.m):
        at = block.held(lists, own.start[v], own.start[v + 1])
        there[at] = True
        out[v] = np.count_nonzero(there) if block.even else block.weight[there].sum()
        there[at] = False
    yield _batch("s place weight near", np.full(own.m, own.s, np.int32), np.arange(own.m), own.weight, out)


def degrees(slices: DataFrame, count: int) -> DataFrame:
    """(weight, degree) of every family with an edge."""
    each = _met(slices, count, False).mapInArrow(_looked(_degrees), "s int, place long, weight long, near long")
    return each.groupBy("s", "place").agg(F.first("weight").alias("weight"), (F.sum("near") - 1).alias("degree")).where("degree > 0").select("weight", "degree")


def _once(own: _Slice, block: _Block, lists, v: int):
    """Nodes of the block tied to a node, by the lists given."""
    at, first = block.near(lists, own.start[v], own.start[v + 1])
    return at[first]


def _neighbours(own: _Slice, block: _Block):
    """(x, near) in rows of bounded length."""
    import numpy as np
    import pyarrow as pa

    held, n = [], 0

    def flush():
        xs = np.array([x for x, _ in held], np.int64)
        at = np.append(0, np.cumsum([len(y) for _, y in held])).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(at), pa.array(np.concatenate([y for _, y in held])))
        return pa.RecordBatch.from_arrays([pa.array(xs), lists], ["x", "near"])

    lists, single = block.lists(own, True), len(block.nodes) == block.width
    for v in range(own.m):
        at = _once(own, block, lists, v)
        far = block.nodes[at if single else block.flat(block.node_at, at)]
        mine = own.nodes[own.first[v] : own.first[v + 1]]
        for i, x in enumerate(mine):
            near = np.append(mine[i + 1 :], far) if own.s in block.of and i + 1 < len(mine) else far
            for j in range(0, len(near), RUN):
                held.append((x, near[j : j + RUN]))
                n += len(held[-1][1])
                if n >= OUT:
                    yield flush()
                    held, n = [], 0
    if held:
        yield flush()


def neighbours(slices: DataFrame, count: int) -> DataFrame:
    """(x, near): lists of neighbours in which every edge is once."""
    return _met(slices, count, True).mapInArrow(_looked(_neighbours), "x long, near array<long>")


def _labelled(own: _Slice, block: _Block):
    """(a, b, edges) by the labels of both ends; labels are taken in order, so that one row of counts is held."""
    import numpy as np

    lists = block.lists(own, True)
    names, label = np.unique(block.label, return_inverse=True)
    by = np.argsort(own.label, kind="stable")
    cuts = np.append(_starts(own.label[by]), own.m)
    for i, j in zip(cuts, cuts[1:]):
        row = np.zeros(len(names), np.int64)
        mine = own.label[by[i]]
        for v in by[i:j]:
            at = _once(own, block, lists, v)
            row += own.weight[v] * np.bincount(label[at], None if block.even else block.weight[at], len(names)).astype(np.int64)
        if own.s in block.of:
            w = own.weight[by[i:j]]
            row[np.searchsorted(names, mine)] += (w * (w - 1) // 2).sum()
        some = np.flatnonzero(row)
        yield _batch("a b edges", np.full(len(some), mine), names[some], row[some])


def labelled(slices: DataFrame, count: int) -> DataFrame:
    """(a, b, edges): edges by the labels of their ends, in either order and in several rows."""
    return _met(slices, count, True).mapInArrow(_looked(_labelled), "a long, b long, edges long")


def _exceeding(own: _Slice, block: _Block):
    """Pairs of a slice's nodes and nodes after them with several common keys: (place, slice and place of the other), and by how many keys
    more than one."""
    import numpy as np
    import pyarrow as pa

    lists, tail, head, more = block.lists(own, True), [], [], []
    for v in range(own.m):
        at, first = block.near(lists, own.start[v], own.start[v + 1])
        again = at[~first]
        if len(again):
            y, n = np.unique(again, return_counts=True)
            tail.append(np.full(len(y), v))
            head.append(y)
            more.append(n)
    tail, head, more = (np.concatenate(c or [np.zeros(0, np.int64)]).astype(np.int64) for c in (tail, head, more))
    of = np.searchsorted(block.base, head, "right") - 1
    head = (np.array([x.s for x in block.slices], np.int64)[of] << 32) + head - block.base[of]
    for i in range(0, len(tail), SLICE):
        t, h, e = (c[i : i + SLICE] for c in (tail, head, more))
        row = own.s, len(t), _packed(t, h), _packed(e, np.zeros(len(e), np.int64))
        yield pa.RecordBatch.from_arrays([pa.array([c], k) for c, k in zip(row, (pa.int32(), pa.int64(), pa.binary(), pa.binary()))], ["x_s", "x_n", "x_pairs", "x_more"])


def exceeding(slices: DataFrame, count: int) -> DataFrame:
    """Packed pairs with several common keys, each once."""
    return _met(slices, count, True).mapInArrow(_looked(_exceeding), "x_s int, x_n long, x_pairs binary, x_more binary")


def _closed(count: int) -> Callable:
    """Closed wedges at the nodes of each slice. Pairs of a node's neighbours (itself one of them) are counted by key, and pairs with several
    common keys taken off again for each further one. Rows are all ``count`` slices and runs of such pairs (columns x_) for each own slice."""
    excess = EXCESS

    def opened(own, held):
        import numpy as np

        block = _Block(held, own)
        lists, k = block.lists(own), np.diff(block.key_at)
        total, degree = np.zeros(own.m, np.int64), np.zeros(own.m, np.int64)
        for v in range(own.m):
            at = _once(own, block, lists, v)
            w = 1 if block.even else block.weight[at]
            degree[v] = (len(at) if block.even else w.sum()) - 1
            keys = block.code[block.flat(block.key_at, at)]
            by = np.bincount(keys, None if block.even else np.repeat(w, k[at]), len(block.keys)).astype(np.int64)
            total[v] = (by * by).sum() - (w * w * (k[at] - 1)).sum()
        return block, lists, total, degree

    def taken(own, block, lists, total, pairs):
        """Twice the weight of some pairs between neighbours of each node."""
        import numpy as np

        base = np.zeros(max(block.of) + 1, np.int64)
        base[list(block.of)] = list(block.of.values())
        tail, head, more = [], [], []
        for s, n, ends, several in pairs:
            x, y = _unpacked(ends, n)
            tail.append(x + base[s])
            head.append((base[y >> 32] + (y & ((1 << 32) - 1))).astype(np.int32))
            more.append(next(_unpacked(several, n)))
        tail, head, more = (np.concatenate(c) for c in (tail, head, more))
        by = np.argsort(tail, kind="stable")
        tail, head, more = tail[by], head[by], more[by]
        more *= block.weight[tail] * block.weight[head]
        start = np.searchsorted(tail, np.arange(block.width + 1))
        one, there = bool((more == 1).all()), np.zeros(block.width, bool)
        for v in range(own.m):
            at = _once(own, block, lists, v)
            there[at] = True
            of = block.flat(start, at)
            hit = there[head[of]]
            total[v] -= 2 * int(np.count_nonzero(hit) if one else more[of[hit]].sum())
            there[at] = False

    def finished(own, held, waiting, state):
        state = state or opened(own, held)
        _, _, total, degree = state
        if waiting:
            taken(own, *state[:3], waiting)
        some = degree > 0
        return _batch("weight degree closed", own.weight[some], degree[some], ((total - 3 * (degree + 1) + 2) // 2)[some])

    def run(batches):
        own = None
        for batch in batches:
            for i in range(batch.num_rows):
                row = {c: v[0] for c, v in batch.slice(i, 1).to_pydict().items()}
                if own is None or own.s != row["own_s"]:
                    if own is not None:
                        yield finished(own, held, waiting, state)
                    own, held, waiting, state = _Slice(*(row[f"own_{c}"] for c in FIELDS)), [], [], None
                if row["x_n"] is None:
                    held.append(_Slice(*(row[c] for c in FIELDS)))
                else:
                    waiting.append((row["x_s"], row["x_n"], row["x_pairs"], row["x_more"]))
                if len(held) == count and sum(x[1] for x in waiting) >= excess:
                    state = state or opened(own, held)
                    taken(own, *state[:3], waiting)
                    waiting = []
        if own is not None:
            yield finished(own, held, waiting, state)

    return run


def closed(slices: DataFrame, pairs: DataFrame, count: int) -> DataFrame:
    """(weight, degree, closed) of every family with an edge; ``pairs`` are those of ``exceeding``. Both tables are stored ones."""
    x = [c for c in pairs.columns if c.startswith("x_")]
    every = slices.select(*FIELDS, *[F.lit(None).cast(pairs.schema[c].dataType).alias(c) for c in x])
    late = pairs.select(*[F.lit(None).cast(slices.schema[c].dataType).alias(c) for c in FIELDS], *x)
    own = slices.select(*[F.col(c).alias(f"own_{c}") for c in FIELDS]).repartitionById(count, "own_s")
    met = own.join(every.unionByName(late).coalesce(1).hint("shuffle_replicate_nl"))
    return met.mapInArrow(_closed(slices.count()), "weight long, degree long, closed long")
