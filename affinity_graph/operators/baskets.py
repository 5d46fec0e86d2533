"""Clustering of graphs that tie the members of many small groups, with pairs exchanged packed and wedges not at all.

Rows (group, member) go to ranges of members, where each gets a label that says its range, its place in it and how many groups it is
in; then to their groups, where pairs are made, from the end in fewer groups to the other; then to the ranges of their tails, where
they are made distinct lists of heads and exchanged once more as such. The task of a range reads these files from all ranges, but for
blocks without a head in its own: it so knows the degrees of its nodes and closes wedges against their lists, and no list is written
twice, however many ranges its heads are in. What is exchanged are blocks of number pairs, sorted, as compressed differences.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK, RANGE_ROWS = 2_000_000, 3_000_000
CLASS, PLACE = 6, 32  # bits of a label: range, place in the range, class of the number of groups
BLOCKS = "r int, kind int, n long, block binary"
LISTS = "r int, part int, of array<int>, n long, block binary"
MARKS, WEDGES = 1 << 25, 1 << 20  # marks and wedges that a task looks at together


def _packed(*columns) -> bytes:
    """Whole numbers as differences, bytes of equal weight side by side, compressed."""
    import numpy as np
    import pyarrow as pa

    if not len(columns[0]):
        return b""
    steps = [np.diff(c, prepend=np.int64(0)) for c in columns]
    planes = [((s << 1) ^ (s >> 63)).view(np.uint8).reshape(-1, 8).T for s in steps]
    return pa.compress(np.concatenate(planes).tobytes(), codec="zstd", asbytes=True)


def _unpacked(block: bytes, n: int):
    import numpy as np
    import pyarrow as pa

    if not n:
        yield from (np.zeros(0, np.int64), np.zeros(0, np.int64))
        return
    planes = np.frombuffer(pa.decompress(block, decompressed_size=16 * n, codec="zstd", asbytes=True), np.uint8).reshape(2, 8, n)
    for p in planes:
        z = np.ascontiguousarray(p.T).view(np.uint64).ravel()
        yield np.cumsum((z >> np.uint64(1)).view(np.int64) ^ -(z & np.uint64(1)).view(np.int64))


def _rows(out: list[tuple]):
    import pyarrow as pa

    types = (pa.int32(), pa.int32(), pa.int64(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], ["r", "kind", "n", "block"])


def _sorted(a, b):
    """Distinct pairs in order."""
    import numpy as np

    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    first = np.ones(len(a), bool)
    first[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    return a[first], b[first]


def _sent(to, a, b, kind: int = 0):
    """A block for each receiver."""
    import numpy as np

    for r in np.unique(to).tolist():
        x, y = _sorted(a[to == r], b[to == r])
        yield _rows([(r, kind, len(x), _packed(x, y))])


def _received(batches) -> Iterator[tuple]:
    """(r, kind, a, b) of every block."""
    for batch in batches:
        for r, kind, n, block in zip(*(batch.column(c) for c in ("r", "kind", "n", "block"))):
            yield r.as_py(), kind.as_py(), *_unpacked(block.as_py(), n.as_py())


def _whole(batches) -> Iterator[tuple]:
    """(r, a, b): all pairs of a receiver together, distinct and in order; a partition's rows are sorted by receiver."""
    import numpy as np

    now, held = None, []

    def merged():
        both = [np.concatenate(c) for c in zip(*held)]
        held.clear()
        return _sorted(*both)

    for r, _, a, b in _received(batches):
        if r != now and held:
            yield now, *merged()
        now = r
        held.append((a, b))
    if held:
        yield now, *merged()


def _by_member(bounds: list[int], most: int) -> Callable:
    """(key, v) to the range of v."""

    def send(batches):
        import numpy as np
        import pyarrow as pa

        cuts, held, n = np.array(bounds, np.int64), [], 0

        def flush():
            t = pa.Table.from_batches(held)
            v, key = t.column("v").to_numpy(), t.column("key").to_numpy()
            yield from _sent(np.searchsorted(cuts, v, "right"), v, key)

        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= most:
                yield from flush()
                held, n = [], 0
        if n:
            yield from flush()

    return send


def _by_key(parts: int, most: int) -> Callable:
    """Members of a range get their labels and go to their groups."""

    def send(batches):
        import numpy as np

        for r, v, key in _whole(batches):
            first = np.flatnonzero(np.diff(v, prepend=v[0] - 1))
            groups = np.diff(np.append(first, len(v)))
            label = (((np.int64(r) << PLACE) + np.arange(len(first))) << CLASS) + np.floor(np.log2(groups)).astype(np.int64)
            label = np.repeat(label, groups)
            for i in range(0, len(v), most):
                k = key[i : i + most]
                mixed = k.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)
                yield from _sent((mixed % np.uint64(parts)).astype(np.int64), k, label[i : i + most])

    return send


def _paired(most: int) -> Callable:
    """Pairs of each group, to the range of the end that comes first by (class, place); a range of heads only gets an empty block."""

    def send(batches):
        import numpy as np

        def flush(held):
            tail, head = (np.concatenate(c) for c in zip(*held))
            to = tail >> (PLACE + CLASS)
            yield from _sent(to, tail, head)
            for r in np.setdiff1d(head >> (PLACE + CLASS), to).tolist():
                yield _rows([(r, 0, 0, b"")])

        mask = np.int64((1 << CLASS) - 1)
        for _, key, label in _whole(batches):
            at = np.flatnonzero(np.diff(key, prepend=key[0] - 1))
            size = np.diff(np.append(at, len(key)))
            left = np.repeat(at + size, size) - np.arange(len(key)) - 1  # members after this one in its group
            held, n = [], 0
            for i in range(0, len(key), most):
                rows, step = np.arange(i, min(i + most, len(key))), 1
                while len(rows := rows[left[rows] >= step]):
                    x, y = label[rows], label[rows + step]
                    up = (x & mask) <= (y & mask)  # places ascend inside a group
                    held.append((np.where(up, x, y), np.where(up, y, x)))
                    n += len(rows)
                    step += 1
                    if n >= 2 * most:
                        yield from flush(held)
                        held, n = [], 0
            if n:
                yield from flush(held)

    return send


def _listed(most: int) -> Callable:
    """Distinct lists of heads of a range, in blocks with the ranges of their heads."""

    def send(batches):
        import numpy as np
        import pyarrow as pa

        types = (pa.int32(), pa.int32(), pa.list_(pa.int32()), pa.int64(), pa.binary())
        for r, tail, head in _whole(batches):
            at = np.append(_starts(tail), len(tail))
            cuts = np.unique(np.append(at[np.searchsorted(at, np.arange(0, len(tail), most))], len(tail)))  # no list is cut
            for part, (i, j) in enumerate(zip(cuts, cuts[1:]) if len(tail) else [(0, 0)]):
                row = r, part, np.unique(head[i:j] >> (PLACE + CLASS)).tolist(), int(j - i), _packed(tail[i:j], head[i:j])
                yield pa.RecordBatch.from_arrays([pa.array([c], t) for c, t in zip(row, types)], ["r", "part", "of", "n", "block"])

    return send


def _starts(a):
    """Where runs of equal numbers begin."""
    import numpy as np

    return np.flatnonzero(np.append(True, a[1:] != a[:-1])) if len(a) else np.zeros(0, np.int64)


def _parts(labels):
    """Range and place of labels."""
    import numpy as np

    return labels >> (PLACE + CLASS), (labels >> CLASS) & np.int64((1 << PLACE) - 1)


class _Range:
    """The lists of a range's tails; lists are looked up against those of their heads. ``own``: (n, block), unpacked one at a time."""

    def __init__(self, r: int, own: list[tuple]):
        import numpy as np

        self.r, tails, sizes, nodes = r, [], [], {}
        for n, block in own:
            tail, head = _unpacked(block, n)
            first = _starts(tail)
            tails.append(tail[first] >> CLASS)
            sizes.append(np.diff(np.append(first, len(tail))))
            of, place = _parts(head)
            for k in np.unique(of).tolist():
                here = np.bincount(place[of == k]) > 0
                if len(nodes.get(k, ())) > len(here):
                    here = np.append(here, np.zeros(len(nodes[k]) - len(here), bool))
                here[: len(nodes.get(k, ()))] |= nodes.get(k, np.zeros(0, bool))
                nodes[k] = here
        self.tails = np.concatenate(tails)  # nodes are range and place, without class
        self.start = np.append(0, np.cumsum(np.concatenate(sizes)))
        self.cols = np.concatenate([(np.int64(k) << PLACE) + np.flatnonzero(nodes[k]) for k in sorted(nodes)] or [np.zeros(0, np.int64)])
        place = self.tails & np.int64((1 << PLACE) - 1)
        self.row = np.full((int(place[-1]) if len(place) else -1) + 2, -1, np.int32)  # of a place, with one more for places beyond
        self.row[place] = np.arange(len(place))
        self.base = np.zeros(max(nodes, default=-1) + 2, np.int64)
        self.width = np.zeros(len(self.base), np.int64)
        for k in nodes:
            self.width[k] = len(nodes[k])
        self.base[1:] = np.cumsum(self.width)[:-1]
        self.col = np.full(int(self.width.sum()) + 1, -1, np.int32)
        of, place = self.cols >> PLACE, self.cols & np.int64((1 << PLACE) - 1)
        self.col[self.base[of] + place] = np.arange(len(self.cols))
        self.near = np.concatenate([self.column(*_parts(list(_unpacked(block, n))[1])) for n, block in own])
        self.degree = np.zeros(0, np.int64)
        self.at_tail, self.at_col = np.zeros(len(self.tails), np.int64), np.zeros(len(self.cols), np.int64)
        self.closed: list[tuple] = []  # (nodes, closed) at the tails of blocks
        self.mark = np.zeros(0, bool)
        self.seen(self.tails & np.int64((1 << PLACE) - 1), np.diff(self.start))

    def column(self, of, place):
        """Numbers of heads among this range's, -1 for others."""
        import numpy as np

        of = np.minimum(of, len(self.base) - 1)  # the last range has no places
        return self.col[np.where(place < self.width[of], self.base[of] + place, -1)]

    def seen(self, places, n=None):
        """Arcs at nodes of this range."""
        import numpy as np

        more = np.bincount(places, n).astype(np.int64)
        if len(more) > len(self.degree):
            self.degree, more = more, self.degree
        self.degree[: len(more)] += more

    def look(self, tail, head):
        """Wedges at the tails of a block of lists: a head of this range and one of that head's own, closed if the list holds it too."""
        import numpy as np

        first = _starts(tail)
        at = np.append(first, len(tail))
        heads_of, place = _parts(head)
        mine = np.flatnonzero(heads_of == self.r)
        self.seen(place[mine])
        if not len(self.tails) or not len(mine):
            return
        x = self.row[np.minimum(place[mine], len(self.row) - 1)]
        mine, x = mine[x >= 0], x[x >= 0]
        col = self.column(heads_of, place)
        some = np.flatnonzero(col >= 0)
        col = col[some]
        x_at, col_at = np.searchsorted(mine, at), np.searchsorted(some, at)
        x_of, col_of = (np.repeat(np.arange(len(first)), np.diff(c)) for c in (x_at, col_at))
        ends = np.append(0, np.cumsum(self.start[x + 1] - self.start[x]))[x_at]
        closed = np.zeros(len(first), np.int64)
        most = max(1, MARKS // len(self.cols))
        i = 0
        while i < len(first):
            j = min(i + most, max(i + 1, int(np.searchsorted(ends, ends[i] + WEDGES, "right")) - 1))
            xs, cols = slice(x_at[i], x_at[j]), slice(col_at[i], col_at[j])
            if x_at[j] > x_at[i] and col_at[j] > col_at[i]:
                closed[i:j] = self._closed(x[xs], x_of[xs] - i, col[cols], col_of[cols] - i, j - i)
            i = j
        some = np.flatnonzero(closed)
        self.closed.append((tail[first[some]] >> CLASS, closed[some]))

    def _closed(self, x, x_of, col, col_of, lists: int):
        """Closed wedges of some lists: ``x`` are their heads with lists here, ``col`` those that are heads here."""
        import numpy as np

        width = len(self.cols)
        if len(self.mark) < lists * width:
            self.mark = np.zeros(lists * width, bool)
        marked = col_of * width + col
        self.mark[marked] = True
        lo, n = self.start[x], self.start[x + 1] - self.start[x]
        ends = np.cumsum(n)
        y = self.near[np.arange(ends[-1]) + np.repeat(lo - ends + n, n)]
        hit = np.flatnonzero(self.mark[y + np.repeat(x_of * width, n)])
        self.mark[marked] = False
        by = np.searchsorted(ends, hit, "right")
        np.add.at(self.at_tail, x[by], 1)
        np.add.at(self.at_col, y[hit], 1)
        return np.bincount(x_of[by], minlength=lists)

    def counts(self):
        """Degrees of this range's nodes (kind 0) and closed wedges at all nodes (kind 1), to the ranges of the nodes."""
        import numpy as np

        place = np.flatnonzero(self.degree)
        if len(place):
            yield from _sent(np.full(len(place), self.r), place, self.degree[place])
        node, closed = (np.concatenate(c) for c in zip((self.tails, self.at_tail), (self.cols, self.at_col), *self.closed))
        node, which = np.unique(node[closed > 0], return_inverse=True)
        n = np.bincount(which, closed[closed > 0], minlength=len(node)).astype(np.int64)
        yield from _sent(node >> PLACE, node & ((1 << PLACE) - 1), n, 1)


def _looked(batches):
    """Lists of all ranges against those of each range, which come with the first of them (columns own_n, own)."""
    own, waiting, now = {}, [], {}

    def opened():
        for r, lists in own.items():
            now[r] = _Range(r, lists)
        own.clear()
        for r, n, block in waiting:
            now[r].look(*_unpacked(block, n))
        waiting.clear()

    for batch in batches:
        for r, n, block, own_n, mine in zip(*(batch.column(c) for c in ("r", "n", "block", "own_n", "own"))):
            if mine.is_valid:
                if now:
                    raise ValueError("a range's own lists come first")
                own.setdefault(r.as_py(), []).append((own_n.as_py(), mine.as_py()))
            elif own:
                opened()
            if block.is_valid:
                waiting.append((r.as_py(), n.as_py(), block.as_py()))
                if now:
                    opened()
    opened()
    for x in now.values():
        yield from x.counts()


def _summed(batches):
    """(v, degree, closed) of a range's nodes."""
    import numpy as np
    import pyarrow as pa

    def out(r, degree, closed):
        place = np.flatnonzero(degree)
        closed = np.append(closed, np.zeros(max(0, len(degree) - len(closed)), np.int64))
        return pa.RecordBatch.from_arrays([pa.array(c) for c in ((np.int64(r) << PLACE) + place, degree[place], closed[place])], ["v", "degree", "closed"])

    at, sums = None, [np.zeros(0, np.int64)] * 2
    for r, kind, place, n in _received(batches):
        if r != at:
            if at is not None:
                yield out(at, *sums)
            at, sums = r, [np.zeros(0, np.int64)] * 2
        if len(place) and place[-1] >= len(sums[kind]):
            sums[kind] = np.append(sums[kind], np.zeros(place[-1] + 1 - len(sums[kind]), np.int64))
        sums[kind][place] += n  # places of a block are distinct
    if at is not None:
        yield out(at, *sums)


def closed_at_nodes(members: DataFrame, ranges: int | None = None, most: int = BLOCK) -> DataFrame:
    """(v, degree, closed) of every node with an edge, v a number of our own: nodes (column v) that share a key (column key) are tied.

    Both columns are bigints; rows with a null are in no group. ``most``: number pairs in a block, of about so many.
    """
    rows = members.select(F.col("v").cast("bigint").alias("v"), F.col("key").cast("bigint").alias("key")).where("v IS NOT NULL AND key IS NOT NULL")
    if ranges is None:
        n = rows.count()
        ranges = max(1, min(math.ceil(n / 50_000), max(members.sparkSession.sparkContext.defaultParallelism, math.ceil(n / RANGE_ROWS))))
    bounds = sorted({int(x) for x in rows.approxQuantile("v", [k / ranges for k in range(1, ranges)], 0.1 / ranges)}) if ranges > 1 else []
    for step in (_by_member(bounds, most), _by_key(ranges, most), _paired(most)):
        rows = rows.mapInArrow(step, BLOCKS).repartitionById(ranges, "r").sortWithinPartitions("r", "kind")
    lists = rows.mapInArrow(_listed(most), LISTS).repartitionById(ranges, "r")
    # Both sides read the files of one exchange: all lists in one partition, which is never written, with each range's own. What is
    # selected names all columns of both, by tests that always hold: else each side would have an exchange of its own, of fewer columns.
    own = lists.select("r", "part", F.col("of").alias("own_of"), F.col("n").alias("own_n"), F.col("block").alias("own"))
    every = lists.coalesce(1).select(F.col("part").alias("every_part"), "of", "n", "block", F.monotonically_increasing_id().alias("at"))
    first, here = F.col("at") == 0, (F.col("part") == 0) & F.array_contains("of", F.col("r"))
    met = every.join(own.hint("shuffle_replicate_nl"), first | here)
    met = met.select("r", "n", F.when(here & (F.col("every_part") >= 0), F.col("block")).alias("block"), "own_n", F.when(first & (F.size("own_of") >= 0), F.col("own")).alias("own"))
    counts = met.mapInArrow(_looked, BLOCKS).repartitionById(ranges, "r").sortWithinPartitions("r", "kind")
    return counts.mapInArrow(_summed, "v long, degree long, closed long")
