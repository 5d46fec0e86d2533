"""A data source of generated edges: ``spark.read.format("affinity_edges")``, a fixed number of edges a task and no input file.

Options: ``plan`` (JSON of the plan's rows, as ``plan_json`` makes it), ``seed``, ``edges`` (total), ``edges_per_task``.
Every task draws its own id range with a generator seeded by (seed, task): the same plan, seed and task size give the same
edges. ``spark.range`` with counter-based uniforms is the faster default; this is the form that needs no expressions.
"""

from __future__ import annotations

import json
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "edge_id long, phase tinyint, a long, b long"


def plan_json(plan) -> str:
    """A plan's rows (distinct degrees and groups only) as one string."""
    g = [(r["first_node"], r["blocks"], r["block_size"], r["w"]) for r in plan.group.orderBy("g").collect()]
    d = [(r["first_node"], r["n_fill"], max(0, r["n"] - r["n_fill"]), r["r"], r["w"]) for r in plan.degree.orderBy("degree").collect()]
    return json.dumps({"groups": g, "degrees": d})


class EdgeRange(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class EdgeReader(DataSourceReader):
    def __init__(self, options: dict):
        self.plan = json.loads(options["plan"])
        self.seed = int(options.get("seed", 1))
        self.weights = [sum(x[-1] for x in self.plan[k]) for k in ("groups", "degrees")]
        self.total = int(options.get("edges", math.floor(sum(self.weights) + 0.5)))
        self.per_task = int(options.get("edges_per_task", options.get("edgespertask", 1_000_000)))

    def partitions(self) -> list[InputPartition]:
        return [EdgeRange(s, min(self.total, s + self.per_task)) for s in range(0, max(1, self.total), self.per_task)]

    def read(self, partition: EdgeRange) -> Iterator[pa.RecordBatch]:
        n = partition.stop - partition.start
        if n <= 0:
            return
        rng = np.random.default_rng([self.seed, partition.start])
        groups, degrees = (np.array(self.plan[k], float).reshape(len(self.plan[k]), -1) for k in ("groups", "degrees"))
        one, two = self.weights
        local = rng.random(n) < one / (one + two)
        a, b = np.zeros(n, np.int64), np.zeros(n, np.int64)
        k = int(local.sum())
        if k:
            g = groups[np.searchsorted(np.cumsum(groups[:, 3]), rng.random(k) * groups[:, 3].sum(), side="right").clip(0, len(groups) - 1)]
            base = g[:, 0] + np.floor(rng.random(k) * g[:, 1]) * g[:, 2]
            i, j = np.floor(rng.random(k) * g[:, 2]), np.floor(rng.random(k) * (g[:, 2] - 1))
            a[local], b[local] = base + i, base + j + (j >= i)
        for end in (a, b):
            d = degrees[np.searchsorted(np.cumsum(degrees[:, 4]), rng.random(n - k) * degrees[:, 4].sum(), side="right").clip(0, len(degrees) - 1)] if n > k else degrees[:0]
            filler, u = rng.random(n - k) < d[:, 3], rng.random(n - k)
            end[~local] = d[:, 0] + np.where(filler, np.floor(u * d[:, 1]), d[:, 1] + np.floor(u * d[:, 2]))
        ids = np.arange(partition.start, partition.stop)
        for lo in range(0, n, 65_536):
            s = slice(lo, lo + 65_536)
            yield pa.RecordBatch.from_arrays([pa.array(ids[s]), pa.array(np.where(local[s], 1, 2).astype(np.int8)), pa.array(a[s]), pa.array(b[s])], ["edge_id", "phase", "a", "b"])


class EdgeSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "affinity_edges"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> EdgeReader:
        return EdgeReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(EdgeSource)
