"""Leading eigenvalues of the adjacency matrix by block subspace iteration.

A node's row of the block is p columns of doubles. One step joins both directions of the edges with the rows on the neighbour
and sums them by node: one shuffle of 2 m rows, in generated code. The p x p Gram matrices are one aggregate, and all
that the driver sees; the rows are turned by a p x p matrix of literals.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rng import uniform
from ..sources.tables import stored
from .profile import degrees


def _columns(p: int) -> list[str]:
    return [f"x{k}" for k in range(p)]


def _multiply(arcs: DataFrame, rows: DataFrame, p: int) -> DataFrame:
    """A times the block: (v, y0..)."""
    near = arcs.join(rows.withColumnRenamed("v", "w"), "w")
    return near.groupBy("v").agg(*[F.sum(c).alias(c.replace("x", "y")) for c in _columns(p)])


def _gram(rows: DataFrame, left: list[str], right: list[str]) -> np.ndarray:
    """Left' Right: a sum in each partition, then one by entry, so that the plan does not grow with p."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(left), len(right)))
        for batch in batches:
            a, b = (np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in names]) for names in (left, right))
            total += a @ b.T
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.size)), pa.array(total.reshape(-1))], ["k", "v"])

    sums = rows.select(*dict.fromkeys([*left, *right])).mapInArrow(run, "k long, v double").groupBy("k").agg(F.sum("v").alias("v")).collect()
    out = np.zeros(len(left) * len(right))
    for r in sums:
        out[r.k] = r.v
    return out.reshape(len(left), len(right))


def _turned(rows: DataFrame, names: list[str], m: np.ndarray, out: list[str]) -> DataFrame:
    """Rows times a small matrix. Arrays keep the expression short: one dot product a column."""
    packed = rows.select("v", F.array(*names).alias("r"))
    dots = [F.aggregate(F.zip_with("r", F.array(*[F.lit(float(x)) for x in m[:, k]]), lambda a, b: a * b), F.lit(0.0), lambda acc, x: acc + x).alias(out[k]) for k in range(len(out))]
    return packed.select("v", *dots)


def leading_eigenvalues(edges: DataFrame, k: int = 50, oversample: int = 14, tol: float = 1e-6, max_iter: int = 30, seed: int = 1) -> DataFrame:
    """(rank, value): the k eigenvalues of largest magnitude; warns if they have not settled after ``max_iter`` steps."""
    spark = edges.sparkSession
    nodes = stored(degrees(edges).select("v"), "nodes")
    n = nodes.count()
    p = min(n, k + oversample)
    if not n:
        return spark.createDataFrame([], "rank int, value double")
    arcs = stored(edges.select(F.col("lo").alias("v"), F.col("hi").alias("w")).unionByName(edges.select(F.col("hi").alias("v"), F.col("lo").alias("w"))), "arcs")
    x, y = _columns(p), [c.replace("x", "y") for c in _columns(p)]
    rows = nodes.select("v", *[(uniform(seed, "v", 1000 + j) - 0.5).alias(c) for j, c in enumerate(x)])
    before = np.zeros(p)
    values = before
    for _ in range(max_iter):
        rows = stored(rows, "block")
        image = stored(_multiply(arcs, rows, p).join(rows, "v"), "image")
        # Rayleigh-Ritz in the span of the block: both Gram matrices from one pass each
        g, h, s = _gram(image, x, x), _gram(image, x, y), _gram(image, y, y)
        w, q = np.linalg.eigh((g + g.T) / 2)
        keep = w > w.max() * 1e-14
        root = q[:, keep] / np.sqrt(w[keep])
        t, z = np.linalg.eigh(root.T @ ((h + h.T) / 2) @ root)
        values = np.zeros(p)
        order = np.argsort(-np.abs(t))
        values[: len(t)] = t[order]
        top = min(k, len(t))
        if np.abs(values[:top] - before[:top]).max() <= tol * max(1e-12, np.abs(values[:top]).max()):
            break
        before = values
        # next block: an orthonormal basis of the image
        w, q = np.linalg.eigh((s + s.T) / 2)
        keep = w > w.max() * 1e-14
        base = np.zeros((p, p))
        base[:, : keep.sum()] = (q[:, keep] / np.sqrt(w[keep]))[:, ::-1]
        rows = _turned(image, y, base, x)
    else:
        warnings.warn(f"eigenvalues not settled to {tol:g} after {max_iter} steps", RuntimeWarning, stacklevel=2)
    return spark.createDataFrame([(i + 1, float(v)) for i, v in enumerate(values[: min(k, p)])], "rank int, value double")
