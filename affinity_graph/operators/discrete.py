"""Weighted draws from a table of bins, all by inversion of the same uniform.

``guide`` cuts [0, 1) into as many slots as there are bins and lists for each slot the bins that reach into it, so that a draw
is an equi-join on the slot and an interval test. It equals ``scan`` row by row; ``search`` and ``array`` too. ``alias``
follows the same law with other draws. Tables have a row per distinct degree or group; that count is read and checked
before they are broadcast, and beyond ``BROADCAST_BINS`` the join is left to the optimizer.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

BROADCAST_BINS, ARRAY_BINS = 2_000_000, 4096
PLACES = 9


def cumulative(weights: DataFrame, key: str, weight: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """(bin, lo, hi, *keep): intervals of [0, 1) in order of ``key``; weights are rounded to 9 places and summed exactly."""
    w = F.greatest(F.col(weight), F.lit(0.0)).cast(f"decimal(28,{PLACES})")
    rows = weights.select(F.col(key).alias("bin"), w.alias("q"), *[F.col(c) for c in keep]).where("q > 0")
    run = F.sum("q").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0))
    total = F.sum("q").over(Window.partitionBy())
    rows = rows.withColumn("run", run).withColumn("total", total)
    return rows.select("bin", ((F.col("run") - F.col("q")).cast("double") / F.col("total").cast("double")).alias("lo"), (F.col("run").cast("double") / F.col("total").cast("double")).alias("hi"), *keep)


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_BINS else df


def guide_table(dist: DataFrame, slots: int) -> DataFrame:
    """(slot, lo, hi, bin, ...): every bin once for each slot its interval reaches into."""
    first, last = F.floor(F.col("lo") * slots), F.least(F.floor(F.col("hi") * slots), F.lit(slots - 1))
    return dist.withColumn("slot", F.explode(F.sequence(first, last)))


def draw(df: DataFrame, u: Column, dist: DataFrame, method: str = "guide", bins: int | None = None) -> DataFrame:
    """``df`` with the columns of the drawn bin of ``dist`` but lo and hi."""
    bins = dist.count() if bins is None else bins
    carried = [c for c in dist.columns if c not in ("lo", "hi")]
    rows = df.withColumn("u_", u)
    if method == "scan":
        out = rows.join(_small(dist, bins), (F.col("u_") >= F.col("lo")) & (F.col("u_") < F.col("hi")))
    elif method == "guide":
        slots = max(1, bins)
        table = guide_table(dist, slots)
        rows = rows.withColumn("slot", F.least(F.floor(F.col("u_") * slots), F.lit(slots - 1)))
        out = rows.join(_small(table, 2 * bins), "slot").where((F.col("u_") >= F.col("lo")) & (F.col("u_") < F.col("hi")))
    elif method in ("search", "array"):
        # both need the cumulative values as one array, which is collected only for tables of checked size
        if bins > (BROADCAST_BINS if method == "search" else ARRAY_BINS):  # an array is literals of one expression
            raise ValueError("too many bins for one array; use guide")
        table = dist.select("bin", "hi").orderBy("hi").collect()
        his, names = [float(r["hi"]) for r in table], [r["bin"] for r in table]
        if method == "search":

            @F.pandas_udf("long")
            def place(us: Iterator[pd.Series]) -> Iterator[pd.Series]:
                cut, name = np.array(his), np.array(names)
                for x in us:
                    yield pd.Series(name[np.minimum(np.searchsorted(cut, x.to_numpy(), side="right"), len(name) - 1)])

            found = place("u_")
        else:
            below = F.size(F.filter(F.array(*map(F.lit, his)), lambda h: h <= F.col("u_")))
            found = F.element_at(F.array(*map(F.lit, names)), below + 1)
        out = rows.withColumn("bin", found).join(_small(dist.drop("lo", "hi"), bins), "bin")
    elif method == "alias":
        slots = max(1, bins)
        rows = rows.withColumn("slot", F.least(F.floor(F.col("u_") * slots), F.lit(slots - 1)))
        rows = rows.join(_small(alias_table(dist, slots), bins), "slot")
        rows = rows.withColumn("bin", F.when(F.col("u_") * slots - F.col("slot") < F.col("cut"), F.col("one")).otherwise(F.col("two"))).drop("cut", "one", "two")
        out = rows.join(_small(dist.drop("lo", "hi"), bins), "bin")
    else:
        raise ValueError(f"unknown method of drawing: {method}")
    return out.select(*df.columns, *carried)


def locate(df: DataFrame, value: str, ranges: DataFrame, lo: str, hi: str, how: str = "inner") -> DataFrame:
    """``df`` with the row of ``ranges`` (disjoint, lo <= value < hi) that its whole number ``value`` falls in.

    As with ``guide``, the span of values is cut into as many slots as there are ranges: an equi-join on the slot and an interval test,
    two rows a value on average. The number of ranges, a row per distinct degree or group, is read before they are broadcast.
    """
    rows, first, last = ranges.agg(F.count(F.lit(1)), F.min(lo), F.max(hi)).head()
    width = max(1, -(-((last or 0) - (first or 0)) // max(1, rows)))
    slot = lambda c: F.expr(f"({c} - {first or 0}L) div {width}L")
    table = ranges.withColumn("slot_", F.explode(F.sequence(slot(lo), slot(f"({hi} - 1)"))))
    hit = (F.col("of_") == F.col("slot_")) & (F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))
    return df.withColumn("of_", slot(value)).join(_small(table, 2 * rows), hit, how).drop("of_", "slot_")


def alias_table(dist: DataFrame, slots: int) -> DataFrame:
    """(slot, cut, one, two): each slot is shared by two bins at most. Built on the driver from a table of checked size."""
    if slots > BROADCAST_BINS:
        raise ValueError("too many bins for an alias table; use guide")
    rows = dist.select("bin", (F.col("hi") - F.col("lo")).alias("p")).orderBy("bin").collect()
    mass = {r["bin"]: r["p"] * slots for r in rows}
    poor, rich, out = [b for b, m in mass.items() if m < 1], [b for b, m in mass.items() if m >= 1], []
    while poor and rich:
        a, b = poor.pop(), rich[-1]
        out.append((a, float(mass[a]), b))
        mass[b] -= 1 - mass[a]
        if mass[b] < 1:
            poor.append(rich.pop())
    out += [(b, 1.0, b) for b in poor + rich]
    return dist.sparkSession.createDataFrame([(k, c, a, b) for k, (a, c, b) in enumerate(out)], "slot long, cut double, one long, two long")
