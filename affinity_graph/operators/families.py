"""Graphs that tie members of a group (all nodes that share a key), measured without making their edges.

Nodes with equal sets of keys are one family: any two of them are tied, and they have the same neighbours beside each other. So a
family is one weighted node, and degrees, triangles and pairs of the whole graph follow exactly from ties between families.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.tables import stored
from . import slices
from .profile import closed_wedges, wedges

PIECE = 256


def keys_of(members: DataFrame, *keys: str) -> DataFrame:
    """(v, keys): the sorted set of each node's keys; rows with a null are in no group."""
    whole = members.where(reduce(lambda a, b: a & b, [F.col(c).isNotNull() for c in ("v", *keys)]))
    return whole.groupBy("v").agg(F.sort_array(F.collect_set(F.struct(*keys))).alias("keys"))


def families(members: DataFrame, *keys: str) -> DataFrame:
    """(family, weight, nodes, keys): nodes with equal sets of keys, named by the smallest."""
    by = keys_of(members, *keys).groupBy("keys").agg(F.sort_array(F.collect_list("v")).alias("nodes"))
    return stored(by.select(F.col("nodes")[0].alias("family"), F.size("nodes").cast("bigint").alias("weight"), "nodes", "keys"), "families")


def _days(fam: DataFrame) -> DataFrame | None:
    """Families with days as numbers, where a day is all of a key; None for other keys. Many nodes share a day, so that pairs of families
    may be nearly all pairs: they are looked at in memory (``slices``) and not joined."""
    key = fam.schema["keys"].dataType.elementType
    if [f.dataType.typeName() for f in key] != ["date"]:
        return None
    return fam.withColumn("keys", F.transform("keys", lambda k: F.unix_date(k[key[0].name]).cast("bigint")))


def _sliced(nodes: DataFrame, *order: str, label: Column | None = None, names: bool = False) -> tuple[DataFrame, int]:
    """Stored slices of families with numbered keys."""
    rows = nodes.select(*order, "weight", (F.lit(0) if label is None else label).cast("bigint").alias("label"), "keys", "nodes" if names else F.array().cast("array<bigint>").alias("nodes"))
    out, n = slices.packed(rows, *order)
    return stored(out, "slices"), n


def links(fam: DataFrame) -> DataFrame:
    """(lo, hi): different families with a common key."""
    m = stored(fam.select("family", F.explode("keys").alias("key")), "family-keys")
    pairs = m.select("key", F.col("family").alias("lo")).join(m.select("key", F.col("family").alias("hi")), "key").where("lo < hi")
    return stored(pairs.select("lo", "hi").distinct(), "links")


def _weighed(fam: DataFrame, ties: DataFrame) -> DataFrame:
    """(v, weight, near, near_pairs, degree): nodes in tied families, pairs inside those, and each node's degree; families without an edge left out."""
    w = fam.select("family", "weight")
    both = ties.join(w.select(F.col("family").alias("lo"), F.col("weight").alias("wl")), "lo").join(w.select(F.col("family").alias("hi"), F.col("weight").alias("wh")), "hi")
    sides = both.select(F.explode(F.array(F.struct(F.col("lo").alias("v"), F.col("wh").alias("w")), F.struct(F.col("hi").alias("v"), F.col("wl").alias("w")))).alias("s")).select("s.v", "s.w")
    near = sides.groupBy("v").agg(F.sum("w").alias("near"), F.sum(wedges("w")).alias("near_pairs"))
    out = w.withColumnRenamed("family", "v").join(near, "v", "left").fillna(0, ["near", "near_pairs"])
    return out.withColumn("degree", F.col("weight") - 1 + F.col("near")).where("degree > 0")


def degree_hist(fam: DataFrame) -> DataFrame:
    """(degree, n)."""
    if (days := _days(fam)) is not None:
        return slices.degrees(*_sliced(days, "family")).groupBy("degree").agg(F.sum("weight").alias("n"))
    return _weighed(fam, links(fam)).groupBy("degree").agg(F.sum("weight").alias("n"))


def clustering_by_degree(fam: DataFrame) -> DataFrame:
    """``profile.clustering_by_degree`` of the graph: closed wedges of a node lie in its own family, between it and a tied one, in one
    tied family, or between two tied families that are tied."""
    if (days := _days(fam)) is not None:
        cut, n = _sliced(days, "family")
        return _by_degree(slices.closed(cut, stored(slices.exceeding(cut, n), "exceeding"), n))
    ties = links(fam)
    nodes = stored(_weighed(fam, ties), "weighed")
    far = closed_wedges(ties, nodes.select("v", "degree", "weight"))
    own = F.col("weight") - 1
    closed = wedges(own) + own * F.col("near") + F.col("near_pairs") + F.coalesce("closed", F.lit(0).cast("bigint"))
    return _by_degree(nodes.join(far, "v", "left").select("degree", "weight", closed.alias("closed")))


def _by_degree(each: DataFrame) -> DataFrame:
    """Classes of (degree, weight, closed) of families."""
    c = F.coalesce(F.try_divide(F.col("closed").cast("double"), wedges("degree").cast("double")), F.lit(0.0))
    by = each.groupBy("degree").agg(F.sum("weight").alias("n"), F.sum(F.col("weight") * F.col("closed")).alias("closed"), (F.sum(F.col("weight") * c) / F.sum("weight")).alias("c_mean"))
    by = by.withColumn("wedges", F.col("n") * wedges("degree"))
    return by.select("degree", "n", "closed", "wedges", F.coalesce(F.try_divide(F.col("closed").cast("double"), F.col("wedges").cast("double")), F.lit(0.0)).alias("c"), "c_mean")


def _pieces(fam: DataFrame) -> DataFrame:
    """(family, piece, nodes): families cut into runs of bounded length, so that the pairs of a large one are many rows."""
    cut = F.transform(F.sequence(F.lit(0), F.floor((F.col("weight") - 1) / PIECE).cast("int")), lambda i: F.slice("nodes", i * PIECE + 1, F.lit(PIECE)))
    return fam.select("family", "keys", F.posexplode(cut).alias("piece", "nodes"))


def pairs(fam: DataFrame) -> DataFrame:
    """(lo, hi): every edge once. Ties are made distinct between families only; their nodes are multiplied out without an exchange after."""
    if (days := _days(fam)) is not None:
        near = slices.neighbours(*_sliced(_pieces(days).withColumn("weight", F.size("nodes").cast("bigint")), "family", "piece", names=True))
        return near.select("x", F.explode("near").alias("y")).select(F.least("x", "y").alias("lo"), F.greatest("x", "y").alias("hi"))
    piece = stored(_pieces(fam).drop("keys"), "pieces")
    a, b = (piece.select(F.col("family").alias(f), F.col("piece").alias(f"p_{f}"), F.col("nodes").alias(f"n_{f}")) for f in ("lo", "hi"))
    across = links(fam).join(b, "hi").join(a, "lo").select("n_lo", "n_hi")
    inside = a.join(b, F.col("lo") == F.col("hi")).where("p_lo <= p_hi").select("n_lo", "n_hi", (F.col("p_lo") == F.col("p_hi")).alias("one"))
    ends = across.withColumn("one", F.lit(False)).unionByName(inside).select("one", F.explode("n_lo").alias("x"), "n_hi").select("one", "x", F.explode("n_hi").alias("y"))
    return ends.where("NOT one OR x < y").select(F.least("x", "y").alias("lo"), F.greatest("x", "y").alias("hi"))


def count_by(fam: DataFrame, attribute: DataFrame, x: str, a: str, b: str) -> DataFrame:
    """(a, b, edges): edges by the smaller and larger value of column ``x`` at their ends; ``attribute`` has one row (v, x) a node, nodes
    without a row are left out."""
    if (days := _days(fam)) is not None and attribute.schema[x].dataType.typeName() in ("byte", "short", "integer", "long"):
        # Nodes of a family with equal values are a family of their own; a value v goes as 2 v + 1 and a null as 0.
        own = days.select("family", "keys", F.explode("nodes").alias("v")).join(attribute, "v").groupBy("family", x).agg(F.first("keys").alias("keys"), F.count(F.lit(1)).alias("weight"))
        own = stored(own.withColumn("nodes", F.array().cast("array<bigint>")), "by-family")
        each = slices.labelled(*_sliced(own, "family", x, label=F.coalesce(F.col(x).cast("bigint") * 2 + 1, F.lit(0))))
        back = [F.when(F.col(c) != 0, F.shiftright(c, 1)).cast(attribute.schema[x].dataType).alias(c) for c in ("a", "b")]
        return each.select(*back, "edges").groupBy(F.least("a", "b").alias(a), F.greatest("a", "b").alias(b)).agg(F.sum("edges").alias("edges"))
    h = fam.select("family", F.explode("nodes").alias("v")).join(attribute, "v").groupBy("family", x).agg(F.count(F.lit(1)).alias("k"))
    h = stored(h, "by-family")
    p, q = (h.select(F.col("family").alias(f), F.col(x).alias(f"x_{f}"), F.col("k").alias(f"k_{f}")) for f in ("lo", "hi"))
    across = links(fam).join(p, "lo").join(q, "hi").select("x_lo", "x_hi", (F.col("k_lo") * F.col("k_hi")).alias("edges"))
    mixed = p.join(q, F.col("lo") == F.col("hi"))
    # Values are told apart null-safe, and of two orders the one with nulls first is taken.
    before: Column = F.col("x_hi").isNotNull() & (F.col("x_lo").isNull() | (F.col("x_lo") < F.col("x_hi")))
    inside = mixed.select("x_lo", "x_hi", F.when(F.col("x_lo").eqNullSafe(F.col("x_hi")), wedges("k_lo")).when(before, F.col("k_lo") * F.col("k_hi")).otherwise(0).alias("edges")).where("edges > 0")
    return across.unionByName(inside).groupBy(F.least("x_lo", "x_hi").alias(a), F.greatest("x_lo", "x_hi").alias(b)).agg(F.sum("edges").alias("edges"))


def touched(members: DataFrame, *keys: str) -> DataFrame:
    """(v): nodes that share a key with another one."""
    shared = members.groupBy(*keys).agg(F.min("v").alias("first"), F.max("v").alias("last")).where("first < last").select(*keys)
    return members.join(shared, list(keys), "left_semi").where("v IS NOT NULL").select("v").distinct()


def among(edges: DataFrame, members: DataFrame, *keys: str) -> DataFrame:
    """Those of the given edges whose ends share a key: both are in one family or in tied ones, so that the group graph is not made."""
    fam = families(members, *keys)
    of = stored(fam.select("family", F.explode("nodes").alias("v")), "nodes")
    both = edges.join(of.select(F.col("v").alias("lo"), F.col("family").alias("x")), "lo").join(of.select(F.col("v").alias("hi"), F.col("family").alias("y")), "hi")
    tied = links(fam).select(F.col("lo").alias("x"), F.col("hi").alias("y"), F.lit(True).alias("tied"))
    both = both.select("lo", "hi", F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"))
    return both.join(tied, ["x", "y"], "left").where("x = y OR tied").select("lo", "hi")
