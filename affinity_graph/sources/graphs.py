"""Graphs on the given tables. Each builder returns simple undirected edges (lo < hi, distinct)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..operators import families
from .tables import stored, table

LINE_LENGTH, LINE_DOCUMENTS = 15, 60


def to_simple(raw: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """Drop direction, loops, repeats and pairs with nulls."""
    pair = raw.select(F.least(src, dst).cast("bigint").alias("lo"), F.greatest(src, dst).cast("bigint").alias("hi"), (F.col(src).isNotNull() & F.col(dst).isNotNull()).alias("whole"))
    return pair.where("whole AND lo < hi").select("lo", "hi").distinct()


def _together(members: DataFrame, *keys: str) -> DataFrame:
    """Pairs of members (column v) that share a key."""
    m = stored(members.distinct(), "members")  # both sides of the join read what was made distinct once
    return to_simple(m.alias("x").join(m.withColumnRenamed("v", "w").alias("y"), list(keys)).where("v < w").select(F.col("v").alias("src"), F.col("w").alias("dst")))


def _hashed(c: Column, side: int) -> Column:
    return F.conv(F.substring(F.md5(c.cast("binary")), 1, 12), 16, 10).cast("bigint") * 2 + side


def doc_line(spark: SparkSession, d: str, most: int | None = LINE_DOCUMENTS) -> DataFrame:
    """Documents that share a trimmed line that 2 to ``most`` documents have (None: any number); more widespread lines are no tie by
    this graph's definition."""
    lines = table(spark, d, "documents").select(F.col("doc_id").alias("v"), F.explode(F.split("text", "\n")).alias("line")).select("v", F.trim("line").alias("line")).where(F.length("line") > LINE_LENGTH)
    lines = lines.select("v", F.md5(F.col("line").cast("binary")).alias("line")).distinct()
    some = lines.groupBy("line").count().where((F.col("count") >= 2) & (F.lit(True) if most is None else F.col("count") <= most)).select("line")
    return _together(lines.join(some, "line"), "line")


def part_basket_members(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"), F.col("l_partkey").alias("v"))


def part_basket(spark: SparkSession, d: str) -> DataFrame:
    return _together(part_basket_members(spark, d), "key")


def supp_basket(spark: SparkSession, d: str) -> DataFrame:
    return _together(table(spark, d, "lineitem").select("l_orderkey", F.col("l_suppkey").alias("v")), "l_orderkey")


def cust_day_members(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").select(F.to_date("o_orderdate").alias("day"), F.col("o_custkey").alias("v"))


def cust_day(spark: SparkSession, d: str) -> DataFrame:
    return families.pairs(families.families(cust_day_members(spark, d), "day"))


def user_next(spark: SparkSession, d: str) -> DataFrame:
    """Users of consecutive events. The order is taken within hours; one row per hour links an hour to the one before."""
    events = table(spark, d, "events").select("ts", "event_id", "user_id", F.date_trunc("hour", "ts").alias("hour"))
    inside = Window.partitionBy("hour").orderBy("ts", "event_id")
    inner = events.select(F.lag("user_id").over(inside).alias("src"), F.col("user_id").alias("dst"))
    at = F.struct("ts", "event_id")
    hours = events.groupBy("hour").agg(F.min_by("user_id", at).alias("first"), F.max_by("user_id", at).alias("last"))
    across = hours.select(F.lag("last").over(Window.orderBy("hour")).alias("src"), F.col("first").alias("dst"))
    return to_simple(inner.unionByName(across))


def user_props_members(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").select("event_type", "props", F.date_trunc("hour", "ts").alias("hour"), F.col("user_id").alias("v"))


def user_props(spark: SparkSession, d: str) -> DataFrame:
    """Users with an event of the same type and properties within one clock hour."""
    return _together(user_props_members(spark, d), "event_type", "props", "hour")


def users_within(spark: SparkSession, d: str, seconds: int = 3600) -> DataFrame:
    """Users with an event of the same type and properties at most ``seconds`` apart: equi-join on time buckets, then the interval."""
    e = table(spark, d, "events").select("event_type", "props", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), F.col("user_id").alias("v"))
    width = seconds * 1_000_000
    left = e.withColumn("bucket", F.expr(f"us div {width}"))
    right = left.select("event_type", "props", F.col("us").alias("us2"), F.col("v").alias("w"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
    near = left.join(right, ["event_type", "props", "bucket"]).where((F.col("us") >= F.col("us2")) & (F.col("us") - F.col("us2") <= width))
    return to_simple(near.select(F.col("v").alias("src"), F.col("w").alias("dst")))


def user_window_members(spark: SparkSession, d: str, minutes: int = 5) -> DataFrame:
    return table(spark, d, "events").select(F.window(F.col("ts").cast("timestamp"), f"{minutes} minutes")["start"].alias("w0"), F.col("user_id").alias("v"))


def user_window(spark: SparkSession, d: str, minutes: int = 5) -> DataFrame:
    return _together(user_window_members(spark, d, minutes), "w0")


def _hrefs(c: str) -> Column:
    return F.explode(F.regexp_extract_all(c, F.lit('href="([^"]+)"'), F.lit(1)))


def page_href(spark: SparkSession, d: str) -> DataFrame:
    links = table(spark, d, "pages").select((F.col("page_id") * 2).alias("src"), _hrefs("html").alias("href"))
    return to_simple(links.select("src", _hashed(F.col("href"), 1).alias("dst")))


def host_href(spark: SparkSession, d: str) -> DataFrame:
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)
    links = table(spark, d, "pages").select(_hashed(host, 0).alias("src"), _hrefs("html").alias("href"))
    return to_simple(links.select("src", _hashed(F.col("href"), 1).alias("dst")))


def cust_order(spark: SparkSession, d: str) -> DataFrame:
    return to_simple(table(spark, d, "orders").select((F.col("o_custkey") * 2).alias("src"), (F.col("o_orderkey") * 2 + 1).alias("dst")))


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return to_simple(table(spark, d, "lineitem").select((F.col("l_orderkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst")))


def turn_chain(spark: SparkSession, d: str) -> DataFrame:
    turns = table(spark, d, "conversations").select("conv_id", "turn", (F.col("conv_id") * 1000 + F.col("turn")).alias("dst"))
    return to_simple(turns.select(F.lag("dst").over(Window.partitionBy("conv_id").orderBy("turn")).alias("src"), "dst"))


def vec_knn(spark: SparkSession, d: str, k: int = 10, block: int = 512) -> DataFrame:
    """Each vector's k nearest by cosine (rounded to 9 places, ties to the smaller id): blocks of queries against blocks of rows.

    Every block pair is a task of bounded size that keeps its k best per query; the best of a query's blocks are ranked after.
    """
    v = table(spark, d, "embeddings").select("vec_id", "embedding")
    n = max(1, -(-v.count() // block))
    mine = F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    other = F.sequence(F.lit(0), F.lit(n - 1))
    queries = v.select("vec_id", "embedding", mine.alias("q"), F.explode(other).alias("r"), F.lit(True).alias("asks"))
    rows = v.select("vec_id", "embedding", F.explode(other).alias("q"), mine.alias("r"), F.lit(False).alias("asks"))

    def best(pdf):
        import numpy as np
        import pandas as pd

        def unit(x):
            m = np.array(x["embedding"].tolist(), np.float64)
            return m / np.maximum(np.sqrt((m * m).sum(axis=1, keepdims=True)), 1e-300)

        asks, has = pdf[pdf.asks].sort_values("vec_id"), pdf[~pdf.asks].sort_values("vec_id")
        if not len(asks) or not len(has):
            return pd.DataFrame({"src": [], "dst": [], "sim": []}).astype({"src": "int64", "dst": "int64", "sim": "float64"})
        sim = np.round(unit(asks) @ unit(has).T, 9)
        sim[asks.vec_id.to_numpy()[:, None] == has.vec_id.to_numpy()[None, :]] = -2
        top = np.argsort(-sim, axis=1, kind="stable")[:, :k]
        out = pd.DataFrame({"src": np.repeat(asks.vec_id.to_numpy(), top.shape[1]), "dst": has.vec_id.to_numpy()[top.ravel()], "sim": np.take_along_axis(sim, top, 1).ravel()})
        return out[out.sim > -2]

    near = queries.unionByName(rows).groupBy("q", "r").applyInPandas(best, "src long, dst long, sim double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("sim"), "dst"))
    return to_simple(near.withColumn("rank", rank).where(F.col("rank") <= k))


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (doc_line, part_basket, cust_day, user_next, user_props, user_window, page_href, host_href, cust_order, order_part, supp_basket, turn_chain, vec_knn)}

#: Graphs whose groups grow with the table: their members and the keys that tie them, for measures by families of nodes.
MEMBERS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], tuple[str, ...]]] = {"cust_day": (cust_day_members, ("day",)), "user_props": (user_props_members, ("event_type", "props", "hour"))}

#: Graphs of many small groups: their members (key, v), for clustering by packed pairs.
BASKETS: dict[str, Callable[[SparkSession, str], DataFrame]] = {"part_basket": part_basket_members}

#: The 73-node example: nodes per degree (fixed values).
FIXTURE73 = {1: 26, 2: 20, 3: 10, 4: 6, 5: 4, 6: 3, 7: 2, 8: 1, 9: 1}


def fixture73(spark: SparkSession) -> DataFrame:
    """The example's profile with clustering 0.9 exp(-0.1 (d - 1))."""
    rows = spark.createDataFrame(list(FIXTURE73.items()), "degree long, n long")
    return rows.select(F.lit("fixture73").alias("graph"), "degree", "n", F.when(F.col("degree") > 1, F.lit(0.9) * F.exp(F.lit(-0.1) * (F.col("degree") - 1))).otherwise(0.0).alias("c"))
