"""Relational operations around graphs: reports, joins in time, sketches, JSON and arrays, the SQL face."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window
from pyspark.sql.types import DoubleType

from ..plans.block_plan import Plan, block_of, register
from ..sources.tables import table
from .families import count_by


def top_hubs(nodes: DataFrame, k: int = 10) -> DataFrame:
    """The k nodes of largest degree, ties to the smaller id."""
    return nodes.orderBy(F.desc("degree"), "v").limit(k)


def top_per_class(nodes: DataFrame, k: int = 3) -> DataFrame:
    """The k smallest ids of each degree class; the rank limit is applied before the shuffle."""
    return nodes.withColumn("rank", F.row_number().over(Window.partitionBy("degree").orderBy("v"))).where(F.col("rank") <= k)


def degree_ranks(nodes: DataFrame) -> DataFrame:
    """(degree, n, dense_rank, percent_rank, cume_dist, quartile) over distinct degrees."""
    h = nodes.groupBy("degree").agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy("degree")
    return h.select("degree", "n", F.dense_rank().over(w).alias("dense_rank"), F.round(F.percent_rank().over(w), 6).alias("percent_rank"), F.round(F.cume_dist().over(w), 6).alias("cume_dist"), F.ntile(4).over(w).alias("quartile"))


def hist_jumps(hist: DataFrame) -> DataFrame:
    """(degree, n, step, next_n, moving): differences of a distribution and a moving mean over five distinct degrees."""
    w = Window.orderBy("degree")
    return hist.select("degree", "n", (F.col("n") - F.lag("n").over(w)).alias("step"), F.lead("n").over(w).alias("next_n"), F.round(F.avg("n").over(w.rowsBetween(-2, 2)), 6).alias("moving"))


def phase_rollup(gen: DataFrame, plan: Plan) -> DataFrame:
    """Edges by phase and by whether both ends are in one block, with subtotals; level tells them apart."""
    a = block_of(gen, plan, "a").withColumnRenamed("g", "ga").withColumnRenamed("block", "ba")
    both = block_of(a, plan, "b")
    same = F.coalesce((F.col("ga") == F.col("g")) & (F.col("ba") == F.col("block")), F.lit(False)).alias("same_block")
    rows = both.select(F.col("phase").cast("int").alias("phase"), same)
    return rows.rollup("phase", "same_block").agg(F.count(F.lit(1)).alias("edges"), F.grouping_id().alias("level"))


def class_cube(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges by the degree classes (powers of two) of their ends, with all margins."""
    cls = nodes.select("v", F.floor(F.log2(F.col("degree").cast("double")) + 1e-9).cast("int").alias("cls"))
    e = edges.join(cls.select(F.col("v").alias("lo"), F.col("cls").alias("class_lo")), "lo").join(cls.select(F.col("v").alias("hi"), F.col("cls").alias("class_hi")), "hi")
    return e.cube("class_lo", "class_hi").agg(F.count(F.lit(1)).alias("edges"), F.grouping_id().alias("level"))


def pivoted(summaries: DataFrame) -> DataFrame:
    """Edges and nodes of each graph with a column per model."""
    return summaries.groupBy("graph").pivot("model", ["original", "model"]).agg(F.first("nodes").alias("nodes"), F.first("edges").alias("edges"))


def previous_order(spark: SparkSession, d: str) -> DataFrame:
    """As-of join: each order with the customer's latest earlier order, by a window over the key."""
    o = table(spark, d, "orders").select("o_custkey", "o_orderkey", "o_orderdate")
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, -1)
    return o.select("o_custkey", "o_orderkey", F.last("o_orderkey", ignorenulls=True).over(w).alias("previous"))


def missing_edges(original: DataFrame, clone: DataFrame) -> DataFrame:
    """Edges of one graph that another lacks."""
    return original.join(clone, ["lo", "hi"], "left_anti").select("lo", "hi")


def shared_edges(a: DataFrame, b: DataFrame) -> DataFrame:
    """Edges of both realisations."""
    return a.select("lo", "hi").intersect(b.select("lo", "hi"))


def isolated_customers(spark: SparkSession, d: str, nodes: DataFrame) -> DataFrame:
    """Customers without an edge."""
    return table(spark, d, "customer").join(nodes.select(F.col("v").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey", "c_nationkey")


def nation_edges(spark: SparkSession, d: str, fam: DataFrame) -> DataFrame:
    """Edges between customers by pair of nations, counted from the nations of families of nodes."""
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("v"), "c_nationkey")
    return count_by(fam, c, "c_nationkey", "nation_a", "nation_b")


def hashed_sample(edges: DataFrame, per_mille: int = 100, salt: str = "s") -> DataFrame:
    """A repeatable sample of edges: the operator is the sample."""
    h = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(salt), F.col("lo").cast("string"), F.col("hi").cast("string")).cast("binary")), 1, 8), 16, 10).cast("bigint")
    return edges.where(h % 1000 < per_mille)


def json_keys(spark: SparkSession, d: str) -> DataFrame:
    """Events and distinct users by the number inside their JSON properties."""
    e = table(spark, d, "events").select("user_id", F.from_json("props", "k INT")["k"].alias("k"))
    return e.groupBy("k").agg(F.count(F.lit(1)).alias("events"), F.count_distinct("user_id").alias("users"))


def hist_map(hist: DataFrame) -> DataFrame:
    """A degree distribution as one map, and back: (degree, n, share)."""
    m = hist.agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("degree", "n")))).alias("m"))
    m = m.withColumn("total", F.aggregate(F.map_values("m"), F.lit(0).cast("bigint"), lambda a, x: a + x))
    return m.select(F.explode("m").alias("degree", "n"), "total").select("degree", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def assortativity(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(r): correlation of the degrees at the two ends, both directions counted."""
    d = nodes
    e = edges.join(d.select(F.col("v").alias("lo"), F.col("degree").cast("double").alias("x")), "lo").join(d.select(F.col("v").alias("hi"), F.col("degree").cast("double").alias("y")), "hi")
    both = e.select("x", "y").unionByName(e.select(F.col("y").alias("x"), F.col("x").alias("y")))
    return both.agg(F.round(F.corr("x", "y"), 6).alias("r"))


def degree_moments(nodes: DataFrame) -> DataFrame:
    x = F.col("degree").cast("double")
    return nodes.agg(F.round(F.avg(x), 6).alias("mean"), F.round(F.stddev_pop(x), 6).alias("deviation"), F.percentile("degree", 0.5).alias("median"))


def sketches(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(nodes_hll, edges_theta, median_kll): one-pass estimates by mergeable sketches."""
    ends = edges.select(F.explode(F.array("lo", "hi")).alias("v")).agg(F.hll_sketch_estimate(F.hll_sketch_agg("v")).alias("nodes_hll"))
    pairs = edges.agg(F.expr("theta_sketch_estimate(theta_sketch_agg(xxhash64(lo, hi)))").alias("edges_theta"))
    q = nodes.agg(F.expr("kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(degree), 0.5D)").alias("median_kll"))
    return ends.join(F.broadcast(pairs)).join(F.broadcast(q))  # one row each


def quality_by_degree(spark: SparkSession, d: str, nodes: DataFrame) -> DataFrame:
    """Labelled documents by degree: how many, and how many of quality."""
    lab = table(spark, d, "labels")
    return nodes.join(lab, nodes["v"] == lab["doc_id"]).groupBy("degree").agg(F.count(F.lit(1)).alias("labelled"), F.count_if(F.col("quality") == 1).alias("good"))


@F.pandas_udf(DoubleType())
def ks_of(x: pd.Series, y: pd.Series) -> float:
    """Grouped aggregate: largest distance of two cumulative count series given in order of degree."""
    return float(((x / max(x.sum(), 1)).cumsum() - (y / max(y.sum(), 1)).cumsum()).abs().max()) if len(x) else 0.0


def register_sql(spark: SparkSession, views: dict[str, DataFrame] | None = None) -> None:
    """The table function ``block_plan``, the aggregate ``ks_of``, and views, for use from ``spark.sql``."""
    register(spark)
    spark.udf.register("ks_of", ks_of)
    for name, df in (views or {}).items():
        df.createOrReplaceTempView(name)


def edges_by_degree(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges by the degree of their smaller end; the nodes are hashed in each partition, without a sort."""
    return edges.join(nodes.select(F.col("v").alias("lo"), "degree").hint("shuffle_hash"), "lo").groupBy("degree").agg(F.count(F.lit(1)).alias("edges"))


def lateral_blocks(plan: Plan) -> DataFrame:
    """(g, block, first_node) by a lateral join of each group with its blocks."""
    return plan.group.sparkSession.sql("SELECT g, block, first_node + block * block_size AS first_node FROM {groups}, LATERAL (SELECT explode(sequence(0L, blocks - 1)) AS block)", groups=plan.group)


def decimal_gcc(by_degree: DataFrame) -> DataFrame:
    """Global clustering as an exact decimal, from counts by degree (closed, wedges)."""
    exact = lambda c: F.sum(F.col(c).cast("decimal(38,0)"))
    return by_degree.agg((exact("closed").cast("decimal(24,0)") / exact("wedges").cast("decimal(20,0)")).cast("decimal(38,9)").cast("double").alias("gcc"))


def multiset_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of both, as often as there are, without one of each of the second's."""
    return a.unionByName(b).exceptAll(b)


def degree_shape(nodes: DataFrame) -> DataFrame:
    """(skewness, kurtosis) of degrees, population moments."""
    return nodes.agg(F.round(F.skewness("degree"), 6).alias("skewness"), F.round(F.kurtosis("degree"), 6).alias("kurtosis"))


def near_degrees(hist: DataFrame, reach: int = 2) -> DataFrame:
    """(degree, near): nodes of degrees at most ``reach`` away, by a frame of values."""
    return hist.select("degree", F.sum("n").over(Window.orderBy("degree").rangeBetween(-reach, reach)).alias("near"))


def hist_json(hist: DataFrame) -> DataFrame:
    """(degree, said): a distribution as JSON lines."""
    return hist.select("degree", F.to_json(F.struct("degree", "n")).alias("said"))


def stratified(nodes: DataFrame, share: float, seed: int) -> DataFrame:
    """Nodes of the ten smallest degrees, each degree sampled by the same share."""
    return nodes.where("degree <= 10").sampleBy("degree", {d: share for d in range(1, 11)}, seed)


def recursive_bins(spark: SparkSession, omega: float = 1.5, upto: int = 3000, steps: int = 40) -> DataFrame:
    """(lo): first degrees of log bins by recursive SQL."""
    power = f"WITH RECURSIVE p(k, x) AS (SELECT 1, 1.0D UNION ALL SELECT k + 1, x * {omega}D FROM p WHERE k < {steps})"
    return spark.sql(f"{power} SELECT DISTINCT CAST(ceil(round((x - 1) / ({omega}D - 1), 9)) AS BIGINT) + 1 AS lo FROM p WHERE ceil(round((x - 1) / ({omega}D - 1), 9)) + 1 <= {upto}")
