"""Explicit state of running degrees: counters of many nodes in one state, kept between batches."""

from pyspark.sql import functions as F

from affinity_graph.streaming import stream


def test_degrees_of_many_nodes_share_a_state(spark, tmp_path):
    """Three batches with new and known nodes, ids below 0, ids far apart and nulls."""
    n = 10_000
    batches = [
        spark.range(n).select(F.col("id").alias("lo"), (F.col("id") - n).alias("hi")),
        spark.range(0, n, 3).select(F.col("id").alias("lo"), F.lit(1 << 60).alias("hi")),
        spark.createDataFrame([(5, None), (None, None), (5, -1), (1 << 61, -(1 << 62))], "lo long, hi long"),
    ]
    want, sofar = [], {}
    for k, b in enumerate(batches):
        touched = set()
        for v in (x for r in b.collect() for x in r):
            sofar[v] = sofar.get(v, 0) + 1
            touched.add(v)
        want.append({v: sofar[v] for v in touched})
        b.coalesce(1).write.parquet(f"{tmp_path}/in/k={k}")
    edges = spark.readStream.schema("lo long, hi long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    with stream.column_families(spark):
        base, progress = stream._run(stream.stateful_degrees(edges), "stateful", "update")
    got = [{r.v: r.degree for r in spark.read.parquet(f"{base}/rows/batch={k}").collect()} for k in range(3)]
    assert got == want
    states = max(op["numRowsTotal"] for p in progress for op in p["stateOperators"])
    assert len(sofar) > 2 * n and 0 < states <= 12
