"""Streams: generation of independent edges, co-activity edges in windows, running degrees."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators.generate import global_edges, local_edges, phase_coin
from ..plans.block_plan import Plan
from ..sources.tables import is_directory, shared_dir, table

EVENT_SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, late: str = "10 minutes") -> DataFrame:
    """The events table as a stream, with event time and a watermark (which takes a time-zoned type only)."""
    folder = is_directory(spark, f"{sf_dir}/events.parquet")
    raw = spark.readStream.schema(EVENT_SCHEMA).option("pathGlobFilter", "*.parquet" if folder else "events.parquet")
    stream = raw.parquet(f"{sf_dir}/events.parquet" if folder else sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def generate_stream(plan: Plan, rows_per_batch: int = 100_000, seed: int = 1, kind: str = "fast", start: int = 0) -> DataFrame:
    """An endless stream of generated edges: the value of a rate source is the edge's id, so batches repeat a batch run's rows."""
    spark = plan.degree.sparkSession
    one, two = plan.totals()
    ids = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows_per_batch).load().select((F.col("value") + start).alias("edge_id"))
    coin = phase_coin(ids, one / (one + two) if one + two else 0.0, seed, kind)
    return local_edges(coin.where("local"), plan, seed, kind).unionByName(global_edges(coin.where("NOT local"), plan, seed, kind))


def window_members(events: DataFrame, kind: str = "tumbling") -> DataFrame:
    """(start, end, user_id, events) of users active in event-time windows; a session is one user's run of events without a gap of ten minutes."""
    if kind == "tumbling":
        w, keys = F.window("ts", "5 minutes"), []
    elif kind == "sliding":
        w, keys = F.window("ts", "15 minutes", "5 minutes"), []
    elif kind == "session":
        w, keys = F.session_window("ts", "10 minutes"), ["user_id"]
    else:
        raise ValueError(f"unknown window: {kind}")
    if kind == "session":
        return events.groupBy(w.alias("w"), *keys).agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "events")
    return events.groupBy(w.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "events")


def by_nation(events: DataFrame, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-static join: events by the nation of the customer with the user's id."""
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return events.join(customers, "user_id").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("events"))


def followed_within(a: DataFrame, b: DataFrame, minutes: int = 60) -> DataFrame:
    """Stream-stream join: pairs of a user's events at most ``minutes`` apart. The bound on event time lets the state of both sides go."""
    x = a.select(F.col("user_id").alias("user_id"), F.col("event_id").alias("first_id"), F.col("ts").alias("ts_a"))
    y = b.select(F.col("user_id").alias("user_b"), F.col("event_id").alias("second_id"), F.col("ts").alias("ts_b"))
    near = F.expr(f"user_id = user_b AND first_id < second_id AND ts_b >= ts_a AND ts_b <= ts_a + INTERVAL {minutes} MINUTES")
    return x.join(y, near).select("user_id", "first_id", "second_id")


def unique_within_watermark(pairs: DataFrame) -> DataFrame:
    """Simple pairs of a stream with event time: repeats within the watermark go, with state bounded by it."""
    return pairs.where("lo < hi").dropDuplicatesWithinWatermark(["lo", "hi"])


def running_degrees(edges: DataFrame) -> DataFrame:
    """(v, degree) of an edge stream, updated as it grows."""
    return edges.select(F.explode(F.array("lo", "hi")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("degree"))


NODES_PER_STATE = 4096


class DegreeState(StatefulProcessor):
    """Running degrees as explicit state: the counters of a run of node ids together, so that Python is called once a run and not once a node."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.counts = handle.getValueState("degrees", "ids binary, degrees binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        import numpy as np

        parts = [(np.frombuffer(i, np.int64), np.frombuffer(n, np.int64)) for frame in rows for i, n in zip(frame["ids"], frame["degrees"])]
        new, of = np.unique(np.concatenate([i for i, _ in parts]), return_inverse=True)
        more = np.zeros(len(new), np.int64)
        np.add.at(more, of, np.concatenate([n for _, n in parts]))
        if self.counts.exists():
            had, n = (np.frombuffer(b, np.int64) for b in self.counts.get())
            at = np.minimum(np.searchsorted(had, new), len(had) - 1)
            more += np.where(had[at] == new, n[at], 0)
            kept = ~np.isin(had, new, assume_unique=True)
            all_, of_all = np.concatenate([had[kept], new]), np.concatenate([n[kept], more])
        else:
            all_, of_all = new, more
        order = np.argsort(all_)
        self.counts.update((all_[order].tobytes(), of_all[order].tobytes()))
        yield pd.DataFrame({"v": pd.array([None] if pd.isna(key[0]) else new, "Int64"), "degree": more})

    def close(self) -> None:
        pass


def _counted(batches):
    """Node ids of a batch to (run, ids, degrees): one row for each run of ids, and one without a run for nulls."""
    import numpy as np
    import pyarrow as pa

    for batch in batches:
        v = batch.column("v")
        ids, n = np.unique(v.drop_null().to_numpy(), return_counts=True)
        run = ids // NODES_PER_STATE
        at = np.append(np.flatnonzero(np.diff(run, prepend=run[:1] - 1)), len(run))
        rows = [(int(run[i]), ids[i:j].tobytes(), n[i:j].astype(np.int64).tobytes()) for i, j in zip(at, at[1:])]
        if v.null_count:
            rows.append((None, np.zeros(1, np.int64).tobytes(), np.array([v.null_count], np.int64).tobytes()))
        if rows:
            types = (pa.int64(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], ["run", "ids", "degrees"])


@contextmanager
def column_families(spark: SparkSession) -> Iterator[None]:
    """Queries started inside keep their state in RocksDB, which explicit state needs; the session's setting comes back after."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def stateful_degrees(edges: DataFrame) -> DataFrame:
    """(v, degree) of an edge stream, a row per node and batch with its degree so far. Run it inside ``column_families``."""
    ends = edges.select(F.explode(F.array("lo", "hi")).alias("v")).mapInArrow(_counted, "run long, ids binary, degrees binary")
    return ends.groupBy("run").transformWithStateInPandas(DegreeState(), outputStructType="v long, degree long", outputMode="Update", timeMode="None")


def _run(stream: DataFrame, name: str, mode: str) -> tuple[str, list]:
    base = f"{shared_dir(stream.sparkSession)}/{name}-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows/batch={number if mode != 'complete' else 0}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/checkpoint").foreachBatch(write).trigger(availableNow=True).start()
    query.awaitTermination()
    return base, query.recentProgress


def finished(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return its sink as a table. Each batch replaces its own folder, so that a repeated batch
    leaves no double rows; in complete mode the last batch is the result."""
    base, _ = _run(stream, name, mode)
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{base}/rows").select(*stream.columns)


def late_rows(stream: DataFrame, name: str = "late") -> int:
    """Rows that came after the watermark and were dropped by the stream's stateful operators, counted as they reach those:
    an aggregate combines a batch's rows of one group before."""
    _, progress = _run(stream, name, "append")
    return sum(op["numRowsDroppedByWatermark"] for p in progress for op in p["stateOperators"])


def generated_by_stream(plan: Plan, rows: int, seed: int = 1, kind: str = "fast") -> DataFrame:
    """The first ``rows`` edges of ``generate_stream``, as a table."""
    return finished(generate_stream(plan, rows, seed, kind), "generated")
