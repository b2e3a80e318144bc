"""Joins of streams with tables and with streams, and a sink that keeps the newest result."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.lattice import dist2


def match_stream(queries: DataFrame, objects: DataFrame, side: int = 64) -> DataFrame:
    """(seq, ts, oid, d2) of a stream of range queries against a table of objects, by an equi-join on grid cells with a residual test."""
    r = F.ceil(F.sqrt(F.col("r2").cast("double"))).cast("long")
    span = lambda v: F.explode(F.sequence(F.floor((F.col(v) - r) / side), F.floor((F.col(v) + r) / side)))
    q = queries.select("seq", "ts", F.col("x").alias("qx"), F.col("y").alias("qy"), "r2", span("x").alias("gx"))
    q = q.withColumn("gy", F.explode(F.sequence(F.floor((F.col("qy") - F.ceil(F.sqrt(F.col("r2").cast("double"))).cast("long")) / side), F.floor((F.col("qy") + F.ceil(F.sqrt(F.col("r2").cast("double"))).cast("long")) / side))))
    o = objects.select("oid", "x", "y", F.floor(F.col("x") / side).alias("gx"), F.floor(F.col("y") / side).alias("gy"))
    d2 = dist2("x", "y", "qx", "qy")
    return q.join(o, ["gx", "gy"]).filter(d2 <= F.col("r2")).select("seq", "ts", "oid", d2.alias("d2"))


def pair_streams(a: DataFrame, b: DataFrame, key: str, within: str, delay: str = "10 minutes") -> DataFrame:
    """Rows of two streams with one key whose times differ by at most `within`. Watermarks on both sides bound the state."""
    a = a.withWatermark("ts", delay).select(F.col(key).alias("k"), F.col("ts").alias("a_ts"), F.col("seq").alias("a_seq"))
    b = b.withWatermark("ts", delay).select(F.col(key).alias("kb"), F.col("ts").alias("b_ts"), F.col("seq").alias("b_seq"))
    near = F.expr(f"k = kb AND b_ts BETWEEN a_ts - INTERVAL {within} AND a_ts + INTERVAL {within}")
    return a.join(b, near).select(F.col("k").alias(key), "a_seq", "b_seq", "a_ts", "b_ts")


def keep_newest(results: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """A foreachBatch sink: each micro-batch's newest window, written under its batch id so that a repeated batch overwrites itself."""

    def put(batch: DataFrame, number: int) -> None:
        last = batch.agg(F.max("win").alias("win"))
        batch.join(F.broadcast(last), "win").write.mode("overwrite").parquet(f"{path}/batch={number}")

    return results.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
