"""Streaming forms of the sketch and of the windowed statistics.

Coins depend on ids only, so the sample of a stream is the sample of the table it becomes; whatever
the batches, their merged sketch equals the batch sketch.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.layered import Sketch, _finish, edge_layers
from ..operators.params import Params

_ROWS = "guess int, layer int, eid string, u long, v long, keep_u boolean, keep_v boolean"


def deduplicated(edges: DataFrame, watermark: str = "2 hours") -> DataFrame:
    """Replayed edges (equal eid) count once within the watermark; copies with other ids stay."""
    return edges.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["eid"])


def sampled_stream(edges: DataFrame, params: Params) -> DataFrame:
    """The stateless part: coins and hash filters in append mode."""
    return edge_layers(edges, {0: params})


def stream_sketch(edges: DataFrame, params: Params, path: str, checkpoint: str) -> StreamingQuery:
    """Each micro-batch writes its sample and count under its batch id; a replayed batch overwrites its
    own folder, so nothing counts twice.  Read the sketch with ``read_sketch``."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch = batch.persist()
        edge_layers(batch.select("eid", "u", "v"), {0: params}).write.mode("overwrite").parquet(f"{path}/rows/batch={batch_id}")
        batch.agg(F.count(F.lit(1)).alias("m")).write.mode("overwrite").parquet(f"{path}/m/batch={batch_id}")
        batch.unpersist()

    return edges.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_sketch(spark: SparkSession, path: str, params: Params) -> Sketch:
    """Merges all batches: counters add, samples unite, caps apply."""
    rows = spark.read.schema(_ROWS).parquet(f"{path}/rows").select("guess", "layer", "eid", "u", "v", "keep_u", "keep_v").distinct()
    m = spark.read.parquet(f"{path}/m").agg(F.sum("m").alias("m"))
    return _finish(rows.persist(), m, {0: params})


def compact_batches(spark: SparkSession, path: str) -> None:
    """Rewrites all batches as one (between runs of the stream)."""
    rows = spark.read.schema(_ROWS + ", batch long").parquet(f"{path}/rows")
    m = spark.read.schema("m long, batch long").parquet(f"{path}/m").agg(F.sum("m").alias("m"), F.max("batch").alias("batch"))
    last = m.first()["batch"]
    rows.drop("batch").distinct().write.mode("overwrite").parquet(f"{path}-compact/rows/batch={last}")
    m.select("m").write.mode("overwrite").parquet(f"{path}-compact/m/batch={last}")


def windowed_degrees(edges: DataFrame, duration: str = "1 day", slide: str | None = None, watermark: str = "2 hours") -> DataFrame:
    """(w, vid, d_out, deg) by event-time window; rows beyond the watermark are dropped."""
    w = F.window("ts", duration, slide) if slide else F.window("ts", duration)
    x = edges.withWatermark("ts", watermark).select("ts", F.explode(F.array(F.struct(F.col("u").alias("vid"), F.lit(1).alias("o")), F.struct(F.col("v").alias("vid"), F.lit(0).alias("o")))).alias("e"))
    return x.groupBy(w.alias("w"), F.col("e.vid").alias("vid")).agg(F.sum("e.o").alias("d_out"), F.count(F.lit(1)).alias("deg"))


def windowed_bias(spark: SparkSession, edges: DataFrame, path: str, checkpoint: str, duration: str = "1 day", slide: str | None = None, watermark: str = "2 hours") -> StreamingQuery:
    """Appends finished windows' vertex degrees to a table; ``net_of_windows`` reads it."""
    return windowed_degrees(edges, duration, slide, watermark).writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()


def net_of_windows(spark: SparkSession, path: str) -> DataFrame:
    x = spark.read.parquet(path)
    return x.groupBy(F.col("w.start").alias("start")).agg(F.count(F.lit(1)).alias("n"), F.sum("d_out").alias("m"), F.sum(F.abs(2 * F.col("d_out") - F.col("deg"))).alias("net"))


def sessions(edges: DataFrame, gap: str = "30 minutes", watermark: str = "2 hours") -> DataFrame:
    """(vid, start, n): sessions of each vertex, streaming."""
    x = edges.withWatermark("ts", watermark).select("ts", F.explode(F.array("u", "v")).alias("vid"))
    s = x.groupBy(F.session_window("ts", gap).alias("s"), "vid").agg(F.count(F.lit(1)).alias("n"))
    return s.select("vid", F.col("s.start").alias("start"), "n")


def running_totals(edges: DataFrame) -> DataFrame:
    """Update mode: degrees of every vertex so far (state by vertex)."""
    x = edges.select(F.explode(F.array(F.struct(F.col("u").alias("vid"), F.lit(1).alias("o")), F.struct(F.col("v").alias("vid"), F.lit(0).alias("o")))).alias("e"))
    return x.groupBy("e.vid").agg(F.sum("e.o").alias("d_out"), F.count(F.lit(1)).alias("deg"))


def interval_pairs(left: DataFrame, right: DataFrame, minutes: int = 30, watermark: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: edges of one stream followed within ``minutes`` by an edge of the
    other with the same tail."""
    a = left.select(F.col("eid").alias("e1"), F.col("u").alias("a_u"), F.col("ts").alias("t1")).withWatermark("t1", watermark)
    b = right.select(F.col("eid").alias("e2"), F.col("u").alias("b_u"), F.col("ts").alias("t2")).withWatermark("t2", watermark)
    return a.join(b, (F.col("a_u") == F.col("b_u")) & (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"INTERVAL {minutes} MINUTES")))


def keyed_degrees(rows: DataFrame, e_cap: int) -> DataFrame:
    """Keyed state by (layer, vid): counts of tracked vertices in the sampled stream, updated batch by
    batch without rewriting whole sketches.  Emits (layer, vid, d_out, deg, saturated)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    ends = rows.select("layer", F.explode(F.array(F.struct(F.col("u").alias("vid"), F.col("keep_u").alias("k"), F.lit(1).alias("o")), F.struct(F.col("v").alias("vid"), F.col("keep_v").alias("k"), F.lit(0).alias("o")))).alias("e")).where("e.k").select("layer", "e.vid", "e.o")

    def update(key, frames, state):
        out, deg = state.get if state.exists else (0, 0)
        for f in frames:
            out, deg = out + int(f.o.sum()), deg + len(f)
        state.update((out, deg))
        yield pd.DataFrame({"layer": [key[0]], "vid": [key[1]], "d_out": [out], "deg": [deg], "saturated": [deg >= e_cap]})

    return ends.groupBy("layer", "vid").applyInPandasWithState(update, "layer int, vid long, d_out long, deg long, saturated boolean", "d_out long, deg long", "update", GroupStateTimeout.NoTimeout)


def run_batches(query: Callable[[], StreamingQuery]) -> None:
    """Starts a query and waits until it has read all that is there."""
    q = query()
    q.awaitTermination()
