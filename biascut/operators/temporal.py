"""Edges with times: prefix biases, windowed statistics, late rows, hubs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .classes import bias_class


def _ends(edges: DataFrame, more: list[str]) -> DataFrame:
    end = lambda c, o: F.struct(F.col(c).alias("vid"), F.lit(o).cast("long").alias("o"), F.lit(1 - o).cast("long").alias("i"))
    return edges.select(*more, F.explode(F.array(end("u", 1), end("v", 0))).alias("e")).select(*more, "e.vid", "e.o", "e.i")


def asof_prefix_counts(edges: DataFrame, ell: int) -> DataFrame:
    """(i, j, weight): classes of both ends of each edge *as of its arrival*: from the edges before it
    (class 0: none).  edges: (eid, u, v, ts); ties in time go by eid."""
    x = _ends(edges, ["eid", "ts"])
    w = W.partitionBy("vid").orderBy("ts", "eid").rowsBetween(W.unboundedPreceding, -1)
    d_out, deg = F.sum("o").over(w), F.sum(F.col("o") + F.col("i")).over(w)
    x = x.select("eid", "vid", "o", F.when(F.coalesce(deg, F.lit(0)) > 0, bias_class(d_out, deg, ell)).otherwise(0).cast("int").alias("c"))
    both = x.groupBy("eid").agg(F.max(F.when(F.col("o") == 1, F.col("c"))).alias("i"), F.max(F.when(F.col("o") == 0, F.col("c"))).alias("j"))
    return both.groupBy("i", "j").agg(F.count(F.lit(1)).alias("weight"))


def as_of(edges: DataFrame, facts: DataFrame, on: str, value: str) -> DataFrame:
    """Each edge with the latest ``facts`` (vid, ts, value) of its end ``on`` at or before its time."""
    e = edges.select(F.col(on).alias("vid"), "ts", F.lit(1).alias("_e"), F.struct(*edges.columns).alias("_row"), F.lit(None).cast(facts.schema[value].dataType).alias(value))
    f = facts.select("vid", "ts", F.lit(0).alias("_e"), F.lit(None).cast(e.schema["_row"].dataType).alias("_row"), value)
    w = W.partitionBy("vid").orderBy("ts", "_e").rowsBetween(W.unboundedPreceding, 0)
    return e.unionByName(f).withColumn("as_of", F.last(value, ignorenulls=True).over(w)).where("_e = 1").select("_row.*", "as_of")


def windowed_bias(edges: DataFrame, key: Column, name: str = "start") -> DataFrame:
    """(start, n, m, net) by window: zeroth-order statistics of each window's edges.  ``key`` is the
    window's start (or an array of starts for sliding windows)."""
    x = _ends(edges.withColumn(name, key), [name])
    d = x.groupBy(name, "vid").agg(F.sum("o").alias("d_out"), F.sum("i").alias("d_in"))
    return d.groupBy(name).agg(F.count(F.lit(1)).alias("n"), F.sum("d_out").alias("m"), F.sum(F.abs(F.col("d_out") - F.col("d_in"))).alias("net"))


def tumbling_bias(edges: DataFrame, duration: str = "1 day") -> DataFrame:
    return windowed_bias(edges, F.window("ts", duration)["start"])


def sliding_bias(edges: DataFrame, duration: str = "1 day", slide: str = "6 hours") -> DataFrame:
    """Sliding windows: an edge counts in each window that holds it."""
    x = edges.select("u", "v", F.window("ts", duration, slide)["start"].alias("start"))
    return windowed_bias(x, F.col("start"))


def session_bias(edges: DataFrame, gap: str = "30 minutes", by: str = "vid") -> DataFrame:
    """(vid, start, n): sessions of each vertex's edges."""
    x = _ends(edges, ["ts"])
    s = x.groupBy("vid", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("n"))
    return s.select("vid", F.col("s.start").alias("start"), "n")


def late_rows(edges: DataFrame, held: Column, hold_s: int, watermark_s: int) -> DataFrame:
    """(day, kept, dropped): what a watermark drops when the rows ``held`` arrive ``hold_s`` late: a held
    row is late if a row that arrived on time lies more than ``watermark_s`` after it.  The band join
    runs on hour buckets."""
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    on_time = edges.where(~held).select(t.alias("t"), F.call_function("div", t, F.lit(3_600_000_000)).alias("hour"))
    late = edges.where(held).select("eid", t.alias("t0"))
    lo, hi = F.col("t0") + watermark_s * 1_000_000, F.col("t0") + hold_s * 1_000_000
    span = F.sequence(F.call_function("div", lo, F.lit(3_600_000_000)), F.call_function("div", hi, F.lit(3_600_000_000)))
    seen = late.select("eid", "t0", F.explode(span).alias("hour")).join(on_time, "hour").where((F.col("t") > lo) & (F.col("t") <= hi)).select("eid").distinct()
    x = edges.select("eid", F.window("ts", "1 day")["start"].alias("day")).join(seen.withColumn("gone", F.lit(1)), "eid", "left")
    return x.groupBy("day").agg(F.sum(F.when(F.col("gone").isNull(), 1).otherwise(0)).alias("kept"), F.sum(F.coalesce("gone", F.lit(0))).alias("dropped"))


def top_hubs(degrees: DataFrame, k: int = 10) -> DataFrame:
    """The k vertices of largest degree."""
    return degrees.orderBy(F.desc("deg"), "vid").limit(k)
