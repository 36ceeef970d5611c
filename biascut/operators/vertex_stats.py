"""Degrees, biases and what follows from them alone."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .edges import as_weighted


def degrees(edges: DataFrame) -> DataFrame:
    """(vid, d_out, d_in, deg); partial sums make hubs harmless."""
    w = as_weighted(edges)
    zero = F.col("weight") * 0
    ends = w.select(F.explode(F.array(F.struct(F.col("u").alias("vid"), F.col("weight").alias("o"), zero.alias("i")), F.struct(F.col("v").alias("vid"), zero.alias("o"), F.col("weight").alias("i")))).alias("e"))
    d = ends.groupBy("e.vid").agg(F.sum("e.o").alias("d_out"), F.sum("e.i").alias("d_in"))
    return d.select("vid", "d_out", "d_in", (F.col("d_out") + F.col("d_in")).alias("deg"))


def biases(edges: DataFrame) -> DataFrame:
    return degrees(edges).withColumn("bias", (F.col("d_out") - F.col("d_in")) / F.col("deg"))


def net_flow(edges: DataFrame) -> DataFrame:
    """One row: m, n, net = sum of |d_out - d_in|; the average bias is net / (2m)."""
    d = degrees(edges)
    return d.agg(F.coalesce(F.sum("d_out"), F.lit(0)).alias("m"), F.count("vid").alias("n"), F.coalesce(F.sum(F.abs(F.col("d_out") - F.col("d_in"))), F.lit(0)).alias("net"))


def upper_bound(edges: DataFrame) -> DataFrame:
    """(1 + B)/2 for B the average bias: the net flow over any cut is at most mB."""
    return net_flow(edges).select("m", "net", ((2 * F.col("m") + F.col("net")) / (4 * F.col("m"))).alias("upper_bound"))
