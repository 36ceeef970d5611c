"""Edge streams: multigraphs as DataFrames of (eid, u, v), and the reductions to them.

``eid`` names an edge *occurrence*; every random choice about an edge is a function of it, so a
retried task, a replay or another partitioning makes the same choices.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def edge_stream(df: DataFrame, src: Column, dst: Column, key: list[Column]) -> DataFrame:
    """(eid, u, v) from any table; edges with a missing end and self-loops go."""
    e = df.select(F.concat_ws("|", *(k.cast("string") for k in key)).alias("eid"), src.cast("long").alias("u"), dst.cast("long").alias("v"))
    return e.where(F.col("u") != F.col("v"))


def file_keyed(df: DataFrame) -> DataFrame:
    """For tables without a key: eid from the place of the row in its file."""
    return df.withColumn("eid", F.concat_ws("#", F.col("_metadata.file_path"), F.col("_metadata.row_index").cast("string")))


def string_id(c: Column) -> Column:
    """A vertex id from a string: the first 60 bits of its md5 (portable to other engines)."""
    return F.conv(F.substring(F.md5(c), 1, 15), 16, 10).cast("long")


def multigraph(edges: DataFrame) -> DataFrame:
    """(u, v, mult): one row a pair; partial sums before the shuffle."""
    return edges.groupBy("u", "v").agg(F.count(F.lit(1)).alias("mult"))


def edge_count(edges: DataFrame) -> DataFrame:
    return edges.agg(F.count(F.lit(1)).alias("m"))


def graph_size(edges: DataFrame) -> DataFrame:
    """One row: n non-isolated vertices, m edges."""
    ends = edges.select(F.explode(F.array("u", "v")).alias("vid"), F.lit(0).alias("one")).union(edges.select(F.lit(None).cast("long"), F.lit(1)))
    per = ends.groupBy("vid").agg(F.sum("one").alias("edges"))  # a row a vertex, and one for the edge count
    return per.agg(F.count("vid").alias("n"), F.coalesce(F.sum("edges"), F.lit(0)).alias("m"))


def round_weights(weighted: DataFrame, eps: float) -> DataFrame:
    """(u, v, mult) from (u, v, weight > 0): scale so that the least weight is about 1/eps and round.

    Each rounded weight is within a factor 1 +- eps/2 of its share; copies are never materialised.
    """
    least = weighted.where("weight > 0").agg(F.min("weight").alias("least"))
    return weighted.where("weight > 0").join(F.broadcast(least)).select("u", "v", F.round(F.col("weight") / (F.col("least") * eps)).cast("long").alias("mult"))  # one row


def cut_as_dicut(edges: DataFrame) -> DataFrame:
    """Both orientations of every edge: the directed optimum is half the undirected one."""
    back = edges.select(F.concat("eid", F.lit("<")).alias("eid"), F.col("v").alias("u"), F.col("u").alias("v"))
    return edges.select("eid", "u", "v").unionByName(back)


def as_weighted(edges: DataFrame) -> DataFrame:
    """(u, v, weight) of unit edges, of a multigraph, or as it is."""
    if "weight" in edges.columns:
        return edges.select("u", "v", "weight")
    return edges.select("u", "v", (F.col("mult") if "mult" in edges.columns else F.lit(1)).cast("long").alias("weight"))
