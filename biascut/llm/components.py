"""Connected components of a link table, by alternating large-star and small-star steps.

Every step is two partial aggregates and one join of the links with the smallest neighbour of each
node; a hub is therefore an aggregate key (pre-aggregated) and a join key (split by adaptive
execution), never a group in memory.  Rounds grow with the logarithm of the longest chain.  Each
round is a table in the shared scratch folder, so lineage stays short and executors may be lost.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, scratch_path

_SCHEMA = "u long, v long"


def _star(links: DataFrame, large: bool) -> DataFrame:
    """links: (u, v) with u > v, distinct.  One large-star or small-star step, same form."""
    both = links.union(links.select(F.col("v").alias("u"), F.col("u").alias("v"))) if large else links
    least = both.groupBy("u").agg(F.min("v").alias("_m")).select("u", F.least("u", "_m").alias("m"))
    if large:  # larger neighbours move to the smallest one
        moved = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:  # smaller neighbours, and the node itself, move to the smallest one
        moved = both.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v")
    return moved.where("u > v").distinct()


def connected_components(links: DataFrame, name: str = "components", most: int = 60) -> DataFrame:
    """(node, root) for every node that has a link; root is the smallest node reachable.

    ``links`` has long columns u and v; direction, repeats and self-links do not matter.
    """
    spark = links.sparkSession
    links = links.where("u is not null and v is not null and u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    path, mark = None, None
    for _ in range(most):
        step = links if path is None else _star(_star(links, True), False)
        now = scratch_path(spark, name)
        step.write.parquet(now)
        links = spark.read.schema(_SCHEMA).parquet(now)
        seen = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if path:
            discard(spark, path)
        path = now
        if tuple(seen) == mark or not seen[0]:
            break
        mark = tuple(seen)
    else:
        raise RuntimeError(f"no fixed point after {most} rounds")
    # at the fixed point every node points to its root, and roots are no sources
    return links.select(F.col("u").alias("node"), F.col("v").alias("root")).union(links.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
