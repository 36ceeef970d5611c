"""Snapshots: histograms of edges over the bias (and degree) classes of their two ends."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .classes import bias_class, class_index, degree_class, degree_class_general
from .edges import as_weighted
from .vertex_stats import degrees


def vertex_classes(edges: DataFrame, ell: int, k: int | None = None, thresholds: tuple[float, ...] | None = None, degree_thresholds: tuple[float, ...] | None = None) -> DataFrame:
    """(vid, i) and with ``k`` also the degree class a (dyadic, or by thresholds)."""
    d = degrees(edges)
    i = class_index((F.col("d_out") - F.col("d_in")) / F.col("deg"), thresholds) if thresholds else bias_class(F.col("d_out"), F.col("deg"), ell)
    return d.select("vid", *([(degree_class_general(F.col("deg"), degree_thresholds) if degree_thresholds else degree_class(F.col("deg"), k)).alias("a")] if k else []), i.alias("i"))


def _labelled(edges: DataFrame, classes: DataFrame, names: list[str]) -> DataFrame:
    """Edges with the class columns of both ends: head columns get the next letter."""
    tail = classes.select(F.col("vid").alias("u"), *(F.col(n) for n in names))
    head = classes.select(F.col("vid").alias("v"), *(F.col(n).alias(chr(ord(n) + 1)) for n in names))
    return as_weighted(edges).join(tail, "u").join(head, "v")


def snapshot_counts(edges: DataFrame, ell: int, thresholds: tuple[float, ...] | None = None) -> DataFrame:
    """(i, j, weight): unnormalised.  At most ell^2 rows leave each task."""
    x = _labelled(edges, vertex_classes(edges, ell, None, thresholds), ["i"])
    return x.groupBy("i", "j").agg(F.sum("weight").alias("weight"))


def normalised(counts: DataFrame) -> DataFrame:
    """weight to x = weight / total; counts is a small table of cells."""
    total = counts.agg(F.sum("weight").alias("_m"))
    return counts.join(F.broadcast(total)).select(*(c for c in counts.columns if c != "weight"), (F.col("weight") / F.col("_m")).alias("x"))  # one row


def snapshot(edges: DataFrame, ell: int, thresholds: tuple[float, ...] | None = None) -> DataFrame:
    return normalised(snapshot_counts(edges, ell, thresholds))


def refined_counts(edges: DataFrame, ell: int, k: int, thresholds: tuple[float, ...] | None = None, degree_thresholds: tuple[float, ...] | None = None) -> DataFrame:
    """(a, b, i, j, weight) over degree and bias classes of tail and head."""
    x = _labelled(edges, vertex_classes(edges, ell, k, thresholds, degree_thresholds), ["a", "i"])
    return x.groupBy("a", "b", "i", "j").agg(F.sum("weight").alias("weight"))


def refined_snapshot(edges: DataFrame, ell: int, k: int, thresholds: tuple[float, ...] | None = None) -> DataFrame:
    return normalised(refined_counts(edges, ell, k, thresholds))


def project(array: DataFrame, value: str = "x") -> DataFrame:
    """Sums an array over its degree classes."""
    return array.groupBy("i", "j").agg(F.sum(value).alias(value))


def bias_histogram(edges: DataFrame, ell: int, by: str = "vertex") -> DataFrame:
    """(i, weight): vertices, or total degree, by bias class."""
    d = degrees(edges)
    w = F.lit(1) if by == "vertex" else F.col("deg")
    return d.groupBy(bias_class(F.col("d_out"), F.col("deg"), ell).alias("i")).agg(F.sum(w.cast("long")).alias("weight"))


def layer_sizes(edges: DataFrame, k: int) -> DataFrame:
    """(a, n, deg): vertices and their total degree by degree class."""
    return degrees(edges).groupBy(degree_class(F.col("deg"), k).alias("a")).agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("deg"))


def second_order(edges: DataFrame, ell: int, shape: str = "path") -> DataFrame:
    """(i, h, j, weight): two-edge patterns by the bias classes of first end, middle and second end.

    ``path`` u->c->v, ``out_star`` u<-c->v, ``in_star`` u->c<-v (ordered pairs of distinct edges for
    stars).  Edges are first counted by (middle, class of the far end), so a hub of degree d gives
    at most ell^2 terms instead of d^2.
    """
    cls = vertex_classes(edges, ell)
    x = _labelled(edges, cls, ["i"])  # u, v, i = class of u, j = class of v
    into = x.groupBy(F.col("v").alias("c"), F.col("j").alias("h"), F.col("i").alias("far")).agg(F.sum("weight").alias("n"))
    out = x.groupBy(F.col("u").alias("c"), F.col("i").alias("h"), F.col("j").alias("far")).agg(F.sum("weight").alias("n"))
    first, second = {"path": (into, out), "out_star": (out, out), "in_star": (into, into)}[shape]
    y = first.select("c", "h", F.col("far").alias("i"), F.col("n").alias("n1")).join(second.select("c", F.col("far").alias("j"), F.col("n").alias("n2")), "c")
    same: Column = F.col("n1") * F.col("n2")
    if shape != "path":  # an edge is no pair with itself
        same = same - F.when(F.col("i") == F.col("j"), F.col("n1")).otherwise(0)
    return y.groupBy("i", "h", "j").agg(F.sum(same).alias("weight")).where("weight <> 0")


def rollup_refined(counts: DataFrame) -> DataFrame:
    """Refined counts with all their marginals: 0 marks a summed-out axis, gid tells which."""
    c = counts.cube("a", "b", "i", "j").agg(F.sum("weight").alias("weight"), F.grouping_id().cast("long").alias("gid"))
    return c.fillna(0, ["a", "b", "i", "j"])
