"""Smoothing graphs: the blow-up of a graph over bias windows, and its bias-shifted form.

Every vertex becomes one copy for each class of its window, edges share their weight among the
copies; then each copy's bias is moved into its class through an auxiliary vertex.  The moves are
closed forms an edge, so the graph is one join and two unions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .classes import uniform_thresholds
from .edges import as_weighted
from .snapshot import vertex_classes
from .vertex_stats import degrees
from .windows import nu, window, window_size

STAR = -1  # the auxiliary vertex's id, with class 0


def _classed(edges: DataFrame, ell: int) -> DataFrame:
    c = vertex_classes(edges, ell)
    x = as_weighted(edges).groupBy("u", "v").agg(F.sum("weight").alias("weight"))
    return x.join(c.select(F.col("vid").alias("u"), "i"), "u").join(c.select(F.col("vid").alias("v"), F.col("i").alias("j")), "v")


def blow_up(edges: DataFrame, ell: int, w: int) -> DataFrame:
    """(u, cu, v, cv, weight): vertices are (id, class copy)."""
    share = F.col("weight") * nu(F.col("i"), w, ell) * nu(F.col("j"), w, ell)
    x = _classed(edges, ell).select("u", "v", share.alias("weight"), F.explode(window(F.col("i"), w, ell)).alias("cu"), "j")
    return x.select("u", "cu", "v", F.explode(window(F.col("j"), w, ell)).alias("cv"), "weight")


def copy_degrees(g: DataFrame) -> DataFrame:
    """(vid, c, d_out, d_in, deg) of a graph on copies."""
    ends = g.select(F.explode(F.array(F.struct(F.col("u").alias("vid"), F.col("cu").alias("c"), F.col("weight").alias("o"), F.lit(0.0).alias("i")), F.struct(F.col("v").alias("vid"), F.col("cv").alias("c"), F.lit(0.0).alias("o"), F.col("weight").alias("i")))).alias("e"))
    d = ends.groupBy("e.vid", "e.c").agg(F.sum("e.o").alias("d_out"), F.sum("e.i").alias("d_in"))
    return d.withColumn("deg", F.col("d_out") + F.col("d_in"))


def midpoint(c: Column, ell: int) -> Column:
    t = uniform_thresholds(ell)
    return F.element_at(F.array(*(F.lit((a + b) / 2) for a, b in zip(t, t[1:]))), c.cast("int"))


def shifts(edges: DataFrame, ell: int, w: int) -> DataFrame:
    """(vid, c, alpha, down, up): by copy, the weight to add, and the share of its out-edges (to
    lower the bias) or in-edges (to raise it) that the auxiliary vertex takes over."""
    d = degrees(edges).join(vertex_classes(edges, ell), "vid")
    bias = (F.col("d_out") - F.col("d_in")) / F.col("deg")
    x = d.select("vid", "i", bias.alias("bias"), (F.col("deg") / window_size(F.col("i"), w, ell)).alias("deg"), F.explode(window(F.col("i"), w, ell)).alias("c"))
    gap = F.when(F.col("c") == F.col("i"), F.lit(0.0)).otherwise(F.col("bias") - midpoint(F.col("c"), ell))
    x = x.withColumn("gap", gap)
    return x.select("vid", "c", "deg", "gap", (F.abs("gap") * F.col("deg") / 2).alias("alpha"), F.when(F.col("gap") > 0, F.col("gap") / (1 + F.col("bias"))).otherwise(0.0).alias("down"), F.when(F.col("gap") < 0, -F.col("gap") / (1 - F.col("bias"))).otherwise(0.0).alias("up"))


def shift_bias(g: DataFrame, s: DataFrame) -> DataFrame:
    """Applies shifts (vid, c, alpha, gap, down, up) to a graph on copies."""
    x = g.join(s.select(F.col("vid").alias("u"), F.col("c").alias("cu"), "down"), ["u", "cu"], "left").join(s.select(F.col("vid").alias("v"), F.col("c").alias("cv"), "up"), ["v", "cv"], "left")
    x = x.withColumn("down", F.coalesce("down", F.lit(0.0))).withColumn("up", F.coalesce("up", F.lit(0.0)))
    star = F.lit(STAR).cast("long")
    kept = x.select("u", "cu", "v", "cv", (F.col("weight") * (1 - F.col("down") - F.col("up"))).alias("weight"))
    to_head = x.where("down > 0").groupBy("v", "cv").agg(F.sum(F.col("weight") * F.col("down")).alias("weight")).select(star.alias("u"), F.lit(0).alias("cu"), "v", "cv", "weight")
    from_tail = x.where("up > 0").groupBy("u", "cu").agg(F.sum(F.col("weight") * F.col("up")).alias("weight")).select("u", "cu", star.alias("v"), F.lit(0).alias("cv"), "weight")
    lower = s.where("gap > 0").select(star.alias("u"), F.lit(0).alias("cu"), F.col("vid").alias("v"), F.col("c").alias("cv"), F.col("alpha").alias("weight"))
    higher = s.where("gap < 0").select(F.col("vid").alias("u"), F.col("c").alias("cu"), star.alias("v"), F.lit(0).alias("cv"), F.col("alpha").alias("weight"))
    return kept.unionByName(to_head).unionByName(from_tail).unionByName(lower).unionByName(higher).where("weight <> 0")


def smoothed_graph(edges: DataFrame, ell: int, w: int) -> DataFrame:
    """(u, cu, v, cv, weight) of the smoothing graph; its copies' classes are their second labels."""
    return shift_bias(blow_up(edges, ell, w), shifts(edges, ell, w))


def smoothed_graph_snapshot(edges: DataFrame, ell: int, w: int) -> DataFrame:
    """(i, j, x): the smoothing graph's own snapshot, from its degrees (the auxiliary one included)."""
    from .classes import class_index

    g = smoothed_graph(edges, ell, w)
    d = copy_degrees(g).where("deg > 0")
    bias = F.round((F.col("d_out") - F.col("d_in")) / F.col("deg"), 12)
    c = d.select("vid", "c", class_index(bias, uniform_thresholds(ell)).alias("i"))
    x = g.join(c.select(F.col("vid").alias("u"), F.col("c").alias("cu"), "i"), ["u", "cu"]).join(c.select(F.col("vid").alias("v"), F.col("c").alias("cv"), F.col("i").alias("j")), ["v", "cv"])
    s = x.groupBy("i", "j").agg(F.sum("weight").alias("weight"))
    return s.join(F.broadcast(s.agg(F.sum("weight").alias("m")))).select("i", "j", (F.col("weight") / F.col("m")).alias("x"))  # one row


def blow_up_checks(edges: DataFrame, ell: int, w: int) -> DataFrame:
    """One row: weight of graph and blow-up, and the worst deviations of copies' degrees and biases."""
    k = copy_degrees(blow_up(edges, ell, w))
    d = degrees(edges).join(vertex_classes(edges, ell), "vid").select("vid", F.col("d_out").alias("go"), F.col("d_in").alias("gi"), window_size(F.col("i"), w, ell).alias("size"))
    x = k.join(d, "vid")
    dev = F.greatest(F.abs(F.col("d_out") - F.col("go") / F.col("size")), F.abs(F.col("d_in") - F.col("gi") / F.col("size")))
    bias = F.abs((F.col("d_out") - F.col("d_in")) / F.col("deg") - (F.col("go") - F.col("gi")) / (F.col("go") + F.col("gi")))
    return x.agg(F.count(F.lit(1)).alias("copies"), (F.sum("deg") / 2).alias("m"), F.max(dev).alias("degree_gap"), F.max(bias).alias("bias_gap"))


def smoothing_gap(edges: DataFrame, ell: int, w: int) -> DataFrame:
    """One row: l1 distance of the smoothing graph's snapshot to the smoothed one, growth of the
    weight, and the bounds of both (7 lam w, and lam (w + 1), with lam = 2/ell)."""
    from .snapshot import snapshot
    from .windows import l1, smooth_matrix

    lam = 2 / ell
    gap = l1(smoothed_graph_snapshot(edges, ell, w), smooth_matrix(snapshot(edges, ell), w, ell))
    total = smoothed_graph(edges, ell, w).agg(F.sum("weight").alias("mh")).join(F.broadcast(as_weighted(edges).agg(F.sum("weight").alias("m"))))
    return gap.join(F.broadcast(total)).select("l1", (F.col("mh") / F.col("m") - 1).alias("growth"), F.lit(7 * lam * w).alias("l1_bound"), F.lit(lam * (w + 1)).alias("growth_bound"))
