"""From a sketch to estimates of the smoothed refined snapshot, the smoothed snapshot and the value."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .classes import bias_class, class_index, degree_class, degree_class_general
from .layered import Sketch, _ends
from .oblivious import Selection
from .params import Params
from .windows import _spread, nu, window_size


def _by_layer(p: Params, values):
    return F.element_at(F.create_map(*(x for a in p.layers for x in (F.lit(a), F.lit(values(a))))), F.col("layer"))


def _suggested(d: DataFrame, p: Params) -> DataFrame:
    scaled = F.least(F.col("deg") * _by_layer(p, lambda a: 1 << p.shift(a)), F.lit(1 << p.k))
    return d.withColumn("a", degree_class_general(scaled, p.d) if p.d else degree_class(scaled, p.k)).withColumn("i", class_index((F.col("d_out") - F.col("d_in")) / F.col("deg"), p.t) if p.t else bias_class(F.col("d_out"), F.col("deg"), p.ell))


def apparent_stats(s: Sketch) -> DataFrame:
    """(layer, vid, d_out, d_in, deg, a, i): stored degrees and the classes they suggest."""
    d = _ends(s.edges).groupBy("layer", "vid").agg(F.sum("out").alias("d_out"), F.sum(1 - F.col("out")).alias("d_in"))
    return _suggested(d.withColumn("deg", F.col("d_out") + F.col("d_in")), s.one)


def usable_vertices(s: Sketch, true_classes: DataFrame | None = None) -> DataFrame:
    """(layer, vid, a, i) of unsaturated vertices whose degree class is within w of their layer.
    ``true_classes`` (vid, a, i) replaces the apparent classes (an oracle variant).

    Below the cap, stored and sampled degrees agree: while the sample is at hand its sums serve."""
    p = s.one
    x = (_suggested(s.stats, p) if s.stats is not None else apparent_stats(s)).where(F.col("deg") < p.e_cap)
    if true_classes is not None:
        x = x.drop("a", "i").join(true_classes.select("vid", "a", "i"), "vid")
    return x.where(F.abs(F.col("a") - F.col("layer")) <= p.w).select("layer", "vid", "a", "i")


def layer_pairs(s: Sketch, usable: DataFrame | None = None, cross: str = "all") -> DataFrame:
    """(la, lb, a, b, i, j, n): stored edges of layer min(la, lb) whose ends are usable in layers la
    and lb, counted by the layers and classes.  ``cross='in_layer'`` keeps la = lb only."""
    usable = usable if usable is not None else usable_vertices(s)
    if s.marked is not None:
        from .marked import marked_pairs

        return marked_pairs(s, usable, cross)
    # a vertex is usable in a few layers: its list meets each edge once, and layers are matched in the row
    lists = usable.groupBy("vid").agg(F.collect_list(F.struct("layer", "a", "i")).alias("at"))
    # ends below the cap keep all their edges, so trimming removes none of these
    rows = s.sample if s.sample is not None else s.edges
    x = rows.select("layer", "u", "v").join(lists.select(F.col("vid").alias("u"), F.col("at").alias("tail")), "u")
    x = x.join(lists.select(F.col("vid").alias("v"), F.col("at").alias("head")), "v")
    x = x.select("layer", F.explode("tail").alias("s"), "head").where("s.layer >= layer").select("layer", "s", F.explode("head").alias("t")).where("least(s.layer, t.layer) = layer")
    if cross == "in_layer":
        x = x.where("s.layer = t.layer")
    x = x.select(F.col("s.layer").alias("la"), F.col("t.layer").alias("lb"), "s.a", F.col("t.a").alias("b"), "s.i", F.col("t.i").alias("j"))
    return x.groupBy("la", "lb", "a", "b", "i", "j").agg(F.count(F.lit(1)).alias("n"))


def _rates(p: Params):
    """1 / (q of the lower layer * p of both), as an expression of la and lb."""
    table = F.create_map(*(x for a in p.layers for x in (F.lit(a), F.lit(float(p.p(a))))))
    q = F.create_map(*(x for a in p.layers for x in (F.lit(a), F.lit(float(p.q(a))))))
    return F.lit(1.0) / (F.element_at(q, F.least("la", "lb")) * F.element_at(table, F.col("la")) * F.element_at(table, F.col("lb")))


def _weighted(s: Sketch, pairs: DataFrame) -> DataFrame:
    p = s.one
    share = F.lit(1.0) / (window_size(F.col("a"), p.w, p.k) * window_size(F.col("b"), p.w, p.k))
    return pairs.withColumn("x", F.col("n") * share * _rates(p)).join(F.broadcast(s.meta)).withColumn("x", F.col("x") / F.col("m"))  # one row


def estimate_array(s: Sketch, usable: DataFrame | None = None, cross: str = "all") -> DataFrame:
    """(a, b, i, j, x): a, b are the layers that counted an edge."""
    p = s.one
    x = _weighted(s, layer_pairs(s, usable, cross)).groupBy(F.col("la").alias("a"), F.col("lb").alias("b"), "i", "j").agg(F.sum("x").alias("x"))
    for axis in ("i", "j"):
        x = _spread(x, axis, nu(F.col(axis), p.w, p.ell), p.w, p.ell)
    return x


def estimate_matrix(s: Sketch, usable: DataFrame | None = None, cross: str = "all") -> DataFrame:
    """(i, j, x) straight to the projection: the array is never made."""
    p = s.one
    x = _weighted(s, layer_pairs(s, usable, cross)).groupBy("i", "j").agg(F.sum("x").alias("x"))
    for axis in ("i", "j"):
        x = _spread(x, axis, nu(F.col(axis), p.w, p.ell), p.w, p.ell)
    return x


def estimate_value(s: Sketch, sel: Selection, self_normalize: bool = False) -> DataFrame:
    """One row: value (the rule's minus eps/4), clipped, mass of the matrix, m, overflow.  With any
    layer overflowed the value is null.  ``self_normalize`` divides by the mass (not the theorem's)."""
    return matrix_value(s, estimate_matrix(s), sel, self_normalize)


def matrix_value(s: Sketch, matrix: DataFrame, sel: Selection, self_normalize: bool = False) -> DataFrame:
    """``estimate_value`` from a sketch's matrix."""
    p = s.one
    x = F.col("x")
    sums = [F.coalesce(F.sum(x * sel.column(F.col("i")) * (1 - sel.column(F.col("j")))), F.lit(0.0)).alias("value"), F.coalesce(F.sum(x), F.lit(0.0)).alias("mass")]
    v = matrix.agg(*sums)
    v = v.join(F.broadcast(s.meta)).join(F.broadcast(s.overflow.agg(F.coalesce(F.max("overflow"), F.lit(False)).alias("overflow"))))
    raw = F.when(~F.col("overflow"), (F.col("value") / F.col("mass") if self_normalize else F.col("value")) - p.eps / 4)
    return v.select(raw.alias("value"), F.least(F.greatest(raw, F.lit(0.0)), F.lit(1.0)).alias("clipped"), "mass", "m", "overflow")


def estimate_of(edges: DataFrame, params: Params, sel: Selection, self_normalize: bool = False) -> DataFrame:
    """The row of ``estimate_value`` for an edge stream, computed now; the sketch is freed again."""
    from .layered import build_sketch

    s = build_sketch(edges, params)
    out = estimate_value(s, sel, self_normalize)
    rows = out.collect()  # one row
    s.close()
    return edges.sparkSession.createDataFrame(rows, out.schema)
