"""Cost and accuracy measures, the proof's good events as checks, and tail-bound calculators."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .classes import bias_class, degree_class
from .hashing import poly4
from .edges import as_weighted
from .layered import Sketch, build_sketch, edge_layers, layer_table
from .params import Params, practical_params
from .snapshot import vertex_classes
from .vertex_stats import degrees


def ratio_report(estimate: DataFrame, optimum: DataFrame, alpha: float = 0.483, eps: float = 0.0) -> DataFrame:
    """One row: ratio and whether (alpha - eps) val <= value <= val."""
    x = estimate.select(F.col("value").alias("estimate")).join(F.broadcast(optimum.select(F.col("value").alias("val"))))  # one row
    return x.select("estimate", "val", (F.col("estimate") / F.col("val")).alias("ratio"), F.abs(F.col("estimate") - F.col("val")).alias("additive"), ((F.col("estimate") >= (alpha - eps) * F.col("val")) & (F.col("estimate") <= F.col("val"))).alias("ok"))


def space_report(s: Sketch) -> DataFrame:
    """(guess, layer, vertices, edges, bits, cap_bits): rows kept and their key bits, against the caps."""
    p = s.one
    v = s.vertices.groupBy("guess", "layer").agg(F.count(F.lit(1)).alias("vertices"))
    e = s.edges.groupBy("guess", "layer").agg(F.count(F.lit(1)).alias("edges"))
    x = v.join(e, ["guess", "layer"], "full").fillna(0, ["vertices", "edges"])
    return x.select("guess", "layer", "vertices", "edges", (64 * F.col("vertices") + 192 * F.col("edges")).alias("bits"), F.lit(float(p.v_cap) * (64 + 192 * float(p.e_cap))).alias("cap_bits"))


def sample_sizes(edges: DataFrame, p: Params) -> DataFrame:
    """(layer, m_a, n_a, kept): sampled edges, their vertices, and the tracked ones among them."""
    everything = edge_layers(edges, {0: p.replace(force_p1=True)})
    ends = everything.select("layer", F.explode(F.array("u", "v")).alias("vid")).distinct()
    kept = edge_layers(edges, {0: p}).select("layer", F.explode(F.filter(F.array(F.when(F.col("keep_u"), F.col("u")), F.when(F.col("keep_v"), F.col("v"))), lambda x: x.isNotNull())).alias("vid")).distinct()
    m = everything.groupBy("layer").agg(F.count(F.lit(1)).alias("m_a"))
    n = ends.groupBy("layer").agg(F.count(F.lit(1)).alias("n_a"))
    k = kept.groupBy("layer").agg(F.count(F.lit(1)).alias("kept"))
    return m.join(n, "layer", "left").join(k, "layer", "left").fillna(0)


def sampled_degrees(edges: DataFrame, p: Params) -> DataFrame:
    """(layer, vid, d_out, deg) in the edge samples of all layers (no vertex sampling)."""
    x = edge_layers(edges, {0: p.replace(force_p1=True, store="incident")})
    e = x.select("layer", F.explode(F.array(F.struct(F.col("u").alias("vid"), F.lit(1).alias("o")), F.struct(F.col("v").alias("vid"), F.lit(0).alias("o")))).alias("e"))
    return e.groupBy("layer", "e.vid").agg(F.sum("e.o").alias("d_out"), F.count(F.lit(1)).alias("deg"))


def good_events(edges: DataFrame, p: Params) -> DataFrame:
    """(event, layer, bad, margin): the events of the analysis for one seed.  ``bad`` counts what
    breaks the event (0: it holds); margin is the worst value over its limit."""
    m = edges.count()
    rho = p.p0 * math.sqrt(m)
    sizes = sample_sizes(edges, p)
    q = F.element_at(F.create_map(*(x for a in p.layers for x in (F.lit(a), F.lit(p.q(a))))), F.col("layer"))
    limit = F.when(F.lit(p.p0) <= q, 2 * q * m).otherwise(5 * rho * math.sqrt(m))
    edge_event = sizes.select(F.lit("edge_count").alias("event"), "layer", (F.col("m_a") > limit).cast("long").alias("bad"), (F.col("m_a") / limit).alias("margin"))
    vertex_event = sizes.select(F.lit("vertex_count").alias("event"), "layer", (F.col("kept") >= p.v_cap).cast("long").alias("bad"), (F.col("kept") / float(p.v_cap)).alias("margin"))
    true = degrees(edges).select("vid", F.col("d_out").alias("o"), F.col("deg").alias("d"))
    layers = edges.sparkSession.createDataFrame([(a,) for a in p.layers], "layer int")
    x = true.crossJoin(F.broadcast(layers)).join(sampled_degrees(edges, p), ["layer", "vid"], "left").fillna(0, ["d_out", "deg"])  # k rows a vertex
    scaled = F.col("deg") / q
    edge_of = F.pow(F.lit(2.0), F.col("layer") - p.w - 3)
    big = F.col("d") >= edge_of
    bad = F.when(big, (scaled <= F.col("d") / 2) | (scaled >= 2 * F.col("d"))).otherwise(scaled >= 4 * edge_of)
    off = F.when(big, F.greatest(scaled / F.col("d"), F.coalesce(F.try_divide(F.col("d"), scaled), F.lit(float("inf")))) / 2).otherwise(scaled / (4 * edge_of))
    degree_event = x.groupBy("layer").agg(F.sum(bad.cast("long")).alias("bad"), F.max(off).alias("margin")).select(F.lit("degree").alias("event"), "layer", "bad", "margin")
    near = big & (F.col("d") <= F.pow(F.lit(2.0), F.col("layer") + p.w + 1)) & (F.col("deg") > 0)
    drift = F.abs(F.try_divide(2 * F.col("d_out"), F.col("deg")) - 2 * F.col("o") / F.col("d")) * p.ell
    bias_event = x.where(near).groupBy("layer").agg(F.sum((drift > 1).cast("long")).alias("bad"), F.max(drift).alias("margin")).select(F.lit("bias").alias("event"), "layer", "bad", "margin")
    return edge_event.unionByName(vertex_event).unionByName(degree_event).unionByName(bias_event)


def event_frequencies(edges: DataFrame, p: Params, seeds: range, target: float = 0.999) -> DataFrame:
    """(event, runs, held, frequency, margin, ok): how often each good event holds in all layers at
    once, over sketches with different seeds, against the share that the analysis asks for."""
    out = None
    for s in seeds:
        row = good_events(edges, p.replace(seed=s)).groupBy("event").agg(F.sum("bad").alias("bad"), F.max("margin").alias("margin"))
        out = row if out is None else out.unionByName(row)
    x = out.groupBy("event").agg(F.count(F.lit(1)).alias("runs"), F.sum((F.col("bad") == 0).cast("long")).alias("held"), F.max("margin").alias("margin"))
    share = F.col("held") / F.col("runs")
    return x.select("event", "runs", "held", share.alias("frequency"), "margin", (share >= target).alias("ok"))


def scale_report(edges: DataFrame, k_star: int, rho: float, shares: tuple[float, ...], seed: int = 0) -> DataFrame:
    """(share, m, n, exact_rows, sketch_rows): rows that meet a shuffle on growing parts of the stream.
    The exact snapshot sends each vertex once at least and each edge to the classes of both its ends; the
    sketch, with p0 = rho / sqrt(m), sends what it samples."""
    rows = []
    for share in shares:
        part = edges.where(F.pmod(F.xxhash64("eid", F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20)))
        size = degrees(part).agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("d_out"), F.lit(0)).alias("m")).first()
        m, n = int(size["m"]), int(size["n"])
        p = practical_params(max(m, 1), k_star=k_star, p0=min(1.0, rho / math.sqrt(max(m, 1))), seed=seed)
        rows.append((share, m, n, n + 2 * m, edge_layers(part, {0: p}).count()))
    return edges.sparkSession.createDataFrame(rows, "share double, m long, n long, exact_rows long, sketch_rows long")


def vertex_sandwich(edges: DataFrame, p: Params) -> DataFrame:
    """One row: vertices missing from, or too many in, the apparent classes' windows, summed over
    layers: of degree alone, and of degree and bias (0 and 0 in all where the good events hold)."""
    true = vertex_classes(edges, p.ell, p.k).select("vid", F.col("a").alias("ta"), F.col("i").alias("ti"))
    layers = edges.sparkSession.createDataFrame([(a,) for a in p.layers], "layer int")
    shift = F.element_at(F.create_map(*(x for a in p.layers for x in (F.lit(a), F.lit(1 << p.shift(a))))), F.col("layer"))
    s = sampled_degrees(edges, p)
    s = s.select("layer", "vid", F.col("deg"), degree_class(F.least(F.col("deg") * shift, F.lit(1 << p.k)), p.k).alias("a"), bias_class(F.col("d_out"), F.col("deg"), p.ell).alias("i"))
    x = true.crossJoin(F.broadcast(layers)).join(s, ["layer", "vid"], "left")  # k rows a vertex
    has = F.coalesce((F.col("deg") < p.e_cap) & (F.abs(F.col("a") - F.col("layer")) <= p.w), F.lit(False))
    far = F.abs(F.col("ta") - F.col("layer"))
    both = has & (F.abs(F.col("i") - F.col("ti")) <= 1)
    count = lambda c: F.sum(c.cast("long"))
    return x.agg(count((far <= p.w - 1) & ~has).alias("missing"), count(has & (far > p.w + 1)).alias("extra"), count((far <= p.w - 1) & has & ~both).alias("bias_moved"))


def sandwich_sums(edges: DataFrame, p: Params) -> DataFrame:
    """(la, lb, y, x): over the exact degree classes of both ends, the sampled edges of layer min(la, lb),
    which average q times the graph's, and those of them whose ends both layers track, which average
    p p times y; one row a pair of classes."""
    c = vertex_classes(edges, p.ell, p.k)
    rows = edge_layers(edges, {0: p.replace(force_p1=True)}).select("layer", "u", "v")
    x = rows.join(c.select(F.col("vid").alias("u"), F.col("a").alias("la")), "u").join(c.select(F.col("vid").alias("v"), F.col("a").alias("lb")), "v").where("layer = least(la, lb)")
    table = layer_table(edges.sparkSession, {0: p}).select(F.col("layer").alias("l"), "threshold", *(f"c{j}" for j in range(4)))

    def tracked(df, end, layer):
        own = F.broadcast(table.select(F.col("l").alias(layer), *(F.col(n).alias(f"{n}_{end}") for n in table.columns[1:])))  # a row a layer
        return df.join(own, layer).withColumn(f"in_{end}", poly4(F.col(end), *(F.col(f"c{j}_{end}") for j in range(4))) < F.col(f"threshold_{end}"))

    x = tracked(tracked(x, "u", "la"), "v", "lb")
    return x.groupBy("la", "lb").agg(F.count(F.lit(1)).alias("y"), F.sum((F.col("in_u") & F.col("in_v")).cast("long")).alias("x"))


def count_events(edges: DataFrame, p: Params) -> DataFrame:
    """(la, lb, edges, y, x, y_off, x_off): the two counting events, as deviations from the expected
    counts in units of their standard deviations (pairwise independent coins)."""
    c = vertex_classes(edges, p.ell, p.k)
    e = as_weighted(edges).select("u", "v").join(c.select(F.col("vid").alias("u"), F.col("a").alias("la")), "u").join(c.select(F.col("vid").alias("v"), F.col("a").alias("lb")), "v")
    n = e.groupBy("la", "lb").agg(F.count(F.lit(1)).alias("edges")).join(sandwich_sums(edges, p), ["la", "lb"], "left").fillna(0)
    rate = lambda f, c: F.element_at(F.create_map(*(v for a in p.layers for v in (F.lit(a), F.lit(float(f(a)))))), c)
    q, pp = rate(p.q, F.least("la", "lb")), rate(p.p, F.col("la")) * rate(p.p, F.col("lb"))
    off = lambda got, want, share: F.when(share >= 1, F.abs(got - want)).otherwise(F.abs(got - want) / F.sqrt(F.greatest(want * (1 - share), F.lit(1.0))))
    return n.withColumns({"y_off": off(F.col("y"), q * F.col("edges"), q), "x_off": off(F.col("x"), pp * F.col("y"), pp)})


def dependence(edges: DataFrame, p: Params) -> DataFrame:
    """(layer, d_max, bound): the largest sampled degree among vertices of the layer's window."""
    c = vertex_classes(edges, p.ell, p.k)
    x = sampled_degrees(edges, p).join(c, "vid").where(F.abs(F.col("a") - F.col("layer")) <= p.w + 1)
    return x.groupBy("layer").agg(F.max("deg").alias("d_max")).withColumn("bound", F.lit(2 * 2 ** (p.k_star + p.w + 2)))


def seed_report(edges: DataFrame, p: Params, sel, target: float, tolerance: float, seeds: range) -> DataFrame:
    """(seed, value, mass, overflow, ok) for each seed: success and overflow rates follow."""
    from .estimator import estimate_value

    out = None
    for s in seeds:
        row = estimate_value(build_sketch(edges, p.replace(seed=s)), sel).select(F.lit(s).alias("seed"), "value", "mass", "overflow", (F.abs(F.col("value") - target) <= tolerance).alias("ok"))
        out = row if out is None else out.unionByName(row)
    return out


def plan_report(df: DataFrame) -> dict[str, int]:
    """Operators of the physical plan: scans, exchanges, joins, Python stages, codegen spans."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: text.count(v) for k, v in {"scans": "FileScan", "exchanges": "Exchange hash", "broadcasts": "BroadcastExchange", "sort_merge": "SortMergeJoin", "python": "Python", "codegen": "*("}.items()}


def chernoff_upper(mean: float, delta: float) -> float:
    """P(X >= (1 + delta) mean) for a sum of independent variables in [0, 1]."""
    return math.exp(-(delta**2) * mean / (2 + delta))


def chernoff_lower(mean: float, delta: float) -> float:
    return math.exp(-(delta**2) * mean / 2)


def weighted_chernoff(mean: float, delta: float, largest: float) -> float:
    """The same for variables in [0, largest]."""
    return chernoff_upper(mean / largest, delta)


def chebyshev(variance: float, deviation: float) -> float:
    return min(1.0, variance / deviation**2)


def chebyshev_dependent(count: int, dependence_degree: int, deviation: float, largest: float = 1.0) -> float:
    """For variables in [0, largest] each correlated with at most ``dependence_degree`` others."""
    return min(1.0, count * (dependence_degree + 1) * largest**2 / deviation**2)


def vertices_of_layer(vid, p: Params, a: int):
    """Whether a vertex is in the drawn set of a layer (whatever the stream holds)."""
    row = next(r for r in p.rows() if r[1] == a)
    return poly4(vid, *row[4:]) < F.lit(row[3])
