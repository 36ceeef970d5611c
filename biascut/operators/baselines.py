"""What the sketch is compared with: constants, zeroth-order values, samples, prefixes, sparsifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .edges import as_weighted
from .exact import cut_value, exact_val, local_search_cut
from .guess import sparsify, sparsify_rate
from .hashing import hash01
from .lineage import cut_lineage
from .oblivious import Selection, oblivious_value, oblivious_value_exact, uniform_clamped
from .snapshot import normalised, snapshot_counts
from .vertex_stats import degrees, net_flow


def baseline_quarter(edges: DataFrame) -> DataFrame:
    """A uniform random cut's expectation."""
    return edges.agg(F.count(F.lit(1)).alias("m")).select("m", F.lit(0.25).alias("value"))


def two_fifths(m: Column, net: Column) -> Column:
    """max(1/4, B) with B = net / (2m)."""
    return F.greatest(F.lit(0.25), net / (2 * m))


def zeroth_order(m: Column, net: Column) -> Column:
    """B from 1/3 on, else 1/4 + B^2 / (4 (1 - 2B)); the border is tested in integers."""
    return F.when(3 * net >= 2 * m, net / (2 * m)).otherwise(F.lit(0.25) + (net * net) / (16 * m * (m - net)))


def baseline_two_fifths(edges: DataFrame) -> DataFrame:
    return net_flow(edges).select("m", two_fifths(F.col("m"), F.col("net")).alias("value"))


def baseline_zeroth_order(edges: DataFrame) -> DataFrame:
    return net_flow(edges).select("m", zeroth_order(F.col("m"), F.col("net")).alias("value"))


def l1_norm_sketch(edges: DataFrame, reps: int = 101, seed: int = 0) -> DataFrame:
    """One row (m, net): the sum of |d_out - d_in| as the median of ``reps`` counters, each the sum
    over edges of a Cauchy variable of the tail minus that of the head: constant space, one pass."""
    w = as_weighted(edges)

    def cauchy(vid, r):
        u = (F.shiftrightunsigned(F.xxhash64(vid, F.lit(seed), F.lit(r)), 11).cast("double") + 0.5) / float(1 << 53)
        return F.tan((u - 0.5) * 3.141592653589793)

    c = w.agg(F.sum("weight").alias("m"), *(F.sum(F.col("weight") * (cauchy(F.col("u"), r) - cauchy(F.col("v"), r))).alias(f"c{r}") for r in range(reps)))
    return c.select("m", F.element_at(F.array_sort(F.array(*(F.abs(F.col(f"c{r}")) for r in range(reps)))), reps // 2 + 1).alias("net"))


def baseline_cauchy(edges: DataFrame, reps: int = 101, seed: int = 0) -> DataFrame:
    x = l1_norm_sketch(edges, reps, seed).withColumn("net", F.least("net", 2.0 * F.col("m")))
    return x.select("m", F.least(F.lit(1.0), zeroth_order(F.col("m"), F.col("net"))).alias("value"))


def bias_from_vertex_sample(edges: DataFrame, p: float, seed: int = 0) -> DataFrame:
    """One row (m, net): net from a uniform vertex sample; ends are filtered before the shuffle."""
    w = as_weighted(edges)
    zero = F.col("weight") * 0
    ends = w.select("weight", F.explode(F.array(F.struct(F.col("u").alias("vid"), F.col("weight").alias("d")), F.struct(F.col("v").alias("vid"), (zero - F.col("weight")).alias("d")))).alias("e"))
    d = ends.where(hash01(F.col("e.vid"), seed) < p).groupBy("e.vid").agg(F.sum("e.d").alias("d"))
    return d.agg((F.coalesce(F.sum(F.abs("d")), F.lit(0)) / p).alias("net")).join(F.broadcast(w.agg(F.sum("weight").alias("m")))).select("m", "net")  # one row


def baseline_vertex_sample(edges: DataFrame, p: float, seed: int = 0) -> DataFrame:
    x = bias_from_vertex_sample(edges, p, seed).withColumn("net", F.least("net", 2.0 * F.col("m")))
    return x.select("m", F.least(F.lit(1.0), zeroth_order(F.col("m"), F.col("net"))).alias("value"))


def lp_norm_sampled(values: DataFrame, p: float, rate: float, seed: int = 0) -> DataFrame:
    """One row (n, norm): the p-norm of a vector (id, x) of bounded coordinates from a sample of them."""
    s = values.where(hash01(F.col("id"), seed) < rate)
    return s.agg(F.count(F.lit(1)).alias("n"), F.pow(F.coalesce(F.sum(F.pow(F.abs("x"), F.lit(float(p)))), F.lit(0.0)) / rate, F.lit(1.0 / p)).alias("norm"))


def gold_standard_counts(edges: DataFrame, n_edges: int, ell: int, seed: int = 0) -> DataFrame:
    """(i, j, weight): classes of ``n_edges`` random edges with the exact biases of their ends.

    The sample is the edges of least hash; degrees are computed for its ends only.
    """
    return sample_counts(gold_sample(edges, n_edges, seed), edges, ell)


def gold_sample(edges: DataFrame, n_edges: int, seed: int = 0) -> DataFrame:
    word = F.md5(F.concat_ws(":", F.col("eid"), F.lit("g"), F.lit(seed)))
    return edges.select("eid", "u", "v", word.alias("h")).orderBy("h", "eid").limit(n_edges)


def sample_counts(s: DataFrame, edges: DataFrame, ell: int) -> DataFrame:
    """(i, j, weight): classes of a small sample's edges with the exact biases of their ends in ``edges``."""
    ends = s.select(F.explode(F.array("u", "v")).alias("vid")).distinct()
    half = lambda end, out: edges.select(F.col(end).alias("vid"), F.lit(out).alias("o"), F.lit(1 - out).alias("i")).join(ends, "vid", "left_semi")
    d = half("u", 1).unionByName(half("v", 0)).groupBy("vid").agg(F.sum("o").alias("d_out"), F.sum(F.col("o") + F.col("i")).alias("deg"))
    from .classes import bias_class

    c = d.select("vid", bias_class(F.col("d_out"), F.col("deg"), ell).alias("i"))
    x = s.join(c.select(F.col("vid").alias("u"), "i"), "u").join(c.select(F.col("vid").alias("v"), F.col("i").alias("j")), "v")
    return x.groupBy("i", "j").agg(F.count(F.lit(1)).alias("weight"))


def prefix_counts(ordered: DataFrame, prefix: int, ell: int, order: list[str]) -> DataFrame:
    """(i, j, weight): classes of the first ``prefix`` edges of the order, with biases over the rest.
    Sound on random orders only."""
    first = ordered.orderBy(*order).limit(prefix).select("eid", "u", "v")
    rest = ordered.join(first.select("eid"), "eid", "left_anti")
    from .classes import bias_class

    ends = first.select(F.explode(F.array("u", "v")).alias("vid")).distinct()
    d = degrees(rest).join(ends, "vid", "left_semi")
    c = d.select("vid", bias_class(F.col("d_out"), F.col("deg"), ell).alias("i"))
    x = first.join(c.select(F.col("vid").alias("u"), "i"), "u").join(c.select(F.col("vid").alias("v"), F.col("i").alias("j")), "v")
    return x.groupBy("i", "j").agg(F.count(F.lit(1)).alias("weight"))


def induced_sample_counts(edges: DataFrame, p: float, ell: int, seed: int = 0) -> DataFrame:
    """(i, j, weight): a uniform vertex sample's induced subgraph with exact biases of its vertices
    (the bounded-degree method); an edge survives with probability p^2, so on stars mostly none do."""
    inside = lambda e: hash01(F.col(e), seed) < p
    sub = edges.where(inside("u") & inside("v"))
    from .classes import bias_class

    half = lambda end, out: edges.where(inside(end)).select(F.col(end).alias("vid"), F.lit(out).alias("o"))
    d = half("u", 1).unionByName(half("v", 0)).groupBy("vid").agg(F.sum("o").alias("d_out"), F.count(F.lit(1)).alias("deg"))
    c = d.select("vid", bias_class(F.col("d_out"), F.col("deg"), ell).alias("i"))
    x = sub.join(c.select(F.col("vid").alias("u"), "i"), "u").join(c.select(F.col("vid").alias("v"), F.col("i").alias("j")), "v")
    return x.groupBy("i", "j").agg(F.count(F.lit(1)).alias("weight"))


def counts_value(counts: DataFrame, sel: Selection) -> DataFrame:
    """The rule's value of sampled counts, normalised by what was sampled (null if nothing was)."""
    x = oblivious_value_exact(counts, sel)
    return x.select("m", F.when(F.col("m") > 0, F.col("value")).alias("value"))


def sparsified_value(edges: DataFrame, n: int, eps: float, max_n: int = 20, seed: int = 0) -> DataFrame:
    """One row: the near-optimal linear-space way, sparsify and solve (exactly for few vertices, else
    by local search)."""
    m = edges.count()
    s = cut_lineage(sparsify(edges, sparsify_rate(n, m, eps), seed))
    try:
        return exact_val(s, max_n)
    except ValueError:
        return cut_value(s, local_search_cut(s))


def exact_snapshot_value(edges: DataFrame, sel: Selection) -> DataFrame:
    """One row (m, value): the non-streaming snapshot and the rule."""
    if sel.num and sel.t == uniform_clamped(sel.ell).t:
        return oblivious_value_exact(snapshot_counts(edges, sel.ell), sel).select("m", "value")
    c = snapshot_counts(edges, sel.ell, sel.t)
    return oblivious_value(normalised(c), sel).join(F.broadcast(c.agg(F.sum("weight").alias("m")))).select("m", "value")  # one row


def best_lower_bound(edges: DataFrame, sel: Selection | None = None) -> DataFrame:
    """The greater of the zeroth-order and the snapshot value: both are lower bounds."""
    sel = sel or uniform_clamped(21)
    z = baseline_zeroth_order(edges).withColumnRenamed("value", "z")
    return exact_snapshot_value(edges, sel).join(F.broadcast(z.select("z"))).select("m", F.greatest("value", "z").alias("value"))  # one row


def half_threshold() -> float:
    """The ratio that no algorithm of sublinear space exceeds: a reference line."""
    return 0.5


def compare_methods(edges: DataFrame, workload: str, methods: list[str] | None = None, sel: Selection | None = None, params=None) -> DataFrame:
    """METHOD_RESULT rows: workload, method, value, m, n, mass, overflow; computed now.

    The graph is made twice: for its length, and for what is kept of it until the last row is there, an edge's two
    ends and two masks of layers (``marked``).  One row is collected at a time, so that no method's shuffles have to
    be held beside another's."""
    from .estimator import estimate_matrix, matrix_value
    from .layered import build_sketch
    from .marked import marked_sketch, with_coins
    from .params import practical_params

    spark, sel = edges.sparkSession, sel or uniform_clamped(21)
    names = ["quarter", "two_fifths", "zeroth_order", "cauchy", "vertex_sample", "gold_standard", "induced_sample", "snapshot", "best_of", "layered", "layered_nested", "layered_normalised", "upper_bound"]
    wanted = names if methods is None else methods
    m = edges.count()
    params = params or practical_params(m, ell=sel.ell)
    modes = {mode: params.replace(mode=mode) for mode, of in (("independent", {"layered", "layered_normalised"}), ("nested", {"layered_nested"})) if of & set(wanted)}
    kept = edges.select("eid", "u", "v")
    for mode, p in modes.items():
        kept = with_coins(kept, p, mode)
    kept = kept.drop("eid").persist()
    size = net_flow(kept)
    flow = spark.createDataFrame(size.collect(), size.schema)  # one row
    n = flow.first()["n"]
    small: dict[str, DataFrame] = {}

    def once(key: str, make) -> DataFrame:
        """A result of few rows that several methods start from."""
        if key not in small:
            df = make()
            small[key] = spark.createDataFrame(df.collect(), df.schema)
        return small[key]

    def sketch(mode: str, norm: bool = False) -> DataFrame:
        meta = spark.createDataFrame([(m,)], "m long")
        if params.store == "incident":
            s = marked_sketch(kept.select("u", "v", F.col(mode).alias("coins"), F.lit(1).cast("long").alias("n")), modes[mode], meta)
        else:
            s = build_sketch(edges, modes[mode], meta)
        matrix = once(mode, lambda: estimate_matrix(s))  # ell x ell rows
        s.overflow = once(f"{mode} overflow", lambda: s.overflow)  # a row a layer
        s.close()
        return matrix_value(s, matrix, sel, norm).select("value", "mass", "overflow")

    zeroth = lambda: flow.select("m", zeroth_order(F.col("m"), F.col("net")).alias("value"))
    snapshot = lambda: once("snapshot", lambda: exact_snapshot_value(kept, sel))  # noqa: E731  (one row)
    runs = {
        "quarter": lambda: flow.select("m", F.lit(0.25).alias("value")), "two_fifths": lambda: flow.select("m", two_fifths(F.col("m"), F.col("net")).alias("value")), "zeroth_order": zeroth,
        "cauchy": lambda: baseline_cauchy(kept), "vertex_sample": lambda: baseline_vertex_sample(kept, 0.5),
        "gold_standard": lambda: counts_value(sample_counts(once("gold", lambda: gold_sample(edges, 1000)), kept, sel.ell), sel), "induced_sample": lambda: counts_value(induced_sample_counts(kept, 0.3, sel.ell), sel),
        "snapshot": snapshot, "best_of": lambda: snapshot().join(F.broadcast(zeroth().select(F.col("value").alias("z")))).select("m", F.greatest("value", "z").alias("value")),  # one row
        "layered": lambda: sketch("independent"), "layered_nested": lambda: sketch("nested"), "layered_normalised": lambda: sketch("independent", True),
        "upper_bound": lambda: flow.select(((2 * F.col("m") + F.col("net")) / (4 * F.col("m"))).alias("value")),
    }
    rows = []
    for name in wanted:
        df = runs[name]()
        row = df.select(F.lit(workload).alias("workload"), F.lit(name).alias("method"), F.col("value").cast("double").alias("value"), F.lit(m).cast("long").alias("m"), F.lit(n).cast("long").alias("n"), (F.col("mass") if "mass" in df.columns else F.lit(None).cast("double")).alias("mass"), (F.col("overflow") if "overflow" in df.columns else F.lit(None).cast("boolean")).alias("overflow"))
        rows += row.collect()  # one row
        del df
        spark.sparkContext._jvm.System.gc()  # a method's shuffle files go when nothing refers to them
    kept.unpersist()
    return spark.createDataFrame(rows, "workload string, method string, value double, m long, n long, mass double, overflow boolean")
