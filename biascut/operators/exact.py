"""Cuts and exact optima: given cuts, random and local-search cuts, enumeration."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .edges import as_weighted
from .lineage import cut_lineage


def cut_value(edges: DataFrame, cut: DataFrame) -> DataFrame:
    """One row: cut weight, m, value of the 0/1 labelling (vid, side); unlabelled vertices are 0."""
    w = as_weighted(edges)
    x = w.join(cut.select(F.col("vid").alias("u"), F.col("side").alias("xu")), "u", "left").join(cut.select(F.col("vid").alias("v"), F.col("side").alias("xv")), "v", "left")
    hit = F.when((F.coalesce("xu", F.lit(0)) == 1) & (F.coalesce("xv", F.lit(0)) == 0), F.col("weight")).otherwise(F.col("weight") * 0)
    return x.agg(F.sum(hit).alias("cut"), F.sum("weight").alias("m")).withColumn("value", F.col("cut") / F.col("m"))


def _numbered(edges: DataFrame, max_n: int) -> tuple[list[tuple[int, int, float]], int]:
    pairs = as_weighted(edges).groupBy("u", "v").agg(F.sum("weight").alias("weight")).limit(max_n * (max_n - 1) + 1).collect()
    ids = sorted({r["u"] for r in pairs} | {r["v"] for r in pairs})
    if len(ids) > max_n or len(pairs) > max_n * (max_n - 1):
        raise ValueError(f"more than {max_n} vertices")
    place = {x: k for k, x in enumerate(ids)}
    return [(place[r["u"]], place[r["v"]], r["weight"]) for r in pairs], len(ids)


def exact_val(edges: DataFrame, max_n: int = 20) -> DataFrame:
    """One row: the best cut weight over all 2^n labellings, m, value; only for n <= max_n.

    Labellings are the numbers of a range, so they are scored in parallel, and one maximum remains.
    """
    spark = edges.sparkSession
    pairs, n = _numbered(edges, max_n)
    if not pairs:
        return spark.createDataFrame([(0, 0, 0.0)], "cut long, m long, value double").where("m > 0")
    whole = all(float(w).is_integer() for *_, w in pairs)
    total = sum(w for *_, w in pairs)
    bit = lambda k: F.shiftright(F.col("id"), k).bitwiseAND(F.lit(1).cast("long"))
    # grouping by tail keeps the expression linear in the number of pairs
    terms = []
    for u in range(n):
        heads = [(v, w) for a, v, w in pairs if a == u]
        if heads:
            inner = sum(((1 - bit(v)) * F.lit(int(w) if whole else float(w)) for v, w in heads[1:]), (1 - bit(heads[0][0])) * F.lit(int(heads[0][1]) if whole else float(heads[0][1])))
            terms.append(bit(u) * inner)
    score = sum(terms[1:], terms[0])
    best = spark.range(1 << n).select(score.alias("s")).agg(F.max("s").alias("cut"))
    return best.select("cut", F.lit(int(total) if whole else float(total)).cast("long" if whole else "double").alias("m"), (F.col("cut") / F.lit(float(total))).alias("value"))


def component_labels(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """(vid, root) by repeated minima over neighbours and pointer jumps, checkpointed each round."""
    both = cut_lineage(edges.select("u", "v").union(edges.select(F.col("v"), F.col("u"))).distinct())
    label = cut_lineage(both.select(F.col("u").alias("vid")).distinct().withColumn("root", F.col("vid")))
    for _ in range(rounds):
        near = both.join(label.select(F.col("vid").alias("v"), "root"), "v").groupBy(F.col("u").alias("vid")).agg(F.min("root").alias("least"))
        step = label.join(near, "vid").select("vid", F.least("root", "least").alias("root"))
        jump = step.select(F.col("vid").alias("root"), F.col("root").alias("up"))
        now = cut_lineage(step.join(jump, "root", "left").select("vid", F.coalesce("up", "root").alias("root")))
        moved = now.join(label.withColumnRenamed("root", "was"), "vid").where("root <> was").limit(1).count()
        label = now
        if not moved:
            return label
    return label


def exact_val_components(edges: DataFrame, max_n: int = 16) -> DataFrame:
    """One row: cut, m, value as a sum of optima over connected components of at most max_n vertices.

    Components are scored one group each; a component's pairs number at most max_n * (max_n - 1).
    """
    import numpy as np
    import pandas as pd

    label = component_labels(edges)
    pairs = as_weighted(edges).groupBy("u", "v").agg(F.sum("weight").alias("weight")).join(label.withColumnRenamed("vid", "u"), "u")

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        ids = sorted({*pdf.u, *pdf.v})
        if len(ids) > max_n:
            raise ValueError(f"a component has more than {max_n} vertices")
        place = {x: k for k, x in enumerate(ids)}
        x = np.arange(1 << len(ids), dtype=np.int64)
        score = sum(w * ((x >> place[u] & 1) & (1 - (x >> place[v] & 1))) for u, v, w in zip(pdf.u, pdf.v, pdf.weight.astype(float)))
        return pd.DataFrame({"cut": [float(score.max())], "m": [float(pdf.weight.sum())]})

    parts = pairs.groupBy("root").applyInPandas(best, "cut double, m double")
    return parts.agg(F.sum("cut").alias("cut"), F.sum("m").alias("m")).withColumn("value", F.col("cut") / F.col("m"))


def hashed_side(vid, seed: int):
    """A fair coin of a vertex: the lowest bit of the first hex digit of an md5."""
    return F.conv(F.substring(F.md5(F.concat(vid.cast("string"), F.lit(f":{seed}"))), 1, 1), 16, 10).cast("int") % 2


def random_cut(edges: DataFrame, seed: int = 0) -> DataFrame:
    """One row: the value of a uniform random labelling; one narrow pass."""
    w = as_weighted(edges)
    hit = F.when((hashed_side(F.col("u"), seed) == 1) & (hashed_side(F.col("v"), seed) == 0), F.col("weight")).otherwise(F.col("weight") * 0)
    return w.agg(F.sum(hit).alias("cut"), F.sum("weight").alias("m")).withColumn("value", F.col("cut") / F.col("m"))


def random_cut_expectation() -> float:
    return 0.25


def local_search_cut(edges: DataFrame, rounds: int = 6, seed: int = 0) -> DataFrame:
    """(vid, side): improves the bias-sign cut; each round half of the vertices (by hash) take their
    better side.  A lower bound for graphs beyond enumeration."""
    from .vertex_stats import degrees

    pairs = cut_lineage(as_weighted(edges).groupBy("u", "v").agg(F.sum("weight").alias("weight")))
    cut = cut_lineage(degrees(edges).select("vid", (F.col("d_out") > F.col("d_in")).cast("int").alias("side")))
    for r in range(rounds):
        x = pairs.join(cut.select(F.col("vid").alias("u"), F.col("side").alias("xu")), "u").join(cut.select(F.col("vid").alias("v"), F.col("side").alias("xv")), "v")
        # gain of label 1: out-edges to 0s; gain of label 0: in-edges from 1s
        gain = x.select(F.explode(F.array(F.struct(F.col("u").alias("vid"), ((1 - F.col("xv")) * F.col("weight")).alias("g")), F.struct(F.col("v").alias("vid"), (-F.col("xu") * F.col("weight")).alias("g")))).alias("e")).groupBy("e.vid").agg(F.sum("e.g").alias("g"))
        turn = hashed_side(F.col("vid"), seed + r) == 1
        cut = cut_lineage(cut.join(gain, "vid", "left").select("vid", F.when(turn, (F.coalesce("g", F.lit(0)) > 0).cast("int")).otherwise(F.col("side")).alias("side")))
    return cut
