"""``register(spark)``: SQL functions as expressions, Python table functions, and Arrow aggregates.

The SQL functions are temporary SQL-bodied ones: they unfold into built-in expressions, so calls stay
in generated code.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..operators.hashing import PRIME, poly4_int
from ..sources.workloads import WORKLOADS

SQL_FUNCTIONS = {
    "bias_class": ("d_out BIGINT, deg BIGINT, ell INT", "INT", "CAST(least(ell, (d_out * ell) DIV deg + 1) AS INT)"),
    "degree_class": ("deg BIGINT, k INT", "INT", "least(length(bin(deg)), k)"),
    "window_size": ("i INT, w INT, size INT", "INT", "least(i + w, size) - greatest(i - w, 1) + 1"),
    "nu": ("i INT, w INT, size INT", "DOUBLE", "1.0D / (least(i + w, size) - greatest(i - w, 1) + 1)"),
    "poly4_sql": ("vid BIGINT, c0 BIGINT, c1 BIGINT, c2 BIGINT, c3 BIGINT", "BIGINT", f"((((((c3 * (vid % {PRIME}) + c2) % {PRIME}) * (vid % {PRIME}) + c1) % {PRIME}) * (vid % {PRIME})) + c0) % {PRIME}"),
    "zeroth_order": ("m BIGINT, net BIGINT", "DOUBLE", "CASE WHEN 3 * net >= 2 * m THEN net / (2.0D * m) ELSE 0.25D + (1.0D * net * net) / (16.0D * m * (m - net)) END"),
}


@udtf(returnType="i int, j int, nu double")
class WindowCells:
    """Cells of the 2-D window around (i, j), with the normalisation of each."""

    def eval(self, i: int, j: int, w: int, ell: int):
        size = lambda x: min(x + w, ell) - max(x - w, 1) + 1
        for a in range(max(i - w, 1), min(i + w, ell) + 1):
            for b in range(max(j - w, 1), min(j + w, ell) + 1):
                yield a, b, 1.0 / (size(a) * size(b))


@udtf(returnType="layer int, q double, p double")
class Layers:
    """Rates of the layers 1..k."""

    def eval(self, k: int, k_star: int, p0: float):
        for a in range(1, k + 1):
            q = 2.0 ** min(k_star - a, 0)
            yield a, q, min(p0 / q, 1.0)


@pandas_udf(T.LongType())
def poly4_check(vid: pd.Series, c0: pd.Series, c1: pd.Series, c2: pd.Series, c3: pd.Series) -> pd.Series:
    """The vertex hash in Python: a cross-check of the expression."""
    return pd.Series([poly4_int(int(v), (int(a), int(b), int(c), int(d))) for v, a, b, c, d in zip(vid, c0, c1, c2, c3)])


def oblivious_value_agg(r: list[float]):
    """A grouped Arrow aggregate (i, j, x) -> value of a rule with probabilities ``r``."""

    @pandas_udf(T.DoubleType())
    def agg(i: pd.Series, j: pd.Series, x: pd.Series) -> float:
        p = pd.Series(r, index=range(1, len(r) + 1))
        return float((x.to_numpy() * p[i].to_numpy() * (1 - p[j].to_numpy())).sum())

    return agg


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Registers everything; with ``sf_dir`` also a view of each workload's edges and of its snapshot."""
    for name, (args, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("window_cells", WindowCells)
    spark.udtf.register("layers", Layers)
    spark.udf.register("poly4_check", poly4_check)
    if sf_dir:
        for name, make in WORKLOADS.items():
            make(spark, sf_dir).createOrReplaceTempView(f"edges_{name}")


def snapshot_sql(edges_view: str, ell: int) -> str:
    """The snapshot counts of an edge view in SQL (after ``register``)."""
    return f"""WITH st AS (SELECT vid, sum(o) AS d_out, count(*) AS deg FROM (SELECT u AS vid, 1 AS o FROM {edges_view} UNION ALL SELECT v, 0 FROM {edges_view}) GROUP BY vid),
cl AS (SELECT vid, bias_class(d_out, deg, {ell}) AS i FROM st)
SELECT s.i AS i, t.i AS j, count(*) AS weight FROM {edges_view} e JOIN cl s ON e.u = s.vid JOIN cl t ON e.v = t.vid GROUP BY s.i, t.i"""


def value_sql(cells_view: str, r: list[float]) -> str:
    """A rule's value of normalised cells (i, j, x)."""
    arr = "array(" + ", ".join(f"{x!r}D" for x in r) + ")"
    return f"SELECT sum(x * element_at({arr}, i) * (1 - element_at({arr}, j))) AS value FROM {cells_view}"


def interval_index(values, thresholds):
    """Class indices by a join with the threshold intervals lo <= x < hi (a table of fixed size, sent to
    every task); an alternative to the comparison tree for thresholds kept in a table."""
    top = thresholds.agg(F.max("idx")).first()[0]
    t = F.broadcast(thresholds.withColumn("last", F.col("idx") == top))
    return values.join(t, (values["x"] >= t["lo"]) & ((values["x"] < t["hi"]) | (t["last"] & (values["x"] <= t["hi"]))))
