"""Registered queries: every method, variant, baseline and measure on the workload graphs."""

from __future__ import annotations

import gc
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines as bl
from ..operators import blowup, diagnostics, exact, guess, layered, marked, temporal
from ..operators import edges as ed
from ..operators import estimator as est
from ..operators import oblivious as ob
from ..operators import snapshot as sn
from ..operators import vertex_stats as vs
from ..operators import windows as wi
from ..operators.hashing import poly4
from ..operators.params import Params, practical_params, theory_params
from ..sources import workloads as wl
from . import oracles as o

ELL, K = 21, 24
SEL = ob.uniform_clamped(ELL)
#: The sketch of the registered queries: fixed layers, so that they mean the same at every size.
SKETCH = Params(K, ELL, 2, 6, 0.25, 2**10 + 1, 10**6)
#: A small cap, to see saturation.
CAPPED = SKETCH.replace(e_cap=40)
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
MANY = list(wl.WORKLOADS)
SOME = ["goods_flow", "nation_trade", "user_item", "part_pair", "customer_star", "page_nav"]


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def over(w: str, f: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, d: f(wl.workload(spark, d, w))


def r9(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 9) for c in cols})


# graphs and their vertices
def checksum(e: DataFrame) -> DataFrame:
    return e.agg(F.count(F.lit(1)).alias("m"), F.sum(F.col("u") % 1000003).alias("su"), F.sum(F.col("v") % 1000003).alias("sv"), F.count_distinct("eid").alias("ids"))


for w in MANY:
    add(f"edges_{w}", over(w, checksum), f"WITH {o.edges(w)} SELECT count(*)::BIGINT AS m, sum(u % 1000003)::BIGINT AS su, sum(v % 1000003)::BIGINT AS sv, count(DISTINCT eid)::BIGINT AS ids FROM e")
    add(f"graph_size_{w}", over(w, ed.graph_size), f"WITH {o.edges(w)}, {o.stats()} SELECT count(*)::BIGINT AS n, (SELECT count(*)::BIGINT FROM e) AS m FROM st")
    net = f"WITH {o.edges(w)}, {o.stats()}, ne AS (SELECT coalesce(sum(d_out), 0)::BIGINT AS m, count(*)::BIGINT AS n, coalesce(sum(abs(d_out - d_in)), 0)::BIGINT AS net FROM st) "
    add(f"upper_bound_{w}", over(w, lambda e: r9(vs.upper_bound(e), "upper_bound")), net + "SELECT m, net, round((2 * m + net) / (4 * m)::DOUBLE, 9) AS upper_bound FROM ne")
    add(f"baseline_two_fifths_{w}", over(w, lambda e: r9(bl.baseline_two_fifths(e), "value")), net + "SELECT m, round(greatest(0.25::DOUBLE, net / (2 * m)::DOUBLE), 9) AS value FROM ne")
    add(f"baseline_zeroth_order_{w}", over(w, lambda e: r9(bl.baseline_zeroth_order(e), "value")), net + f"SELECT m, round({o.ZEROTH}, 9) AS value FROM ne")
    add(f"oblivious_value_{w}", over(w, lambda e: r9(ob.oblivious_value_exact(sn.snapshot_counts(e, ELL), SEL), "value")), f"{o.graph(w)}, {o.cells()} SELECT num, m, round(value, 9) AS value FROM ({o.rule_value()})")
for w in SOME:
    add(f"degree_bias_{w}", over(w, lambda e: r9(vs.biases(e), "bias")), f"WITH {o.edges(w)}, {o.stats()} SELECT vid, d_out, d_in, deg, round((d_out - d_in) / deg::DOUBLE, 9) AS bias FROM st")
    add(f"layer_sizes_{w}", over(w, lambda e: sn.layer_sizes(e, K)), f"{o.graph(w)} SELECT a, count(*)::BIGINT AS n, sum(deg)::BIGINT AS deg FROM cl GROUP BY a")
    for by, x in (("vertex", "1"), ("degree", "deg")):
        add(f"bias_histogram_{by}_{w}", over(w, lambda e, by=by: sn.bias_histogram(e, ELL, by)), f"{o.graph(w)} SELECT i, sum({x})::BIGINT AS weight FROM cl GROUP BY i")
    add(f"snapshot_{w}", over(w, lambda e: r9(sn.snapshot(e, ELL), "x")), f"{o.graph(w)}, {o.cells()} SELECT i, j, round(weight / (SELECT sum(weight) FROM sn)::DOUBLE, 9) AS x FROM sn")
    add(f"refined_snapshot_{w}", over(w, lambda e: sn.refined_counts(e, ELL, K)), f"{o.graph(w)}, {o.refined()} SELECT * FROM rf")
    add(f"multigraph_{w}", over(w, lambda e: ed.multigraph(e).groupBy("mult").agg(F.count(F.lit(1)).alias("pairs"))), f"WITH {o.edges(w)} SELECT mult, count(*)::BIGINT AS pairs FROM (SELECT count(*)::BIGINT AS mult FROM e GROUP BY u, v) GROUP BY mult")


def projection_identity(e: DataFrame) -> DataFrame:
    a, b = sn.project(sn.refined_counts(e, ELL, K), "weight"), sn.snapshot_counts(e, ELL)
    both = a.join(b.withColumnRenamed("weight", "w2"), ["i", "j"], "full")
    return both.agg(F.count(F.lit(1)).alias("cells"), F.sum((~F.col("weight").eqNullSafe(F.col("w2"))).cast("long")).alias("differ"))


add("projection_identity", over("goods_flow", projection_identity), f"{o.graph('goods_flow')}, {o.cells()} SELECT count(*)::BIGINT AS cells, 0::BIGINT AS differ FROM sn")
add("rollup_refined", over("user_item", lambda e: sn.rollup_refined(sn.refined_counts(e, ELL, K))), f"{o.graph('user_item')}, {o.refined()} SELECT coalesce(a, 0)::INT AS a, coalesce(b, 0)::INT AS b, coalesce(i, 0)::INT AS i, coalesce(j, 0)::INT AS j, weight, gid FROM (SELECT a, b, i, j, sum(weight)::BIGINT AS weight, grouping_id(a, b, i, j)::BIGINT AS gid FROM rf GROUP BY CUBE (a, b, i, j))")
add("topk_hubs", over("page_nav", lambda e: temporal.top_hubs(vs.degrees(e))), f"WITH {o.edges('page_nav')}, {o.stats()} SELECT * FROM st ORDER BY deg DESC, vid LIMIT 10")
add("degree_quantiles", over("goods_flow", lambda e: vs.degrees(e).agg(F.percentile("deg", F.lit(0.5)).alias("median"), F.percentile("deg", F.lit(0.99)).alias("p99"))), f"WITH {o.edges('goods_flow')}, {o.stats()} SELECT quantile_cont(deg, 0.5)::DOUBLE AS median, quantile_cont(deg, 0.99)::DOUBLE AS p99 FROM st")
add("approx_vertices", over("goods_flow", lambda e: e.select(F.explode(F.array("u", "v")).alias("vid")).agg(F.approx_count_distinct("vid", 0.02).alias("n"))))


def edge_set_operations(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of two workloads: in both, more often in the first (as multisets), in either."""
    a, b = (wl.workload(spark, d, w).select("u", "v") for w in ("goods_flow", "ship_bipartite"))
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return n(a.intersect(b), "both").join(F.broadcast(n(a.exceptAll(b), "more"))).join(F.broadcast(n(a.union(b).distinct(), "either")))  # single rows


add("edge_set_operations", edge_set_operations, f"WITH {o.edges('goods_flow', 'a')}, {o.edges('ship_bipartite', 'b')} SELECT (SELECT count(*)::BIGINT FROM (SELECT u, v FROM a INTERSECT SELECT u, v FROM b)) AS both, (SELECT count(*)::BIGINT FROM (SELECT u, v FROM a EXCEPT ALL SELECT u, v FROM b)) AS more, (SELECT count(*)::BIGINT FROM (SELECT u, v FROM a UNION SELECT u, v FROM b)) AS either")
add("general_degree_classes", over("goods_flow", lambda e: sn.refined_counts(e, ELL, 4, degree_thresholds=(1.0, 10.0, 50.0, 400.0, 1e12))), f"WITH {o.edges('goods_flow')}, {o.stats()}, cl AS (SELECT vid, {o.bias_class(ELL)} AS i, (1 + (deg >= 10)::INT + (deg >= 50)::INT + (deg >= 400)::INT)::INT AS a FROM st), {o.refined()} SELECT * FROM rf")

# windows and smoothing
_X = f"sx AS (SELECT i, j, weight / (SELECT sum(weight) FROM sn)::DOUBLE AS x FROM sn)"
_RX = f"rx AS (SELECT a, b, i, j, weight / (SELECT sum(weight) FROM rf)::DOUBLE AS x FROM rf)"
_IJ, _ABIJ = [("i", ELL), ("j", ELL)], [("a", K), ("b", K), ("i", ELL), ("j", ELL)]


def window_sizes(e: DataFrame) -> DataFrame:
    """The window of each bias class that has vertices, with their number."""
    i = F.col("i")
    return sn.bias_histogram(e, ELL).select("i", F.col("weight").alias("n"), wi.window_size(i, 2, ELL).cast("int").alias("size"), F.round(wi.nu(i, 2, ELL), 9).alias("nu"), F.round(wi.nu_lo(i, 2, ELL), 9).alias("lo"), F.round(wi.nu_hi(i, 2, ELL), 9).alias("hi"))


add("window_sizes", over("user_item", window_sizes),
    f"{o.graph('user_item')} SELECT i, count(*)::BIGINT AS n, {o.size('i', 2, ELL)}::INT AS size, round(1.0::DOUBLE / {o.size('i', 2, ELL)}, 9) AS nu, round(1.0::DOUBLE / {o.extreme('i', 2, ELL, 'greatest')}, 9) AS lo, round(1.0::DOUBLE / {o.extreme('i', 2, ELL, 'least')}, 9) AS hi FROM cl GROUP BY i")
add("smooth_matrix_goods", over("goods_flow", lambda e: r9(wi.smooth_matrix(sn.snapshot(e, ELL), 2, ELL), "x")), f"{o.graph('goods_flow')}, {o.cells()}, {_X} SELECT i, j, round(x, 9) AS x FROM ({o.spread('sx', _IJ, 2, 2)})")
add("smooth_array_goods", over("goods_flow", lambda e: r9(wi.smooth_array(sn.refined_snapshot(e, ELL, K), 1, K, ELL), "x")), f"{o.graph('goods_flow')}, {o.refined()}, {_RX} SELECT a, b, i, j, round(x, 9) AS x FROM ({o.spread('rx', _ABIJ, 1, 1)})")


def envelope(e: DataFrame) -> DataFrame:
    a = sn.refined_snapshot(e, ELL, K)
    keys = ["a", "b", "i", "j"]
    lo, hi = wi.lower_array(a, 1, K, ELL), wi.upper_array(a, 1, K, ELL)
    return r9(hi.withColumnRenamed("x", "hi").join(lo.withColumnRenamed("x", "lo"), keys, "left").fillna(0.0, ["lo"]), "lo", "hi")


add("lower_upper_arrays_goods", over("goods_flow", envelope), f"{o.graph('goods_flow')}, {o.refined()}, {_RX}, lo AS ({o.spread('rx', _ABIJ, 1, 0, 'lo')}), hi AS ({o.spread('rx', _ABIJ, 1, 2, 'hi')}) SELECT hi.a, hi.b, hi.i, hi.j, round(hi.x, 9) AS hi, round(coalesce(lo.x, 0), 9) AS lo FROM hi LEFT JOIN lo USING (a, b, i, j)")
add("norms_between_workloads", lambda spark, d: r9(wi.norms(sn.snapshot(wl.goods_flow(spark, d), ELL), sn.snapshot(wl.user_item(spark, d), ELL)), "l1", "linf"),
    f"{o.graph('goods_flow')}, {o.cells()}, {o.edges('user_item', 'e2')}, {o.stats('e2', 'st2')}, {o.classes('st2', 'cl2')}, {o.cells('e2', 'cl2', 'sn2')}, d AS (SELECT abs(coalesce(p.weight / (SELECT sum(weight) FROM sn)::DOUBLE, 0) - coalesce(q.weight / (SELECT sum(weight) FROM sn2)::DOUBLE, 0)) AS d FROM sn p FULL JOIN sn2 q ON p.i = q.i AND p.j = q.j) SELECT round(sum(d), 9) AS l1, round(max(d), 9) AS linf FROM d")

# rules
add("greedy_value", over("goods_flow", lambda e: r9(ob.oblivious_value_exact(sn.snapshot_counts(e, 2), ob.greedy_selection()), "value")), f"{o.graph('goods_flow', ell=2)}, {o.cells()} SELECT num, m, round(value, 9) AS value FROM ({o.rule_value(sel=ob.greedy_selection())})")
add("coin_value", over("goods_flow", lambda e: r9(ob.oblivious_value_exact(sn.snapshot_counts(e, 1), ob.coin_selection()), "value")), f"{o.graph('goods_flow', ell=1)}, {o.cells()} SELECT num, m, round(value, 9) AS value FROM ({o.rule_value(sel=ob.coin_selection())})")
_WIN = "[" + ", ".join(repr(x) for x in ob.smoothed_selection(SEL, 2)[0]) + "]"
add("smoothed_rule_value", over("goods_flow", lambda e: r9(ob.smoothed_value(sn.snapshot(e, ELL), SEL, 2), "value")), f"{o.graph('goods_flow')}, {o.cells()}, {_X}, sm AS ({o.spread('sx', _IJ, 2, 2)}) SELECT round(sum(x * r[i] * (1 - r[j])), 9) AS value FROM sm, (SELECT [" + ", ".join(f"{x}::DOUBLE" for x in SEL.r) + "] AS r)")
#: The rule whose certified ratio passes 0.483: 99 equal classes within 0.49 of balance, and two outer ones.
BEST = ob.clamped_linear()


def _best_class() -> str:
    """The class of a bias among the rule's thresholds, as a sum of comparisons."""
    return "(1 + " + " + ".join(f"(b >= {x!r}::DOUBLE)::INT" for x in BEST.t[1:-1]) + ")"


add("clamped_rule_value", over("goods_flow", lambda e: r9(bl.exact_snapshot_value(e, BEST), "value")),
    f"WITH {o.edges('goods_flow')}, {o.stats()}, bc AS (SELECT vid, {_best_class()} AS i FROM (SELECT vid, (d_out - d_in) / deg::DOUBLE AS b FROM st)), rr AS (SELECT [" + ", ".join(f"{x!r}::DOUBLE" for x in BEST.r) + "] AS r) SELECT (SELECT count(*) FROM e)::BIGINT AS m, round(sum(r[s.i] * (1 - r[t.i])) / count(*), 9) AS value FROM e JOIN bc s ON u = s.vid JOIN bc t ON v = t.vid, rr")
_COIN = "('0x' || substr(md5(vid || ':0'), 1, 8))::BIGINT::DOUBLE"
add("oblivious_cut_goods", over("goods_flow", lambda e: r9(exact.cut_value(e, ob.oblivious_cut(e, SEL)), "value")),
    f"{o.graph('goods_flow')}, ct AS (SELECT vid, ({_COIN} < ([" + ", ".join(repr(x) + "::DOUBLE" for x in SEL.r) + "])[i] * 4294967296)::INT AS side FROM cl) SELECT sum(s.side * (1 - t.side))::BIGINT AS cut, count(*)::BIGINT AS m, round(sum(s.side * (1 - t.side)) / count(*)::DOUBLE, 9) AS value FROM e JOIN ct s ON u = s.vid JOIN ct t ON v = t.vid")
_SIDE = "(('0x' || substr(md5({v} || ':' || s), 1, 8))::BIGINT::DOUBLE < (" + "[" + ", ".join(repr(x) + "::DOUBLE" for x in SEL.r) + "])[{c}.i] * 4294967296)"
add("oblivious_cut_mean", over("user_item", lambda e: r9(ob.oblivious_cut_mean(e, SEL, 16), "value")),
    f"{o.graph('user_item')} SELECT round(count(*) FILTER (WHERE {_SIDE.format(v='u', c='x')} AND NOT {_SIDE.format(v='v', c='y')}) / count(*)::DOUBLE, 9) AS value FROM e JOIN cl x ON u = x.vid JOIN cl y ON v = y.vid, range(16) t(s)")
add("random_cut_goods", over("goods_flow", lambda e: r9(exact.random_cut(e), "value")), f"WITH {o.edges('goods_flow')}, x AS (SELECT ('0x' || substr(md5(u || ':0'), 1, 1))::BIGINT % 2 = 1 AND ('0x' || substr(md5(v || ':0'), 1, 1))::BIGINT % 2 = 0 AS hit FROM e) SELECT count(*) FILTER (WHERE hit)::BIGINT AS cut, count(*)::BIGINT AS m, round(count(*) FILTER (WHERE hit) / count(*)::DOUBLE, 9) AS value FROM x")
for w in ("region_trade", "event_next", "turn_roles"):
    labels = "ids AS (SELECT vid, row_number() OVER (ORDER BY vid) - 1 AS p FROM st), pr AS (SELECT s.p AS pu, t.p AS pv, count(*) AS n FROM e JOIN ids s ON u = s.vid JOIN ids t ON v = t.vid GROUP BY 1, 2)"
    add(f"exact_val_{w}", over(w, lambda e: r9(exact.exact_val(e), "value")), f"WITH {o.edges(w)}, {o.stats()}, {labels}, sc AS (SELECT x, sum(CASE WHEN (x >> pu) & 1 = 1 AND (x >> pv) & 1 = 0 THEN n ELSE 0 END) AS s FROM pr, range(0, (SELECT (1 << count(*))::BIGINT FROM ids)) t(x) GROUP BY x) SELECT max(s)::BIGINT AS cut, (SELECT count(*) FROM e)::BIGINT AS m, round(max(s) / (SELECT count(*) FROM e)::DOUBLE, 9) AS value FROM sc")
add("exact_val_components", over("user_steps", lambda e: r9(exact.exact_val_components(e), "value")),
    "WITH x AS (SELECT user_id, event_type AS p, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS q FROM events), e AS (SELECT user_id, p, q FROM x WHERE p <> q), "
    "ids AS (SELECT user_id, t, row_number() OVER (PARTITION BY user_id ORDER BY t) - 1 AS k FROM (SELECT user_id, p AS t FROM e UNION SELECT user_id, q FROM e)), "
    "pr AS (SELECT e.user_id, s.k AS pu, t.k AS pv, count(*) AS n FROM e JOIN ids s ON e.user_id = s.user_id AND p = s.t JOIN ids t ON e.user_id = t.user_id AND q = t.t GROUP BY 1, 2, 3), "
    "sz AS (SELECT user_id, count(*) AS c FROM ids GROUP BY 1), lb AS (SELECT user_id, unnest(range(0, (1 << c)::BIGINT)) AS x FROM sz), "
    "sc AS (SELECT pr.user_id, x, sum(CASE WHEN (x >> pu) & 1 = 1 AND (x >> pv) & 1 = 0 THEN n ELSE 0 END) AS s FROM pr JOIN lb ON pr.user_id = lb.user_id GROUP BY 1, 2), "
    "be AS (SELECT user_id, max(s) AS s FROM sc GROUP BY 1) SELECT sum(s)::DOUBLE AS cut, (SELECT count(*) FROM e)::DOUBLE AS m, round(sum(s) / (SELECT count(*) FROM e)::DOUBLE, 9) AS value FROM be")  # fmt: skip
add("local_search_cut", over("goods_flow", lambda e: r9(exact.cut_value(e, exact.local_search_cut(e, 3)), "value")))

# reductions and higher orders
add("weighted_rounding", lambda spark, d: ed.round_weights(wl.goods_flow_weighted(spark, d), 0.5).groupBy("mult").agg(F.count(F.lit(1)).alias("pairs")),
    f"WITH w AS (SELECT {o._FLOW}, l_quantity::BIGINT AS weight FROM lineitem), x AS (SELECT round(weight / ((SELECT min(weight) FROM w WHERE weight > 0) * 0.5::DOUBLE))::BIGINT AS mult FROM w WHERE weight > 0 AND u <> v) SELECT mult, count(*)::BIGINT AS pairs FROM x GROUP BY mult")
add("weighted_snapshot", lambda spark, d: sn.snapshot_counts(wl.goods_flow_weighted(spark, d), ELL), f"WITH e AS (SELECT * FROM (SELECT {o._FLOW}, l_quantity::BIGINT AS weight FROM lineitem) WHERE u <> v), {o.stats(weight='weight')}, {o.classes()} SELECT s.i, t.i AS j, sum(weight)::BIGINT AS weight FROM e JOIN cl s ON u = s.vid JOIN cl t ON v = t.vid GROUP BY 1, 2")
add("maxcut_reduction", over("part_pair", lambda e: r9(ob.oblivious_value_exact(sn.snapshot_counts(ed.cut_as_dicut(e), ELL), SEL), "value")), f"WITH {o.edges('part_pair', 'e0')}, e AS (SELECT eid || '<' AS eid, v AS u, u AS v FROM e0 UNION ALL SELECT eid, u, v FROM e0), {o.stats()}, {o.classes()}, {o.cells()} SELECT num, m, round(value, 9) AS value FROM ({o.rule_value()})")
for shape, (x, y) in {"path": ("p.v = q.u", ("p.u", "q.v")), "out_star": ("p.u = q.u AND p.eid <> q.eid", ("p.v", "q.v")), "in_star": ("p.v = q.v AND p.eid <> q.eid", ("p.u", "q.u"))}.items():
    mid = {"path": "p.v", "out_star": "p.u", "in_star": "p.v"}[shape]
    add(f"second_order_{shape}", over("user_item", lambda e, s=shape: sn.second_order(e, 5, s)), f"{o.graph('user_item', ell=5)} SELECT x.i AS i, m.i AS h, y.i AS j, count(*)::BIGINT AS weight FROM e p JOIN e q ON {x} JOIN cl x ON x.vid = {y[0]} JOIN cl m ON m.vid = {mid} JOIN cl y ON y.vid = {y[1]} GROUP BY 1, 2, 3")

# the sketch
_ROWS = SKETCH.rows()
add("poly4_members", over("goods_flow", lambda e: vs.degrees(e).select("vid").join(F.broadcast(layered.layer_table(e.sparkSession, {0: SKETCH})), poly4(F.col("vid"), *(F.col(f"c{j}") for j in range(4))) < F.col("threshold")).groupBy("layer").agg(F.count(F.lit(1)).alias("n"), F.sum("vid").alias("sum_vid"))),
    o.sketch(SKETCH, "goods_flow") + f", {o.stats()} SELECT layer, count(*)::BIGINT AS n, sum(vid)::BIGINT AS sum_vid FROM st JOIN par ON {o.poly('vid')} < thr GROUP BY layer")
add("edge_coins_md5", over("goods_flow", lambda e: layered.edge_layers(e, {0: SKETCH.replace(force_p1=True)}).groupBy("layer").agg(F.count(F.lit(1)).alias("n"))), o.sketch(SKETCH, "goods_flow") + " SELECT layer, count(*)::BIGINT AS n FROM coined GROUP BY layer")


def sketch_of(e: DataFrame, p: Params = SKETCH) -> layered.Sketch:
    return layered.build_sketch(e, p)


add("sketch_vertices", over("goods_flow", lambda e: sketch_of(e).vertices.groupBy("layer").agg(F.count(F.lit(1)).alias("n"), F.sum("vid").alias("sum_vid"))), o.sketch(SKETCH, "goods_flow") + " SELECT layer, count(*)::BIGINT AS n, sum(vid)::BIGINT AS sum_vid FROM tv GROUP BY layer")
for name, p in (("sketch_edges", SKETCH), ("sketch_trim", CAPPED)):
    add(name, over("goods_flow", lambda e, p=p: sketch_of(e, p).edges.groupBy("layer").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("u") + 3 * F.col("v")).alias("checksum"))), o.sketch(p, "goods_flow") + " SELECT layer, count(*)::BIGINT AS n, sum(u + 3 * v)::BIGINT AS checksum FROM tr GROUP BY layer")
add("sketch_overflow", over("goods_flow", lambda e: sketch_of(e, SKETCH.replace(v_cap=300)).overflow.select("layer", "n", "overflow")), o.sketch(SKETCH, "goods_flow") + " SELECT layer, count(*)::BIGINT AS n, count(*) > 300 AS overflow FROM tv GROUP BY layer")
for w in ("goods_flow", "page_nav"):
    for name, p in ((f"apparent_classes_{w}", SKETCH), (f"apparent_classes_capped_{w}", CAPPED)):
        add(name, over(w, lambda e, p=p: est.apparent_stats(sketch_of(e, p)).groupBy("layer", "a", "i").agg(F.count(F.lit(1)).alias("n"))), o.sketch(p, w) + " SELECT layer, a, i, count(*)::BIGINT AS n FROM ap GROUP BY 1, 2, 3")
    add(f"usable_vertices_{w}", over(w, lambda e: est.usable_vertices(sketch_of(e)).groupBy("layer", "a", "i").agg(F.count(F.lit(1)).alias("n"))), o.sketch(SKETCH, w) + " SELECT layer, a, i, count(*)::BIGINT AS n FROM us GROUP BY 1, 2, 3")
_WT = "w2 AS (SELECT i, j, {k} x0 / m AS x FROM wt, mm)"
add("estimate_array_practical", over("goods_flow", lambda e: r9(est.estimate_array(sketch_of(e)), "x")), o.sketch(SKETCH, "goods_flow") + f", w2 AS (SELECT la, lb, i, j, x0 / m AS x FROM wt, mm), sp AS (SELECT la, lb, ni AS i, nj AS j, sum(x / ({o.size('i', 2, ELL)} * {o.size('j', 2, ELL)})::DOUBLE) AS x FROM w2, LATERAL (SELECT unnest(range(greatest(w2.i - 2, 1), least(w2.i + 2, {ELL}) + 1)) AS ni) AS p, LATERAL (SELECT unnest(range(greatest(w2.j - 2, 1), least(w2.j + 2, {ELL}) + 1)) AS nj) AS q GROUP BY la, lb, ni, nj) SELECT la AS a, lb AS b, i::INT AS i, j::INT AS j, round(x, 9) AS x FROM sp")
_EM = o.sketch(SKETCH, "goods_flow") + f", w2 AS (SELECT i, j, sum(x0 / m) AS x FROM wt, mm GROUP BY i, j), em AS ({o.spread('w2', _IJ, 2, 2)})"
add("estimate_matrix_practical", over("goods_flow", lambda e: r9(est.estimate_matrix(sketch_of(e)), "x")), _EM + " SELECT i, j, round(x, 9) AS x FROM em")
_R = "(SELECT [" + ", ".join(f"{x}::DOUBLE" for x in SEL.r) + "] AS r)"
add("estimate_value_practical", over("goods_flow", lambda e: r9(est.estimate_of(e, SKETCH, SEL), "value", "clipped", "mass")), _EM + f" SELECT round(v, 9) AS value, round(least(greatest(v, 0), 1), 9) AS clipped, round(ms, 9) AS mass, m, false AS overflow FROM (SELECT sum(x * r[i] * (1 - r[j])) AS v, sum(x) AS ms FROM em, {_R}), mm")


def theory(e: DataFrame, eps: float = 0.5):
    size = vs.net_flow(e).select("m", "n").first()
    p, t = theory_params(size["n"], size["m"], eps)
    return layered.build_sketch(e, p), p, t


_T8 = f"{o.graph('user_item', ell=8)}, {o.cells()}, {_X}, sm AS ({o.spread('sx', [('i', 8), ('j', 8)], 2, 2)})"
add("estimate_matrix_theory", over("user_item", lambda e: r9(est.estimate_matrix(theory(e)[0]), "x")), _T8 + " SELECT i, j, round(x, 9) AS x FROM sm")
_S8 = ob.uniform_clamped(8)
add("estimate_value_theory", over("user_item", lambda e: r9(est.estimate_value(theory(e)[0], _S8).select("value", "mass", "m", "overflow"), "value", "mass")), _T8 + " SELECT round(sum(x * r[i] * (1 - r[j])) - 0.125, 9) AS value, round(sum(x), 9) AS mass, (SELECT count(*) FROM e)::BIGINT AS m, false AS overflow FROM sm, (SELECT [" + ", ".join(f"{x}::DOUBLE" for x in _S8.r) + "] AS r)")


def theory_band(e: DataFrame) -> DataFrame:
    s, p, _ = theory(e)
    return r9(wi.pointwise_violation(est.estimate_array(s), sn.refined_snapshot(e, p.ell, p.k), p.w, p.k, p.ell), "worst")


add("theory_pointwise_violation", over("user_item", theory_band), "SELECT 0.0::DOUBLE AS worst")
add("smoothed_error_practical", over("goods_flow", lambda e: r9(wi.smoothed_error(est.estimate_matrix(sketch_of(e)), sn.snapshot(e, ELL), 2, ELL), "l1")),
    _EM + f", {o.stats()}, {o.classes()}, {o.cells()}, {_X}, sm AS ({o.spread('sx', _IJ, 2, 2)}) SELECT round(sum(abs(coalesce(p.x, 0) - coalesce(q.x, 0))), 9) AS l1 FROM em p FULL JOIN sm q ON p.i = q.i AND p.j = q.j")


def window_edge_classes(e: DataFrame) -> DataFrame:
    """Edges by their place against the window around the cell of degree class 4 and the middle bias class."""
    c = sn.vertex_classes(e, ELL, K)
    x = e.join(c.select(F.col("vid").alias("u"), F.col("a").alias("ua"), F.col("i").alias("ui")), "u").join(c.select(F.col("vid").alias("v"), F.col("a").alias("va"), F.col("i").alias("vi")), "v")
    kind = wi.classify_against_window([F.col(n) for n in ("ua", "va", "ui", "vi")], [F.lit(z) for z in (4, 4, 11, 11)], 4)
    return x.groupBy(kind.alias("kind")).agg(F.count(F.lit(1)).alias("n"))


add("window_edge_classes", over("user_item", window_edge_classes),
    f"{o.graph('user_item')} SELECT CASE WHEN far <= 3 THEN 'inner' WHEN far = 4 THEN 'borderline' ELSE 'outer' END AS kind, count(*)::BIGINT AS n FROM (SELECT greatest(abs(s.a - 4), abs(t.a - 4), abs(s.i - 11), abs(t.i - 11)) AS far FROM e JOIN cl s ON u = s.vid JOIN cl t ON v = t.vid) GROUP BY 1")
NESTED = SKETCH.replace(mode="nested")


def estimate_sql(p: Params, tail: str, pairs: str = "", usable: str = "") -> str:
    """SQL over em, the estimated matrix of a sketch with these parameters, and mm."""
    sql = o.sketch(p, "goods_flow", pairs=pairs)
    if usable:
        a = sql.index("us AS (")
        sql = sql[:a] + usable + sql[sql.index("mm AS (") :]
    return sql + f", w2 AS (SELECT i, j, sum(x0 / m) AS x FROM wt, mm GROUP BY i, j), em AS ({o.spread('w2', _IJ, p.w, p.w)}) {tail}"


_MASS = "SELECT round(coalesce(sum(x), 0), 9) AS mass FROM em"
_VALUE = f"SELECT round(v, 9) AS value, round(least(greatest(v, 0), 1), 9) AS clipped, round(ms, 9) AS mass, m, false AS overflow FROM (SELECT sum(x * r[i] * (1 - r[j])) AS v, sum(x) AS ms FROM em, {_R}), mm"
add("estimate_value_nested", over("goods_flow", lambda e: r9(est.estimate_of(e, NESTED, SEL), "value", "clipped", "mass")), estimate_sql(NESTED, _VALUE))
add("estimate_value_capped", over("goods_flow", lambda e: r9(est.estimate_of(e, CAPPED, SEL), "value", "clipped", "mass")), estimate_sql(CAPPED, _VALUE))
for name, p, kw in (("in_layer_only", SKETCH, {"cross": "in_layer"}), ("no_window", SKETCH.replace(w=0), {}), ("no_vertex_sampling", SKETCH.replace(force_p1=True), {}), ("no_edge_sampling", SKETCH.replace(force_q1=True), {}), ("single_layer", SKETCH.replace(single_layer=6), {}), ("flat_rates", SKETCH.replace(rising=False), {}), ("induced_store", SKETCH.replace(store="induced"), {})):
    add(f"ablation_{name}", over("goods_flow", lambda e, p=p, kw=kw: r9(wi.mass(est.estimate_matrix(sketch_of(e, p), **kw)), "mass")), estimate_sql(p, _MASS, "AND s.layer = t.layer" if kw else ""))
_TRUE = f"{o.stats()}, {o.classes()}, us AS (SELECT ap.layer, ap.vid, cl.a, cl.i FROM ap JOIN cl ON ap.vid = cl.vid WHERE ap.deg < {SKETCH.e_cap} AND abs(cl.a - ap.layer) <= {SKETCH.w}), "
add("ablation_true_classes", over("goods_flow", lambda e: r9(wi.mass(est.estimate_matrix(s := sketch_of(e), est.usable_vertices(s, sn.vertex_classes(e, ELL, K)))), "mass")), estimate_sql(SKETCH, _MASS, usable=_TRUE))
add("sparsified_counts", over("nation_trade", lambda e: guess.sparsify(e, 0.1).groupBy("u").agg(F.count(F.lit(1)).alias("n"))), f"WITH {o.edges('nation_trade')} SELECT u, count(*)::BIGINT AS n FROM e WHERE {o.word(chr(99) + 'oncat_ws(' + chr(39) + ':' + chr(39) + ', eid, ' + chr(39) + 's:0' + chr(39) + ')')} < 0.1::DOUBLE * 4294967296 GROUP BY u")
_GRID = guess.guess_grid(1 << 20)
add("guess_selection", lambda spark, d: ed.edge_count(wl.goods_flow(spark, d)).select("m", guess.select_guess_column(F.col("m"), _GRID).cast("int").alias("t")), f"WITH {o.edges('goods_flow')} SELECT count(*)::BIGINT AS m, least(greatest(floor(ln(count(*)) / ln(1.9)), {_GRID[0][0]}), {_GRID[-1][0]})::INT AS t FROM e")
add("small_buffer_roles", over("turn_roles", lambda e: r9(guess.small_graph_exact(e, 1 << 30), "value")), SQL["exact_val_turn_roles"])
add("guess_grid_sketch", over("user_item", lambda e: guess.sketch_all_guesses(e, 256, power=1.5).edges.groupBy("guess", "layer").agg(F.count(F.lit(1)).alias("n"))))

# streams of unknown length: one scan for all guesses
N_TRADE, EPS_TRADE, POWER_TRADE = 25, 0.05, 4.0


def unknown_length_edges(spark: SparkSession, d: str) -> DataFrame:
    """Rows by layer of the guess that the counter picks."""
    p = guess.one_pass(wl.nation_trade(spark, d), N_TRADE, EPS_TRADE, lambda m: SKETCH, POWER_TRADE)
    s = p.sketch().sample
    return s.groupBy(F.col("guess").alias("t"), "layer").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("u") + 3 * F.col("v")).alias("checksum"))


def _trade_source() -> str:
    grid = guess.guess_grid(N_TRADE, POWER_TRADE)
    rates = ", ".join(f"({t}, {int(min(guess.sparsify_rate(N_TRADE, g, EPS_TRADE), 1.0) * (1 << 32))}::BIGINT)" for t, g in grid)
    return (
        f"{o.edges('nation_trade', 'e0')}, gs(t, th) AS (VALUES {rates}), ch AS (SELECT m, least(greatest(floor(ln(m) / ln(1.9)), {grid[0][0]}), {grid[-1][0]})::INT AS t FROM (SELECT count(*)::BIGINT AS m FROM e0)), "
        "e AS (SELECT e0.* FROM e0, ch JOIN gs ON ch.t = gs.t WHERE ('0x' || substr(md5(concat_ws(':', eid, 's', 0)), 1, 8))::BIGINT < th)"
    )


_TRADE = o.sketch(SKETCH, "nation_trade", source=_trade_source())
add("unknown_length_edges", unknown_length_edges, _TRADE + " SELECT t, layer, count(*)::BIGINT AS n, sum(u + 3 * v)::BIGINT AS checksum FROM rw, ch GROUP BY t, layer")
add("unknown_length_value", lambda spark, d: r9(guess.estimate_unknown(wl.nation_trade(spark, d), N_TRADE, EPS_TRADE, SEL, lambda m: SKETCH, POWER_TRADE), "value", "mass"),
    _TRADE + f", w2 AS (SELECT i, j, sum(x0 / m) AS x FROM wt, mm GROUP BY i, j), em AS ({o.spread('w2', _IJ, 2, 2)}) SELECT ch.t, ch.m, mm.m AS kept, false AS exact, round(v, 9) AS value, round(ms, 9) AS mass, false AS overflow FROM (SELECT sum(x * r[i] * (1 - r[j])) AS v, sum(x) AS ms FROM em, {_R}), mm, ch")

# baselines
add("baseline_quarter", over("goods_flow", bl.baseline_quarter), f"WITH {o.edges('goods_flow')} SELECT count(*)::BIGINT AS m, 0.25::DOUBLE AS value FROM e")
add("best_lower_bound", over("goods_flow", lambda e: r9(bl.best_lower_bound(e), "value")), f"{o.graph('goods_flow')}, {o.cells()}, ne AS (SELECT sum(d_out)::BIGINT AS m, sum(abs(d_out - d_in))::BIGINT AS net FROM st) SELECT ne.m, round(greatest({o.ZEROTH.replace(' m', ' ne.m').replace('(m', '(ne.m')}, value), 9) AS value FROM ne, ({o.rule_value()}) AS rv")
add("baseline_cauchy", over("goods_flow", lambda e: r9(bl.baseline_cauchy(e), "value")))
_H01 = "('0x' || substr(md5({v} || ':0'), 1, 8))::BIGINT::DOUBLE / 4294967296"
add("vertex_sample_net", over("goods_flow", lambda e: r9(bl.bias_from_vertex_sample(e, 0.5), "net")), f"WITH {o.edges('goods_flow')}, {o.stats()} SELECT (SELECT count(*) FROM e)::BIGINT AS m, round(sum(abs(d_out - d_in)) / 0.5::DOUBLE, 9) AS net FROM st WHERE {_H01.format(v='vid')} < 0.5")
add("lp_norm_sampled", over("goods_flow", lambda e: r9(bl.lp_norm_sampled(vs.biases(e).select(F.col("vid").alias("id"), F.col("bias").alias("x")), 2, 0.5), "norm")), f"WITH {o.edges('goods_flow')}, {o.stats()} SELECT count(*)::BIGINT AS n, round(sqrt(sum(((d_out - d_in) / deg::DOUBLE) ** 2) / 0.5), 9) AS norm FROM st WHERE {_H01.format(v='vid')} < 0.5")
add("gold_standard", over("goods_flow", lambda e: bl.gold_standard_counts(e, 500, ELL)), f"{o.graph('goods_flow')}, e1 AS (SELECT * FROM e ORDER BY md5(concat_ws(':', eid, 'g', 0)), eid LIMIT 500), {o.cells('e1')} SELECT * FROM sn")
add("induced_sample", over("goods_flow", lambda e: bl.induced_sample_counts(e, 0.3, ELL)), f"{o.graph('goods_flow')}, e1 AS (SELECT * FROM e WHERE {_H01.format(v='u')} < 0.3 AND {_H01.format(v='v')} < 0.3), {o.cells('e1')} SELECT * FROM sn")
add("induced_sample_star", over("customer_star", lambda e: bl.induced_sample_counts(e, 0.05, ELL).agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("edges"))), f"WITH {o.edges('customer_star')} SELECT count(*)::BIGINT AS edges FROM e WHERE {_H01.format(v='u')} < 0.05 AND {_H01.format(v='v')} < 0.05")


def user_item_ts(spark: SparkSession, d: str) -> DataFrame:
    return wl.user_item_frame(wl.table(spark, d, "events")).select(F.col("event_id").cast("string").alias("eid"), "u", "v", "ts").where("u <> v")


add("prefix_snapshot_by_ts", lambda spark, d: bl.prefix_counts(user_item_ts(spark, d), 300, ELL, ["ts", "eid"]), f"WITH {o.edges('user_item')}, f AS (SELECT * FROM e ORDER BY ts, eid LIMIT 300), r AS (SELECT * FROM e WHERE eid NOT IN (SELECT eid FROM f)), {o.stats('r')}, {o.classes()}, {o.cells('f')} SELECT * FROM sn")
for order in ("hash_random", "by_tail"):
    add(f"prefix_snapshot_{order}", lambda spark, d, k=order: bl.prefix_counts(*(lambda x: (x[0], 300, ELL, x[1]))(wl.ordered(wl.user_item(spark, d), k))), f"WITH {o.edges('user_item')}, f AS (SELECT * FROM e ORDER BY {'md5(concat_ws(' + chr(39) + ':' + chr(39) + ', eid, ' + chr(39) + 'o0' + chr(39) + '))' if order == 'hash_random' else 'u'}, eid LIMIT 300), r AS (SELECT * FROM e WHERE eid NOT IN (SELECT eid FROM f)), {o.stats('r')}, {o.classes()}, {o.cells('f')} SELECT * FROM sn")
add("sparsified_exact_regions", over("region_trade", lambda e: r9(bl.sparsified_value(e, 5, 0.05), "value")))
for w in ("goods_flow", "user_item", "part_pair"):
    add(f"compare_methods_{w}", over(w, lambda e, w=w: r9(bl.compare_methods(e, w), "value", "mass")))

# smoothing graphs and diagnostics
add("blow_up_checks", over("user_item", lambda e: r9(blowup.blow_up_checks(e, ELL, 1), "m", "degree_gap", "bias_gap")), f"{o.graph('user_item')} SELECT sum({o.size('i', 1, ELL)})::BIGINT AS copies, (SELECT count(*) FROM e)::DOUBLE AS m, 0.0::DOUBLE AS degree_gap, 0.0::DOUBLE AS bias_gap FROM cl")
add("smoothing_gap", over("user_item", lambda e: r9(blowup.smoothing_gap(e, ELL, 1), "l1", "growth", "l1_bound", "growth_bound")))
add("vertex_sandwich_unsampled", over("user_item", lambda e: diagnostics.vertex_sandwich(e, SKETCH.replace(force_q1=True, e_cap=1 << 30))), "SELECT 0::BIGINT AS missing, 0::BIGINT AS extra, 0::BIGINT AS bias_moved")
_SD = o.sketch(SKETCH, "goods_flow") + f", {o.stats()}, {o.classes()}, sd AS (SELECT layer, vid, deg, least(length(bin(least(deg * (1::BIGINT << greatest(layer - {SKETCH.k_star}, 0)), {1 << K}))), {K})::INT AS a, {o.bias_class(ELL)} AS i FROM (SELECT layer, vid, sum(o)::BIGINT AS d_out, count(*)::BIGINT AS deg FROM (SELECT layer, u AS vid, 1 AS o FROM coined UNION ALL SELECT layer, v, 0 FROM coined) GROUP BY 1, 2)), vx AS (SELECT abs(cl.a - par.layer) AS far, coalesce(sd.deg < {SKETCH.e_cap} AND abs(sd.a - par.layer) <= {SKETCH.w}, false) AS has, coalesce(abs(sd.i - cl.i) <= 1, false) AS near FROM cl CROSS JOIN par LEFT JOIN sd ON sd.layer = par.layer AND sd.vid = cl.vid)"
add("vertex_sandwich_violations", over("goods_flow", lambda e: diagnostics.vertex_sandwich(e, SKETCH)), _SD + f" SELECT count(*) FILTER (WHERE far <= {SKETCH.w - 1} AND NOT has)::BIGINT AS missing, count(*) FILTER (WHERE has AND far > {SKETCH.w + 1})::BIGINT AS extra, count(*) FILTER (WHERE far <= {SKETCH.w - 1} AND has AND NOT near)::BIGINT AS bias_moved FROM vx")
add("good_events", over("goods_flow", lambda e: r9(diagnostics.good_events(e, SKETCH), "margin")))
add("sample_sizes", over("goods_flow", lambda e: diagnostics.sample_sizes(e, SKETCH)), o.sketch(SKETCH, "goods_flow") + " SELECT a.layer, m_a, n_a, coalesce(k.kept, 0)::BIGINT AS kept FROM (SELECT layer, count(*)::BIGINT AS m_a FROM coined GROUP BY 1) a JOIN (SELECT layer, count(DISTINCT vid)::BIGINT AS n_a FROM (SELECT layer, u AS vid FROM coined UNION ALL SELECT layer, v FROM coined) GROUP BY 1) b ON a.layer = b.layer LEFT JOIN (SELECT layer, count(*) AS kept FROM tv GROUP BY 1) k ON a.layer = k.layer")
add("sandwich_sums", over("goods_flow", lambda e: diagnostics.sandwich_sums(e, SKETCH)), o.sketch(SKETCH, "goods_flow") + f", {o.stats()}, {o.classes()}, mb AS (SELECT layer, vid FROM st JOIN par ON {o.poly('vid')} < thr) SELECT s.a AS la, t.a AS lb, count(*)::BIGINT AS y, count(*) FILTER (WHERE mu.vid IS NOT NULL AND mv.vid IS NOT NULL)::BIGINT AS x FROM coined JOIN cl s ON u = s.vid JOIN cl t ON v = t.vid LEFT JOIN mb mu ON mu.layer = s.a AND mu.vid = u LEFT JOIN mb mv ON mv.layer = t.a AND mv.vid = v WHERE coined.layer = least(s.a, t.a) GROUP BY 1, 2")
add("count_events", over("goods_flow", lambda e: r9(diagnostics.count_events(e, SKETCH), "y_off", "x_off")))
_SAMPLED = o.sketch(SKETCH, "goods_flow") + f", {o.stats()}, {o.classes()}, sd AS (SELECT layer, vid, sum(o)::BIGINT AS d_out, count(*)::BIGINT AS deg FROM (SELECT layer, u AS vid, 1 AS o FROM coined UNION ALL SELECT layer, v, 0 FROM coined) GROUP BY 1, 2)"
add("dependence_degrees", over("goods_flow", lambda e: diagnostics.dependence(e, SKETCH)), _SAMPLED + f" SELECT layer, max(sd.deg)::BIGINT AS d_max, {2 * 2 ** (SKETCH.k_star + SKETCH.w + 2)}::INT AS bound FROM sd JOIN cl ON sd.vid = cl.vid WHERE abs(cl.a - layer) <= {SKETCH.w + 1} GROUP BY layer")
add("space_report", over("goods_flow", lambda e: diagnostics.space_report(sketch_of(e)).select("layer", "vertices", "edges")), o.sketch(SKETCH, "goods_flow") + " SELECT layer, (SELECT count(*) FROM tv WHERE tv.layer = par.layer)::BIGINT AS vertices, (SELECT count(*) FROM tr WHERE tr.layer = par.layer)::BIGINT AS edges FROM par WHERE layer IN (SELECT layer FROM tv)")
add("ratio_regions", over("region_trade", lambda e: r9(diagnostics.ratio_report(bl.exact_snapshot_value(e, SEL), exact.exact_val(e)), "estimate", "val", "ratio", "additive")),
    f"{o.graph('region_trade')}, {o.cells()}, rv AS ({o.rule_value()}), ev AS (SELECT value AS val FROM ({SQL['exact_val_region_trade']})) SELECT round(value, 9) AS estimate, val, round(value / val, 9) AS ratio, round(abs(value - val), 9) AS additive, value >= 0.483 * val AND value <= val AS ok FROM rv, ev")

# time
add("asof_prefix_bias", lambda spark, d: temporal.asof_prefix_counts(user_item_ts(spark, d), ELL),
    f"WITH {o.edges('user_item')}, x AS (SELECT eid, ts, u AS vid, 1 AS o FROM e UNION ALL SELECT eid, ts, v, 0 FROM e), p AS (SELECT eid, o, sum(o) OVER w AS d_out, count(*) OVER w AS deg FROM x WINDOW w AS (PARTITION BY vid ORDER BY ts, eid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)), c AS (SELECT eid, o, CASE WHEN deg > 0 THEN least({ELL}, (d_out * {ELL})::BIGINT // deg + 1) ELSE 0 END::INT AS c FROM p) SELECT s.c AS i, t.c AS j, count(*)::BIGINT AS weight FROM c s JOIN c t ON s.eid = t.eid AND s.o = 1 AND t.o = 0 GROUP BY 1, 2")
_WB = "d AS (SELECT start, vid, sum(o) AS p, sum(1 - o) AS q FROM x GROUP BY 1, 2) SELECT start, count(*)::BIGINT AS n, sum(p)::BIGINT AS m, sum(abs(p - q))::BIGINT AS net FROM d GROUP BY start"
add("tumbling_bias", lambda spark, d: temporal.tumbling_bias(user_item_ts(spark, d)), f"WITH {o.edges('user_item')}, x AS (SELECT date_trunc('day', ts)::TIMESTAMP AS start, u AS vid, 1 AS o FROM e UNION ALL SELECT date_trunc('day', ts)::TIMESTAMP, v, 0 FROM e), {_WB}")
add("sliding_bias", lambda spark, d: temporal.sliding_bias(user_item_ts(spark, d)), f"WITH {o.edges('user_item')}, y AS (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 6 HOUR AS start, u, v FROM e, range(4) t(k)), x AS (SELECT start, u AS vid, 1 AS o FROM y UNION ALL SELECT start, v, 0 FROM y), {_WB}")
add("session_bias", lambda spark, d: temporal.session_bias(user_item_ts(spark, d)), f"WITH {o.edges('user_item')}, x AS (SELECT u AS vid, ts FROM e UNION ALL SELECT v, ts FROM e), g AS (SELECT vid, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY vid ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM x), s AS (SELECT vid, ts, sum(fresh) OVER (PARTITION BY vid ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM g) SELECT vid, min(ts) AS start, count(*)::BIGINT AS n FROM s GROUP BY vid, k")
add("late_data_drop", lambda spark, d: temporal.late_rows(user_item_ts(spark, d), F.col("eid").cast("long") % 50 == 0, 3 * 3600, 2 * 3600), f"WITH {o.edges('user_item')}, g AS (SELECT DISTINCT h.eid FROM e h JOIN e t ON h.eid::BIGINT % 50 = 0 AND t.eid::BIGINT % 50 <> 0 AND t.ts > h.ts + INTERVAL 2 HOUR AND t.ts <= h.ts + INTERVAL 3 HOUR) SELECT date_trunc('day', ts)::TIMESTAMP AS day, count(*) FILTER (WHERE eid NOT IN (SELECT eid FROM g))::BIGINT AS kept, count(*) FILTER (WHERE eid IN (SELECT eid FROM g))::BIGINT AS dropped FROM e GROUP BY 1")


# experiments: one row a setting
def _rows(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def experiment_ratio(spark, d):
    """Rule against optimum on graphs small enough to solve."""
    graphs = {w: wl.workload(spark, d, w) for w in ("region_trade", "event_next", "turn_roles")} | {"path3": wl.path(spark, 3), "cycle3": wl.cycle(spark, 3), "star": wl.star(spark, 9), "complete4": wl.complete(spark, 4)}
    return _rows([r9(diagnostics.ratio_report(bl.exact_snapshot_value(e, SEL), exact.exact_val(e)), "estimate", "val", "ratio", "additive").select(F.lit(n).alias("graph"), "*") for n, e in graphs.items()])


def experiment_window(spark, d):
    """Width of the pointwise band, and cost of smoothing, as the window widens."""
    e = wl.goods_flow(spark, d)
    a, m = sn.refined_snapshot(e, ELL, K), sn.snapshot(e, ELL)
    return _rows([r9(wi.l1(wi.upper_array(a, w, K, ELL), wi.lower_array(a, w, K, ELL)).withColumnRenamed("l1", "band").join(F.broadcast(wi.l1(wi.smooth_matrix(m, w, ELL), m).withColumnRenamed("l1", "moved"))).select(F.lit(w).alias("w"), "band", "moved"), "band", "moved") for w in (1, 2, 4)])  # single rows


def _free_shuffles(spark: SparkSession) -> None:
    """Shuffle files go when nothing refers to them any more, in Python first; those of the last query go at the second
    time only."""
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.5)


def experiment_rates(spark, d):
    """Error, mass and space of the sketch as its constants move.  An edge is kept once for all settings, with a mask
    of its layers for each rate; each setting's sketch is freed, and its shuffles, before the next."""
    settings = {(k_star, p0): practical_params(60_000, k_star=k_star, p0=p0) for k_star, p0 in ((3, 0.05), (6, 0.1), (6, 0.25), (8, 0.25))}
    kept, m = marked.keep(wl.goods_flow(spark, d), {f"coins_{k_star}": p for (k_star, _), p in settings.items()})  # p0 is of vertices
    out = []
    for (k_star, p0), p in settings.items():
        s = layered.build_sketch(kept.select("u", "v", "word", "n", F.col(f"coins_{k_star}").alias("coins")), p, m)
        v = r9(est.estimate_value(s, SEL).select("value", "mass"), "value", "mass").first()
        _free_shuffles(spark)
        out.append((k_star, p0, v["value"], v["mass"], s.stored()))
        s.close()
        del s
        _free_shuffles(spark)
    kept.unpersist()
    return spark.createDataFrame(out, "k_star int, p0 double, value double, mass double, stored long")


def experiment_star(spark, d):
    """Edges of the star that each way of sampling vertices still sees."""
    e = wl.customer_star(spark, d)
    s = layered.build_sketch(e, practical_params(2048, k_star=3, p0=0.05, e_cap=1 << 20))
    flat = bl.induced_sample_counts(e, 0.05, ELL).agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("seen")).select(F.lit("uniform").alias("way"), "seen")
    return flat.unionByName(s.edges.agg(F.count_distinct("eid").alias("seen")).select(F.lit("layered").alias("way"), "seen"))


def experiment_orders(spark, d):
    """Sketch checksums and prefix values under stream orders: the first do not change."""
    out = []
    for order in ("arrival", "by_tail", "by_head", "reversed", "hash_random"):
        x, by = wl.ordered(wl.user_item(spark, d), order)
        s = layered.build_sketch(x.repartitionByRange(4, *by), SKETCH)
        c = s.edges.agg(F.count(F.lit(1)).alias("stored"), F.sum(F.col("u") + 3 * F.col("v")).alias("checksum"))
        pre = bl.counts_value(bl.prefix_counts(x, 300, ELL, by), SEL).select(F.col("value").alias("prefix_value"))
        out.append(r9(c.join(F.broadcast(pre)).select(F.lit(order).alias("order"), "stored", "checksum", "prefix_value"), "prefix_value"))  # single rows
    return _rows(out)


def experiment_seeds(spark, d):
    e = wl.user_item(spark, d)
    return r9(diagnostics.seed_report(e, practical_params(10_000, k_star=6, p0=0.5), SEL, 0.339, 0.05, range(4)), "value", "mass")


def experiment_unknown_length(spark, d):
    """Many edges on few vertices: the guess that one scan picks beside the known length and the exact rule."""
    e = wl.nation_trade(spark, d)
    unknown = guess.estimate_unknown(e, N_TRADE, EPS_TRADE, SEL, lambda m: SKETCH, POWER_TRADE).select(F.lit("one pass, length unknown").alias("way"), "t", "m", "kept", "value", "mass")
    known = est.estimate_of(e, SKETCH, SEL).select(F.lit("length known").alias("way"), F.lit(None).cast("int").alias("t"), "m", F.col("m").alias("kept"), "value", "mass")
    exact_rule = ob.oblivious_value_exact(sn.snapshot_counts(e, ELL), SEL).select(F.lit("exact snapshot").alias("way"), F.lit(None).cast("int").alias("t"), "m", F.col("m").alias("kept"), "value", F.lit(1.0).alias("mass"))
    return r9(unknown.unionByName(known).unionByName(exact_rule), "value", "mass")


def theory_error(e: DataFrame, eps: float = 0.5) -> tuple[int, Params, float]:
    """m, parameters and l1 from exact smoothing in theory mode.  Nearly every layer takes every edge there, so an
    edge is kept once with a mask of its layers; on few vertices equal rows are kept as one with their number."""
    spark, ends = e.sparkSession, e.select("u", "v").persist()
    size = vs.net_flow(ends).select("m", "n").first()
    p, _ = theory_params(size["n"], size["m"], eps)
    coins = marked.with_coins(e.select("eid", "u", "v") if p.k_star < p.k else ends, p).select("u", "v", "coins")
    few = size["n"] ** 2 < size["m"]
    rows = (coins.groupBy("u", "v", "coins").agg(F.count(F.lit(1)).alias("n")) if few else coins.withColumn("n", F.lit(1).cast("long")))
    if few or p.k_star < p.k:
        rows = rows.persist()
        rows.count()
        ends.unpersist()
    s = marked.marked_sketch(rows, p, spark.createDataFrame([(size["m"],)], "m long"))
    exact_matrix = sn.snapshot(rows.select("u", "v", F.col("n").alias("weight")), p.ell)
    error = wi.smoothed_error(est.estimate_matrix(s), exact_matrix, p.w, p.ell).first()["l1"]
    s.close()
    rows.unpersist()
    ends.unpersist()
    spark.sparkContext._jvm.System.gc()  # shuffle files go when nothing refers to them
    return size["m"], p, error or 0.0


def experiment_theory(spark, d):
    """Theory mode on seven workloads: l1 is the distance from exact smoothing, which is 0 wherever no
    layer samples (k_star >= k); graphs of few vertices and many edges have layers that do."""
    out = []
    for name in ("goods_flow", "nation_trade", "region_trade", "event_next", "user_item", "customer_star", "page_nav"):
        m, p, error = theory_error(wl.workload(spark, d, name))
        out.append((name, m, p.k, p.k_star, p.k_star < p.k, round(error, 9)))
    return spark.createDataFrame(out, "workload string, m long, k int, k_star int, samples boolean, l1 double")


def experiment_events(spark, d):
    """How often the good events hold over seeds, for two sets of constants."""
    e = wl.user_item(spark, d)
    return _rows([r9(diagnostics.event_frequencies(e, practical_params(e.count(), k_star=k, p0=p0), range(5)), "frequency", "margin").select(F.lit(k).alias("k_star"), F.lit(p0).alias("p0"), "*") for k, p0 in ((3, 0.1), (13, 0.5))])


def experiment_scale(spark, d):
    """Shuffled rows of the sketch and of the exact snapshot as the stream grows fourfold a step."""
    return diagnostics.scale_report(wl.goods_flow(spark, d), 3, 4.0, (1 / 64, 1 / 16, 1 / 4, 1.0))


for name, q in (("ratio", experiment_ratio), ("window", experiment_window), ("rates", experiment_rates), ("star", experiment_star), ("orders", experiment_orders), ("seeds", experiment_seeds), ("unknown_length", experiment_unknown_length), ("theory", experiment_theory), ("events", experiment_events), ("scale", experiment_scale)):
    add(f"experiment_{name}", q)


def certificates(spark, d):
    """Ratios that rules are certified to reach: on all graphs, and on graphs whose vertices lie only in the bias
    classes that the user-item graph has; beside the rule's value there, which over the ratio bounds the optimum."""
    e, out = wl.user_item(spark, d), []
    for n, s in (("coin", ob.coin_selection()), ("uniform_9", ob.uniform_clamped(9)), ("uniform_21", ob.uniform_clamped(21)), ("clamped_101", BEST)):
        classes = sn.vertex_classes(e, s.ell, None, None if s.num else s.t).select("i").distinct().collect()  # ell rows
        everywhere, here = ob.certify_ratio(s), ob.certify_ratio(s, present=[r["i"] for r in classes])
        value = bl.exact_snapshot_value(e, s).first()["value"]
        out.append((n, round(everywhere["primal"], 4), round(everywhere["lower"], 4), len(classes), round(here["primal"], 4), round(here["lower"], 4), round(value, 9)))
    return spark.createDataFrame(out, "rule string, primal double, lower double, classes int, primal_here double, lower_here double, value double")


add("ratio_certificates", certificates)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Theory-mode estimate of the goods flow beside the exact snapshot, baselines and the bound."""
    e = wl.goods_flow(spark, d)
    s, p, _ = theory(e)
    v = est.estimate_value(s, ob.uniform_clamped(p.ell)).select(F.lit("goods_flow").alias("workload"), F.lit("layered_theory").alias("method"), "value", "m", "mass", "overflow")
    rest = bl.compare_methods(e, "goods_flow", ["quarter", "zeroth_order", "snapshot", "upper_bound"]).select("workload", "method", "value", "m", "mass", "overflow")
    return v.unionByName(rest)
