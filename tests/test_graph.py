"""Primitives, snapshots, smoothing, rules and smoothing graphs on graphs that can be checked by hand."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from biascut.operators import baselines, blowup, classes, diagnostics, edges, exact, oblivious, params, snapshot, vertex_stats, windows
from biascut.sources import workloads as wl


@pytest.fixture(scope="session", autouse=True)
def checkpoints(spark, tmp_path_factory):
    spark.sparkContext.setCheckpointDir(str(tmp_path_factory.mktemp("ck")))


def graph(spark, n=12, m=60, seed=0):
    r = random.Random(seed)
    return wl.from_pairs(spark, [(r.randrange(n), r.randrange(n)) for _ in range(m)])


def cells(df):
    return {tuple(r[c] for c in df.columns[:-1]): r[df.columns[-1]] for r in df.collect()}


@pytest.mark.parametrize("make,val,net_value", [
    (lambda s: wl.path(s, 1), 1, 1), (lambda s: wl.path(s, 3), 2 / 3, 1 / 3), (lambda s: wl.cycle(s, 3), 1 / 3, 1 / 4), (lambda s: wl.star(s, 6), 1, 1),
    (lambda s: wl.star(s, 6, out=False), 1, 1), (lambda s: wl.bipartite(s, 3, 4), 1, 1), (lambda s: wl.complete(s, 4), 1 / 3, 1 / 4),
])
def test_closed_forms(spark, make, val, net_value):
    e = make(spark)
    assert exact.exact_val(e).first()["value"] == pytest.approx(val)
    assert exact.exact_val_components(e).first()["value"] == pytest.approx(val)
    assert baselines.baseline_zeroth_order(e).first()["value"] == pytest.approx(net_value)
    assert vertex_stats.upper_bound(e).first()["upper_bound"] >= val - 1e-12
    assert baselines.exact_snapshot_value(e, oblivious.uniform_clamped(21)).first()["value"] <= val + 1e-12


@pytest.mark.parametrize("seed", range(3))
def test_rule_is_sound_and_certified_ratio_holds(spark, seed):
    e = graph(spark, 8, 25, seed)
    best = exact.exact_val(e).first()["value"]
    for sel, ratio in ((oblivious.uniform_clamped(21), 0.469), (oblivious.clamped_linear(), 0.483), (oblivious.greedy_selection(), 0)):
        v = baselines.exact_snapshot_value(e, sel).first()["value"] if sel.num is None or sel.ell == 21 else oblivious.oblivious_value(snapshot.snapshot(e, sel.ell), sel).first()["value"]
        assert ratio * best - 1e-9 <= v <= best + 1e-9
    cut = exact.local_search_cut(e, 4)
    assert exact.cut_value(e, cut).first()["value"] <= best + 1e-12
    mean = oblivious.oblivious_cut_mean(e, oblivious.uniform_clamped(21), 400).first()["value"]
    assert mean == pytest.approx(baselines.exact_snapshot_value(e, oblivious.uniform_clamped(21)).first()["value"], abs=0.05)


def test_certificates():
    for ell, want in ((1, 0.25), (3, 0.375), (9, 0.4441), (21, 0.4693)):
        c = oblivious.certify_ratio(oblivious.uniform_clamped(ell))
        assert c["primal"] == pytest.approx(want, abs=3e-4) and want - 2e-3 <= c["lower"] <= c["primal"] + 1e-6
    assert oblivious.certify_ratio(oblivious.clamped_linear(0.49, 49))["lower"] > 0.481


def test_degrees_graph_size_and_multigraph(spark):
    e = wl.from_pairs(spark, [(0, 1), (0, 1), (1, 2), (3, 3)])
    assert cells(vertex_stats.degrees(e).select("vid", "d_out", "d_in", "deg").select("vid", "deg")) == {(0,): 2, (1,): 3, (2,): 1}
    assert edges.graph_size(e).first().asDict() == {"n": 3, "m": 3}
    assert cells(edges.multigraph(e)) == {(0, 1): 2, (1, 2): 1}
    w = spark.createDataFrame([(0, 1, 1.0), (1, 2, 2.6)], "u long, v long, weight double")
    assert cells(edges.round_weights(w, 0.5)) == {(0, 1): 2, (1, 2): 5}
    empty = wl.from_pairs(spark, [(0, 0)])
    assert edges.graph_size(empty).first()["m"] == 0 and exact.exact_val(empty).count() == 0


@pytest.mark.parametrize("ell", [2, 5, 21])
def test_integer_classes_agree_with_thresholds(spark, ell):
    df = spark.createDataFrame([(o, i) for o in range(9) for i in range(9) if o + i], "o long, i long")
    t = classes.uniform_thresholds(ell)
    x = df.select("o", "i", classes.bias_class(F.col("o"), F.col("o") + F.col("i"), ell).alias("a"), classes.class_index((F.col("o") - F.col("i")) / (F.col("o") + F.col("i")), t).alias("b")).collect()
    for r in x:
        frac = (r.o * ell) % (r.o + r.i) == 0  # on a border doubles may fall either way
        assert r.a == min(ell, r.o * ell // (r.o + r.i) + 1) and (r.a == r.b or frac)
    d = spark.range(1, 70).select("id", classes.degree_class(F.col("id"), 5).alias("a")).collect()
    assert all(r.a == min(5, int(r.id).bit_length()) for r in d)


def test_partition_refinement():
    t, base = classes.refine_partition((-1.0, 0.1, 1.0), 0.25)
    assert classes.is_lambda_wide(t, 0.25) and len(base) == len(t) - 1 and base[0] == 1 and base[-1] == 2
    with pytest.raises(ValueError):
        classes.refine_partition((-1.0, -0.99, 1.0), 0.25, strict=True)


def test_refined_rule_has_the_same_value(spark):
    e, sel = graph(spark), oblivious.greedy_selection()
    fine = oblivious.refine_selection(sel, 0.3)
    a, b = (baselines.exact_snapshot_value(e, oblivious.Selection(s.t, s.r)).first()["value"] for s in (sel, fine))
    assert a == pytest.approx(b)


@pytest.mark.parametrize("k,ell,w", [(3, 4, 1), (4, 5, 2)])
def test_smoothing_equals_the_definition(spark, k, ell, w):
    r = np.random.default_rng(1)
    A = r.random((k, k, ell, ell)) * (r.random((k, k, ell, ell)) < 0.4)
    A /= A.sum()
    df = spark.createDataFrame([(int(a) + 1, int(b) + 1, int(i) + 1, int(j) + 1, float(A[a, b, i, j])) for a, b, i, j in zip(*A.nonzero())], "a int, b int, i int, j int, x double")
    size = lambda x, n, w: min(x + w, n) - max(x - w, 1) + 1
    every = list(itertools.product(range(1, k + 1), range(1, k + 1), range(1, ell + 1), range(1, ell + 1)))
    dims = (k, k, ell, ell)
    nu = {c: 1 / np.prod([size(x, n, w) for x, n in zip(c, dims)]) for c in every}
    near = lambda c, w: [z for z in every if max(abs(x - y) for x, y in zip(c, z)) <= w]
    lo, hi = ({c: f(nu[z] for z in near(c, 1)) for c in every} for f in (min, max))
    at = lambda z: A[tuple(x - 1 for x in z)]
    for made, weight, radius in ((windows.smooth_array(df, w, k, ell), nu, w), (windows.lower_array(df, w, k, ell), lo, w - 1), (windows.upper_array(df, w, k, ell), hi, w + 1)):
        got = cells(made)
        for c in every:
            assert got.get(c, 0.0) == pytest.approx(sum(weight[z] * at(z) for z in near(c, radius)), abs=1e-12)
    assert windows.mass(windows.smooth_array(df, w, k, ell)).first()["mass"] == pytest.approx(1)
    p1 = cells(windows.smooth_matrix(snapshot.project(df), w, ell))
    p2 = cells(snapshot.project(windows.smooth_array(df, w, k, ell)))
    assert set(p1) == set(p2) and all(p1[c] == pytest.approx(p2[c]) for c in p1)
    # any off-by-one relabelling stays inside the band
    shift = {"a": F.when(F.col("i") % 2 == 0, 1).otherwise(-1), "j": F.when(F.col("b") % 2 == 0, -1).otherwise(1)}
    moved = windows.adversarial_relabel(df, shift, w, k, ell)
    assert windows.pointwise_violation(moved, df, w, k, ell).first()["worst"] <= 1e-12
    assert windows.pointwise_violation(df.limit(0), df, w, k, ell).first()["worst"] == pytest.approx(max(cells(windows.lower_array(df, w, k, ell)).values(), default=0))


def test_window_facts():
    for n in range(2, 9):
        for w in range(1, n):
            for i in range(1, n + 1):
                s = windows.size_of(i, w, n)
                assert w + 1 <= s <= 2 * w + 1
                assert windows.size_of(i, min(w + 1, n - 1), n) - s <= 2
                assert s == sum(abs(i - z) <= w for z in range(1, n + 1))
    assert windows.border_fraction(4, 41, 41) < windows.border_fraction(2, 41, 41) < windows.border_fraction(1, 41, 41)
    assert windows.array_to_matrix_bound(0.0, 5, 5, 2) == windows.C_WIN / 2


def test_continuity_and_smoothed_rule(spark):
    sel = oblivious.uniform_clamped(9)
    p, q = snapshot.snapshot(graph(spark, seed=1), 9), snapshot.snapshot(graph(spark, seed=2), 9)
    a, b = (oblivious.oblivious_value(x, sel).first()["value"] for x in (p, q))
    assert abs(a - b) <= windows.l1(p, q).first()["l1"] + 1e-12
    direct = oblivious.oblivious_value(windows.smooth_matrix(p, 2, 9), sel).first()["value"]
    assert oblivious.smoothed_value(p, sel, 2).first()["value"] == pytest.approx(direct)


def test_second_order_counts_pairs(spark):
    e = graph(spark, 6, 20, 3)
    rows = [(r.u, r.v) for r in e.collect()]
    for shape, pairs in (("path", sum(a[1] == b[0] for a in rows for b in rows)), ("out_star", sum(a[0] == b[0] for a in rows for b in rows) - len(rows)), ("in_star", sum(a[1] == b[1] for a in rows for b in rows) - len(rows))):
        assert sum(r.weight for r in snapshot.second_order(e, 3, shape).collect()) == pairs


def test_smoothing_graph(spark):
    e, ell, w = graph(spark, 20, 300, 4), 9, 1
    c = blowup.blow_up_checks(e, ell, w).first()
    assert c["m"] == pytest.approx(e.count()) and c["degree_gap"] < 1e-9 and c["bias_gap"] < 1e-9
    d = blowup.copy_degrees(blowup.smoothed_graph(e, ell, w)).where(f"vid <> {blowup.STAR}")
    t = classes.uniform_thresholds(ell)
    for r in d.collect():
        b = (r.d_out - r.d_in) / r.deg
        assert t[r.c - 1] - 1e-9 <= b <= t[r.c] + 1e-9
    g = blowup.smoothing_gap(e, ell, w).first()
    assert 0 <= g["growth"] <= g["growth_bound"] and g["l1"] <= g["l1_bound"]


def test_reductions_and_sparsifier(spark):
    from biascut.operators import guess

    e = graph(spark, 7, 30, 5)
    both = exact.exact_val(edges.cut_as_dicut(e)).first()["value"]
    und = [(r.u, r.v) for r in e.collect()]
    best = max(sum((x >> u & 1) != (x >> v & 1) for u, v in und) for x in range(1 << 7)) / len(und)
    assert 2 * both == pytest.approx(best)
    big = wl.planted(spark, 12, 20_000, 0.6)
    s = guess.sparsify(big, 0.2)
    assert abs(s.count() - 0.2 * big.count()) < 0.05 * 0.2 * 20_000 * 2
    assert abs(exact.exact_val(s).first()["value"] - exact.exact_val(big).first()["value"]) < 0.03
    grid = guess.guess_grid(1 << 16)
    for m in (300, 5_000, 10**6):
        g = dict(grid)[guess.select_guess(m, grid)]
        assert g <= m < guess.GROWTH * g * (1 + 1e-9)


def test_norm_sketches(spark):
    e = wl.planted(spark, 400, 20_000, 0.5)
    x = vertex_stats.net_flow(e).first()
    c = baselines.l1_norm_sketch(e, 101).first()
    assert c["m"] == x["m"] and abs(c["net"] / x["net"] - 1) < 0.5
    assert abs(baselines.bias_from_vertex_sample(e, 0.5).first()["net"] / x["net"] - 1) < 0.3


def test_tail_bounds_and_budget():
    assert diagnostics.chernoff_upper(100, 1) < 1e-10 and diagnostics.chernoff_lower(100, 0.5) < 1e-5
    assert diagnostics.weighted_chernoff(100, 1, 10) > diagnostics.chernoff_upper(100, 1)
    assert diagnostics.chebyshev(4, 10) == 0.04 and diagnostics.chebyshev_dependent(4, 0, 10) == 0.04
    b = params.error_budget(0.1)
    assert b["total"] == pytest.approx(b["smoothing"] + b["window"] + b["estimate"])


def test_workload_orders_chain_without_gaps(spark):
    from pyspark.sql import Window

    df = spark.range(50).select(F.col("id"), (F.col("id") * 7 % 50).alias("t")).where("t not between 20 and 29")
    got = wl.next_in_order(df, [F.col("t")], F.expr("t div 5"), ["id"])
    want = df.withColumn("n", F.lead("id").over(Window.orderBy("t"))).where("n is not null")
    assert {(r.id, r.next_id) for r in got.collect()} == {(r.id, r.n) for r in want.collect()}


def test_edges_by_their_place_against_a_window(spark):
    x = spark.createDataFrame([(a,) for a in range(8)], "a int")
    kinds = lambda reach: [r[0] for r in x.orderBy("a").select(windows.classify_against_window([F.col("a"), F.lit(1)], [F.lit(0), F.lit(0)], 3, reach)).collect()]
    assert kinds(0) == ["inner"] * 3 + ["borderline"] + ["outer"] * 4
    assert kinds(1) == ["inner"] * 3 + ["borderline"] * 2 + ["outer"] * 3


def test_scale_report_counts_the_stream(spark):
    e = graph(spark, n=40, m=400)
    r = diagnostics.scale_report(e, 2, 1.0, (0.25, 1.0)).orderBy("share").collect()
    n = len({x for row in e.collect() for x in (row["u"], row["v"])})
    assert (r[1]["m"], r[1]["n"], r[1]["exact_rows"]) == (e.count(), n, n + 2 * e.count())
    assert 0 < r[0]["m"] < r[1]["m"] and r[1]["sketch_rows"] > 0


def test_good_events_hold_without_sampling(spark):
    p = params.practical_params(400, k_star=20, p0=1.0)
    got = {r["event"]: r for r in diagnostics.event_frequencies(graph(spark, n=40, m=400), p, range(2)).collect()}
    assert got["edge_count"]["frequency"] == got["vertex_count"]["frequency"] == 1.0 and got["edge_count"]["runs"] == 2


def test_a_bias_on_a_threshold_is_in_the_class_it_opens(spark):
    """Each vertex with d_out of deg edges out: the rule's probability is that of the class told in integers."""
    sel, pairs, want = oblivious.uniform_clamped(21), [], {}
    for hub, (d_out, deg) in enumerate((o, d) for d in (3, 6, 7, 12, 14, 21, 42) for o in range(d + 1)):
        want[hub] = sel.r[min(21, d_out * 21 // deg + 1) - 1]
        pairs += [(hub, 1000 + k) for k in range(d_out)] + [(1000 + k, hub) for k in range(deg - d_out)]
    got = {r["vid"]: r["p"] for r in oblivious.vertex_chances(wl.from_pairs(spark, pairs), sel).where("vid < 1000").collect()}
    assert got == want
    floats = {r["vid"]: sel.r[r["i"] - 1] for r in vertex_stats.biases(wl.from_pairs(spark, pairs)).where("vid < 1000").select("vid", classes.class_index(F.col("bias"), sel.t).alias("i")).collect()}
    assert floats != want  # what the cut went by before


def test_overlap_with_a_benchmark_is_exact_and_linear_in_a_text(spark, tmp_path):
    """Pairs as by brute force, null and short texts and empty words included; a text of 200,000 words takes seconds."""
    import time

    r = random.Random(3)
    words = lambda n: " ".join(r.choice(["a", ""]) for _ in range(n))
    long = " ".join(str(k) for k in range(200_000))
    docs = [(k, words(r.randrange(40))) for k in range(60)] + [(60, None), (61, long)]
    items = [(k, words(r.randrange(30))) for k in range(20)] + [(20, None), (21, " ".join(str(k) for k in range(150_000, 150_008))), (22, "1 2 3 4 5 6 7 9")]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    grams = lambda t: {" ".join(w[i : i + 8]) for w in [(t or "").split(" ")] for i in range(len(w) - 7)} if t is not None else set()
    g = {k: grams(t) for k, t in docs}
    want = {(2 * d, 2 * i + 1) for i, t in items for d in g if g[d] & grams(t) and 2 * d != 2 * i + 1}
    begin = time.time()
    got = [(x["u"], x["v"]) for x in wl.bench_overlap(spark, str(tmp_path)).collect()]
    assert time.time() - begin < 60
    assert len(got) == len(set(got)) and set(got) == want and (122, 43) in want and len(want) > 20


def test_certificates_of_the_classes_a_graph_has():
    """Fewer classes, no smaller ratio; all classes, the same; two outer classes, a cut that the rule finds."""
    sel = oblivious.uniform_clamped(9)
    every = oblivious.certify_ratio(sel)
    assert oblivious.certify_ratio(sel, present=list(range(1, 10))) == every
    some = oblivious.certify_ratio(sel, present=[2, 5, 8])
    assert every["lower"] - 1e-6 <= some["lower"] <= some["primal"] + 1e-6
    assert oblivious.certify_ratio(sel, present=[1, 9])["lower"] > 0.9


def test_moved_queries_read_the_events(spark, tmp_path):
    """Window sizes, component optima and certificates follow the given events: a chain of types for each user."""
    from biascut.plans import queries as plans

    rows = [(k, f"2024-01-01 00:00:{k:02d}", k % 2, "abcab"[k // 2], 0.0, '{"k": %d}' % (k % 3)) for k in range(10)]
    spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string").selectExpr("event_id", "cast(ts as timestamp) ts", "user_id", "event_type", "value", "props").write.parquet(f"{tmp_path}/events.parquet")
    got = plans.QUERIES["exact_val_components"](spark, str(tmp_path)).first()
    assert (got["cut"], got["m"]) == (4.0, 8.0)  # two users, each a>b b>c c>a a>b: a alone gives 2
    n = wl.user_item(spark, str(tmp_path)).selectExpr("explode(array(u, v)) as x").distinct().count()
    assert sum(r["n"] for r in plans.QUERIES["window_sizes"](spark, str(tmp_path)).collect()) == n
    assert all(r["classes"] >= 1 and r["lower"] <= r["lower_here"] + 1e-4 for r in plans.QUERIES["ratio_certificates"](spark, str(tmp_path)).collect())


def test_rates_keep_no_sketch(spark):
    from biascut.plans import queries as plans

    kept = lambda: spark.sparkContext._jsc.getPersistentRDDs().size()
    before = kept()
    assert plans.QUERIES["experiment_rates"](spark, "/root/testdata/sf0.001").count() == 4
    assert kept() == before
