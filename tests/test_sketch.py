"""The layered sketch: invariants, merging, theory mode, unbiased counts, streams, SQL surface."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from biascut.functions import register as reg
from biascut.operators import baselines, estimator, exact, guess, hashing, layered, marked, oblivious, snapshot, temporal, windows
from biascut.operators.params import Params, practical_params, theory_params
from biascut.plans import queries
from biascut.sources import io
from biascut.sources import workloads as wl
from biascut.streaming import sketches as st

SMALL = Params(8, 9, 1, 3, 0.5, 2**6 + 1, 10**6)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def e(spark):
    return wl.planted(spark, 60, 3000, 0.4).unionByName(wl.star(spark, 200).select(F.concat(F.lit("s"), "eid").alias("eid"), (F.col("u") + 1000).alias("u"), (F.col("v") + 1000).alias("v"))).persist()


def test_hash_expression_equals_integers(spark):
    c = hashing.coefficients(3, 5)
    got = spark.createDataFrame([(v,) for v in (0, 1, 17, 2**31 - 1, 2**40 + 3)], "v long").select("v", hashing.poly4(F.col("v"), *c).alias("h")).collect()
    assert all(r.h == hashing.poly4_int(r.v, c) for r in got)
    assert hashing.coefficients(3, 5, shared=True) == hashing.coefficients(3, 1, shared=True) != c


def test_sampling_rates(spark, e):
    p = SMALL
    n = {r.layer: r.n for r in layered.edge_layers(e, {0: p.replace(force_p1=True)}).groupBy("layer").agg(F.count("*").alias("n")).collect()}
    m = e.count()
    for a in p.layers:
        want = m * p.q(a)
        assert abs(n.get(a, 0) - want) <= 5 * np.sqrt(want) + 1
    assert [p.q(a) for a in (1, 3, 4, 8)] == [1, 1, 0.5, 2.0**-5] and p.p(8) == 1.0


@pytest.mark.parametrize("cap", [65, 12])
def test_trim_invariants(e, cap):
    p = SMALL.replace(e_cap=cap)
    sampled = layered._ends(layered.edge_layers(e, {0: p}))
    full = {(r.layer, r.vid): r.n for r in sampled.groupBy("layer", "vid").agg(F.count("*").alias("n")).collect()}
    s = layered.build_sketch(e, p)
    stored = {(r.layer, r.vid): r.n for r in layered._ends(s.edges).groupBy("layer", "vid").agg(F.count("*").alias("n")).collect()}
    for key, n in full.items():
        assert stored[key] == n if n < cap else stored[key] >= cap
    assert set(stored) == set(full) == {(r.layer, r.vid) for r in s.vertices.collect()}


def test_merging_any_split_gives_the_same_sketch(e):
    p = SMALL.replace(e_cap=12, v_cap=40)
    whole = layered.build_sketch(e, p)
    parts = [layered.build_sketch(e.where(F.pmod(F.xxhash64("eid"), F.lit(3)) == k), p) for k in range(3)]
    merged = layered.combine(layered.combine(parts[0], parts[1]), parts[2])
    over = {r.layer for r in whole.overflow.where("overflow").collect()}
    assert over and over == {r.layer for r in merged.overflow.where("overflow").collect()}
    assert merged.meta.first()["m"] == whole.meta.first()["m"] == e.count()
    assert rows(merged.vertices) == rows(whole.vertices)
    cols = ["guess", "layer", "eid"]
    assert rows(merged.edges.select(*cols)) == rows(whole.edges.select(*cols))
    assert estimator.estimate_value(whole, oblivious.uniform_clamped(9)).first()["value"] is None


@pytest.mark.parametrize("mode", ["independent", "nested"])
def test_theory_mode_is_exact_smoothing(spark, e, mode):
    p, t = theory_params(300, 3200, 0.5)
    p = p.replace(mode=mode)
    assert all(p.q(a) == 1 == p.p(a) for a in p.layers) and p.ell == len(t) - 1
    s = layered.build_sketch(e, p)
    a, m = snapshot.refined_snapshot(e, p.ell, p.k), snapshot.snapshot(e, p.ell)
    assert windows.l1(estimator.estimate_array(s), windows.smooth_array(a, p.w, p.k, p.ell)).first()["l1"] < 1e-9
    assert windows.smoothed_error(estimator.estimate_matrix(s), m, p.w, p.ell).first()["l1"] < 1e-9
    assert windows.pointwise_violation(estimator.estimate_array(s), a, p.w, p.k, p.ell).first()["worst"] < 1e-9
    v = estimator.estimate_value(s, oblivious.uniform_clamped(p.ell)).first()
    want = oblivious.oblivious_value(windows.smooth_matrix(m, p.w, p.ell), oblivious.uniform_clamped(p.ell)).first()["value"] - p.eps / 4
    assert v["value"] == pytest.approx(want) and v["mass"] == pytest.approx(1)


def test_matrix_shortcut_equals_projected_array(e):
    s = layered.build_sketch(e, SMALL)
    assert windows.l1(estimator.estimate_matrix(s), snapshot.project(estimator.estimate_array(s))).first()["l1"] < 1e-9


def test_mean_of_seeds_is_near_the_target(spark):
    e = wl.planted(spark, 200, 4000, 0.3)
    p = practical_params(4000, k_star=5, p0=0.6, w=2, ell=9)
    sel = oblivious.uniform_clamped(9)
    target = oblivious.smoothed_value(snapshot.snapshot(e, 9), sel, 2).first()["value"]
    got = [estimator.estimate_value(layered.build_sketch(e, p.replace(seed=s)), sel).first()["value"] for s in range(4)]
    assert abs(np.mean(got) - target) < 0.08


def test_star_needs_rising_rates(spark):
    e = wl.star(spark, 4000)
    p = practical_params(4000, k_star=4, p0=0.05, ell=9, e_cap=1 << 20)
    hub = lambda p: layered.build_sketch(e, p).vertices.where("vid = 0").select("layer").distinct().count()
    assert hub(p) >= 6 > hub(p.replace(rising=False))
    assert p.p(p.k) == 1.0


def test_guesses_and_small_graphs(spark, e):
    s = guess.sketch_all_guesses(e, 64, power=2.2, ell=9, k_star=3, p0=0.5, w=1)
    one = guess.guess_of(s, e.count())
    t = next(iter(one.params))
    assert guess.GROWTH**t <= e.count() < guess.GROWTH ** (t + 1)
    direct = layered.build_sketch(e, s.params[t])
    assert rows(one.edges.select("layer", "eid")) == rows(direct.edges.select("layer", "eid"))
    tiny = wl.path(spark, 3)
    assert guess.small_graph_exact(tiny, 5).first()["value"] == pytest.approx(2 / 3)
    assert guess.small_graph_exact(e, 5) is None
    v = guess.estimate_maxdicut(e, eps=0.5, n=300, sel=oblivious.coin_selection()).first()
    assert v["value"] == pytest.approx(0.25 - 0.125) and not v["overflow"]


def test_save_load_and_compact(spark, e, tmp_path):
    s = layered.build_sketch(e, SMALL)
    layered.save(s, str(tmp_path / "s"))
    back = layered.load(spark, str(tmp_path / "s"), s.params)
    assert rows(back.edges.select("layer", "eid", "keep_u")) == rows(s.edges.select("layer", "eid", "keep_u")) and rows(back.vertices) == rows(s.vertices)
    c = layered.compact(s).first()
    assert c["m"] == e.count() and sum(len(x.es or []) for x in c["layers"]) == s.edges.count()


def test_streams_give_the_batch_sketch(spark, tmp_path):
    r = random.Random(2)
    data = [(k, r.randrange(40), r.randrange(40)) for k in range(900)]
    df = spark.createDataFrame(data, "id long, src long, dst long").withColumn("ts", F.timestamp_seconds(F.lit(1_704_067_200) + F.col("id") * 600))
    for k in range(3):
        df.where(F.pmod("id", F.lit(3)) == k).coalesce(1).write.parquet(str(tmp_path / "in" / f"part{k}"))
    files = str(tmp_path / "in" / "*")
    stream = lambda: io.stream_edges(spark, files, "id long, src long, dst long, ts timestamp", "src", "dst", ["id"])
    batch = df.select(F.col("id").cast("string").alias("eid"), F.col("src").alias("u"), F.col("dst").alias("v"), "ts").where("u <> v")
    for _ in range(2):  # a second run finds nothing new
        st.stream_sketch(stream(), SMALL, str(tmp_path / "sk"), str(tmp_path / "ck")).awaitTermination()
    live, whole = st.read_sketch(spark, str(tmp_path / "sk"), SMALL), layered.build_sketch(batch, SMALL)
    assert live.meta.first()["m"] == batch.count() and rows(live.edges) == rows(whole.edges)
    q = st.sampled_stream(stream(), SMALL).writeStream.format("memory").queryName("sampled").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    assert rows(spark.table("sampled").select("layer", "eid")) == rows(layered.edge_layers(batch, {0: SMALL}).select("layer", "eid"))
    q = st.keyed_degrees(st.sampled_stream(stream(), SMALL), 65).writeStream.format("memory").queryName("keyed").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.table("keyed").groupBy("layer", "vid").agg(F.max("deg").alias("deg"), F.max("d_out").alias("d_out"))
    want = layered._ends(layered.edge_layers(batch, {0: SMALL})).groupBy("layer", "vid").agg(F.count("*").alias("deg"), F.sum("out").alias("d_out"))
    assert rows(last) == rows(want)


def test_stream_windows_equal_batch_windows(spark, tmp_path):
    df = spark.range(600).select(F.col("id"), (F.col("id") % 7).alias("src"), (F.col("id") % 5 + 10).alias("dst"), F.timestamp_seconds(F.lit(1_704_067_200) + F.col("id") * 600).alias("ts"))
    df.where("id < 300").coalesce(1).write.parquet(str(tmp_path / "in" / "a"))
    df.where("id >= 300").coalesce(1).write.parquet(str(tmp_path / "in" / "b"))
    stream = io.stream_edges(spark, str(tmp_path / "in" / "*"), "id long, src long, dst long, ts timestamp", "src", "dst", ["id"])
    st.windowed_bias(spark, stream, str(tmp_path / "out"), str(tmp_path / "ck")).awaitTermination()
    live = {r.start: (r.n, r.m, r.net) for r in st.net_of_windows(spark, str(tmp_path / "out")).collect()}
    batch = df.select(F.col("id").cast("string").alias("eid"), F.col("src").alias("u"), F.col("dst").alias("v"), "ts")
    want = {r.start: (r.n, r.m, r.net) for r in temporal.tumbling_bias(batch).collect()}
    assert live and all(want[k] == v for k, v in live.items()) and len(want) - len(live) <= 1  # the last window is open
    q = st.deduplicated(stream.union(stream)).select("eid").writeStream.format("memory").queryName("dedup").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("dedup").count() == 600


def test_as_of_and_sources(spark, tmp_path):
    facts = spark.createDataFrame([(1, 10, 0.5), (1, 20, 0.7)], "vid long, ts long, b double")
    e = spark.createDataFrame([("a", 1, 2, 5), ("b", 1, 2, 10), ("c", 1, 2, 25)], "eid string, u long, v long, ts long")
    assert {r.eid: r.as_of for r in temporal.as_of(e, facts, "u", "b").collect()} == {"a": None, "b": 0.5, "c": 0.7}
    pairs = spark.createDataFrame([(0, 1), (1, 2), (2, 2)], "src long, dst long")
    for f in ("parquet", "csv", "json"):
        io.write_table(pairs, str(tmp_path / f), f)
        got = io.read_edges(spark, str(tmp_path / f), f)
        assert rows(got.select("u", "v")) == [(0, 1), (1, 2)] and got.select("eid").distinct().count() == 2
    (tmp_path / "pairs.txt").write_text("# c\n0 1\n1\t2\n")
    assert rows(io.read_edges(spark, str(tmp_path / "pairs.txt"), "text").select("u", "v")) == [(0, 1), (1, 2)]


def test_sql_surface(spark, e):
    reg.register(spark)
    e.createOrReplaceTempView("some_edges")
    assert rows(spark.sql(reg.snapshot_sql("some_edges", 9)).select("i", "j", "weight")) == rows(snapshot.snapshot_counts(e, 9).select("i", "j", "weight"))
    sel = oblivious.uniform_clamped(9)
    snapshot.snapshot(e, 9).createOrReplaceTempView("some_cells")
    v = oblivious.oblivious_value(snapshot.snapshot(e, 9), sel).first()["value"]
    assert spark.sql(reg.value_sql("some_cells", list(sel.r))).first()["value"] == pytest.approx(v)
    agg = reg.oblivious_value_agg(list(sel.r))
    assert spark.table("some_cells").agg(agg("i", "j", "x").alias("value")).first()["value"] == pytest.approx(v)
    cells = spark.sql("SELECT * FROM window_cells(1, 9, 2, 9)").collect()
    assert len(cells) == 9 and sum(c.nu for c in cells) > 0
    assert spark.sql("SELECT count(*) AS n FROM layers(8, 3, 0.5D)").first()["n"] == 8
    c = hashing.coefficients(0, 1)
    x = spark.range(20).selectExpr(f"poly4_sql(id, {c[0]}, {c[1]}, {c[2]}, {c[3]}) = poly4_check(id, {c[0]}L, {c[1]}L, {c[2]}L, {c[3]}L) AS ok").collect()
    assert all(r.ok for r in x)
    t = spark.createDataFrame([(1, -1.0, 0.0), (2, 0.0, 1.0)], "idx int, lo double, hi double")
    got = reg.interval_index(spark.createDataFrame([(-1.0,), (0.0,), (1.0,)], "x double"), t)
    assert sorted((r.x, r.idx) for r in got.collect()) == [(-1.0, 1), (0.0, 2), (1.0, 2)]


def test_plan_has_one_scan_and_no_python(spark, tmp_path):
    from biascut.operators.diagnostics import plan_report

    wl.planted(spark, 50, 500, 0.5).write.parquet(str(tmp_path / "e"))
    p = plan_report(layered.edge_layers(spark.read.parquet(str(tmp_path / "e")), {0: SMALL}))
    assert p["scans"] == 1 and p["exchanges"] == 0 and p["python"] == 0


def test_entry_point_imports_and_names_match(spark):
    import __spark_entry__ as entry

    q, s = entry.queries(), entry.oracle_sql()
    assert set(s) <= set(q) and len(q) > 200
    assert exact.random_cut_expectation() == 0.25


def test_one_pass_serves_every_guess_and_short_streams_exactly(spark, tmp_path):
    from biascut.operators.diagnostics import plan_report

    r = random.Random(5)
    rows = [(str(k), r.randrange(30), 30 + r.randrange(30)) for k in range(3000)]
    spark.createDataFrame(rows, "eid string, u long, v long").repartition(3).write.parquet(str(tmp_path / "e"))
    e = spark.read.parquet(str(tmp_path / "e"))
    p = guess.one_pass(e, 60, 0.2, lambda m: SMALL, power=2.0)
    assert p.m == 3000 and p.buffer is None and p.guess == 12
    rates = {t: guess.sparsify_rate(60, g, 0.2) for t, g in p.grid}
    assert rates[p.grid[-1][0]] < 1 and all(abs(p.kept[t] - 3000 * rates[t]) <= 5 * (3000 * rates[t]) ** 0.5 for t in rates)
    kept = {x.eid for x in guess.sparsify(e, rates[p.guess]).collect()}
    own = {x.eid for x in p.rows.where(f"guess = {p.guess}").collect()}
    assert own <= kept and len(kept) == p.kept[p.guess]
    alone = {(x.layer, x.eid) for x in layered.edge_layers(e.where(e.eid.isin(list(kept))), {0: SMALL}).collect()}
    assert alone == {(x.layer, x.eid) for x in p.rows.where(f"guess = {p.guess}").collect()}
    p.rows.unpersist()
    assert plan_report(layered.edge_layers(e, {t: SMALL for t in rates}, rates, head=7))["scans"] == 1
    short = spark.createDataFrame([("a", 1, 2), ("b", 2, 3), ("c", 3, 1)], "eid string, u long, v long")
    got = guess.estimate_unknown(short, 100, 0.2).first()
    assert got.exact and got.m == 3 and abs(got.value - 1 / 3) < 1e-12
    assert guess.estimate_unknown(short.where("false"), 100, 0.2).first().value == 0.0


def test_the_best_rule_is_certified(spark):
    for sel, least in ((oblivious.clamped_linear(), 0.483), (oblivious.uniform_clamped(9), 0.444), (oblivious.coin_selection(), 0.25)):
        got = oblivious.certify_ratio(sel)
        assert least <= got["lower"] <= got["dual"] + 1e-6
    # no small graph is worse than the certificate: all digraphs on three vertices with up to two parallel edges
    sel = oblivious.clamped_linear()
    pairs = [(a, b) for a in range(3) for b in range(3) if a != b]
    worst = 1.0
    for weights in itertools.product(range(3), repeat=6):
        m = sum(weights)
        if not m:
            continue
        deg, out = [0] * 3, [0] * 3
        for (a, b), w in zip(pairs, weights):
            deg[a] += w
            deg[b] += w
            out[a] += w
        side = []
        for v in range(3):
            bias = (2 * out[v] - deg[v]) / deg[v] if deg[v] else 0.0
            side.append(sel.r[next(i for i in range(sel.ell - 1, -1, -1) if bias >= sel.t[i])])
        value = sum(w * side[a] * (1 - side[b]) for (a, b), w in zip(pairs, weights))
        best = max(sum(w for (a, b), w in zip(pairs, weights) if x >> a & 1 and not x >> b & 1) for x in range(8))
        worst = min(worst, value / best)
    assert worst >= 0.483


@pytest.mark.parametrize("p", [SMALL, SMALL.replace(p0=0.2, e_cap=12 + 2**6), SMALL.replace(coin="xxhash64"), SMALL.replace(mode="nested"), SMALL.replace(v_cap=60)])
def test_marked_edges_give_the_sketch_matrix(spark, e, p):
    m = spark.createDataFrame([(e.count(),)], "m long")
    one = marked.with_coins(e, p).withColumn("n", F.lit(1).cast("long"))
    merged = one.groupBy("u", "v", "coins").agg(F.count("*").alias("n"))
    s = layered.build_sketch(e, p)
    near = lambda df: {(r["i"], r["j"]): pytest.approx(r["x"], rel=1e-9) for r in df.collect()}
    want = near(estimator.estimate_matrix(s))
    flags = rows(s.overflow.select("layer", "n", "overflow"))
    s.close()
    for x in (one, merged):
        k = marked.marked_sketch(x, p, m)
        assert near(estimator.estimate_matrix(k)) == want and rows(k.overflow.select("layer", "n", "overflow")) == flags
        k.close()


def test_compared_methods_keep_no_sketch(spark, e):
    kept = lambda: spark.sparkContext._jsc.getPersistentRDDs().size()
    e.count()
    before = kept()
    got = {r["method"]: r for r in baselines.compare_methods(e, "x", ["layered", "layered_nested", "layered_normalised", "best_of"]).collect()}
    assert kept() == before  # three sketches stayed in storage
    p, sel = practical_params(e.count(), ell=21), oblivious.uniform_clamped(21)
    for name, mode, norm in (("layered", "independent", False), ("layered_nested", "nested", False), ("layered_normalised", "independent", True)):
        want = estimator.estimate_of(e, p.replace(mode=mode), sel, norm).first()
        assert got[name]["value"] == pytest.approx(want["value"]) and got[name]["mass"] == pytest.approx(want["mass"])
    assert got["best_of"]["value"] == pytest.approx(baselines.best_lower_bound(e).first()["value"])


def test_theory_error_keeps_an_edge_once(spark, monkeypatch):
    e = wl.complete(spark, 6).unionByName(wl.star(spark, 40).select(F.concat(F.lit("s"), "eid").alias("eid"), (F.col("u") + 10).alias("u"), (F.col("v") + 10).alias("v")))
    monkeypatch.setattr(layered, "edge_layers", lambda *a, **k: pytest.fail("an edge is stored for every layer"))
    m, p, error = queries.theory_error(e)
    assert m == 70 and p.k_star >= p.k and error < 1e-9


@pytest.mark.parametrize("p, few", [(SMALL, 0), (SMALL.replace(e_cap=5), 0), (SMALL.replace(e_cap=5), marked.FEW), (SMALL.replace(e_cap=5, v_cap=100), 0), (SMALL.replace(e_cap=5, coin="xxhash64"), 0), (SMALL.replace(mode="nested", e_cap=5), 0)])
def test_kept_edges_store_what_trimming_leaves(spark, e, p, few, monkeypatch):
    monkeypatch.setattr(marked, "FEW", few)
    s = layered.build_sketch(e, p)
    want = s.stored()
    assert want == s.edges.count()
    kept, m = marked.keep(e, {"one": p, "two": p.replace(k_star=p.k_star + 1)})
    k = layered.build_sketch(kept.select("u", "v", "word", "n", F.col("one").alias("coins")), p, m)
    near = lambda df: {(r["i"], r["j"]): pytest.approx(r["x"], rel=1e-9) for r in df.collect()}
    assert k.stored() == want and near(estimator.estimate_matrix(k)) == near(estimator.estimate_matrix(s))
    for x in (s, k):
        x.close()
    kept.unpersist()


def test_last_words_do_without_their_bound(spark, e, monkeypatch):
    p = SMALL.replace(e_cap=5)
    s = layered.build_sketch(e, p)
    kept, m = marked.keep(e, {"coins": p})
    k = layered.build_sketch(kept, p, m)
    heavy = k.stats.where("deg > 5").select("layer", "vid", "deg")
    both = [rows(marked._last_words(k, heavy, heavy.count(), spread)) for spread in (-2.0, 8.0)]  # nothing lies below the first bound
    assert both[0] == both[1] and k.stored() == s.edges.count()
    for x in (s, k):
        x.close()
    kept.unpersist()


def test_rates_keep_an_edge_once(spark, monkeypatch):
    monkeypatch.setattr(layered, "edge_layers", lambda *a, **k: pytest.fail("an edge is stored for every layer"))
    got = queries.QUERIES["experiment_rates"](spark, "/root/testdata/sf0.001").collect()
    assert [(r["k_star"], r["p0"]) for r in got] == [(3, 0.05), (6, 0.1), (6, 0.25), (8, 0.25)] and all(r["stored"] > 0 for r in got)
