"""The layered sketch as one distributed fold over the edges.

Every edge makes one digest for the coins of four layers, and hashes its ends only for layers whose
coin falls; only edges one of whose ends is tracked leave the scan stage.  Several guesses share the
coins and hashes of a layer, and differ by thresholds from a table of guesses x layers rows.  Everything
after works on those samples.  All choices are functions of edge and vertex ids, so partial sketches of any split
of the stream merge to the same sketch.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .hashing import DIGEST_WORDS, PRIME, coefficients, digest, digest_word, edge_word, hex_threshold, poly4
from .params import Params

_TABLE = "guess int, layer int, q double, threshold long, c0 long, c1 long, c2 long, c3 long"


@dataclass
class Sketch:
    """meta (guess, m), vertices (guess, layer, vid), edges (guess, layer, eid, u, v, keep_u,
    keep_v), overflow (guess, layer, overflow); params by guess."""

    meta: DataFrame
    vertices: DataFrame
    edges: DataFrame
    overflow: DataFrame
    params: dict[int, Params]
    #: while the sample is at hand: its untrimmed edges, and its (guess, layer, vid, d_out, d_in, deg)
    sample: DataFrame | None = None
    stats: DataFrame | None = None
    #: what the sketch keeps in Spark's storage
    held: tuple[DataFrame, ...] = ()
    #: instead of a sample: edges (u, v, coins, n) with a mask of layers (see ``marked``)
    marked: DataFrame | None = None

    def close(self) -> None:
        """Frees what is kept; the sketch can still be read, at the price of making it again."""
        for df in self.held:
            df.unpersist()

    def stored(self) -> int:
        """How many edges the layers store after trimming; counted now."""
        if self.marked is None:
            return self.edges.count()
        from .marked import stored_masks

        return stored_masks(self).agg(F.coalesce(F.sum(F.bit_count("kept")), F.lit(0)).alias("n")).first()["n"]

    @property
    def one(self) -> Params:
        return next(iter(self.params.values()))


def layer_table(spark: SparkSession, params: dict[int, Params]) -> DataFrame:
    return spark.createDataFrame([r for g, p in params.items() for r in p.rows(g)], _TABLE)


def sparse_word(eid, seed: int = 0):
    """The coin by which a guess's sparsifier keeps an edge: the same word for all guesses."""
    return digest_word(F.md5(F.concat_ws(":", eid, F.lit("s"), F.lit(seed))), 0)


def edge_layers(edges: DataFrame, params: dict[int, Params], rates: dict[int, float] | None = None, head: int = 0) -> DataFrame:
    """(guess, layer, eid, u, v, keep_u, keep_v): the sketch of each edge, in one narrow pass.  ``rates``
    are the guesses' sparsifiers: the share of the stream that each guess's sketch sees.  With ``rates``,
    the first ``head`` edges of every task come along whole, as guess -1 and layer 0."""
    p = next(iter(params.values()))
    if p.mode == "nested":
        return _nested_layers(edges, params)
    if len({(x.seed, x.coin, x.store) for x in params.values()}) > 1:
        raise ValueError("guesses share their seed, coin and store")
    layers = sorted({a for x in params.values() for a in x.layers})
    most = [max(x.q(a) for x in params.values() if a in x.layers) for a in layers]
    by_place = lambda values: F.element_at(F.array(*(F.lit(v) for v in values)), F.greatest("n", F.lit(1)))  # noqa: E731  (a constant array)
    c = [coefficients(p.seed, a) for a in layers]
    tossed = sum(q >= 1 for q in most)  # layers from this place on toss coins: rates fall with the layer
    digits = F.lit(b"")
    if p.coin == "md5" and tossed < len(layers):
        blocks = sorted({(a - 1) // DIGEST_WORDS for a in layers[tossed:]})
        digits = F.concat(*(digest(F.col("eid"), b, p.seed) for b in blocks)).cast("binary")  # cut by byte, not by character
        places = [8 * DIGEST_WORDS * (blocks.index((a - 1) // DIGEST_WORDS)) + 8 * ((a - 1) % DIGEST_WORDS) + 1 if k >= tossed else 1 for k, a in enumerate(layers)]
        word = F.substring(F.col("_d"), by_place(places), F.lit(8))
    else:
        word = F.lower(F.lpad(F.hex(F.shiftrightunsigned(F.xxhash64("eid", by_place(layers), F.lit(p.seed)), 32)), 8, "0")).cast("binary")
    more = [] if rates is None else ["_s"]
    x = edges.select("eid", "u", "v", digits.alias("_d"), *([] if rates is None else [sparse_word(F.col("eid"), p.seed).alias("_s")]))
    begin = F.when(F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1) < head, 0).otherwise(1) if rates and head else F.lit(1)
    x = x.select("*", begin.alias("_n")).select("*", F.explode(F.sequence(F.col("_n"), F.lit(len(layers)))).alias("n"))
    low = by_place([(b"g" if q >= 1 else hex_threshold(q).encode()) for q in most])  # "g" follows all hex digits
    x = x.select("eid", "u", "v", *more, "n", F.when(F.col("n") > tossed, word).otherwise(F.lit(b"")).alias("w")).where(F.col("w") < low)
    h = lambda end: poly4(F.col(end), *(by_place([r[j] for r in c]) for j in range(4)))
    layer = F.when(F.col("n") > 0, by_place(layers)).otherwise(0)
    x = x.select(layer.alias("layer"), "eid", "u", "v", *more, "w", "n", h("u").alias("hu"), h("v").alias("hv"))
    if len(params) == 1 and rates is None:
        x = x.select(F.lit(next(iter(params))).alias("guess"), "layer", "eid", "u", "v", *((F.col(f"h{e}") < by_place([p.threshold(a) for a in layers])).alias(f"keep_{e}") for e in "uv"))
    else:
        rate = rates or {}
        rows = [(g, a, "g" if q.q(a) >= 1 else hex_threshold(q.q(a)), q.threshold(a), "g" if rate.get(g, 1.0) >= 1 else hex_threshold(rate[g])) for g, q in params.items() for a in q.layers]
        rows += [(-1, 0, "g", PRIME, "g")]
        table = edges.sparkSession.createDataFrame(rows, "guess int, layer int, below string, threshold long, sparse string")
        x = x.join(F.broadcast(table), "layer").where("w < cast(below as binary)" + (" and _s < sparse" if rates else ""))  # guesses x layers rows
        x = x.select("guess", "layer", "eid", "u", "v", (F.col("hu") < F.col("threshold")).alias("keep_u"), (F.col("hv") < F.col("threshold")).alias("keep_v"))
    return x.where((F.col("keep_u") & F.col("keep_v")) if p.store == "induced" else (F.col("keep_u") | F.col("keep_v")))


def _nested_layers(edges: DataFrame, params: dict[int, Params]) -> DataFrame:
    """Shared coins: one word of the edge gives its top layer, one hash of a vertex its first."""
    out = None
    for g, p in params.items():
        word = edge_word(F.col("eid"), F.concat_ws(":", F.lit("n"), F.lit(p.seed)), p.coin)
        rows = p.rows(g)
        c = rows[0][4:]
        firsts = {r[3]: r[1] for r in reversed(rows)}
        if p.single_layer:
            raise ValueError("a single layer has nothing to nest")
        # rates halve with each layer past k_star, so the coin's leading zeros name the last layer it falls in
        zeros = F.when(F.col("word") == 0, 32).otherwise(32 - F.length(F.bin("word")))
        top = F.lit(p.k) if p.force_q1 else F.least(F.lit(p.k), p.k_star + zeros)

        def first(h):
            at = F.lit(p.k + 1)
            for threshold, layer in sorted(firsts.items(), reverse=True):  # few differ: they double up to one
                at = F.when(F.col(h) < F.lit(threshold), F.lit(layer)).otherwise(at)
            return at

        # each word and hash is made once; a vertex tracked by no layer needs no coin
        x = edges.select("eid", "u", "v", poly4(F.col("u"), *c).alias("hu"), poly4(F.col("v"), *c).alias("hv"))
        x = x.where(F.least("hu", "hv") < max(r[3] for r in rows)).select("*", word.alias("word"))
        x = x.select("eid", "u", "v", top.alias("top"), first("hu").alias("fu"), first("hv").alias("fv"))
        least = F.greatest("fu", "fv") if p.store == "induced" else F.least("fu", "fv")
        x = x.where(F.col("top") >= least)  # stored once; layers unfold only for the sample
        x = x.select("eid", "u", "v", "fu", "fv", F.explode(F.sequence(least, F.col("top"))).alias("layer"))
        x = x.select(F.lit(g).alias("guess"), "layer", "eid", "u", "v", (F.col("fu") <= F.col("layer")).alias("keep_u"), (F.col("fv") <= F.col("layer")).alias("keep_v"))
        out = x if out is None else out.unionByName(x)
    return out


def _ends(rows: DataFrame) -> DataFrame:
    """One row for each tracked end of a stored edge: guess, layer, vid, out, eid, u, v, keeps."""
    end = lambda vid, keep, out: F.struct(F.col(vid).alias("vid"), F.col(keep).alias("keep"), F.lit(out).alias("out"))
    x = rows.select("*", F.explode(F.array(end("u", "keep_u", 1), end("v", "keep_v", 0))).alias("e"))
    return x.where("e.keep").select("guess", "layer", F.col("e.vid").alias("vid"), F.col("e.out").alias("out"), "eid", "u", "v", "keep_u", "keep_v")


def sampled_stats(rows: DataFrame) -> DataFrame:
    """(guess, layer, vid, d_out, d_in, deg) of the tracked vertices; partial sums before the shuffle."""
    d = _ends(rows).groupBy("guess", "layer", "vid").agg(F.sum("out").alias("d_out"), F.count(F.lit(1)).alias("deg"))
    return d.select("guess", "layer", "vid", "d_out", (F.col("deg") - F.col("d_out")).alias("d_in"), "deg")


def overflow_layers(vertices: DataFrame, params: dict[int, Params]) -> DataFrame:
    """(guess, layer, n, overflow) for layers with a vertex."""
    cap = F.create_map(*(x for g, p in params.items() for x in (F.lit(g), F.lit(min(p.v_cap, (1 << 62))))))
    n = vertices.groupBy("guess", "layer").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("overflow", F.col("n") > F.element_at(cap, F.col("guess")))


def trim(rows: DataFrame, stats: DataFrame, params: dict[int, Params]) -> DataFrame:
    """Keeps an edge iff it is among the first e_cap, by a hash of its id, of one of its tracked ends.

    A vertex below the cap keeps all its layer's edges, and stored degrees reach the cap exactly when
    sampled ones do.  So only edges all of whose tracked ends are over the cap are ranked, and the
    rank limit is applied in each map task first: no hub meets one reducer.
    """
    p = next(iter(params.values()))
    cap = F.element_at(F.create_map(*(x for g, q in params.items() for x in (F.lit(g), F.lit(int(q.e_cap))))), F.col("guess"))
    heavy = stats.where(F.col("deg") > cap).select("guess", "layer", "vid")
    at = lambda end: heavy.select("guess", "layer", F.col("vid").alias(end), F.lit(True).alias(f"heavy_{end}"))
    x = rows.join(at("u"), ["guess", "layer", "u"], "left").join(at("v"), ["guess", "layer", "v"], "left")
    free = lambda end: F.col(f"keep_{end}") & F.col(f"heavy_{end}").isNull()
    names = ["guess", "layer", "eid", "u", "v", "keep_u", "keep_v"]
    light = x.where(free("u") | free("v")).select(names)
    # every edge of a heavy vertex has a rank with it, kept or not for other reasons
    word = edge_word(F.col("eid"), F.concat_ws(":", F.lit("t"), F.lit(p.seed)), p.coin)
    by = W.partitionBy("guess", "layer", "vid").orderBy("word", "eid")
    most = max(min(q.e_cap, (1 << 31) - 2) for q in params.values())
    bound = x.where("heavy_u or heavy_v").select(*names, (free("u") | free("v")).alias("free"))
    ends = bound.select("*", F.explode(F.array(F.struct(F.col("u").alias("vid"), F.col("keep_u").alias("keep")), F.struct(F.col("v").alias("vid"), F.col("keep_v").alias("keep")))).alias("e")).where("e.keep")
    ranked = ends.select(*names, "free", F.col("e.vid").alias("vid"), word.alias("word")).withColumn("rank", F.row_number().over(by)).where((F.col("rank") <= most) & ~F.col("free"))
    return light.unionByName(ranked.select(names).distinct())


def build_sketch(edges: DataFrame, params: Params | dict[int, Params], m: DataFrame | None = None) -> Sketch:
    """The sketch of all edges, in one scan.  Layers over the vertex cap are emptied and flagged.

    The sampled rows are made at once and kept (in memory or on disk, recomputed if lost) until
    ``close``; the same scan counts the stream, unless ``m`` is given.  Edges that carry their coins
    (``marked.keep``) are sampled from where they are kept, without a row a layer.
    """
    params = params if isinstance(params, dict) else {0: params}
    if "coins" in edges.columns:
        from .marked import marked_sketch

        (p,) = params.values()
        return marked_sketch(edges, p, m if m is not None else edges.agg(F.sum("n").alias("m")))
    if m is not None:
        return _finish(edge_layers(edges, params).persist(), m, params)
    seen = Observation()
    rows = edge_layers(edges.observe(seen, F.count(F.lit(1)).alias("m")), params).persist()
    rows.count()
    return _finish(rows, edges.sparkSession.createDataFrame([(seen.get["m"],)], "m long"), params)


def _finish(rows: DataFrame, m: DataFrame, params: dict[int, Params]) -> Sketch:
    held = (rows, sampled_stats(rows).persist())
    over = overflow_layers(held[1], params)
    lost = F.broadcast(over.where("overflow").select("guess", "layer"))  # guesses x layers rows at most
    rows, stats = (x.join(lost, ["guess", "layer"], "left_anti") for x in held)
    return Sketch(m, stats.select("guess", "layer", "vid"), trim(rows, stats, params), over, params, rows, stats, held)


def combine(one: Sketch, two: Sketch) -> Sketch:
    """Merges sketches of two parts of a stream: counters add, samples unite, caps apply again; a
    layer lost in either is lost."""
    m = one.meta.unionByName(two.meta).agg(F.sum("m").alias("m"))
    s = _finish(one.edges.unionByName(two.edges), m, one.params)
    lost = F.broadcast(one.overflow.where("overflow").select("guess", "layer").union(two.overflow.where("overflow").select("guess", "layer")).distinct())  # guesses x layers rows at most
    flags = s.overflow.unionByName(lost.withColumn("n", F.lit(0).cast("long")).withColumn("overflow", F.lit(True))).groupBy("guess", "layer").agg(F.max("n").alias("n"), F.max("overflow").alias("overflow"))
    return Sketch(s.meta, s.vertices.join(lost, ["guess", "layer"], "left_anti"), s.edges.join(lost, ["guess", "layer"], "left_anti"), flags, one.params)


def compact(s: Sketch) -> DataFrame:
    """One row a guess: m and an array of layers, each with its flag, vertices and edges (for stores
    that keep whole sketches; sizes are bounded by the caps)."""
    vs = s.vertices.groupBy("guess", "layer").agg(F.collect_list("vid").alias("vs"))
    es = s.edges.groupBy("guess", "layer").agg(F.collect_list(F.struct("eid", "u", "v", "keep_u", "keep_v")).alias("es"))
    x = s.overflow.join(vs, ["guess", "layer"], "left").join(es, ["guess", "layer"], "left")
    return x.groupBy("guess").agg(F.collect_list(F.struct("layer", "overflow", "vs", "es")).alias("layers")).join(F.broadcast(s.meta))  # one row


def save(s: Sketch, path: str) -> None:
    for name in ("meta", "vertices", "edges", "overflow"):
        df = getattr(s, name)
        (df.write.partitionBy("guess", "layer") if name == "edges" else df.write).mode("overwrite").parquet(f"{path}/{name}")


def load(spark: SparkSession, path: str, params: dict[int, Params]) -> Sketch:
    t = {n: spark.read.parquet(f"{path}/{n}") for n in ("meta", "vertices", "overflow")}
    e = spark.read.schema("eid string, u long, v long, keep_u boolean, keep_v boolean, guess int, layer int").parquet(f"{path}/edges")
    return Sketch(t["meta"], t["vertices"], e.select("guess", "layer", "eid", "u", "v", "keep_u", "keep_v"), t["overflow"], params)


assert PRIME < 1 << 31
