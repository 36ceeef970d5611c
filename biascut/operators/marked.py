"""The layered sample of a stream whose edges are kept anyway: one row an edge, not one a layer.

An edge keeps its ends and a mask of the layers in whose coins it falls; its id is not needed after the coins.  All layers
that take every edge share one degree a vertex, and which vertices a layer tracks is told on vertices, after degrees
are summed.  Coins, hashes, caps and classes are those of ``build_sketch``, so the estimates are the same.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .hashing import DIGEST_WORDS, PRIME, digest, edge_word, hex_threshold, poly4
from .layered import Sketch, overflow_layers
from .params import Params


def _mask(layers: list[int]) -> int:
    if layers and max(layers) > 62:
        raise ValueError("a mask holds layers up to 62")
    return sum(1 << a for a in layers)


def _split(p: Params) -> tuple[list[int], list[int]]:
    """Layers that take every edge, and those that toss a coin."""
    return [a for a in p.layers if p.q(a) >= 1], [a for a in p.layers if p.q(a) < 1]


def trim_word(p: Params) -> Column:
    """60 bits of an edge by which ``trim`` ranks: the first 32 are its word, the others tell apart edges equal in those."""
    tag = F.concat_ws(":", F.lit("t"), F.lit(p.seed))
    if p.coin == "md5":
        return F.conv(F.substring(F.md5(F.concat_ws(":", F.col("eid"), tag)), 1, 15), 16, 10).cast("long")
    return F.shiftrightunsigned(F.xxhash64(F.col("eid"), tag), 4)


def keep(edges: DataFrame, settings: dict[str, Params]) -> tuple[DataFrame, DataFrame]:
    """(u, v, word, n, a mask for each setting) of every edge, made once and kept until ``unpersist``, and m.  What
    ``build_sketch`` takes of it is a setting's mask as ``coins``.  Settings of one seed share their digests."""
    digests = {n: p for n, p in settings.items() if p.mode != "nested" and p.coin == "md5" and _split(p)[1]}
    first = next(iter(settings.values()))
    if len({(p.seed, p.coin) for p in settings.values()}) > 1:
        raise ValueError("settings share their seed and coin")
    blocks = sorted({(a - 1) // DIGEST_WORDS for p in digests.values() for a in _split(p)[1]})
    x = edges.select("eid", "u", "v", trim_word(first).alias("word"), *(digest(F.col("eid"), b, first.seed).alias(f"_d{b}") for b in blocks))
    for name, p in settings.items():
        x = x.withColumn(name, _digest_mask(p)) if name in digests else with_coins(x, p, name)
    x = x.select("u", "v", "word", F.lit(1).cast("long").alias("n"), *settings).persist()
    return x, edges.sparkSession.createDataFrame([(x.count(),)], "m long")


def _digest_mask(p: Params) -> Column:
    """The mask from digests that stand in columns."""
    whole, tossed = _split(p)
    word = lambda a: F.substring(F.col(f"_d{(a - 1) // DIGEST_WORDS}"), 8 * ((a - 1) % DIGEST_WORDS) + 1, 8)
    bits = [F.when(word(a) < hex_threshold(p.q(a)), F.lit(1 << a)).otherwise(F.lit(0)).cast("long") for a in tossed]
    return reduce(Column.bitwiseOR, bits, F.lit(_mask(whole)).cast("long"))


def with_coins(edges: DataFrame, p: Params, name: str = "coins") -> DataFrame:
    """Adds the mask of layers in whose coins an edge falls; reads ids only if a layer tosses one."""
    whole, tossed = _split(p)
    always = F.lit(_mask(whole)).cast("long")
    if p.mode == "nested" and p.single_layer:
        raise ValueError("a single layer has nothing to nest")
    if not tossed:
        return edges.withColumn(name, always)
    if p.mode == "nested":
        x = edges.withColumn("_w", edge_word(F.col("eid"), F.concat_ws(":", F.lit("n"), F.lit(p.seed)), p.coin))
        zeros = F.when(F.col("_w") == 0, 32).otherwise(32 - F.length(F.bin("_w")))
        tops = [F.when(a - p.k_star <= F.col("_z"), F.lit(1 << a)).otherwise(F.lit(0)).cast("long") for a in tossed]
        return x.withColumn("_z", zeros).withColumn(name, reduce(Column.bitwiseOR, tops, always)).drop("_w", "_z")
    if p.coin == "md5":
        blocks = sorted({(a - 1) // DIGEST_WORDS for a in tossed})
        x = edges.select("*", *(digest(F.col("eid"), b, p.seed).alias(f"_d{b}") for b in blocks))
        return x.select(*(F.col(c) for c in edges.columns), _digest_mask(p).alias(name))
    word = lambda a: F.lower(F.lpad(F.hex(F.shiftrightunsigned(F.xxhash64("eid", F.lit(a), F.lit(p.seed)), 32)), 8, "0"))
    bits = [F.when(word(a) < hex_threshold(p.q(a)), F.lit(1 << a)).otherwise(F.lit(0)).cast("long") for a in tossed]
    return edges.withColumn(name, reduce(Column.bitwiseOR, bits, always))


def _has(coins: Column, layer: Column) -> Column:
    return F.call_function("getbit", coins, layer) == 1


def _vertex_sums(marked: DataFrame, p: Params) -> DataFrame:
    """(g, vid, d_out, deg): degrees in the sample of layer g, untracked vertices included; 0 stands for
    all layers that take every edge."""
    whole, tossed = _split(p)
    groups = ([0] if whole else []) + tossed
    x = marked
    if len(groups) > 1 or tossed:
        x = x.select("u", "v", "coins", "n", F.explode(F.array(*(F.lit(g) for g in groups))).alias("g")).where((F.col("g") == 0) | _has(F.col("coins"), F.col("g")))
    else:
        x = x.withColumn("g", F.lit(0))
    end = lambda vid, out: F.struct(F.col(vid).alias("vid"), out.alias("out"))
    x = x.select("g", "n", F.explode(F.array(end("u", F.col("n")), end("v", F.lit(0).cast("long")))).alias("e"))
    return x.groupBy("g", F.col("e.vid").alias("vid")).agg(F.sum("e.out").alias("d_out"), F.sum("n").alias("deg"))


def _tracked(sums: DataFrame, p: Params) -> DataFrame:
    """(guess, layer, vid, d_out, d_in, deg) of the vertices that each layer tracks."""
    whole, _ = _split(p)
    rows = {r[1]: r for r in p.rows()}
    of = lambda k: F.element_at(F.create_map(*(x for a in p.layers for x in (F.lit(a), F.lit(rows[a][k]).cast("long")))), F.col("layer"))
    layers = F.when(F.col("g") == 0, F.array(*(F.lit(a) for a in whole))).otherwise(F.array("g")) if whole else F.array("g")
    x = sums.select(F.explode(layers).alias("layer"), "vid", "d_out", "deg")
    if min(r[3] for r in rows.values()) < PRIME:
        x = x.where(poly4(F.col("vid"), *(of(k) for k in range(4, 8))) < of(3))
    return x.select(F.lit(0).alias("guess"), "layer", "vid", "d_out", (F.col("deg") - F.col("d_out")).alias("d_in"), "deg")


def marked_sketch(marked: DataFrame, p: Params, m: DataFrame) -> Sketch:
    """A sketch for estimates over (u, v, coins, n), n equal edges a row; its ``edges`` are these rows."""
    if p.store != "incident":
        raise ValueError("only samples of incident edges are marked")
    sums = _vertex_sums(marked, p)
    # the vertices that layers track are fewer than edges; in theory mode all layers track all, and their sums are kept
    if "word" in marked.columns:
        held = stats = _tracked(sums, p).persist()
    else:
        held = sums.persist()
        stats = _tracked(held, p)
    over = overflow_layers(stats, {0: p})
    lost = F.broadcast(over.where("overflow").select("guess", "layer"))  # layers rows at most
    stats = stats.join(lost, ["guess", "layer"], "left_anti")
    return Sketch(m, stats.select("guess", "layer", "vid"), marked, over, {0: p}, None, stats, (held,), marked)


def marked_pairs(s: Sketch, usable: DataFrame, cross: str = "all") -> DataFrame:
    """``layer_pairs`` over marked edges.  A vertex's usable layers and classes travel as a list of numbers;
    where every vertex is tracked few lists differ, and edges are counted by their lists first."""
    p = s.one
    kind = "int" if (p.k + 1) ** 2 * (p.ell + 1) < 1 << 31 else "long"
    code = (((F.col("layer") * (p.k + 1) + F.col("a")).cast("long") * (p.ell + 1)) + F.col("i")).cast(kind)
    lists = usable.groupBy("vid").agg(F.sort_array(F.collect_list(code)).alias("at"))
    if "word" in s.marked.columns:
        lists = lists.persist()  # read for both ends
        s.held += (lists,)
    x = s.marked.select("u", "v", "coins", "n").join(lists.select(F.col("vid").alias("u"), F.col("at").alias("tail")).hint("shuffle_hash"), "u").select("v", "coins", "n", "tail")
    x = x.join(lists.select(F.col("vid").alias("v"), F.col("at").alias("head")).hint("shuffle_hash"), "v").select("coins", "n", "tail", "head")
    if all(p.threshold(a) >= PRIME for a in p.layers):
        x = x.groupBy("coins", "tail", "head").agg(F.sum("n").alias("n"))
    div = lambda c, by: F.call_function("div", F.col(c).cast("long"), F.lit(by).cast("long"))
    x = x.select("coins", "n", "head", F.explode("tail").alias("s")).select("coins", "n", "s", F.explode("head").alias("t"))
    size = (p.k + 1) * (p.ell + 1)
    x = x.select("coins", "n", "s", "t", div("s", size).cast("int").alias("la"), div("t", size).cast("int").alias("lb"))
    x = x.where(_has(F.col("coins"), F.least("la", "lb")))
    if cross == "in_layer":
        x = x.where("la = lb")
    x = x.groupBy("la", "lb", "s", "t").agg(F.sum("n").alias("n"))
    cls = lambda c: (div(c, p.ell + 1) % (p.k + 1)).cast("int")
    return x.select("la", "lb", cls("s").alias("a"), cls("t").alias("b"), (F.col("s") % (p.ell + 1)).cast("int").alias("i"), (F.col("t") % (p.ell + 1)).cast("int").alias("j"), "n")


#: Tables of up to so many vertices are broadcast.
FEW = 1 << 16


def _last_words(s: Sketch, heavy: DataFrame, many: int, spread: float | None = 8.0) -> DataFrame:
    """(layer, vid, last): of vertices over the cap, the word of the last edge they keep.  Words are uniform and degrees
    known, so only those below a bound are ranked; should too few of a vertex lie there, all are."""
    cap = s.one.e_cap
    share = F.lit(1.0) if spread is None else F.least(F.lit((cap + spread * cap**0.5 + 4 * spread) * 1.0) / F.col("deg"), F.lit(1.0))
    at = heavy.groupBy("vid").agg(F.collect_list(F.struct("layer", F.ceil(share * float(1 << 60)).alias("below"))).alias("at"))
    ends = s.marked.select(F.explode(F.array("u", "v")).alias("vid"), "coins", "word").join(F.broadcast(at) if many <= FEW else at, "vid")  # FEW rows
    x = ends.select("vid", "coins", "word", F.explode("at").alias("h")).where(_has(F.col("coins"), F.col("h.layer")) & (F.col("word") < F.col("h.below")))
    by = W.partitionBy("layer", "vid").orderBy("word")
    x = x.select(F.col("h.layer").alias("layer"), "vid", "word").withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= cap)
    last = x.where(F.col("rank") == cap).select("layer", "vid", F.col("word").alias("last")).persist()
    s.held += (last,)
    if spread is not None and last.count() < many:
        return _last_words(s, heavy, many, None)
    return last


def stored_masks(s: Sketch) -> DataFrame:
    """(kept): for every edge the mask of layers that store it after trimming.  A tracked end below the cap keeps all
    its edges, one above it those up to its last word."""
    cap = s.one.e_cap
    bit = F.expr("shiftleft(cast(1 as bigint), layer)")
    heavy = s.stats.where(F.col("deg") > cap).select("layer", "vid", "deg")
    many = heavy.count()
    info = s.stats.groupBy("vid").agg(F.coalesce(F.bit_or(F.when(F.col("deg") <= cap, bit)), F.lit(0).cast("long")).alias("free"))
    word, ranked = [], lambda mask: mask
    if many:
        word, last = ["word"], _last_words(s, heavy, many)
        info = info.join(last.groupBy("vid").agg(F.collect_list(F.struct(bit.alias("bit"), "last")).alias("lasts")), "vid", "left")
        within = lambda acc, x: F.when(x["last"] >= F.col("word"), acc.bitwiseOR(x["bit"])).otherwise(acc)
        ranked = lambda mask: F.when(F.col("lasts").isNull(), mask).otherwise(F.aggregate("lasts", mask, within))
    info = info.persist()  # read for both ends
    s.held += (info,)
    mask = ranked(F.coalesce("free", F.lit(0).cast("long"))).bitwiseAND(F.col("coins"))
    x = s.marked.select("u", "v", "coins", *word)
    x = x.join(info.withColumnRenamed("vid", "u").hint("shuffle_hash"), "u", "left").select("v", "coins", *word, mask.alias("kept"))
    return x.join(info.withColumnRenamed("vid", "v").hint("shuffle_hash"), "v", "left").select(F.col("kept").bitwiseOR(mask).alias("kept"))
