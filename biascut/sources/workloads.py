"""Workload graphs on the shared tables, and synthetic graphs with known optima.

Vertex ids of different kinds are tagged apart (2x and 2x + 1; strings by 60 bits of their md5).
Every edge id is a key that is unique over its table.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators.edges import cut_as_dicut, edge_stream, string_id


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def even(c: str | Column) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("long") * 2


def odd(c: str | Column) -> Column:
    return even(c) + 1


_LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]


def _line_key() -> list[Column]:
    return [*(F.col(c) for c in _LINE_KEY), F.round(F.col("l_extendedprice") * 100).cast("long"), F.datediff(F.to_date("l_shipdate"), F.lit("1970-01-01").cast("date")), F.round(F.col("l_discount") * 100).cast("long"), F.round(F.col("l_tax") * 100).cast("long"), F.col("l_quantity").cast("long")]


def next_in_order(df: DataFrame, order: list[Column], chunk: Column, keep: list[str]) -> DataFrame:
    """Adds next_<c> for the row that follows in the order, without one global sort: rows follow each
    other within a chunk (a coarse prefix of the order), and each chunk's last row meets the first
    row of the next chunk through a table of chunks."""
    x = df.withColumn("_chunk", chunk)
    w = W.partitionBy("_chunk").orderBy(*order)
    nxt = F.struct(*(F.col(c) for c in keep))
    x = x.withColumn("_next", F.lead(nxt).over(w)).withColumn("_rank", F.row_number().over(w))
    firsts = x.where("_rank = 1").select("_chunk", nxt.alias("_first"))
    firsts = firsts.select("_chunk", F.lead("_first").over(W.orderBy("_chunk")).alias("_follow"))  # a row a chunk
    x = x.join(firsts, "_chunk").withColumn("_next", F.coalesce("_next", "_follow"))
    return x.select(*df.columns, *(F.col("_next").getField(c).alias(f"next_{c}") for c in keep)).where(F.col("_next").isNotNull())


def goods_flow(spark, d):
    t, back = table(spark, d, "lineitem"), F.col("l_returnflag") == "R"
    return edge_stream(t, F.when(back, odd("l_partkey")).otherwise(even("l_suppkey")), F.when(back, even("l_suppkey")).otherwise(odd("l_partkey")), _line_key())


def ship_bipartite(spark, d):
    return edge_stream(table(spark, d, "lineitem"), even("l_suppkey"), odd("l_partkey"), _line_key())


def _nations(spark, d):
    t = table(spark, d, "lineitem").join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    t = t.join(table(spark, d, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return t.join(table(spark, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))


def nation_trade(spark, d):
    return edge_stream(_nations(spark, d), F.col("s_nationkey"), F.col("c_nationkey"), _line_key())


def region_trade(spark, d):
    n = table(spark, d, "nation").select("n_nationkey", "n_regionkey")
    t = _nations(spark, d).join(F.broadcast(n.withColumnsRenamed({"n_nationkey": "s_nationkey", "n_regionkey": "sr"})), "s_nationkey")  # the 25 nations
    t = t.join(F.broadcast(n.withColumnsRenamed({"n_nationkey": "c_nationkey", "n_regionkey": "cr"})), "c_nationkey")
    return edge_stream(t, F.col("sr"), F.col("cr"), _line_key())


def event_next(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    t = table(spark, d, "events").select("event_id", "event_type", F.lead("event_type").over(w).alias("nxt"))
    return edge_stream(t.where("nxt is not null"), string_id(F.col("event_type")), string_id(F.col("nxt")), [F.col("event_id")])


def user_steps(spark, d):
    """Each user's own graph of steps between types of events: a component or two a user, of as many vertices as
    there are types."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    t = table(spark, d, "events").select("event_id", "user_id", "event_type", F.lead("event_type").over(w).alias("nxt"))
    own = lambda c: string_id(F.concat(F.col("user_id").cast("string"), F.lit(":"), c))
    return edge_stream(t.where("nxt is not null"), own("event_type"), own("nxt"), [F.col("event_id")])


def user_next(spark, d):
    t = table(spark, d, "events").select("event_id", "ts", "user_id")
    t = next_in_order(t, [F.col("ts"), F.col("event_id")], F.to_date("ts"), ["user_id"])
    return edge_stream(t, F.col("user_id"), F.col("next_user_id"), [F.col("event_id")])


def user_item_frame(events: DataFrame) -> DataFrame:
    """(event_id, ts, u, v) of an events table or stream."""
    item = odd(F.get_json_object("props", "$.k").cast("long"))
    buys = F.col("event_type").isin("click", "purchase")
    return events.select("event_id", "ts", F.when(buys, even("user_id")).otherwise(item).alias("u"), F.when(buys, item).otherwise(even("user_id")).alias("v"))


def user_item(spark, d):
    return edge_stream(user_item_frame(table(spark, d, "events")), F.col("u"), F.col("v"), [F.col("event_id")])


def part_pair(spark, d):
    t = table(spark, d, "lineitem")
    a = t.select("l_orderkey", F.col("l_partkey").alias("p1"), F.concat_ws(",", *_line_key()).alias("k1"))
    b = t.select("l_orderkey", F.col("l_partkey").alias("p2"), F.concat_ws(",", *_line_key()).alias("k2"))
    x = a.join(b, "l_orderkey").where("p1 < p2")  # an order's lines are few
    return edge_stream(x, F.col("p1"), F.col("p2"), [F.col("k1"), F.col("k2")])


def customer_star(spark, d):
    return edge_stream(table(spark, d, "customer"), even("c_custkey"), odd("c_nationkey"), [F.col("c_custkey")])


def embed_knn(spark, d, k: int = 8):
    """Each vector to its k nearest by cosine, exactly: tiles of vectors meet every tile, and each
    vector keeps its best k after every tile.  Exact neighbours compare all pairs, whatever the plan;
    this workload is meant for tables where that is wanted."""
    import numpy as np
    import pandas as pd

    t = table(spark, d, "embeddings").where("embedding is not null").select("vec_id", "embedding")
    tiles = max(1, t.count() // 2048)
    t = t.withColumn("tile", F.pmod(F.xxhash64("vec_id"), F.lit(tiles)).cast("int"))
    packed = t.groupBy("tile").agg(F.collect_list(F.struct("vec_id", "embedding")).alias("rows"))
    # every tile asks for every tile by number: tiles^2 rows, dealt by an equi-join
    asks = packed.select(F.col("rows").alias("r1"), F.explode(F.sequence(F.lit(0), F.lit(tiles - 1))).alias("tile"))
    pairs = asks.join(packed.select("tile", F.col("rows").alias("r2")), "tile")

    def best(batches):
        for pdf in batches:
            for r1, r2 in zip(pdf.r1, pdf.r2):
                a, b = (np.array([x["embedding"] for x in r], np.float64) for r in (r1, r2))
                ia, ib = (np.array([x["vec_id"] for x in r]) for r in (r1, r2))
                a, b = (x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300) for x in (a, b))
                s = a @ b.T
                s[ia[:, None] == ib[None, :]] = -np.inf
                order = np.lexsort((np.broadcast_to(ib, s.shape), -s), axis=1)[:, :k]
                for row, (i, o) in enumerate(zip(ia, order)):
                    o = o[np.isfinite(s[row, o])]
                    yield pd.DataFrame({"vec_id": i, "other": ib[o], "sim": s[row, o]})

    near = pairs.select("r1", "r2").mapInPandas(best, "vec_id long, other long, sim double")
    near = near.withColumn("r", F.row_number().over(W.partitionBy("vec_id").orderBy(F.desc("sim"), "other"))).where(F.col("r") <= k)
    return edge_stream(near, F.col("vec_id"), F.col("other"), [F.col("vec_id"), F.col("other")])


def turn_roles(spark, d):
    w = W.partitionBy("conv_id").orderBy("turn")
    t = table(spark, d, "conversations").select("conv_id", "turn", "role", F.lead("role").over(w).alias("nxt")).where("nxt is not null")
    return edge_stream(t, string_id(F.col("role")), string_id(F.col("nxt")), [F.col("conv_id"), F.col("turn")])


def doc_lang(spark, d):
    t = table(spark, d, "documents").select("doc_id", "source", "lang").join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id").where("source is not null and lang is not null")
    good, s, g = F.col("quality") == 1, string_id(F.concat(F.lit("s:"), "source")), string_id(F.concat(F.lit("l:"), "lang"))
    return edge_stream(t, F.when(good, s).otherwise(g), F.when(good, g).otherwise(s), [F.col("doc_id")])


def page_nav(spark, d):
    t = table(spark, d, "pages").select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host"), F.posexplode(F.regexp_extract_all("html", F.lit(r'href="/([^"]*)"'), F.lit(1))).alias("n", "target"))
    return edge_stream(t, string_id(F.concat(F.lit("h:"), "host")), string_id(F.concat(F.lit("t:"), "target")), [F.col("page_id"), F.col("n")])


def _gram_hashes(text: bytes, n: int):
    """64-bit hashes of the runs of n words of a text cut at single blanks.  A run is a stretch of the text, so the
    work is linear in the words: words are hashed once each and n hashes are combined by position."""
    import numpy as np
    from xxhash import xxh64_intdigest

    words = text.split(b" ")
    if len(words) < n:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(xxh64_intdigest, words), np.uint64, len(words))
    with np.errstate(over="ignore"):
        out, factor = np.zeros(len(words) - n + 1, np.uint64), np.uint64(1)
        for k in range(n):
            out += h[k : k + len(out)] * factor
            factor *= np.uint64(0x9E3779B97F4A7C15)  # odd
        out = (out ^ (out >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        return out ^ (out >> np.uint64(29))


def _grams(table: DataFrame, key: str, n: int, filter_bits=None) -> DataFrame:
    """(key, g): the distinct runs of n words of each text, by hash.  With ``filter_bits``, a table of bits, only
    those whose bit is set."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        for b in batches:
            keys, out = [], []
            for i, text in enumerate(b.column(1)):
                g = _gram_hashes(text.as_buffer().to_pybytes() if text.is_valid else b"", n)
                if filter_bits is not None:
                    at = g & np.uint64(8 * len(filter_bits) - 1)
                    g = g[(filter_bits[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 > 0]
                g = np.unique(g)
                keys.append(np.full(len(g), i))
                out.append(g)
            if keys:
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(np.concatenate(keys), pa.int64())), pa.array(np.concatenate(out).view(np.int64))], names=[key, "g"])

    source = table.where("text is not null").select(key, F.col("text").cast("string"))
    return source.mapInArrow(run, f"{key} {source.schema[key].dataType.simpleString()}, g long")


def _gram_filter(grams: DataFrame, bits: int):
    """A table of 2^bits bits, of which those of the grams are set: made in the tasks, united on the driver."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        t = np.zeros(1 << (bits - 3), np.uint8)
        for b in batches:
            at = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64) & np.uint64((1 << bits) - 1)
            np.bitwise_or.at(t, at >> np.uint64(3), (1 << (at & np.uint64(7))).astype(np.uint8))
        yield pa.RecordBatch.from_arrays([pa.array([t.tobytes()], pa.binary())], names=["t"])

    out = np.zeros(1 << (bits - 3), np.uint8)
    for r in grams.select("g").repartition(4).mapInArrow(run, "t binary").toLocalIterator():  # four tables of fixed size
        out |= np.frombuffer(bytes(r["t"]), np.uint8)
    return out


def bench_overlap(spark, d, n: int = 8):
    """Documents and benchmark items sharing a run of n words (split at single blanks).

    Documents' runs are looked up in a bit table of the items' runs first (4 MB, whatever the benchmark's size), so
    only runs that items may share meet them in the join."""
    items = _grams(table(spark, d, "benchmark"), "item_id", n)
    docs = _grams(table(spark, d, "documents"), "doc_id", n, _gram_filter(items, 25))
    pairs = docs.join(items, "g").select("doc_id", "item_id").distinct()
    return edge_stream(pairs, even("doc_id"), odd("item_id"), [F.col("doc_id"), F.col("item_id")])


def order_chain(spark, d):
    t = table(spark, d, "orders").select("o_orderkey", "o_orderdate", "o_custkey")
    t = next_in_order(t, [F.col("o_orderdate"), F.col("o_orderkey")], F.trunc(F.to_date("o_orderdate"), "month"), ["o_custkey"])
    return edge_stream(t, F.col("o_custkey"), F.col("next_o_custkey"), [F.col("o_orderkey")])


def goods_flow_weighted(spark, d):
    """(u, v, weight) of the goods flow by quantity."""
    t, back = table(spark, d, "lineitem"), F.col("l_returnflag") == "R"
    return t.select(F.when(back, odd("l_partkey")).otherwise(even("l_suppkey")).alias("u"), F.when(back, even("l_suppkey")).otherwise(odd("l_partkey")).alias("v"), F.col("l_quantity").cast("long").alias("weight")).where("u <> v")


def part_pair_undirected(spark, d):
    return cut_as_dicut(part_pair(spark, d))


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "goods_flow": goods_flow, "ship_bipartite": ship_bipartite, "nation_trade": nation_trade, "region_trade": region_trade, "event_next": event_next,
    "user_next": user_next, "user_item": user_item, "part_pair": part_pair, "customer_star": customer_star, "embed_knn": embed_knn,
    "turn_roles": turn_roles, "doc_lang": doc_lang, "page_nav": page_nav, "bench_overlap": bench_overlap, "order_chain": order_chain,
}


#: Graphs of single queries.
OTHERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {"user_steps": user_steps}


def workload(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return (WORKLOADS.get(name) or OTHERS[name])(spark, sf_dir)


def ordered(edges: DataFrame, order: str, seed: int = 0) -> tuple[DataFrame, list[str]]:
    """Edges with an order column: arrival (by id), by_tail, by_head, reversed or hash_random."""
    h = F.md5(F.concat_ws(":", "eid", F.lit(f"o{seed}")))
    key = {"arrival": F.col("eid"), "by_tail": F.col("u"), "by_head": F.col("v"), "reversed": F.col("eid"), "hash_random": h}[order]
    if order == "reversed":
        return edges.withColumn("ord", -F.xxhash64("eid").cast("double")), ["ord", "eid"]
    return edges.withColumn("ord", key), ["ord", "eid"]


# synthetic graphs with known optima


def from_pairs(spark: SparkSession, pairs: list[tuple[int, int]]) -> DataFrame:
    return spark.createDataFrame([(str(k), u, v) for k, (u, v) in enumerate(pairs)], "eid string, u long, v long").where("u <> v")


def path(spark, edges: int):
    return spark.range(edges).select(F.col("id").cast("string").alias("eid"), F.col("id").alias("u"), (F.col("id") + 1).alias("v"))


def cycle(spark, n: int):
    return spark.range(n).select(F.col("id").cast("string").alias("eid"), F.col("id").alias("u"), ((F.col("id") + 1) % n).alias("v")).where("u <> v")


def star(spark, leaves: int, out: bool = True):
    hub, leaf = F.lit(0).cast("long"), F.col("id") + 1
    return spark.range(leaves).select(F.col("id").cast("string").alias("eid"), (hub if out else leaf).alias("u"), (leaf if out else hub).alias("v"))


def bipartite(spark, a: int, b: int):
    return spark.range(a * b).select(F.col("id").cast("string").alias("eid"), (F.col("id") % a).alias("u"), (F.expr(f"id div {a}") + a).alias("v"))


def complete(spark, n: int):
    return spark.range(n * n).select(F.col("id").cast("string").alias("eid"), (F.col("id") % n).alias("u"), F.expr(f"id div {n}").alias("v")).where("u <> v")


def disjoint(parts: list[DataFrame], gap: int = 1 << 32) -> DataFrame:
    out = None
    for k, e in enumerate(parts):
        e = e.select(F.concat(F.lit(f"{k}:"), "eid").alias("eid"), (F.col("u") + k * gap).alias("u"), (F.col("v") + k * gap).alias("v"))
        out = e if out is None else out.unionByName(e)
    return out


def planted(spark, n: int, m: int, share: float, seed: int = 0):
    """m hashed edges over n vertices, of which about ``share`` lead from odd to even ones."""
    h = lambda tag: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(tag)), F.lit(1 << 30))
    ahead = h(3) < int(share * (1 << 30))
    half = n // 2
    u = F.when(ahead, h(1) % half * 2 + 1).otherwise(h(1) % n)
    v = F.when(ahead, h(2) % half * 2).otherwise(h(2) % n)
    return spark.range(m).select(F.col("id").cast("string").alias("eid"), u.alias("u"), v.alias("v")).where("u <> v")
