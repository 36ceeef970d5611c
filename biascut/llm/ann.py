"""Approximate nearest neighbours by inner product: NN-descent graph and greedy graph search.

Equal vectors are one node, so a vector that a third of all rows share is one node with members.
Vectors are lifted by one coordinate to equal length (so that near in angle means near in space).  Their
components are quantised to bytes, each row by its own largest, for everything but the final scores;
the lift is kept as a float beside them, as what it lacks to 1, so that short vectors lose nothing.

Graph.  Random hyperplanes through pairs of sampled vectors give each node a code a tree; nodes in
code order are cut into blocks of equal size (balanced whatever the data) whose best pairs start the
graph.  Then NN-descent: each node sends its vector to its neighbours and to those that list it, and
everyone introduces its visitors to each other, which are the joins of neighbours of neighbours; a
node keeps its ``degree`` best.  Rounds end when few lists change, or
when the lists of sampled nodes gain next to none of their true neighbours.  Reverse lists keep their
``degree`` best (a graph parameter; hubs lose in-links only, never their row).

Search.  A query starts from its own node's list and from the best of the ``ENTRIES`` longest vectors
(large products are with long vectors, which a short vector's list need not lead to), and expands its
``width`` best unexpanded nodes a round through the joined adjacency lists; the ``pool`` best are scored
exactly in double precision.  How many rounds there are is decided by measurement: a fixed number of
sampled queries is answered by an exact scan of all rows as well, and the search goes on until it finds
``recall`` of their true neighbours, or a round gains next to nothing, so the work follows what the table
needs and not a constant.  ``exact_nearest`` is the exact way for all queries, and the one taken where
the measured recall stays below ``LEAST``.

Defined cases: vectors that are null, zero, of another dimension than most, or hold null or
non-finite components take no part; of rows repeating a vec_id one counts; ties go to the smaller
vec_id; an empty table gives an empty result; products beyond the range of doubles are infinite, and
one that is no number ranks last.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import drop, hashed_head, materialize, tidy

TREES, BITS, BLOCK, STARTS = 12, 28, 256, 12
DEGREE, ROUNDS, OFFERS = 28, 8, 8
WIDTH, HOPS, POOL = 64, 40, 64
ENTRIES = 512
#: Sampled queries, and the share of their true neighbours at which the search ends.
MEASURED, RECALL = 128, 0.985
#: Below this measured recall the answer comes from the exact way.
LEAST = 0.9


def usable(rows: DataFrame, vec_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(vec_id, v array<double>) of the rows that take part, one a vec_id."""
    v = F.transform(F.col(vector), lambda x: x.cast("double"))
    df = rows.where(F.col(vec_id).isNotNull() & F.col(vector).isNotNull()).select(F.col(vec_id).cast("long").alias("vec_id"), v.alias("v"))
    df = df.where((F.size("v") > 0) & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0))
    common = df.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if common is None:
        return df
    return df.where(F.size("v") == common["d"]).groupBy("vec_id").agg(F.min("v").alias("v"))


def _shortfall(v: np.ndarray) -> np.ndarray:
    """What the lift of vectors of length at most 1 lacks to 1."""
    square = (v * v).sum(axis=1)
    return (square / (1 + np.sqrt(np.maximum(1 - square, 0)))).astype("<f4")


def _near(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Products of lifted vectors, less 1: exact for short ones too, whose products are all near 1."""
    return x @ x.T - c[:, None] - c[None, :] + c[:, None] * c[None, :]


def _matrix(column, d: int) -> np.ndarray:
    """A list column of equally long vectors as rows."""
    return column.flatten().to_numpy().reshape(-1, d)


def _bytes_matrix(column, d: int, kind) -> np.ndarray:
    """Equally long byte strings as rows, read in place from the column's buffer."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    if not n:
        return np.zeros((0, d), kind)
    wide = np.int64 if pa.types.is_large_binary(column.type) else np.int32
    off = np.frombuffer(column.buffers()[1], wide, n + 1, column.offset * wide().itemsize)
    return np.frombuffer(column.buffers()[2], np.uint8)[off[0] : off[-1]].view(kind).reshape(-1, d)


def _cut(batches, rows: int):
    """Batches of at most ``rows`` rows: bounds what one step unpacks."""
    for b in batches:
        for i in range(0, b.num_rows, rows):
            yield b.slice(i, rows)


def _quantised(v: np.ndarray) -> tuple[list[bytes], np.ndarray]:
    """Components as bytes, followed by the lift's shortfall as a float, and the components' scale."""
    scale = np.maximum(np.abs(v).max(axis=1) / 127, np.finfo(np.float32).tiny)
    q = np.rint(v / scale[:, None]).astype(np.int8)
    return [r.tobytes() for r in np.concatenate([q, _shortfall(v)[:, None].view(np.int8)], axis=1)], scale.astype(np.float32)


def _opened(q: np.ndarray, s: np.ndarray, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Components and shortfalls from rows of d + 4 bytes and their scales."""
    return q[:, :d] * s[:, None].astype(np.float32), np.ascontiguousarray(q[:, d:]).view("<f4")[:, 0]


def _best(ids: np.ndarray, sims: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best distinct ids, best first."""
    order = np.lexsort((ids, -sims))
    ids, sims = ids[order], sims[order]
    _, once = np.unique(ids, return_index=True)
    once.sort()
    return ids[once[:k]], sims[once[:k]]


def _groups(batches, rows: int):
    """Batches sorted by their first column, regrouped so that no group is cut."""
    held = None
    for b in batches:
        if not b.num_rows:
            continue
        t = pa.Table.from_batches([b])
        held = t if held is None else pa.concat_tables([held, t])
        if held.num_rows < rows:
            continue
        key = held.column(0).to_numpy()
        cut = int(np.searchsorted(key, key[-1]))
        if cut:
            yield held.slice(0, cut).combine_chunks()
            held = held.slice(cut)
    if held is not None and held.num_rows:
        yield held.combine_chunks()


def _lists(schema_ids, schema_sims):
    return pa.array([x.astype("<i8").tobytes() for x in schema_ids], pa.binary()), pa.array([x.astype("<f4").tobytes() for x in schema_sims], pa.binary())


def nodes_of(distinct: DataFrame, d: int, peak: float, longest: float) -> DataFrame:
    """(id, q, s): vectors as bytes with their lift and their scale.  ``peak`` is the largest component,
    ``longest`` the largest length once all are divided by it (so that no square overflows)."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            q, s = _quantised(_matrix(b.column(1), d) / peak / longest)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(q, pa.binary()), pa.array(s, pa.float32())], names=["id", "q", "s"])

    return distinct.select("id", "v").mapInArrow(run, "id long, q binary, s float")


def start_lists(nodes: DataFrame, d: int, trees: int = TREES, block: int = BLOCK, starts: int = STARTS, seed: int = 9) -> DataFrame:
    """(id, ids, sims) a tree: each node's best ``starts`` of its block."""

    def lifted(q, scale):
        x, c = _opened(q, scale, d)
        return np.concatenate([x, 1 - c[:, None]], axis=1)

    sample = hashed_head(nodes, 512, "id").collect()  # fixed size
    pts = lifted(np.stack([np.frombuffer(r["q"], np.int8) for r in sample]), np.array([r["s"] for r in sample], np.float32))
    rng = np.random.default_rng(seed)
    a, b = pts[rng.integers(0, len(pts), trees * BITS)], pts[rng.integers(0, len(pts), trees * BITS)]
    normal = np.where((a == b).all(axis=1)[:, None], rng.normal(size=a.shape), a - b).astype(np.float32)
    offset = (normal * (a + b) / 2).sum(axis=1)
    weights = 1 << np.arange(BITS - 1, -1, -1, dtype=np.int64)

    def codes(batches):
        for c in _cut(batches, 2000):
            x = lifted(_bytes_matrix(c.column(1), d + 4, np.int8), c.column(2).to_numpy())
            side = (x @ normal.T > offset).reshape(len(x), trees, BITS)
            code = side.astype(np.int64) @ weights
            for t in range(trees):
                yield pa.RecordBatch.from_arrays([pa.array((np.int64(t) << BITS) + code[:, t]), *c.columns], names=["code", "id", "q", "s"])

    def blocks(batches):
        rest = []

        def solve(code, ids, q, s):
            x, c = _opened(np.frombuffer(b"".join(q), np.int8).reshape(-1, d + 4), np.array(s, np.float32), d)
            tree, ids = np.array(code) >> BITS, np.array(ids, np.int64)
            out_id, out_n, out_s = [], [], []
            edges = [0, *(np.flatnonzero(np.diff(tree)) + 1), len(ids)]
            for lo, hi in zip(edges, edges[1:]):
                parts = max(1, round((hi - lo) / block))
                for part in np.array_split(np.arange(lo, hi), parts):
                    sim = _near(x[part], c[part])
                    np.fill_diagonal(sim, -np.inf)
                    k = min(starts, len(part) - 1)
                    if k <= 0:
                        continue
                    top = np.argpartition(-sim, k - 1, axis=1)[:, :k]
                    out_id += ids[part].tolist()
                    out_n += list(ids[part][top])
                    out_s += list(np.take_along_axis(sim, top, axis=1))
            return pa.RecordBatch.from_arrays([pa.array(out_id, pa.int64()), *_lists(out_n, out_s)], names=["id", "ids", "sims"])

        for c in batches:
            rest.append(c)
            n = sum(r.num_rows for r in rest)
            if n >= 16 * block:
                yield solve(*([v for r in rest for v in r.column(k).to_pylist()] for k in range(4)))
                rest = []
        if rest:
            yield solve(*([v for r in rest for v in r.column(k).to_pylist()] for k in range(4)))

    coded = nodes.mapInArrow(codes, "code long, id long, q binary, s float")
    return coded.repartitionByRange("code").sortWithinPartitions("code", "id").mapInArrow(blocks, "id long, ids binary, sims binary")


def merge_lists(lists: DataFrame, degree: int) -> DataFrame:
    """The best ``degree`` of all lists of a node: (id, ids, sims, changed)."""
    gathered = lists.groupBy("id").agg(F.collect_list("ids").alias("ids"), F.collect_list("sims").alias("sims"))  # a few lists a node

    def run(batches):
        for b in _cut(batches, 1000):
            ids, sims = [], []
            for n, s in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                n, s = _best(np.frombuffer(b"".join(n), "<i8"), np.frombuffer(b"".join(s), "<f4"), degree)
                ids.append(n)
                sims.append(s)
            yield pa.RecordBatch.from_arrays([b.column(0), *_lists(ids, sims)], names=["id", "ids", "sims"])

    return gathered.mapInArrow(run, "id long, ids binary, sims binary")


def both_ways(graph: DataFrame, degree: int) -> DataFrame:
    """(id, back): for each node the ``degree`` nearest nodes that list it."""

    def run(batches):
        for b in batches:
            n = [np.frombuffer(x, "<i8") for x in b.column(1).to_pylist()]
            s = [np.frombuffer(x, "<f4") for x in b.column(2).to_pylist()]
            if n:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(n)), pa.array(np.repeat(b.column(0).to_numpy(), [len(x) for x in n])), pa.array(np.concatenate(s))], names=["id", "src", "sim"])

    edges = graph.select("id", "ids", "sims").mapInArrow(run, "id long, src long, sim float")
    near = edges.withColumn("r", F.row_number().over(W.partitionBy("id").orderBy(F.desc("sim"), "src"))).where(F.col("r") <= degree)
    return near.groupBy("id").agg(F.collect_list("src").alias("back"))


def _visits(graph: DataFrame, nodes: DataFrame, degree: int) -> DataFrame:
    """(u, id, q, s, least): every node's vector sent along its links in both directions, with the
    similarity an offer must exceed."""
    joined = graph.join(nodes, "id").join(both_ways(graph, degree), "id", "left").select("id", "q", "s", "ids", "sims", "back")

    def run(batches):
        for b in _cut(batches, 1000):
            ids, q, s = b.column(0).to_numpy(), b.column(1), b.column(2).to_numpy()
            to, src, least = [], [], []
            for k, (n, sims, back) in enumerate(zip(b.column(3).to_pylist(), b.column(4).to_pylist(), b.column(5).to_pylist())):
                out = np.union1d(np.frombuffer(n, "<i8"), np.array(back or [], np.int64))
                to.append(out)
                src.append(np.full(len(out), k))
                least.append(np.frombuffer(sims, "<f4")[-1] if len(n) >= 8 * degree else -np.inf)
            if to:
                src = np.concatenate(src)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(to)), pa.array(ids[src]), q.take(pa.array(src)), pa.array(s[src]), pa.array(np.array(least, np.float32)[src])], names=["u", "id", "q", "s", "least"])

    return joined.mapInArrow(run, "u long, id long, q binary, s float, least float")


def descend(graph: DataFrame, nodes: DataFrame, d: int, degree: int = DEGREE, offers: int = OFFERS) -> DataFrame:
    """One NN-descent round: (id, ids, sims) offers from the introductions at every node."""
    visits = _visits(graph, nodes, degree).repartition("u").sortWithinPartitions("u")

    def run(batches):
        for t in _groups(batches, 20_000):
            u, ids = t.column(0).to_numpy(), t.column(1).to_numpy()
            x, c = _opened(_bytes_matrix(t.column(2), d + 4, np.int8), t.column(3).to_numpy(), d)
            least = t.column(4).to_numpy()
            edges = np.concatenate([np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]])), [len(u)]])
            who, out_n, out_s = [], [], []
            for lo, hi in zip(edges, edges[1:]):
                if hi - lo < 2:
                    continue
                own = ids[lo:hi]
                sim = _near(x[lo:hi], c[lo:hi])
                np.fill_diagonal(sim, -np.inf)
                k = min(offers, hi - lo - 1)
                top = np.argpartition(-sim, k - 1, axis=1)[:, :k]
                val = np.take_along_axis(sim, top, axis=1)
                good = val > least[lo:hi, None]
                for r in np.flatnonzero(good.any(axis=1)):
                    who.append(own[r])
                    out_n.append(own[top[r][good[r]]])
                    out_s.append(val[r][good[r]])
            yield pa.RecordBatch.from_arrays([pa.array(who, pa.int64()), *_lists(out_n, out_s)], names=["id", "ids", "sims"])

    return visits.mapInArrow(run, "id long, ids binary, sims binary")


def build_graph(nodes: DataFrame, d: int, degree: int = DEGREE, rounds: int = ROUNDS, settled: float = 0.1, watch=None) -> DataFrame:
    """The neighbour graph (id, ids, sims) of ``nodes`` (a table).  ``watch`` is called with the graph of
    the blocks alone and after each round, and may end the rounds."""
    graph = materialize(merge_lists(start_lists(nodes, d), degree), "graph")
    if watch:
        watch(graph)
    for _ in range(rounds):
        better = materialize(merge_lists(graph.unionByName(descend(graph, nodes, d, degree)), degree), "graph")
        changed = graph.join(better.select("id", F.col("ids").alias("now")), "id").agg(F.avg(F.when(F.col("ids") != F.col("now"), 1.0).otherwise(0.0))).first()[0]
        drop(graph)
        graph = better
        if (watch and watch(graph)) or changed is None or changed < settled:
            break
    return graph


def adjacency(graph: DataFrame, nodes: DataFrame, degree: int = DEGREE) -> DataFrame:
    """(u, links array of (id, q, s)): each node and its links in both directions with their vectors."""
    v = _visits(graph, nodes, degree).select("u", "id", "q", "s").unionByName(nodes.select(F.col("id").alias("u"), "id", "q", "s"))
    return v.groupBy("u").agg(F.collect_list(F.struct("id", "q", "s")).alias("links"))  # 2 * degree a node


def search(queries: DataFrame, graph: DataFrame, links: DataFrame, entries: list, d: int, width: int = WIDTH, hops: int = HOPS, pool: int = POOL, enough=None) -> DataFrame:
    """Greedy search from each query's own node and from ``entries``, rows of nodes.  queries:
    (id, q, s), nodes themselves.  Returns (id, q, s, ids, sims, done): the best found, and all that were
    expanded.  ``enough``, asked after each round with its table, ends the search."""
    beam = 6 * width
    entry_ids = np.array([r["id"] for r in entries], np.int64)
    entry_x = _opened(np.stack([np.frombuffer(r["q"], np.int8) for r in entries]), np.array([r["s"] for r in entries]), d)[0]

    def begin(batches):
        for b in _cut(batches, 2000):
            x = _opened(_bytes_matrix(b.column(1), d + 4, np.int8), b.column(2).to_numpy(), d)[0]
            ids, sims = [], []
            for own, n, row in zip(b.column(0).to_pylist(), b.column(3).to_pylist(), x @ entry_x.T):
                # the list's similarities are lifted: it is expanded first, which gives its products
                n = np.frombuffer(n, "<i8")
                free = np.flatnonzero((entry_ids != own) & ~np.isin(entry_ids, n))
                free = free[np.argsort(-row[free], kind="stable")][:width]
                ids.append(np.concatenate([n, entry_ids[free]]))
                sims.append(np.concatenate([np.full(len(n), -3.0), row[free]]))
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(3)), *_lists(ids, sims), pa.array([b""] * b.num_rows, pa.binary())], names=["id", "q", "s", "ids", "sims", "done"])

    state = queries.join(graph, "id").select("id", "q", "s", "ids").mapInArrow(begin, "id long, q binary, s float, ids binary, sims binary, done binary")
    state = materialize(state, "search")
    for _ in range(hops):

        def frontier(batches):
            for b in batches:
                who, to = [], []
                for k, (n, done) in enumerate(zip(b.column(3).to_pylist(), b.column(5).to_pylist())):
                    n = np.frombuffer(n, "<i8")
                    new = n[~np.isin(n, np.frombuffer(done, "<i8"))][:width]
                    who.append(np.full(len(new), k))
                    to.append(new)
                if who:
                    k = np.concatenate(who)
                    ids, sims = b.column(0).to_numpy(), [np.frombuffer(x, "<f4") for x in b.column(4).to_pylist()]
                    least = np.array([x[beam - 1] if len(x) >= beam else -2.0 for x in sims], np.float32)
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(to)), pa.array(ids[k]), b.column(1).take(pa.array(k)), b.column(2).take(pa.array(k)), pa.array(least[k])], names=["u", "id", "q", "s", "least"])

        def expand(batches):
            for b in _cut(batches, 512):
                links_ = b.column(5)
                size = np.diff(links_.offsets.to_numpy())
                items = links_.flatten()
                x = _opened(_bytes_matrix(items.field(1), d + 4, np.int8), items.field(2).to_numpy(), d)[0]
                v = items.field(0).to_numpy()
                me = _opened(_bytes_matrix(b.column(2), d + 4, np.int8), b.column(3).to_numpy(), d)[0]
                owner = np.repeat(np.arange(b.num_rows), size)
                sim = np.einsum("ij,ij->i", x, me[owner])  # inner product: without the lift
                ids = b.column(1).to_numpy()
                good = (sim > b.column(4).to_numpy()[owner]) & (v != ids[owner])
                first = np.concatenate([[0], np.cumsum(np.bincount(owner[good], minlength=b.num_rows))])
                v, sim = v[good], sim[good]
                some = np.flatnonzero(np.diff(first))
                yield pa.RecordBatch.from_arrays([pa.array(ids[some]), *_lists([v[first[k] : first[k + 1]] for k in some], [sim[first[k] : first[k + 1]] for k in some]), pa.array([np.array([b.column(0)[int(k)].as_py()], "<i8").tobytes() for k in some], pa.binary())], names=["id", "ids", "sims", "done"])

        found = state.mapInArrow(frontier, "u long, id long, q binary, s float, least float").join(links, "u").select("u", "id", "q", "s", "least", "links").mapInArrow(expand, "id long, ids binary, sims binary, done binary")
        gathered = state.select("id", "ids", "sims", "done").unionByName(found).groupBy("id").agg(F.collect_list("ids").alias("n"), F.collect_list("sims").alias("m"), F.collect_list("done").alias("w"))

        def merge(batches):
            for b in _cut(batches, 500):
                ids, sims, done = [], [], []
                for n, m, w in zip(*(b.column(k).to_pylist() for k in (1, 2, 3))):
                    n, m = _best(np.frombuffer(b"".join(n), "<i8"), np.frombuffer(b"".join(m), "<f4"), beam)
                    ids.append(n)
                    sims.append(m)
                    done.append(b"".join(w))
                yield pa.RecordBatch.from_arrays([b.column(0), *_lists(ids, sims), pa.array(done, pa.binary())], names=["id", "ids", "sims", "done"])

        merged = gathered.mapInArrow(merge, "id long, ids binary, sims binary, done binary")
        before, state = state, materialize(state.select("id", "q", "s").join(merged, "id").select("id", "q", "s", "ids", "sims", "done"), "search")
        # a round that expanded nothing leaves its table as it was
        idle = before.agg(F.sum(F.length("done"))).first()[0] == state.agg(F.sum(F.length("done"))).first()[0]
        drop(before)
        if idle or (enough is not None and enough(state)):
            break
    return state


def true_neighbours(members: DataFrame, queries: list, d: int, k: int) -> dict[int, set[int]]:
    """The ``k`` nearest nodes of a few query rows (id, v), by one exact scan."""
    ids, v = np.array([r["id"] for r in queries], np.int64), np.array([r["v"] for r in queries], np.float64)

    def run(batches):
        for b in _cut(batches, 4000):
            own = b.column(0).to_numpy()
            with np.errstate(all="ignore"):
                sim = np.nan_to_num(v @ _matrix(b.column(1), d).T, nan=-np.inf, posinf=np.inf, neginf=-np.inf)
            sim[ids[:, None] == own[None, :]] = -np.inf
            top = np.argpartition(-sim, min(k, len(own)) - 1, axis=1)[:, :k]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, top.shape[1])), pa.array(own[top].ravel()), pa.array(np.take_along_axis(sim, top, axis=1).ravel())], names=["id", "c", "sim"])

    near = members.select("id", "v").mapInArrow(tidy(run), "id long, c long, sim double").where(F.col("sim") > float("-inf"))
    best = near.withColumn("r", F.row_number().over(W.partitionBy("id").orderBy(F.desc("sim"), "c"))).where(F.col("r") <= k)
    out: dict[int, set[int]] = {}
    for r in best.select("id", "c").collect():  # k rows a query
        out.setdefault(r["id"], set()).add(r["c"])
    return out


def measured_recall(lists: DataFrame, truth: dict[int, set[int]], pool: int) -> float:
    """The share of the true neighbours among the first ``pool`` of the queries' lists (id, ids)."""
    picked = lists.where(F.col("id").isin(list(truth))).select("id", "ids").collect()  # MEASURED rows
    hit = sum(len(truth[r["id"]] & set(np.frombuffer(r["ids"], "<i8")[:pool].tolist())) for r in picked)
    return hit / max(1, sum(map(len, truth.values())))


def exact_nearest(rows: DataFrame, queries, k: int = 20, vec_id: str = "vec_id", vector: str = "embedding", block: int = 4096) -> DataFrame:
    """The same columns as ``nearest`` by comparing every query with every row, ``block`` queries at a time:
    exact, and as much work as that."""
    spark, out_schema = rows.sparkSession, "query_id long, rank int, vec_id long, score double"
    every = materialize(usable(rows, vec_id, vector), "vectors")
    first = every.select(F.size("v").alias("d")).first()
    out = spark.createDataFrame([], out_schema)
    if first is None:
        return out
    d, asked, after = first["d"], every.where(queries(F.col("vec_id"))), None
    while True:
        part = (asked if after is None else asked.where(F.col("vec_id") > after)).orderBy("vec_id").limit(block).collect()
        if not part:
            return out
        after, ids, v = part[-1]["vec_id"], np.array([r["vec_id"] for r in part], np.int64), np.array([r["v"] for r in part])

        def run(batches, ids=ids, v=v):
            for b in _cut(batches, 2000):
                own, x = b.column(0).to_numpy(), _matrix(b.column(1), d)
                with np.errstate(all="ignore"):
                    sim = np.nan_to_num(np.stack([np.einsum("ij,j->i", x, q) for q in v]), nan=-np.inf, posinf=np.inf, neginf=-np.inf)
                for q, row in zip(ids, sim):
                    best = np.lexsort((own, -row))[: k + 1]
                    best = best[own[best] != q][:k]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(best), q)), pa.array(own[best]), pa.array(row[best])], names=["query_id", "vec_id", "score"])

        near = every.mapInArrow(tidy(run), "query_id long, vec_id long, score double")
        ranked = near.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")).cast("int")).where(F.col("rank") <= k)
        out = out.unionByName(materialize(ranked.select("query_id", "rank", "vec_id", "score"), "exact"))


def nearest(rows: DataFrame, queries, k: int = 20, vec_id: str = "vec_id", vector: str = "embedding", degree: int = DEGREE, rounds: int = ROUNDS, width: int = WIDTH, hops: int = HOPS, pool: int = POOL, recall: float = RECALL, report: dict | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the ``k`` nearest of every row that the column condition
    ``queries`` on vec_id picks, among all other rows.  ``report`` receives the recall measured on the
    sampled queries: of the graph's own lists by round, and of the search by round."""
    spark = rows.sparkSession
    out_schema = "query_id long, rank int, vec_id long, score double"
    all_rows = materialize(usable(rows, vec_id, vector), "vectors")
    first = all_rows.select(F.size("v").alias("d")).first()
    if first is None:
        return spark.createDataFrame([], out_schema)
    d = first["d"]
    peak = float(all_rows.agg(F.max(F.aggregate("v", F.lit(0.0), lambda a, x: F.greatest(a, F.abs(x))))).first()[0])
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + (x / peak) * (x / peak)))
    longest = float(all_rows.agg(F.max(norm)).first()[0])
    keyed = all_rows.withColumn("h", F.struct(F.xxhash64("v").alias("a"), F.xxhash64(F.lit(11), "v").alias("b")))
    # the k + 1 smallest ids of each distinct vector; its node is named by the first
    members = keyed.withColumn("r", F.row_number().over(W.partitionBy("h").orderBy("vec_id"))).where(F.col("r") <= k + 1)
    members = materialize(members.groupBy("h").agg(F.min("vec_id").alias("id"), F.first("v").alias("v"), F.array_sort(F.collect_list("vec_id")).alias("members")), "members")
    nodes = materialize(nodes_of(members, d, peak, longest), "nodes")
    asked = materialize(keyed.where(queries(F.col("vec_id"))).join(members.select("h", "id"), "h").select("vec_id", "id"), "asked")
    wanted = asked.groupBy("id").agg(F.count(F.lit(1)).alias("n"))
    sampled = members.join(F.broadcast(hashed_head(wanted.select("id"), MEASURED, "id")), "id").select("id", "v").collect()  # fixed size
    truth = true_neighbours(members, sampled, d, k)
    report = {} if report is None else report
    report.update(graph=[], search=[])

    def seen(name: str, lists: DataFrame, first: int, least: float) -> float | None:
        """Notes the recall, and returns it unless the round gained less than ``least``."""
        report[name].append(measured_recall(lists, truth, first))
        gained = len(report[name]) < 2 or report[name][-1] - report[name][-2] >= least
        return report[name][-1] if gained else None

    graph = build_graph(nodes, d, degree, rounds, watch=lambda g: seen("graph", g, degree, 0.015) is None)
    links = materialize(adjacency(graph, nodes, degree), "links")
    entries = nodes_of(members.orderBy(norm.desc(), "id").limit(ENTRIES), d, peak, longest).collect()  # fixed size

    def enough(state: DataFrame) -> bool:
        now = seen("search", state, pool, 0.002)
        return now is None or now >= recall

    found = search(nodes.join(wanted, "id").select("id", "q", "s"), graph, links, entries, d, width, hops, pool, enough)
    if truth and report["search"][-1] < LEAST:  # lengths too far apart for one scale: the exact way
        return exact_nearest(rows, queries, k, vec_id, vector)

    def pairs(batches):
        for b in batches:
            n = [np.append(np.frombuffer(x, "<i8")[:pool], own) for x, own in zip(b.column(1).to_pylist(), b.column(0).to_pylist())]
            if n:
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(b.column(0).to_numpy(), [len(x) for x in n])), pa.array(np.concatenate(n))], names=["id", "c"])

    def exact(batches):
        for b in _cut(batches, 2000):
            if b.num_rows:
                with np.errstate(all="ignore"):
                    score = np.einsum("ij,ij->i", _matrix(b.column(1), d), _matrix(b.column(2), d))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.where(np.isnan(score), -np.inf, score)), b.column(3)], names=["id", "score", "members"])

    lone = nodes.join(wanted, "id").join(graph.select("id"), "id", "left_anti").select("id", F.col("id").alias("c"))  # a single node has no list
    pair = found.select("id", "ids").mapInArrow(pairs, "id long, c long").unionByName(lone)
    scored = pair.join(members.select("id", F.col("v").alias("a")), "id").join(members.select(F.col("id").alias("c"), F.col("v").alias("b"), "members"), "c").select("id", "a", "b", "members").mapInArrow(exact, "id long, score double, members array<bigint>")
    best = scored.groupBy("id").agg(F.collect_list(F.struct((-F.col("score")).alias("m"), "members")).alias("l"))  # pool + 1 a node
    flat = F.flatten(F.transform("l", lambda x: F.transform(x["members"], lambda i: F.struct(x["m"].alias("m"), i.alias("i")))))
    best = materialize(best.select("id", F.slice(F.array_sort(flat), 1, k + 1).alias("best")), "best")
    answer = asked.join(best, "id").select(F.col("vec_id").alias("query_id"), F.posexplode(F.slice(F.filter("best", lambda x: x["i"] != F.col("vec_id")), 1, k)).alias("p", "x"))
    return answer.select("query_id", (F.col("p") + 1).alias("rank"), F.col("x.i").alias("vec_id"), (-F.col("x.m")).alias("score"))
