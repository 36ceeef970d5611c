"""Near-duplicate groups by SimHash with a tiled exact comparison.

Fingerprints.  A-Z is lower-cased, words are runs of anything but ASCII white space, and every
shingle of ``width`` words (repeats included) votes with its XXH64 (seed 42) on 64 bits.

Comparison.  Equal fingerprints are one row first, so thousands of exact copies cost nothing.  Two
fingerprints within ``radius`` bits agree on some ``blocks - radius`` of ``blocks`` bit blocks, so
rows meet under every such choice of blocks; the number of blocks follows from the number of
fingerprints by a cost estimate and never loses a pair.  A block bucket is further divided by
population count: a pair within the radius lies in the same or in neighbouring count bands.  All
buckets of a task, small ones too, are one sequence sorted by bucket and population count and cut
into tiles; tiles that share a bucket are compared by exclusive-or and bit counts, many tile pairs at
once, and tile pairs whose counts differ beyond the radius are skipped.  Bands with more than
``TILE_ROWS`` rows are dealt to different tasks by pairs of parts.

Wide fingerprints.  64 bits tell apart little but copies with a changed word.  With ``bits`` of 128 or
more, shingles vote with 128-bit hashes, and rows meet under ``tables`` samples of the bits, as many
as catch all but ``MISS`` of the pairs at the stated similarity; the comparison is the same.

Only a spanning set of links leaves a task (as many as rows, not pairs); components follow from
``components``.

Defined cases: null, empty and word-free texts have fingerprint zero, linked like any other; fewer
words than a shingle vote with the whole sequence; rows repeating a doc_id count as one document
with several texts; rows without doc_id get a fingerprint and component_id null.
"""

from __future__ import annotations

from itertools import combinations
from math import acos, ceil, comb, log, log2, pi

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, slices, text_bytes, tidy
from .components import connected_components

WIDTH, RADIUS, SEED = 4, 4, 42
TILE_ROWS = 8192
_TILE = 64
#: A search for shingle similarity 0.8: that angle flips 39 of 256 bits on average, give or take 6.
WIDE_BITS, WIDE_RADIUS = 256, 46
#: Share of pairs at the stated similarity that no table of a wide search brings together.
MISS = 0.005


def fingerprint_slice(offsets: np.ndarray, raw: np.ndarray, width: int = WIDTH, seed: int = SEED, bits: int = 64) -> np.ndarray:
    """The fingerprint of each text of a byte array, as rows of 64-bit words."""
    import xxhash

    xx, wide = xxhash.xxh64_intdigest, xxhash.xxh3_128_digest
    if bits > 64:
        xx = lambda s, seed: b"".join([wide(s, seed + k) for k in range(bits // 128)])
    blob, n = raw.tobytes().lower(), len(offsets) - 1  # bytes.lower() touches A-Z only
    hashes: list = []
    sizes = np.zeros(n, np.int64)
    for k, (a, b) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist())):
        words = blob[a:b].split()
        if not words:
            continue
        joined = b" ".join(words)
        if len(words) <= width:
            hashes.append(xx(joined, seed))
            sizes[k] = 1
            continue
        ends = np.cumsum([len(w) + 1 for w in words]).tolist()
        starts = [0, *ends[: len(words) - width]]
        hashes += [xx(joined[s : e - 1], seed) for s, e in zip(starts, ends[width - 1 :])]
        sizes[k] = len(words) - width + 1
    out = np.zeros((n, bits // 64), np.uint64)
    some = np.flatnonzero(sizes)
    if not len(some):
        return out
    votes = (np.array(hashes, "<u8").view(np.uint8) if bits == 64 else np.frombuffer(b"".join(hashes), np.uint8)).reshape(-1, bits // 8)
    first = np.concatenate([[0], np.cumsum(sizes[some])])
    for i, j in slices(first, (1 << 22) // bits):
        flags = np.unpackbits(votes[first[i] : first[j]], axis=1, bitorder="little")
        counts = np.add.reduceat(flags, first[i:j] - first[i], axis=0, dtype=np.int32)
        ones = (2 * counts > sizes[some[i:j]][:, None]).astype(np.uint8)
        out[some[i:j]] = np.packbits(ones, axis=1, bitorder="little").view("<u8")
    return out


def fingerprints(docs: DataFrame, width: int = WIDTH, keep: list[str] | None = None, bits: int = 64) -> DataFrame:
    """``keep`` columns (doc_id by default) and the fingerprint fp: a signed long, or ``bits`` of bytes."""
    keep = keep or ["doc_id"]
    source = docs.select(F.col("text").cast("string").alias("_text"), *keep)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[1:]) + (", fp long" if bits == 64 else ", fp binary")

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(0))
            for i, j in slices(offsets, 1 << 20):
                fp = fingerprint_slice(offsets[i : j + 1] - offsets[i], raw[offsets[i] : offsets[j]], width, SEED, bits)
                column = pa.array(fp[:, 0].view(np.int64), pa.int64()) if bits == 64 else pa.array([r.tobytes() for r in fp], pa.binary())
                yield pa.RecordBatch.from_arrays([*(b.column(k).slice(i, j - i) for k in range(1, b.num_columns)), column], names=[*keep, "fp"])

    return source.mapInArrow(tidy(run), schema)


def choose_blocks(rows: int, radius: int = RADIUS) -> int:
    """The number of bit blocks with the least estimated work; every choice finds every pair."""

    def work(blocks: int) -> float:
        tables = comb(blocks, radius)
        bits = 64 * (blocks - radius) // blocks
        return tables * (200.0 * rows + rows * rows / 2.0 ** (bits + 1))

    return min(range(radius + 1, radius + 6), key=work)


def _block_keys(blocks: int, radius: int) -> list[int]:
    """A bit mask for every choice of ``blocks - radius`` blocks."""
    edges = [64 * k // blocks for k in range(blocks + 1)]
    masks = [((1 << edges[k + 1]) - (1 << edges[k])) for k in range(blocks)]
    return [sum(masks[k] for k in chosen) for chosen in combinations(range(blocks), blocks - radius)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def _roots(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Smallest index reachable from each of n rows over the links i-j."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[i], label[j])
        before = label.copy()
        np.minimum.at(label, i, low)
        np.minimum.at(label, j, low)
        label = label[label]
        if (label == before).all():
            return label


def tiled_links(g: np.ndarray, fp: np.ndarray, side: np.ndarray, radius: int, tile: int = _TILE, most: int = 1 << 20) -> tuple[np.ndarray, np.ndarray, dict]:
    """Spanning links (row, row) within the buckets ``g`` of one sequence: home rows (side 0) with each
    other and with visitors (1).  Rows of fp are 64-bit words.  Also returns how many tile pairs share a
    bucket, and how many of them were skipped by their population counts."""
    n, words = fp.shape
    pop = np.bitwise_count(fp).sum(axis=1, dtype=np.int32)
    order = np.lexsort((pop, g))
    g, fp, side, pop = g[order], fp[order], side[order], pop[order]
    tiles = -(-n // tile)
    pad = lambda x, fill: np.concatenate([x, np.full((tiles * tile - n, *x.shape[1:]), fill, x.dtype)]).reshape(tiles, tile, *x.shape[1:])
    head = np.arange(tiles) * tile
    tail = np.minimum(head + tile, n) - 1
    bucket, wide_fp, wide_side = np.cumsum(np.concatenate([[0], g[1:] != g[:-1]])).astype(np.int32), pad(fp, 0), pad(side, 2)
    wide_bucket = pad(bucket, -1)
    left, right, seen, skipped, held = [], [], 0, 0, 0
    for d in range(tiles):
        a = np.arange(tiles - d)
        a = a[bucket[tail[a]] == bucket[head[a + d]]] if d else a
        if not len(a):
            break
        seen += len(a)
        if d:  # sorted by count: what the tiles share lies between these two rows
            near = pop[head[a + d]] - pop[tail[a]] <= radius
            skipped += int((~near).sum())
            a = a[near]
        for s in range(0, len(a), 64):
            x, y = a[s : s + 64], a[s : s + 64] + d
            far = np.zeros((len(x), tile, tile), np.uint16)
            for w in range(words):
                far += np.bitwise_count(wide_fp[x, :, None, w] ^ wide_fp[y, None, :, w])
            t, i, j = np.nonzero((far <= radius) & (wide_bucket[x][:, :, None] == wide_bucket[y][:, None, :]) & (wide_side[x][:, :, None] + wide_side[y][:, None, :] < 2))
            i, j = x[t] * tile + i, y[t] * tile + j
            ok = (i < j) & (j < n)
            left.append(i[ok])
            right.append(j[ok])
            held += len(left[-1])
            if held > most:  # keep a spanning set only
                label = _roots(n, np.concatenate(left), np.concatenate(right))
                own = np.flatnonzero(label != np.arange(n))
                left, right, held = [own], [label[own]], len(own)
    label = _roots(n, np.concatenate(left), np.concatenate(right)) if left else np.arange(n)
    own = np.flatnonzero(label != np.arange(n))
    return order[own], order[label[own]], {"tile_pairs": seen, "skipped": skipped}


def _bucket_links(keyed: DataFrame, words: int, radius: int) -> DataFrame:
    """(u, v) from rows (g, fp, side): the spanning links of every bucket g."""
    kind = "long" if words == 1 else "binary"
    sorted_rows = keyed.select("g", "fp", "side").repartition("g").sortWithinPartitions("g")

    def run(batches):
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

        def links(last: bool):
            nonlocal held
            g, fp, side = (np.concatenate(x) for x in zip(*held))
            cut = len(g) if last else int(np.searchsorted(g, g[-1]))  # the last bucket may go on
            if cut:
                i, j, _ = tiled_links(g[:cut], fp[:cut], side[:cut], radius)
                out = [pa.array(fp[k][:, 0].view(np.int64), pa.int64()) if words == 1 else pa.array([r.tobytes() for r in fp[k]], pa.binary()) for k in (i, j)]
                yield pa.RecordBatch.from_arrays(out, names=["u", "v"])
            held = [(g[cut:], fp[cut:], side[cut:])]

        for b in batches:
            if not b.num_rows:
                continue
            fp = b.column(1).to_numpy().view(np.uint64)[:, None] if words == 1 else np.frombuffer(b"".join(b.column(1).to_pylist()), "<u8").reshape(-1, words)
            held.append((b.column(0).to_numpy(), fp, b.column(2).to_numpy().astype(np.int8)))
            if sum(len(x[0]) for x in held) >= 10_000:
                yield from links(False)
        if held:
            yield from links(True)

    return sorted_rows.mapInArrow(tidy(run), f"u {kind}, v {kind}")


def _dealt(keyed: DataFrame, keys: list[str], tile_rows: int) -> DataFrame:
    """Names the buckets: those with more than ``tile_rows`` rows are dealt by pairs of parts."""
    large = keyed.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > tile_rows)
    if large.isEmpty():
        return keyed.select(F.xxhash64(*keys).alias("g"), "fp", "side")
    large = large.select(*keys, F.ceil(F.col("n") / tile_rows).cast("int").alias("tiles"))
    keyed = keyed.join(large, keys, "left").withColumn("tiles", F.coalesce("tiles", F.lit(1)))
    keyed = keyed.withColumn("tile", F.pmod(F.xxhash64("fp"), F.col("tiles")).cast("int"))
    partner = F.sequence(F.lit(0), F.col("tiles") - 1)
    keyed = keyed.select("fp", *keys, "side", F.explode(F.transform(partner, lambda p: F.least(p, F.col("tile")) * F.col("tiles") + F.greatest(p, F.col("tile")))).alias("pair"))
    # one long names the bucket; equal names of different buckets only add comparisons
    return keyed.select(F.xxhash64(*keys, "pair").alias("g"), "fp", "side")


def bit_tables(rows: int, bits: int, similarity: float, seed: int = 7) -> np.ndarray:
    """The bits each table of a wide search compares: enough of them that usual buckets stay small,
    and tables enough that pairs of that shingle similarity meet but for ``MISS``."""
    each = max(8, ceil(log2(max(rows, 2) / 64)))
    agree = (1 - acos(2 * similarity / (1 + similarity)) / pi) ** each
    rng = np.random.default_rng(seed)
    return np.array([rng.choice(bits, each, replace=False) for _ in range(ceil(log(MISS) / log(1 - agree)))])


def wide_links(distinct: DataFrame, bits: int, radius: int, similarity: float, tile_rows: int = TILE_ROWS) -> DataFrame:
    """Spanning links (u, v) among distinct wide fingerprints ``fp``."""
    tables = bit_tables(distinct.count(), bits, similarity)
    weights = 1 << np.arange(tables.shape[1], dtype=np.int64)

    def run(batches):
        for b in batches:
            for s in range(0, b.num_rows, 1000):
                fp = b.column(0).slice(s, 1000)
                flags = np.unpackbits(np.frombuffer(b"".join(fp.to_pylist()), np.uint8).reshape(len(fp), -1), axis=1, bitorder="little")
                for t, places in enumerate(tables):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(fp), t, np.int32)), pa.array(flags[:, places].astype(np.int64) @ weights), fp, pa.array(np.zeros(len(fp), np.int32))], names=["t", "key", "fp", "side"])

    keyed = distinct.select("fp").mapInArrow(tidy(run), "t int, key long, fp binary, side int")
    return _bucket_links(_dealt(materialize(keyed, "wide-keys"), ["t", "key"], tile_rows), bits // 64, radius)


def near_links(distinct: DataFrame, radius: int = RADIUS, tile_rows: int = TILE_ROWS) -> DataFrame:
    """Spanning links (u, v) among the distinct fingerprints ``fp`` within ``radius`` bits."""
    rows = distinct.count()
    masks = _block_keys(choose_blocks(rows, radius), radius)
    band = (F.bit_count(F.col("fp")) / (radius + 1)).cast("int")
    keyed = distinct.select("fp", band.alias("band"), F.posexplode(F.array(*(F.col("fp").bitwiseAND(F.lit(_signed(m))) for m in masks))).alias("t", "key"))
    # a row is at home in its own band and visits the next one
    keyed = keyed.select("fp", "t", "key", F.explode(F.array(F.struct(F.col("band").alias("band"), F.lit(0).alias("side")), F.struct((F.col("band") + 1).alias("band"), F.lit(1).alias("side")))).alias("b")).select("fp", "t", "key", "b.band", "b.side")
    return _bucket_links(_dealt(keyed, ["t", "key", "band"], tile_rows), 1, radius)


def near_duplicates(docs: DataFrame, width: int = WIDTH, radius: int = RADIUS, tile_rows: int = TILE_ROWS, bits: int = 64, similarity: float = 0.8) -> DataFrame:
    """doc_id, fingerprint (hex digits) and component_id, the smallest doc_id reachable.  ``similarity``
    sets the search of wide fingerprints only; at 64 bits no pair within the radius is missed."""
    prints = materialize(fingerprints(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), width, bits=bits), "fingerprints")
    # a node is named by the smallest doc_id that has the fingerprint, so a doc_id with several texts ties them
    name = F.coalesce(F.min("doc_id"), F.xxhash64("fp"))
    nodes = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id"), name.alias("node")), "fp-nodes")
    links = near_links(nodes.select("fp"), radius, tile_rows) if bits == 64 else wide_links(nodes.select("fp"), bits, radius, similarity, tile_rows)
    at = lambda end: nodes.select(F.col("fp").alias(end), F.col("node").alias(f"n{end}"))
    links = links.distinct().join(at("u"), "u").join(at("v"), "v").select(F.col("nu").alias("u"), F.col("nv").alias("v"))
    several = prints.where("doc_id is not null").join(nodes, "fp").where("node <> doc_id").select(F.col("doc_id").alias("u"), F.col("node").alias("v"))
    several = several.join(prints.groupBy("doc_id").agg(F.min("fp").alias("a"), F.max("fp").alias("b")).where("a <> b").select(F.col("doc_id").alias("u")), "u")
    roots = connected_components(links.union(several).where("u <> v").distinct())
    rooted = nodes.join(roots.withColumnRenamed("node", "_n"), F.col("node") == F.col("_n"), "left").select("fp", "first_id", F.coalesce("root", "node").alias("root"))
    rooted = materialize(rooted, "fp-roots")
    least = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    component = materialize(rooted.join(least, "root").select("fp", "component_id"), "fp-components")
    out = prints.join(component, "fp")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), bits // 4, "0")).alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))
