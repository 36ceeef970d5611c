"""Removal of repeated byte strings, by column-wise multi-document suffix sorting.

Every byte covered by a string of ``length`` bytes that also starts anywhere else is removed.

Candidates.  In each window of ``length`` bytes the ``gram``-byte string of least hash (leftmost
among equals) is the window's *anchor*.  Equal windows have equal anchors at equal places, so a
repeated window shows as a repeated anchor string, and all of it lies in the anchor's *context*:
``length - gram`` bytes before and ``length`` bytes from its start.  About one position in
``(length - gram) / 2`` is an anchor; anchors whose string occurs once are dropped.

Sorting.  Contexts that differ but share an anchor string are lined up at it and sorted column by
column from the right: each round inserts one symbol per context in front of its suffix.  A round
reads from a sequential file what the round before left there (the transform: the symbols before the
suffixes in suffix order; the order; the common prefixes of neighbours), deals the suffixes by their
new first symbol, derives the new common prefixes, and writes the same for the next round.  The
files are private to the running task, like those of Spark's own sorts.  A window is repeated where
a neighbour's common prefix reaches ``length``.  Equal contexts are one row with a count, so exact
copies cost nothing here.

Inserting every suffix of whole documents into one transform would take as many rewrites of the
corpus as the longest document has bytes; lining contexts up bounds the rounds by
``2 * length - gram`` and the file of a round by the contexts of one task.

Skew.  Anchor strings found everywhere are join keys (tables on both sides, so that adaptive
execution splits them) and partial aggregates.  Contexts of one anchor string are dealt into chunks
of about ``CHUNK`` rows, all of which are sorted.  Where there are several chunks, each sends one
name of 128 bits for every class of equal windows that its order shows, and names that two chunks
send are repeated as well: what is sent is aggregated by the sort, and no group is gathered.
Texts, contexts and windows are told apart by 128 bits throughout.

Memory.  Texts are read in parts of ``_PART`` bytes, contexts in blocks of ``_ROWS`` rows as flat bytes.

Defined cases: null text is empty; texts shorter than ``length`` lose nothing; rows repeating a
doc_id are texts of their own (their equal strings are repeats); rows without doc_id count too; exact
repeats of a row stay as many rows as they are.
"""

from __future__ import annotations

import hashlib
import tempfile

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop, materialize, row_id, slices, text_bytes, tidy, worker_state

LENGTH, GRAM = 200, 64
CHUNK = 512
_ROWS = 4096
_POS_BITS = np.uint64(22)
_POS_MASK = np.uint64((1 << 22) - 1)
_PART = 1 << 18
_BASE = np.uint64(0xD6E8FEB86659FD93)
_BASE2 = np.uint64(0x9FB21C651E98DF25)


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def _codes(seed: int) -> np.ndarray:
    """64 random bits for each byte."""
    with np.errstate(over="ignore"):
        return _mix((np.arange(256, dtype=np.uint64) + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15))


_CODE, _CODE2 = _codes(1), _codes(1001)


def _power_table(n: int, base: np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2^64."""
    out = []
    for b in (int(base), pow(int(base), -1, 1 << 64)):
        p = np.full(n + 1, b, np.uint64)
        p[0] = 1
        out.append(np.cumprod(p, dtype=np.uint64))
    return out[0], out[1]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The table of the first base; the usual length is kept in the worker."""
    usual = 2 * _PART + 2
    return worker_state(__name__, usual, lambda: _power_table(usual, _BASE)) if n <= usual else _power_table(n, _BASE)


def _gram_hashes(code: np.ndarray, k: int) -> np.ndarray:
    """A hash of every k-byte window, by doubling."""
    have, size, base, out, done = code, 1, _BASE, None, 0
    while k:
        if k & 1:
            if out is None:
                out, done = have, size
            else:
                n = len(code) - done - size + 1
                out, done = out[:n] * base + have[done : done + n], done + size
        k >>= 1
        if k:
            have, size, base = have[: len(have) - size] * base + have[size:], size * 2, base * base
    return _mix(out)


def _window_least(x: np.ndarray, w: int) -> np.ndarray:
    size, n = 1, len(x) - w + 1
    while size * 2 <= w:
        x, size = np.minimum(x[: len(x) - size], x[size:]), size * 2
    return np.minimum(x[:n], x[w - size : w - size + n]) if size < w else x


def slice_anchors(x: np.ndarray, off: np.ndarray, length: int, gram: int, first: int = 0, last: int | None = None) -> tuple[np.ndarray, ...]:
    """(place, anchor hash, context hash, bytes before, bytes from the start) of the anchors of the
    windows that start in [first, last) and lie in one of the texts with offsets ``off``."""
    none = tuple(np.zeros(0, t) for t in (np.int64, np.uint64, np.uint64, np.int64, np.int64))
    if len(x) < length:
        return none
    with np.errstate(over="ignore"):
        code = _CODE[x]
        h = _gram_hashes(code, gram)
        least = _window_least((h & ~_POS_MASK) | np.arange(len(h), dtype=np.uint64), length - gram + 1)
        ends = np.repeat(off[1:], np.diff(off))[: len(least)]
        ok = np.arange(len(least)) + length <= ends
        if first or last is not None:
            ok[:first] = False
            ok[len(least) if last is None else last :] = False
        at = (least[ok] & _POS_MASK).astype(np.int64)
        if not len(at):
            return none
        at = np.unique(at[np.concatenate([[True], at[1:] != at[:-1]])])
        owner = np.searchsorted(off, at, side="right") - 1
        lo, hi = np.maximum(at - (length - gram), off[owner]), np.minimum(at + length, off[owner + 1])
        up, down = _powers(len(x) + 1)
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(code * up[: len(x)], dtype=np.uint64)])
        ctx = (total[hi] - total[lo]) * down[lo]
        ctx = _mix(ctx ^ ((at - lo) * 1024 + (hi - at)).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return at, h[at], ctx, at - lo, hi - at


def text_anchors(offsets: np.ndarray, raw: np.ndarray, length: int, gram: int):
    """Yields (text, place in the text, hashes, extents); long texts are read in overlapping parts."""
    for i, j in slices(offsets, _PART):
        off = offsets[i : j + 1] - offsets[i]
        x = raw[offsets[i] : offsets[j]]
        if len(x) <= 2 * _PART:
            at, *rest = slice_anchors(x, off, length, gram)
            owner = np.searchsorted(off, at, side="right") - 1
            yield owner + i, at - off[owner], *rest
            continue
        found = []  # one long text
        for c in range(0, len(x), _PART):
            lo, hi = max(0, c - length), min(len(x), c + _PART + 2 * length)
            at, *rest = slice_anchors(x[lo:hi], np.array([0, hi - lo]), length, gram, c - lo, c - lo + _PART)
            found.append((at + lo, *rest))
        found = [np.concatenate(v) for v in zip(*found)]
        _, once = np.unique(found[0], return_index=True)
        yield np.full(len(once), i), *(v[once] for v in found)


class ColumnwiseSuffixSort:
    """Suffix order and common prefixes of lined-up contexts, one inserted symbol per round.

    ``matrix`` goes to a sequential file by columns.  Two more files take turns: a round reads
    transform, order and common prefixes from one and writes its own to the other."""

    def __init__(self, matrix: np.ndarray):
        self.rows, self.width = matrix.shape
        self._columns, self._files = tempfile.TemporaryFile(), [tempfile.TemporaryFile(), tempfile.TemporaryFile()]
        np.ascontiguousarray(matrix.T).tofile(self._columns)
        # before the first round: all suffixes are empty, in row order, without common prefixes
        self._write(self.column(self.width - 1), np.arange(self.rows, dtype=np.int32), np.zeros(self.rows + 1, np.int16))

    def column(self, c: int) -> np.ndarray:
        self._columns.seek(c * self.rows)
        return np.fromfile(self._columns, np.uint8, self.rows)

    def _write(self, *arrays: np.ndarray) -> None:
        self._files.reverse()
        self._files[0].seek(0)
        for a in arrays:
            a.tofile(self._files[0])

    def _read(self) -> list[np.ndarray]:
        self._files[0].seek(0)
        return [np.fromfile(self._files[0], t, self.rows + k) for t, k in ((np.uint8, 0), (np.int32, 0), (np.int16, 1))]

    def insert(self, c: int) -> tuple[np.ndarray, np.ndarray]:
        """The round of column c: (order, common prefix with the one before; a guard at both ends)."""
        symbol, order, before = self._read()
        take = np.argsort(symbol, kind="stable")
        same = symbol[take[1:]] == symbol[take[:-1]]
        common = np.zeros(self.rows + 1, np.int16)
        a, b = take[:-1][same], take[1:][same]  # neighbours with one symbol: rows a < b of the old order
        if len(a):
            edges = np.stack([a + 1, b + 1], axis=1).ravel()
            common[1:-1][same] = np.minimum.reduceat(before, edges)[::2] + 1
        order = order[take]
        self._write(self.column(c - 1)[order] if c else np.full(self.rows, 255, np.uint8), order, common)
        return order, common

    def classes(self, length: int, starts: int) -> tuple[np.ndarray, np.ndarray]:
        """Boolean (start, row) twice: the window from that column occurs in another row; the row is
        the first of its class of equal windows."""
        again, first = (np.zeros((starts, self.rows), bool) for _ in range(2))
        for c in range(self.width - 1, -1, -1):
            order, common = self.insert(c)
            if c < starts:
                reach = common >= length
                again[c, order] = reach[:-1] | reach[1:]
                first[c, order] = ~reach[:-1]
        for f in (self._columns, *self._files):
            f.close()
        return again, first


def _flat(lo: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Positions of the ranges [lo, lo + size), one after another."""
    begin = np.cumsum(size) - size
    return np.arange(int(size.sum())) + np.repeat(lo - begin, size)


def _lined_up(offsets: np.ndarray, raw: np.ndarray, before: np.ndarray, length: int, gram: int) -> np.ndarray:
    n, width = len(before), 2 * length - gram
    matrix = np.full(n * width, 255, np.uint8)  # no UTF-8 text holds 255
    matrix[_flat(np.arange(n) * width + (length - gram - before), np.diff(offsets))] = raw
    return matrix.reshape(n, width)


def window_names(matrix: np.ndarray, length: int, starts: int) -> list[np.ndarray]:
    """Two longs for each (row, start): together 128 bits that stand for the window's bytes."""
    out = []
    with np.errstate(over="ignore"):
        for code, base in ((_CODE, _BASE), (_CODE2, _BASE2)):
            up, down = _power_table(matrix.shape[1], base)
            total = np.zeros((len(matrix), matrix.shape[1] + 1), np.uint64)
            np.cumsum(code[matrix] * up[: matrix.shape[1]], axis=1, dtype=np.uint64, out=total[:, 1:])
            out.append(_mix((total[:, length : length + starts] - total[:, :starts]) * down[:starts]).view(np.int64))
    return out


_ANCHORS = "kh long, ch long, _u1 long, _u2 long, p long, before int, after int"


def _identified(docs: DataFrame, keep: list[str]) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(*row_id(F.col("doc_id").cast("long"), text), text.alias("_text"), F.struct(*(F.col(c) for c in keep)).alias("_keep"))


def _anchors(docs: DataFrame, length: int, gram: int) -> DataFrame:
    def run(batches):
        for b in batches:
            u1, u2 = b.column(0).to_numpy(), b.column(1).to_numpy()
            for owner, p, kh, ch, before, after in text_anchors(*text_bytes(b.column(2)), length, gram):
                yield pa.RecordBatch.from_arrays([pa.array(kh.view(np.int64)), pa.array(ch.view(np.int64)), pa.array(u1[owner]), pa.array(u2[owner]), pa.array(p), pa.array(before, pa.int32()), pa.array(after, pa.int32())], names=["kh", "ch", "_u1", "_u2", "p", "before", "after"])

    return docs.select("_u1", "_u2", "_text").mapInArrow(tidy(run), _ANCHORS)


def _contexts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """The bytes of the contexts ``wanted`` (kh, ch, chunk, _u1, _u2, p, before, after): kh, ch,
    chunk, before, ctx.  chunk is null where an anchor string has one only."""
    lists = wanted.groupBy("_u1", "_u2").agg(F.collect_list(F.struct("kh", "ch", "chunk", "p", "before", "after")).alias("_at"))  # bounded by a text's length
    texts = docs.select("_u1", "_u2", "_text").join(lists, ["_u1", "_u2"]).select("_text", "_at")

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(0))
            at = b.column(1)
            size, items = np.diff(at.offsets.to_numpy()), at.flatten()
            base = np.repeat(offsets[:-1], size)
            for s in range(0, len(items), _ROWS):
                part, off = items.slice(s, _ROWS), base[s : s + _ROWS]
                p, before, after = (part.field(k).to_numpy() for k in (3, 4, 5))
                width = (before + after).astype(np.int64)
                ends = np.concatenate([[0], np.cumsum(width)]).astype(np.int32)
                ctx = pa.BinaryArray.from_buffers(pa.binary(), len(part), [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(raw[_flat(off + p - before, width)].tobytes())])
                yield pa.RecordBatch.from_arrays([*(part.field(k) for k in range(3)), pa.array(before, pa.int32()), ctx], names=["kh", "ch", "chunk", "before", "ctx"])

    return texts.mapInArrow(tidy(run), "kh long, ch long, chunk int, before int, ctx binary")


def _runs(flags: np.ndarray, zero: int) -> tuple[np.ndarray, np.ndarray]:
    """(ends of the rows' lists, flat list) of the runs [first, last] of each row of flags; starts
    are counted from column ``zero``."""
    n, w = flags.shape
    edge = np.diff(np.concatenate([np.zeros((n, 1), np.int8), flags.view(np.int8), np.zeros((n, 1), np.int8)], axis=1), axis=1)
    row, col = np.nonzero(edge)
    last = edge[row, col] < 0
    return np.concatenate([[0], np.cumsum(np.bincount(row, minlength=n))]).astype(np.int32), (col - zero - last).astype(np.int32)


def _sorted_windows(contexts: DataFrame, length: int, gram: int, rows: int = 4 * _ROWS) -> DataFrame:
    """kh, ch, runs of windows repeated in the context's chunk, and for chunks with others beside
    them the windows (s, w1, w2, lone) of which the context is the chunk's first."""
    starts = length - gram + 1
    wins_type = pa.struct([("s", pa.int32()), ("w1", pa.int64()), ("w2", pa.int64()), ("lone", pa.bool_())])

    def solve(t: pa.Table):
        kh, ch, chunk = t.column("kh").to_numpy(), t.column("ch"), t.column("chunk").combine_chunks()
        before, ctx = t.column("before").to_numpy().astype(np.int64), t.column("ctx").combine_chunks()
        ends = np.frombuffer(ctx.buffers()[1], np.int32, len(ctx) + 1, ctx.offset * 4).astype(np.int64)
        raw = np.frombuffer(ctx.buffers()[2], np.uint8)[ends[0] : ends[-1]]
        ends -= ends[0]
        matrix = _lined_up(ends, raw, before, length, gram)
        again, first = (x.T for x in ColumnwiseSuffixSort(matrix).classes(length, starts))
        start, origin = np.arange(starts)[None, :], (length - gram - before)[:, None]
        inside = (start >= origin) & (start + length <= origin + np.diff(ends)[:, None])
        run_ends, run_flat = _runs(np.ascontiguousarray(again & inside), length - gram)
        split = np.flatnonzero(~np.asarray(chunk.is_null()))
        send = np.zeros_like(inside)
        send[split] = (first & inside)[split]
        row, col = np.nonzero(send)
        w1, w2 = np.zeros(len(row), np.int64), np.zeros(len(row), np.int64)
        for a in range(0, len(split), 512):
            own = split[a : a + 512]
            lo, hi = np.searchsorted(row, [own[0], own[-1] + 1])
            names = window_names(matrix[own], length, starts)
            place = np.searchsorted(own, row[lo:hi])
            w1[lo:hi], w2[lo:hi] = (x[place, col[lo:hi]] for x in names)
        lists = pa.StructArray.from_arrays([pa.array(col - (length - gram), pa.int32()), pa.array(w1), pa.array(w2), pa.array(~again[row, col])], fields=list(wins_type))
        win_ends = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(kh)))]).astype(np.int32)
        return pa.RecordBatch.from_arrays([pa.array(kh), ch.combine_chunks(), pa.ListArray.from_arrays(pa.array(run_ends), pa.array(run_flat)), pa.ListArray.from_arrays(pa.array(win_ends), lists)], names=["kh", "ch", "runs", "wins"])

    def run(batches):
        held = None
        for b in batches:
            if not b.num_rows:
                continue
            held = pa.concat_tables([*([held] if held is not None else []), pa.Table.from_batches([b])])
            while held.num_rows >= rows:
                key, part = held.column("kh").to_numpy(), held.column("chunk").fill_null(-1).to_numpy()
                edge = np.flatnonzero((key[1:] != key[:-1]) | (part[1:] != part[:-1])) + 1
                edge = edge[edge <= rows] if (edge <= rows).any() else edge[:1]  # whole chunks only
                if not len(edge):
                    break
                yield solve(held.slice(0, int(edge[-1])))
                held = held.slice(int(edge[-1])).combine_chunks()
        if held is not None and held.num_rows:
            yield solve(held)

    return contexts.repartition("kh", "chunk").sortWithinPartitions("kh", "chunk").mapInArrow(tidy(run), "kh long, ch long, runs array<int>, wins array<struct<s: int, w1: long, w2: long, lone: boolean>>")


def context_runs(docs: DataFrame, reps: DataFrame, length: int, gram: int, chunk: int = CHUNK) -> DataFrame:
    """(kh, ch, runs): the repeated windows of distinct contexts ``reps`` (kh, ch, _u1, _u2, p, before,
    after), which is read several times."""
    chunks = reps.groupBy("kh").agg(F.ceil(F.count(F.lit(1)) / chunk).cast("int").alias("chunks")).where("chunks > 1")
    chunks = materialize(chunks, "chunked-groups")
    dealt = reps.join(chunks, "kh", "left").withColumn("chunk", F.pmod("ch", "chunks").cast("int"))
    out = materialize(_sorted_windows(_contexts(docs, dealt), length, gram), "windows")
    runs = out.where("size(runs) > 0").select("kh", "ch", "runs")
    if chunks.isEmpty():
        return runs
    windows = materialize(out.where("size(wins) > 0").select("kh", "ch", F.explode("wins").alias("w")).select("kh", "ch", "w.*"), "class-windows")
    twice = materialize(windows.groupBy("kh", "s", "w1", "w2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").drop("n"), "windows-twice")
    hit = windows.where("lone").join(twice, ["kh", "s", "w1", "w2"]).groupBy("kh", "ch").agg(F.flatten(F.collect_list(F.array("s", "s"))).alias("runs"))
    return runs.unionByName(hit)


def repeated_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(_u1, _u2, lo, hi): byte ranges of the texts of ``_identified`` rows that are to go."""
    spark = docs.sparkSession
    anchors = materialize(_anchors(docs, length, gram), "anchors")
    twice = materialize(anchors.groupBy("kh").agg(F.count(F.lit(1)).alias("n"), F.min("ch").alias("c0"), F.max("ch").alias("c1")).where("n > 1").select("kh", (F.col("c0") == F.col("c1")).alias("alike")), "anchor-repeats")
    found = materialize(anchors.join(twice, "kh"), "anchor-hits")
    drop(anchors, twice)
    _collect_garbage(spark)
    whole = F.struct((F.col("p") - F.col("before")).alias("lo"), (F.col("p") + F.col("after")).alias("hi"))
    same = found.where("alike").select("_u1", "_u2", whole.alias("span"))
    # one representative of each distinct context of an anchor string
    shape = F.struct("_u1", "_u2", "p", "before", "after")
    reps = materialize(found.where("not alike").groupBy("kh", "ch").agg(F.count(F.lit(1)).alias("n"), F.min(shape).alias("at")).select("kh", "ch", "n", "at.*"), "contexts")
    runs = context_runs(docs, reps.drop("n"), length, gram)
    # a context that occurs again goes whole, whether or not another one shares a window with it
    copies = reps.where("n > 1").select("kh", "ch", "n", F.array().cast("array<int>").alias("runs"))
    single = reps.where("n = 1").select("kh", "ch", "n").join(runs, ["kh", "ch"])
    result = materialize(copies.unionByName(single), "context-runs")
    _collect_garbage(spark)
    pairs = F.transform(F.sequence(F.lit(0), (F.size("runs") / 2 - 1).cast("int")), lambda k: F.struct((F.col("p") + F.element_at("runs", (2 * k + 1).cast("int"))).alias("lo"), (F.col("p") + F.element_at("runs", (2 * k + 2).cast("int")) + length).alias("hi")))
    other = found.where("not alike").drop("alike").join(result, ["kh", "ch"]).select("_u1", "_u2", F.explode(F.when(F.col("n") > 1, F.array(whole)).otherwise(pairs)).alias("span"))
    spans = materialize(same.unionByName(other).select("_u1", "_u2", "span.lo", "span.hi").where(F.col("hi") - F.col("lo") >= length), "spans")
    drop(found, reps, result)
    return spans


def _collect_garbage(spark) -> None:
    """Lets Spark remove the shuffle files of finished steps before the next one writes its own."""
    spark.sparkContext._jvm.System.gc()


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, keep: list[str] | None = None, with_text: bool = False) -> DataFrame:
    """``keep`` columns (doc_id by default), n_bytes, n_removed, n_spans, kept_sha256, and with
    ``with_text`` kept_text (characters that a cut splits are left out)."""
    keep = keep or ["doc_id"]
    source = _identified(docs, keep)
    spans = repeated_spans(source, length, gram)
    _collect_garbage(docs.sparkSession)
    lists = spans.groupBy("_u1", "_u2").agg(F.collect_list(F.struct("lo", "hi")).alias("_spans"))  # bounded by a text's length
    joined = source.join(lists, ["_u1", "_u2"], "left").select("_text", "_spans", "_keep.*")
    kept = [f for f in joined.schema.fields[2:]]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept) + ", n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept_text string" if with_text else "")

    def cut(text: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, int, int]:
        """What is left of a text, and its removed bytes and runs."""
        if not len(lo):
            return text, 0, 0
        order = np.argsort(lo, kind="stable")
        lo, hi = lo[order], np.maximum.accumulate(hi[order])
        new = np.concatenate([[True], lo[1:] > hi[:-1]])  # touching spans are one run
        lo, hi = lo[new], hi[np.concatenate([new[1:], [True]])]
        ends = np.concatenate([[0], np.stack([lo, hi], axis=1).ravel(), [len(text)]])
        return np.concatenate([text[a:b] for a, b in zip(ends[::2], ends[1::2])]), int((hi - lo).sum()), len(lo)

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(0))
            at = b.column(1)
            size = np.diff(at.offsets.to_numpy()) if len(at) else np.zeros(0, int)
            size = np.where(np.asarray(at.is_null()), 0, size) if len(at) else size
            first, items = np.concatenate([[0], np.cumsum(size)]), at.flatten()
            lo, hi = items.field(0).to_numpy(), items.field(1).to_numpy()
            for i, j in slices(offsets, 1 << 20):  # bounds what is unpacked at once
                rows, texts = [], []
                for k in range(i, j):
                    text, removed, n = cut(raw[offsets[k] : offsets[k + 1]], lo[first[k] : first[k + 1]], hi[first[k] : first[k + 1]])
                    left = text.tobytes()
                    rows.append((removed, n, hashlib.sha256(left).hexdigest()))
                    if with_text:
                        texts.append(left.decode("utf-8", "ignore"))
                removed, n, sha = zip(*rows)
                cols = [*(b.column(c).slice(i, j - i) for c in range(2, b.num_columns)), pa.array(np.diff(offsets[i : j + 1]), pa.int64()), pa.array(removed, pa.int64()), pa.array(n, pa.int64()), pa.array(sha, pa.string())]
                yield pa.RecordBatch.from_arrays([*cols, *([pa.array(texts, pa.string())] if with_text else [])], names=[*(f.name for f in kept), "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept_text"] if with_text else [])])

    return joined.mapInArrow(tidy(run), schema)
