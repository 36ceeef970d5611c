"""Quality rules with an isolation forest over rule statistics.

Base rules reject texts with too few words or too many repeated 8-word windows.  What they pass is
judged by an isolation forest: trees of random splits over the rule statistics isolate unusual
documents after few splits, so a short mean path marks an anomaly.  Scales, the range of the cuts and
the cut-off of the score come from *all* labelled rows outside the held-out part, exactly, and each tree
draws its few rows (``sample``, as the method has it) from all growing rows labelled good.  Among
cut-offs that keep at least ``keep_good`` of the other good rows, the one that rejects most of the
bad ones is taken, placed midway between the scores around it.

Statistics cover whole texts; words are maximal runs of anything but ASCII white space, compared
as they stand.

Defined cases: null text has no words (and fails the base rules); without labelled rows of both
kinds the forest rejects nothing; rows repeating a doc_id are judged each on its own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop, hashed_head, held_out, materialize, slices, text_bytes, tidy

WINDOW = 8
SYMBOL_CHARS = b"#*$%&|<>"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
FEATURES = 9
QUANTILES = (0.01, 0.5, 0.99)
_MIX = np.uint64(0x9E3779B97F4A7C15)


class _Numbering(dict):
    def __missing__(self, word):
        self[word] = n = len(self)
        return n


def _table(chars: bytes) -> np.ndarray:
    t = np.zeros(256, bool)
    t[list(chars)] = True
    return t


_BLANK, _SYMBOL = _table(b" \t\n\x0b\x0c\r"), _table(SYMBOL_CHARS)
_UPPER, _DIGIT, _PUNCT = _table(bytes(range(65, 91))), _table(bytes(range(48, 58))), _table(b"!\"'()+,-./:;=?@[\\]^_`{}~")


def _sums(flags: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    return np.diff(np.concatenate([[0], np.cumsum(flags)])[offsets])


def _spread(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def repeated_words(codes: np.ndarray, starts: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """By text: the words that lie in a window of ``window`` words found twice or more in it."""
    n = len(codes)
    if n < window:
        return np.zeros(len(starts) - 1, np.int64)
    with np.errstate(over="ignore"):
        h, step, base = _spread(codes.astype(np.uint64) + np.uint64(1)), 1, np.uint64(0xD6E8FEB86659FD93)
        while step < window:
            h, step, base = h[: len(h) - step] * base + h[step:], step * 2, base * base
        owner = np.repeat(np.arange(len(starts) - 1), np.diff(starts))
        inside = owner[: len(h)] == owner[window - 1 :]
        at = np.flatnonzero(inside)
        h = h[at] + _spread(owner[at].astype(np.uint64) + _MIX)
    order = np.argsort(h)
    same = h[order[1:]] == h[order[:-1]]
    twice = np.zeros(len(h), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(n + 1, np.int32)
    np.add.at(edge, at[twice], 1)
    np.add.at(edge, at[twice] + window, -1)
    return _sums(np.cumsum(edge[:-1]) > 0, starts)


def text_statistics(offsets: np.ndarray, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(counts as in COUNTS, features for the forest) of each text."""
    n = len(offsets) - 1
    counts, features = np.zeros((n, len(COUNTS)), np.int64), np.zeros((n, FEATURES))
    for i, j in slices(offsets, 1 << 20):
        part, off = raw[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        blob, number, codes, sizes, distinct, dups, n_lines = part.tobytes(), _Numbering(), [], [], [], [], []
        for a, b in zip(off[:-1].tolist(), off[1:].tolist()):
            text = blob[a:b]
            words = text.split()
            codes += [number[w] for w in words]
            sizes.append(len(words))
            distinct.append(len(set(words)))
            lines = text.split(b"\n")
            n_lines.append(len(lines))
            repeats = 0
            if len(set(lines)) < len(lines):
                seen = set()
                for line in lines:
                    if line in seen:
                        repeats += bool(line.strip())
                    seen.add(line)
            dups.append(repeats)
        starts = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)
        words, blank = np.array(sizes, np.int64), _BLANK[part]
        chars = _sums((part & 0xC0) != 0x80, off) - _sums(blank, off)
        symbols, repeat = _sums(_SYMBOL[part], off), repeated_words(np.array(codes, np.int64), starts)
        counts[i:j] = np.stack([words, chars, symbols, np.array(dups, np.int64), repeat], axis=1)
        w, c = np.maximum(words, 1), np.maximum(chars, 1)
        features[i:j] = np.stack([
            symbols / c, chars / w, np.minimum(symbols / w, 1), np.array(dups) / np.array(n_lines), repeat / w, np.array(distinct) / w ** 0.8,
            _sums(_UPPER[part], off) / c, _sums(_DIGIT[part], off) / c, _sums(_PUNCT[part], off) / c,
        ], axis=1)
    return counts, features


def _mean_path(n: float) -> float:
    """Mean depth of an unsuccessful search among ``n`` keys: what a leaf of n rows stands for."""
    return 0.0 if n <= 1 else 1.0 if n == 2 else 2 * (np.log(n - 1) + 0.5772156649) - 2 * (n - 1) / n


class IsolationForest:
    """Trees as flat arrays: feature (-1 in a leaf), cut, left child (right is next), path length.

    Cuts are uniform in the *box* that the earlier cuts leave of the range of all sampled rows, so a
    statistic that is constant among the rows a tree grows on still separates rows that differ.
    Statistics are first centred and scaled by the spread of the grown rows and bent by arcsinh.
    """

    def __init__(self, rows: np.ndarray, every: np.ndarray, trees: int = 200, sample: int = 256, seed: int = 11):
        rng = np.random.default_rng(seed)
        size = min(sample, len(rows))
        draws = (rows[rng.choice(len(rows), size, replace=False)] for _ in range(trees))
        self._build(np.quantile(rows, QUANTILES, axis=0), every.min(axis=0), every.max(axis=0), draws, size, rng)

    @classmethod
    def of_draws(cls, quantiles: np.ndarray, least: np.ndarray, most: np.ndarray, draws: list[np.ndarray], seed: int = 11) -> IsolationForest:
        """A forest of one tree for each of ``draws``; ``quantiles`` (as QUANTILES) of the growing rows and the range of
        all rows are known."""
        self = cls.__new__(cls)
        self._build(quantiles, least, most, draws, max(map(len, draws)), np.random.default_rng(seed))
        return self

    def _build(self, quantiles, least, most, draws, size, rng) -> None:
        low, self.mid, high = quantiles
        self.spread = np.maximum(high - low, 0.04) / 2
        box = self._bend(least), self._bend(most)
        self.roots, self.feature, self.cut, self.left, self.path = [], [], [], [], []
        self.norm = _mean_path(max(size, 2))
        self.depth = int(np.ceil(np.log2(max(size, 2)))) + 4
        for drawn in draws:
            self.roots.append(self._new())
            self._grow(self.roots[-1], self._bend(drawn), *box, 0, rng)
        self.feature, self.left = np.array(self.feature), np.array(self.left)
        self.cut, self.path = np.array(self.cut), np.array(self.path)

    def _bend(self, rows: np.ndarray) -> np.ndarray:
        return np.arcsinh((rows - self.mid) / self.spread)

    def _new(self) -> int:
        for column, v in ((self.feature, -1), (self.cut, 0.0), (self.left, 0), (self.path, 0.0)):
            column.append(v)
        return len(self.feature) - 1

    def _grow(self, node, rows, low, high, level, rng) -> None:
        usable = np.flatnonzero(high > low)
        if level >= self.depth or len(rows) <= 1 or not len(usable):
            self.path[node] = level + _mean_path(len(rows))
            return
        f = int(rng.choice(usable))
        cut = rng.uniform(low[f], high[f])
        self.feature[node], self.cut[node] = f, cut
        self.left[node] = left = self._new()
        right = self._new()
        mid_high, mid_low = high.copy(), low.copy()
        mid_high[f] = mid_low[f] = cut
        self._grow(left, rows[rows[:, f] < cut], low, mid_high, level + 1, rng)
        self._grow(right, rows[rows[:, f] >= cut], mid_low, high, level + 1, rng)

    def score(self, rows: np.ndarray) -> np.ndarray:
        """2^(-mean path / usual path): near 1 for anomalies."""
        rows = self._bend(rows)
        total, every = np.zeros(len(rows)), np.arange(len(rows))
        for root in self.roots:
            node = np.full(len(rows), root)
            for _ in range(self.depth):
                f = self.feature[node]
                inner = f >= 0
                if not inner.any():
                    break
                right = rows[every, np.maximum(f, 0)] >= self.cut[node]
                node = np.where(inner, self.left[node] + right, node)
            total += self.path[node]
        return np.exp2(-total / len(self.roots) / self.norm)


def calibrate(scores: np.ndarray, good: np.ndarray, keep_good: float) -> float:
    """The cut-off that rejects most bad rows while ``keep_good`` of the good ones stay below it."""
    if not good.any() or good.all():
        return np.inf
    g, b = np.sort(scores[good]), np.sort(scores[~good])
    floor = g[min(len(g) - 1, int(np.ceil(keep_good * len(g))) - 1)]
    above = b[b > floor]
    return float((floor + above[0]) / 2) if len(above) else np.inf


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, rows: int, modulus: int = 5) -> DataFrame:
    """At most ``rows`` labelled documents outside the held-out part: those of smallest id hash."""
    chosen = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(modulus))
    chosen = hashed_head(chosen.groupBy("doc_id").agg(F.max(label).alias("_label")), rows, "doc_id")
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id")


def order_statistics(table: DataFrame, column: str, ranks: list[list[int]]) -> list[list[float]]:
    """Exactly the values at 0-based ``ranks`` (by place) of each place of an array column of non-negative doubles.

    Their bits order as the doubles do: rounds of twelve bits count the values that share the bits found so far, so at
    most 4096 counts a rank come to the driver in each of six rounds, whatever the number of rows."""
    found = [[0] * len(r) for r in ranks]  # the bits so far
    left = [list(r) for r in ranks]  # ranks among the values that share them
    for shift in (52, 40, 28, 16, 4, 0):
        width = 4 if shift == 0 else 12
        heads = [sorted(set(f)) for f in found]

        def run(batches):
            counts = [[np.zeros(1 << width, np.int64) for _ in h] for h in heads]
            for b in batches:
                x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, len(heads))
                for c, hs in enumerate(heads):
                    bits = np.ascontiguousarray(x[:, c]).view(np.int64) >> shift
                    for k, h in enumerate(hs):
                        counts[c][k] += np.bincount(bits[bits >> width == h] & ((1 << width) - 1), minlength=1 << width)
            for c, hs in enumerate(heads):
                for k, h in enumerate(hs):
                    at = np.flatnonzero(counts[c][k])
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), c, np.int32)), pa.array(np.full(len(at), h, np.int64)), pa.array(at.astype(np.int32)), pa.array(counts[c][k][at])], names=["c", "h", "b", "n"])

        got = table.select(column).mapInArrow(tidy(run), "c int, h long, b int, n long").groupBy("c", "h", "b").agg(F.sum("n").alias("n")).collect()
        tally: dict = {}
        for r in got:
            tally.setdefault((r["c"], r["h"]), []).append((r["b"], r["n"]))
        for c in range(len(ranks)):
            for k, h in enumerate(found[c]):
                for bucket, n in sorted(tally[c, h]):
                    if left[c][k] < n:
                        break
                    left[c][k] -= n
                found[c][k] = (h << width) | bucket
    return [np.array(f, np.int64).view(np.float64).tolist() for f in found]


def quantiles_of(table: DataFrame, column: str, n: int) -> np.ndarray:
    """QUANTILES of each place of the array column over all ``n`` rows, interpolated as numpy does."""
    at = [q * (n - 1) for q in QUANTILES]
    v = np.array(order_statistics(table, column, [[int(np.floor(x)) for x in at] + [int(np.ceil(x)) for x in at]] * FEATURES))
    part = np.array([x - np.floor(x) for x in at])
    return (v[:, :3] + (v[:, 3:] - v[:, :3]) * part).T


def labelled_statistics(docs: DataFrame, labels: DataFrame, label: str, modulus: int = 5) -> DataFrame:
    """(y, grow, h, x): label, half, hash and statistics of every labelled document outside the held-out part.  Texts
    stay where they are read: only their statistics meet the labels."""
    chosen = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(modulus))
    chosen = chosen.groupBy("doc_id").agg(F.max(label).alias("_label"))
    source = docs.where(F.col("doc_id").isNotNull() & ~held_out(modulus)).select("doc_id", F.col("text").cast("string").alias("text"))

    def run(batches):
        for b in batches:
            _, features = text_statistics(*text_bytes(b.column(1)))
            edges = np.arange(0, features.size + 1, FEATURES, dtype=np.int32)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(edges, pa.array(features.ravel()))], names=["doc_id", "x"])

    x = source.mapInArrow(tidy(run), f"doc_id {source.schema['doc_id'].dataType.simpleString()}, x array<double>").join(chosen, "doc_id")
    h = F.xxhash64("doc_id", "x")
    return x.select((F.col("_label") == 1).alias("y"), ((F.col("_label") == 1) & (h % 2 == 0)).alias("grow"), F.xxhash64(F.lit(7), h).alias("h"), "x")


def tree_draws(rows: DataFrame, n: int, trees: int, sample: int) -> list[np.ndarray]:
    """For each tree the ``sample`` rows of least hash with it, out of all ``n`` rows (h, x)."""
    bound = min(1.0, (sample + 9 * np.sqrt(sample)) / n)  # leaves a few rows more than each tree takes

    def run(batches):
        for b in batches:
            h = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for t in range(trees):
                with np.errstate(over="ignore"):
                    g = _spread(h + np.uint64(t + 1) * _MIX)
                at = np.flatnonzero(g.astype(np.float64) <= bound * 2.0**64)
                if len(at):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), t, np.int32)), pa.array(g[at].view(np.int64)), b.column(1).take(pa.array(at))], names=["t", "g", "x"])

    got = rows.select("h", "x").mapInArrow(tidy(run), "t int, g long, x array<double>").collect()  # trees x about 400 rows
    by: list[list] = [[] for _ in range(trees)]
    for r in got:
        by[r["t"]].append((r["g"] % (1 << 64), r["x"]))
    return [np.array([x for _, x in sorted(d)[:sample]]) for d in by if d]


def fit(docs: DataFrame, labels: DataFrame, keep_good: float = 0.998, trees: int = 200, sample: int = 256) -> tuple[IsolationForest | None, float]:
    table = materialize(labelled_statistics(docs, labels, "quality"), "rule-statistics")
    try:
        return _fit(table, keep_good, trees, sample)
    finally:
        drop(table)


def _fit(table: DataFrame, keep_good: float, trees: int, sample: int) -> tuple[IsolationForest | None, float]:
    ends = [f(F.col("x")[k]) for f in (F.min, F.max) for k in range(FEATURES)]
    size = table.agg(F.count(F.when(F.col("y"), 1)), F.count(F.when(F.col("grow"), 1)), *ends).first()
    n_good, n_grow = size[0], size[1]
    if not n_good:
        return None, np.inf
    # half of the good rows grow the forest; the other half and the bad rows set the cut-off
    grow = table.where("grow" if n_grow else "y")
    n = n_grow or n_good
    least, most = np.array(size[2 : 2 + FEATURES]), np.array(size[2 + FEATURES :])
    forest = IsolationForest.of_draws(quantiles_of(grow, "x", n), least, most, tree_draws(grow, n, trees, sample))

    def run(batches):
        for b in batches:
            x = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, FEATURES)
            if len(x):
                yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(np.arange(len(x) + 1, dtype=np.int32), pa.array(forest.score(x)))], names=["y", "s"])

    scored = materialize(table.where("not grow").select("y", "x").mapInArrow(tidy(run), "y boolean, s array<double>"), "rule-scores")
    rest = n_good - n_grow
    cut = np.inf
    if rest:
        floor = order_statistics(scored.where("y"), "s", [[min(rest - 1, int(np.ceil(keep_good * rest)) - 1)]])[0][0]
        above = scored.where(~F.col("y") & (F.col("s")[0] > floor)).agg(F.min(F.col("s")[0])).first()[0]
        cut = np.inf if above is None else (floor + above) / 2
    drop(scored)
    return forest, cut


def judge(docs: DataFrame, forest: IsolationForest | None, cut: float, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns, the statistics, base_failed, anomaly, kept."""
    keep = keep or ["doc_id"]
    source = docs.select(F.col("text").cast("string").alias("_text"), *keep)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[1:]) + "".join(f", {c} long" for c in COUNTS) + ", base_failed boolean, anomaly double, kept boolean"

    def run(batches):
        for b in batches:
            counts, features = text_statistics(*text_bytes(b.column(0)))
            failed = (counts[:, 0] < 20) | (100 * counts[:, 4] > 30 * counts[:, 0])
            anomaly = forest.score(features) if forest is not None else np.zeros(len(counts))
            rest = [b.column(k) for k in range(1, b.num_columns)]
            yield pa.RecordBatch.from_arrays([*rest, *(pa.array(counts[:, k], pa.int64()) for k in range(len(COUNTS))), pa.array(failed), pa.array(anomaly), pa.array(~failed & (anomaly < cut))], names=[*keep, *COUNTS, "base_failed", "anomaly", "kept"])

    return source.mapInArrow(tidy(run), schema)
