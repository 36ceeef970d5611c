"""Whole-document log-likelihood under a gated recurrent language model, and an additive baseline.

Tokens are ASCII-lower-cased words and one end a document.

Corpus counts.  Every word of every training document is counted (pre-aggregated in each task), so
what is gathered grows with the corpus.  Words stand as a 64-bit and a 32-bit hash.  At most ``HEAD``
most frequent words travel to the tasks as a sorted array; all others meet their counts in a join.

Model.  A GRU reads the tokens.  The next token's probability is class-factored: a softmax over
``CLASSES`` classes of ``PER_CLASS`` frequent words each and ``TAILS`` classes of all other words,
then either a softmax within the class or, in a tail class (words by a hash of their last two
bytes), the class's smoothed corpus shares.  The output biases start from the corpus counts.

Training is truncated backpropagation in numpy over windows of ``WINDOW`` steps.  A first network is
fitted on the driver from the windows of a bounded sample (``sample_docs`` documents,
``sample_windows`` windows each, spread over the whole text), whose states enter from the window
before.  Then every task goes on from it over every window of all of its training documents (``EVERY``
is 1), and the tasks' weights are averaged by their tokens, in ``GROUPS`` sums of which the driver gets
the results.  So every position of every training text gives a gradient.  Tasks read documents side by
side and carry each state from its document's first token on (``Lanes``), so no window is run twice;
only what is left when a task's documents run out takes its states from the window before.

Scoring runs documents in step, longest first, and carries each state from its first token to its
end, windows and groups of ``ABREAST`` documents only bounding memory.

Defined cases: null text is empty (one end); without training documents the base score is that of
the formula with zero counts and the model scores by its initial weights; rows repeating a doc_id
are scored each on its own, exact repeats alike.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import drop, hashed_head, held_out, materialize, row_id, slices, text_bytes, tidy

CLASSES, PER_CLASS, TAILS = 32, 32, 32
FREQUENT = CLASSES * PER_CLASS  # the end token is the first of them
HIDDEN = 24
WINDOW = 24
HEAD = 60_000
EVERY = 1
ABREAST = 512  # documents scored in step
GROUPS = 16  # of tasks whose weights are added up together
ALPHA = 0.1
_INPUTS = FREQUENT + TAILS
# by input token
CLASS_OF = np.concatenate([np.arange(FREQUENT) // PER_CLASS, CLASSES + np.arange(TAILS)]).astype(np.int16)
WORD_OF = np.concatenate([np.arange(FREQUENT) % PER_CLASS, np.zeros(TAILS)]).astype(np.int16)


def word_hash(word: bytes) -> int:
    h = xxh64_intdigest(word)
    return h - (1 << 64) if h >= 1 << 63 else h


def tail_class(word: bytes) -> int:
    return zlib.crc32(word[-2:]) % TAILS


def second_hash(word: bytes) -> int:
    return zlib.crc32(word) - (1 << 31)


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxh64_intdigest, words), np.uint64, len(words)).view(np.int64)


def tail_classes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(zlib.crc32, [w[-2:] for w in words]), np.int64, len(words)) % TAILS


def second_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(zlib.crc32, words), np.int64, len(words)) - (1 << 31)


def slice_words(offsets: np.ndarray, raw: np.ndarray) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """(distinct words, code of every token, first token of each text); A-Z lower-cased."""
    texts = pa.LargeStringArray.from_buffers(len(offsets) - 1, pa.py_buffer(np.ascontiguousarray(offsets, np.int64)), pa.py_buffer(np.ascontiguousarray(raw)))
    split = pc.ascii_split_whitespace(pc.ascii_lower(texts))  # at bytes 9 to 13 and 32, with empty strings at the ends
    coded = split.flatten().dictionary_encode()
    edges, data = text_bytes(coded.dictionary)
    blob, edges = data.tobytes(), edges.tolist()
    words = [blob[a:b] for a, b in zip(edges, edges[1:])]
    codes, first = coded.indices.to_numpy().astype(np.int64), split.offsets.to_numpy().astype(np.int64)
    if b"" in words:
        empty = words.index(b"")
        kept = codes != empty
        first = np.concatenate([[0], np.cumsum(kept)])[first - first[0]]
        codes = codes[kept]
        codes -= codes > empty
        del words[empty]
    return words, codes, first - first[0]


def count_words(docs: DataFrame) -> DataFrame:
    """(h, h2, tail, c): the count of each word over all texts of ``docs``."""

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(0))
            for i, j in slices(offsets, 8 << 20):
                words, codes, _ = slice_words(offsets[i : j + 1] - offsets[i], raw[offsets[i] : offsets[j]])
                yield pa.RecordBatch.from_arrays([pa.array(word_hashes(words)), pa.array(second_hashes(words), pa.int32()), pa.array(tail_classes(words), pa.int32()), pa.array(np.bincount(codes, minlength=len(words)), pa.int64())], names=["h", "h2", "tail", "c"])

    counted = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), "h long, h2 int, tail int, c long")
    return counted.groupBy("h", "h2").agg(F.first("tail").alias("tail"), F.sum("c").alias("c"))


class GatedLm:
    """GRU weights by gate (reset, update, candidate): of the input token, of the state; class output, word output."""

    def __init__(self, seed: int = 17):
        r = np.random.default_rng(seed)
        draw = lambda *shape: (r.normal(size=shape) * 0.1).astype(np.float32)
        by_gate = lambda x: np.ascontiguousarray(x.reshape(len(x), 3, HIDDEN).transpose(1, 0, 2))
        self.w = {"X": by_gate(draw(_INPUTS, 3 * HIDDEN)), "U": by_gate(draw(HIDDEN, 3 * HIDDEN)), "C": draw(HIDDEN, CLASSES + TAILS), "c": np.zeros(CLASSES + TAILS, np.float32), "W": draw(CLASSES, HIDDEN, PER_CLASS), "w": np.zeros((CLASSES, PER_CLASS), np.float32)}

    def step(self, h: np.ndarray, token: np.ndarray) -> np.ndarray:
        """Consume one token a row."""
        return self.turn(h, np.take(self.w["X"], token, axis=1))[0]

    def turn(self, h: np.ndarray, gates: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(next states, the candidate's share of h).  ``gates``, by gate and row, come as the tokens' shares
        and are left as the gates' values."""
        s = np.matmul(h, self.w["U"])
        rz, n = gates[:2], gates[2]
        rz += s[:2]
        np.negative(rz, out=rz)
        np.exp(rz, out=rz)
        rz += 1
        np.reciprocal(rz, out=rz)
        n += rz[0] * s[2]
        np.tanh(n, out=n)
        out = h - n
        out *= rz[1]
        out += n
        return out, s[2]

    def outputs(self, h: np.ndarray, cls: np.ndarray, word: np.ndarray):
        """Rows in order of class: (order, borders of the classes, states and a column of ones for the biases,
        classes, words, class logits, word logits of the rows in a class of words)."""
        order = np.argsort(cls.astype(np.int16), kind="stable")
        of_class, of_word = np.vstack([self.w["C"], self.w["c"]]), np.concatenate([self.w["W"], self.w["w"][:, None]], axis=1)
        ones, cls, word = np.ones((len(h), HIDDEN + 1), np.result_type(h, of_class)), cls[order], word[order]
        ones[:, :HIDDEN] = np.take(h, order, axis=0)
        edges = np.searchsorted(cls, np.arange(CLASSES + 1)).tolist()
        p = ones @ of_class
        q = np.empty((edges[-1], PER_CLASS), p.dtype)
        for k, (a, b) in enumerate(zip(edges, edges[1:])):
            if a < b:
                np.matmul(ones[a:b], of_word[k], out=q[a:b])
        most = max(1.0, np.abs(h).max(initial=0.0)) * max(np.abs(of_class).sum(axis=0).max(), np.abs(of_word).sum(axis=1).max())
        if not most < 40:  # exponentials might leave the numbers' range
            p -= p.max(axis=1, keepdims=True)
            q -= q.max(axis=1, keepdims=True)
        return order, edges, ones, cls, word[: edges[-1]], p, q

    def log_probabilities(self, h: np.ndarray, cls: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Natural log of each row's class probability times its word's share of the class."""
        order, _, h, cls, word, p, q = self.outputs(h, cls, word)
        logs = p[np.arange(len(p)), cls]
        logs[: len(q)] += q[np.arange(len(q)), word]
        logs -= np.log(_row_sums(np.exp(p, out=p)))
        logs[: len(q)] -= np.log(_row_sums(np.exp(q, out=q)))
        out = np.empty_like(logs)
        out[order] = logs
        return out

    def output_gradients(self, h, cls, word, grads) -> np.ndarray:
        """Adds the output layers' gradients of the summed loss; returns that of the states."""
        order, edges, h, cls, word, p, q = self.outputs(h, cls, word)
        for x, own in ((p, cls), (q, word)):
            np.exp(x, out=x)
            x *= (1 / _row_sums(x))[:, None]
            x[np.arange(len(x)), own] -= 1
        g = h.T @ p
        grads["C"] += g[:HIDDEN]
        grads["c"] += g[HIDDEN]
        d = p @ self.w["C"].T
        for k, (a, b) in enumerate(zip(edges, edges[1:])):
            if a < b:
                g = h[a:b].T @ q[a:b]
                grads["W"][k] += g[:HIDDEN]
                grads["w"][k] += g[HIDDEN]
                d[a:b] += q[a:b] @ self.w["W"][k].T
        out = np.empty_like(d)
        out[order] = d
        return out

    def start_from(self, class_counts: np.ndarray, word_counts: np.ndarray) -> GatedLm:
        """Output biases that give the corpus shares of classes and of words within a class."""
        share = class_counts + 1.0
        self.w["c"] = np.log(share / share.sum()).astype(np.float32)
        inner = word_counts.reshape(CLASSES, PER_CLASS) + 0.5
        self.w["w"] = np.log(inner / inner.sum(axis=1, keepdims=True)).astype(np.float32)
        return self

    def gradients(self, h: np.ndarray, token: np.ndarray, cls: np.ndarray, word: np.ndarray, live: np.ndarray) -> dict:
        """Of the summed loss of the ``live`` places, truncated to these steps (rows) from states h."""
        return self.unrolled(h, token, cls, word, live)[0]

    def unrolled(self, h, token, cls, word, live) -> tuple[dict, np.ndarray]:
        """(``gradients``, the states after the last step)."""
        gates = np.take(self.w["X"], token, axis=1)
        states, share = (np.empty((*token.shape, HIDDEN), h.dtype) for _ in range(2))
        for t in range(len(token)):
            states[t] = h
            h, share[t] = self.turn(h, gates[:, t])
        grads = {k: np.zeros_like(v) for k, v in self.w.items()}
        flat, at = states.reshape(-1, HIDDEN), np.flatnonzero(live)
        d_out = np.zeros_like(states)
        d_out.reshape(-1, HIDDEN)[at] = self.output_gradients(np.take(flat, at, axis=0), cls.ravel()[at], word.ravel()[at], grads)
        # what a state's gradient is times to be that of the step's sums: reset, update, candidate, share of h
        r, z, n = gates
        back = np.empty_like(gates)
        of_n = (1 - n * n) * (1 - z)
        np.multiply(of_n, r, out=back[2])
        np.multiply(back[2], share * (1 - r), out=back[0])
        np.multiply((states - n) * z, 1 - z, out=back[1])
        d, turned = np.zeros_like(h), self.w["U"].transpose(0, 2, 1).copy()
        for t in range(len(token) - 1, -1, -1):
            of_n[t] *= d
            back[:, t] *= d
            d = d * z[t]
            d += d_out[t]
            for x in np.matmul(back[:, t], turned):
                d += x
        for k in range(3):
            grads["U"][k] = flat.T @ back[k].reshape(-1, HIDDEN)
        tokens = token.ravel().astype(np.int16)
        order = np.argsort(tokens, kind="stable")
        tokens = tokens[order]
        first = np.flatnonzero(np.concatenate([[True], np.diff(tokens) != 0]))
        for k, x in enumerate((back[0], back[1], of_n)):
            grads["X"][k][tokens[first]] = np.add.reduceat(np.take(x.reshape(-1, HIDDEN), order, axis=0), first, axis=0)
        return grads, h

    def train(self, windows: np.ndarray, epochs: int = 1, rate: float = 0.01, size: int = 64, decay: float = 0.9) -> GatedLm:
        """Adam over ``windows`` (as by ``window_rows``: windows x places x fields)."""
        adam, turns = Adam(self), epochs * -(-len(windows) // size)
        for turn in range(turns):
            k = turn % -(-len(windows) // size) * size
            adam.learn(windows[k : k + size], rate * (1 - decay * turn / turns))
        return self


class Adam:
    def __init__(self, lm: GatedLm):
        self.lm, self.turn = lm, 0
        self.all, views = np.concatenate([v.ravel() for v in lm.w.values()]), {}
        for k, v in lm.w.items():
            n = sum(x.size for x in views.values())
            views[k] = self.all[n : n + v.size].reshape(v.shape)
        lm.w = views  # one vector holds the weights
        self.first, self.second = (np.zeros_like(self.all) for _ in range(2))

    def learn(self, windows: np.ndarray, rate: float) -> None:
        token, cls, word, kind = (windows[:, :, k].T.astype(np.int64) for k in range(4))
        h = np.zeros((len(windows), HIDDEN), np.float32)
        for t in range(WINDOW):  # the state enters from the window before
            h = self.lm.step(h, token[t]) * (kind[t] > 0)[:, None]
        self.follow(h, token[WINDOW:], cls[WINDOW:], word[WINDOW:], kind[WINDOW:] > 0, rate)

    def follow(self, h, token, cls, word, live, rate: float) -> np.ndarray:
        """One step from states ``h``; returns the states after the last token."""
        grads, h = self.lm.unrolled(h, token, cls, word, live)
        g = np.concatenate([x.ravel() for x in grads.values()])
        g *= 1 / max(int(live.sum()), 1)
        g *= min(1.0, 1.0 / max(float(np.sqrt(g @ g)), 1e-9))
        self.turn += 1
        self.first *= 0.9
        self.first += 0.1 * g
        self.second *= 0.99
        g *= g
        self.second += 0.01 * g
        np.multiply(self.second, 1 / (1 - 0.99**self.turn), out=g)
        np.sqrt(g, out=g)
        g += 1e-6
        np.divide(self.first, g, out=g)
        g *= rate / (1 - 0.9**self.turn)
        self.all -= g
        return h


class Lanes:
    """Documents side by side, a window of each lane a turn.  A lane's state passes from a window to the next,
    from the first token of a document to its end, and a new document starts anew."""

    def __init__(self, size: int):
        self.token = np.zeros(0, np.int16)
        self.begin, self.at, self.stop = (np.zeros(size, np.int64) for _ in range(3))
        self.h = np.zeros((size, HIDDEN), np.float32)

    def turns(self, token: np.ndarray, first: np.ndarray):
        """Takes in documents token[first[k]:first[k+1]] and yields (tokens, live) by place and lane, as long as
        every lane has a document; whoever reads them puts the states after the window into ``h``."""
        kept, _ = self._cut()
        self.token = np.concatenate([kept, token])
        starts, stops, k = first[:-1] + len(kept), first[1:] + len(kept), 0
        while True:
            idle = np.flatnonzero(self.at >= self.stop)
            new = idle[: len(starts) - k]
            self.begin[new] = self.at[new] = starts[k : k + len(new)]
            self.stop[new] = stops[k : k + len(new)]
            self.h[new] = 0
            k += len(new)
            if len(new) < len(idle):
                break
            at = self.at[None, :] + np.arange(WINDOW)[:, None]
            live = at < self.stop[None, :]
            yield np.where(live, self.token[np.minimum(at, len(self.token) - 1)], 0), live
            self.at += WINDOW

    def _cut(self) -> tuple[np.ndarray, np.ndarray]:
        """Leaves of each document the part not passed yet and the window before it; (tokens, borders)."""
        busy = np.flatnonzero(self.at < self.stop)
        low = np.maximum(self.begin[busy], self.at[busy] - WINDOW)
        parts = [self.token[a:b] for a, b in zip(low.tolist(), self.stop[busy].tolist())]
        edges = np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int64)
        self.token = np.concatenate([np.zeros(0, np.int16), *parts])
        past = self.at[busy] - low
        self.begin[:] = self.at[:] = self.stop[:] = 0
        self.begin[busy], self.at[busy], self.stop[busy] = edges[:-1], edges[:-1] + past, edges[1:]
        return self.token, edges

    def rest(self) -> np.ndarray:
        """The windows not passed, as by ``window_rows``."""
        token, first = self._cut()
        past = (self.at > self.begin)[self.at < self.stop]
        rows = window_rows(token, CLASS_OF[token], WORD_OF[token], first, np.zeros(len(past), np.int64), np.ones(len(past), np.int64))
        count = -(-np.diff(first) // WINDOW)
        return np.delete(rows, (np.cumsum(count) - count)[past], axis=0)


def window_rows(token: np.ndarray, cls: np.ndarray, word: np.ndarray, first: np.ndarray, phase: np.ndarray, every: np.ndarray) -> np.ndarray:
    """Windows of documents token[first[k]:first[k+1]]: those numbered phase, phase + every, ... of each,
    as (windows, 2 * WINDOW places, token class word kind): a window and the one before it; kind is 0
    outside the document."""
    count = -(-np.diff(first) // WINDOW)
    phase = phase % np.minimum(every, count)
    per = (count - 1 - phase) // every + 1
    doc = np.repeat(np.arange(len(per)), per)
    nth = phase[doc] + (np.arange(len(doc)) - np.repeat(np.cumsum(per) - per, per)) * every[doc]
    at = (first[:-1][doc] + (nth - 1) * WINDOW)[:, None] + np.arange(2 * WINDOW)[None, :]
    inside = (at >= first[:-1][doc][:, None]) & (at < first[1:][doc][:, None])
    at = np.where(inside, at, 0)
    return np.stack([np.where(inside, x[at], 0) for x in (token, cls, word)] + [inside], axis=2).astype(np.int16)


def _row_sums(x: np.ndarray) -> np.ndarray:
    return x @ np.ones(x.shape[1], x.dtype)


@dataclass
class Model:
    """What scoring needs: counts of the frequent words, totals, tail classes, the network."""

    head: np.ndarray  # sorted hashes
    head_count: np.ndarray
    rank: np.ndarray  # by head word: its number among the frequent words, or -1
    tokens: int  # N
    distinct: int  # V
    ends: int  # training documents
    tail_tokens: np.ndarray
    tail_distinct: np.ndarray
    counts: DataFrame | None = None
    lm: GatedLm = field(default_factory=GatedLm)

    def words(self, words: list[bytes]) -> dict[str, np.ndarray]:
        """By distinct word: its hash, input token, log10 of the smoothed count (0 for words outside the
        head), whether it is in the head."""
        h, tail = word_hashes(words), tail_classes(words)
        at = np.minimum(np.searchsorted(self.head, h), max(len(self.head) - 1, 0))
        inside = self.head[at] == h if len(self.head) else np.zeros(len(h), bool)
        count = np.where(inside, self.head_count[at], 0) if len(self.head) else np.zeros(len(h))
        rank = np.where(inside, self.rank[at], -1) if len(self.head) else np.full(len(h), -1)
        often = rank >= 0
        return {"h": h, "token": np.where(often, rank, FREQUENT + tail).astype(np.int16), "log": np.where(inside, np.log10(count + ALPHA), 0.0), "head": inside}

    @property
    def base_log(self) -> float:
        return float(np.log10(self.tokens + ALPHA * (self.distinct + 1)))


def _training(docs: DataFrame, modulus: int) -> DataFrame:
    return docs.where(~held_out(modulus))


def coded(model: Model, offsets: np.ndarray, raw: np.ndarray):
    """(word columns, code of each token, owner, first, [token, class, word] with ends, first with ends)."""
    words, codes, first = slice_words(offsets, raw)
    w, n = model.words(words), len(offsets) - 1
    owner = np.repeat(np.arange(n), np.diff(first))
    token = np.zeros(len(codes) + n, np.int16)
    token[np.arange(len(codes)) + owner] = w["token"][codes]
    return words, w, codes, owner, first, [token, CLASS_OF[token], WORD_OF[token]], first + np.arange(n + 1)


def _phases(ids: pa.Array) -> np.ndarray:
    return np.array([zlib.crc32(str(x).encode()) for x in ids.to_pylist()], np.int64)


def sampled_windows(train: DataFrame, model: Model, documents: int, windows: int) -> np.ndarray:
    """At most ``windows`` windows, spread over the whole text, of each of at most ``documents`` documents."""
    # ids first: texts travel only for the sample
    chosen = hashed_head(train.where("doc_id is not null").select("doc_id"), documents, "doc_id").distinct()
    sample = train.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id")

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(1))
            phase = _phases(b.column(0))
            for i, j in slices(offsets, 1 << 20):
                *_, seq, first = coded(model, offsets[i : j + 1] - offsets[i], raw[offsets[i] : offsets[j]])
                for k in range(j - i):
                    own = first[k : k + 2] - first[k]
                    every = np.array([max(1, -(-int(own[1]) // WINDOW // windows))])
                    rows = window_rows(*(x[first[k] : first[k + 1]] for x in seq), own, phase[i + k : i + k + 1], every)[:windows]
                    yield pa.RecordBatch.from_arrays([pa.array([int(phase[i + k])]), pa.array([rows.tobytes()], pa.binary())], names=["p", "x"])

    got = sorted((r["p"], bytes(r["x"])) for r in sample.mapInArrow(tidy(run), "p long, x binary").collect())  # documents x windows x 48 places
    every = [np.frombuffer(x, np.int16).reshape(-1, 2 * WINDOW, 4) for _, x in got]
    rows = np.concatenate(every) if every else np.zeros((0, 2 * WINDOW, 4), np.int16)
    return rows[np.random.default_rng(23).permutation(len(rows))]


def trained_everywhere(train: DataFrame, model: Model, every: int = EVERY, rate: float = 0.004, size: int = 256) -> GatedLm:
    """The average of the networks that the tasks make of ``model``'s from all their documents."""
    start, names = model.lm.w, list(model.lm.w)
    shapes = [start[k].shape for k in names]

    def learn(batches):
        from pyspark import TaskContext

        lm = GatedLm()
        lm.w = {k: v.copy() for k, v in start.items()}
        adam, lanes, tokens = Adam(lm), Lanes(size), 0
        held = np.zeros((0, 2 * WINDOW, 4), np.int16)
        for b in batches:
            offsets, raw = text_bytes(b.column(1))
            phase = _phases(b.column(0))
            for i, j in slices(offsets, 8 << 20):
                *_, seq, first = coded(model, offsets[i : j + 1] - offsets[i], raw[offsets[i] : offsets[j]])
                if every == 1:
                    for token, live in lanes.turns(seq[0], first):
                        lanes.h = adam.follow(lanes.h, token, CLASS_OF[token], WORD_OF[token], live, rate)
                        tokens += int(live.sum())
                    continue
                held = np.concatenate([held, window_rows(*seq, first, phase[i:j], np.full(j - i, every))])
                while len(held) >= size:
                    adam.learn(held[:size], rate)
                    tokens += int((held[:size, WINDOW:, 3] > 0).sum())
                    held = held[size:]
        held = np.concatenate([held, lanes.rest()])
        for k in range(0, len(held), size):
            some = held[k : k + size]
            adam.learn(some, rate * len(some) / size)
            tokens += int((some[:, WINDOW:, 3] > 0).sum())
        if tokens:
            move = np.concatenate([(lm.w[k] - start[k]).ravel() for k in names]) * tokens
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId() % GROUPS], pa.int32()), pa.array([float(tokens)]), pa.array([move.astype("<f4").tobytes()], pa.binary())], names=["g", "n", "move"])

    def add(batches):
        n, total = 0.0, 0.0
        for b in batches:
            for tokens, move in zip(b.column(1).to_pylist(), b.column(2)):
                n, total = n + tokens, total + np.frombuffer(move.as_buffer(), "<f4").astype(float)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([n]), pa.array([total.astype("<f4").tobytes()], pa.binary())], names=["g", "n", "move"])

    schema = "g int, n double, move binary"
    moved = materialize(train.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(tidy(learn), schema), "lm-moves")
    sums = moved.repartition(GROUPS, "g").mapInArrow(add, schema).collect()  # GROUPS rows of weights
    drop(moved)
    lm = GatedLm()
    lm.w = {k: v.copy() for k, v in start.items()}
    if sums:
        move, at = sum(np.frombuffer(r["move"], "<f4").astype(float) for r in sums) / sum(r["n"] for r in sums), 0
        for k, shape in zip(names, shapes):
            size_k = int(np.prod(shape))
            lm.w[k] = (start[k] + move[at : at + size_k].reshape(shape)).astype(np.float32)
            at += size_k
    return lm


def fit(docs: DataFrame, modulus: int = 10, sample_docs: int = 1000, sample_windows: int = 10, epochs: int = 4, every: int = EVERY) -> Model:
    """Counts over all training documents, and the network from windows of all of them."""
    train = _training(docs, modulus)
    counts = materialize(count_words(train), "word-counts")
    ends = train.count()
    totals = counts.groupBy("tail").agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("v")).collect()  # TAILS rows
    # the least count that at most HEAD words reach, from a histogram of fixed width
    bins = sorted(counts.groupBy(F.floor(F.log2("c") * 16).alias("b")).agg(F.count(F.lit(1)).alias("n"), F.min("c").alias("least")).collect(), key=lambda r: -r["b"])
    least, have = None, 0
    for r in bins:
        have += r["n"]
        if have > HEAD:
            break
        least = r["least"]
    head = counts.where(F.col("c") >= least).collect() if least is not None else []  # HEAD rows at most
    head.sort(key=lambda r: (-r["c"], r["h"]))
    rank = {r["h"]: k + 1 for k, r in enumerate(head[: FREQUENT - 1])}
    often = np.zeros(FREQUENT)
    often[0], often[1 : len(rank) + 1] = ends, [r["c"] for r in head[: FREQUENT - 1]]
    head.sort(key=lambda r: r["h"])
    tail_n, tail_v = np.zeros(TAILS), np.zeros(TAILS)
    for r in totals:
        tail_n[r["tail"]], tail_v[r["tail"]] = r["n"], r["v"]
    words = int(tail_n.sum())
    for r in head:
        if r["h"] in rank:
            tail_n[r["tail"]] -= r["c"]
            tail_v[r["tail"]] -= 1
    model = Model(np.array([r["h"] for r in head], np.int64), np.array([r["c"] for r in head], np.int64), np.array([rank.get(r["h"], -1) for r in head], np.int64), words + ends, sum(r["v"] for r in totals) + (ends > 0), ends, tail_n, tail_v)
    model.lm.start_from(np.concatenate([often.reshape(CLASSES, PER_CLASS).sum(axis=1), tail_n]), often)
    if ends:
        model.lm.train(sampled_windows(train, model, sample_docs, sample_windows), epochs)
        model.lm = trained_everywhere(train, model, every)
    model.counts = counts
    return model


def sequence_scores(lm: GatedLm, token: np.ndarray, cls: np.ndarray, word: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Summed natural logs by document; documents are token[first[k]:first[k+1]], ends included."""
    order, out = np.argsort(-np.diff(first), kind="stable"), np.zeros(len(first) - 1)
    for k in range(0, len(order), ABREAST):  # so many that a step's numbers stay near the processor
        some = order[k : k + ABREAST]
        out[some] = _abreast(lm, token, cls, word, first[some], first[some + 1] - first[some])
    return out


def _abreast(lm, token, cls, word, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """``sequence_scores`` of the documents at ``start``, longest first."""
    total = np.zeros(len(size))
    h = np.zeros((len(size), HIDDEN), np.float32)
    t, longest = 0, int(size[0])
    while t < longest:
        stop = min(t + WINDOW, longest)
        rows = np.searchsorted(-size, -np.arange(t, stop), side="left")  # documents with more than t tokens
        edges = np.concatenate([[0], np.cumsum(rows)])
        doc = np.arange(edges[-1]) - np.repeat(edges[:-1], rows)
        at = start[doc] + np.repeat(np.arange(t, stop), rows)
        gates, states = np.take(lm.w["X"], token[at], axis=1), np.empty((len(at), HIDDEN), np.float32)
        for a, b in zip(edges.tolist(), edges[1:].tolist()):
            states[a:b] = h = h[: b - a]
            h = lm.turn(h, gates[:, a:b])[0]
        total += np.bincount(doc, lm.log_probabilities(states, cls[at], word[at]), len(total))
        t = stop
    return total


def score(docs: DataFrame, model: Model, modulus: int = 10, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    keep = keep or ["doc_id"]
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    source = docs.select(text.alias("_text"), *row_id("doc_id", text), held_out(modulus).alias("_held"), *keep)
    counts, model = model.counts, Model(**{**model.__dict__, "counts": None})

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[4:])
    schema = f"_u1 long, _u2 long, _held boolean, {kinds}, n_tokens long, head_known long, base_part double, part double, rare array<struct<h: long, h2: int, tf: long>>"
    end_log = float(np.log10(model.ends + ALPHA))
    tail_log = np.log10(model.tail_tokens + ALPHA * (model.tail_distinct + 1))

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(0))
            n = len(offsets) - 1
            n_tokens, known, base, part = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n), np.zeros(n)
            rare_h, rare_h2, rare_tf, rare_n = ([np.zeros(0, np.int64)] for _ in range(4))
            for i, j in slices(offsets, 8 << 20):
                words, w, codes, owner, first, seq, ends = coded(model, offsets[i : j + 1] - offsets[i], raw[offsets[i] : offsets[j]])
                sizes, any_word = np.diff(first), len(codes) > 0
                logs = sequence_scores(model.lm, *seq, ends)
                in_tail = w["token"][codes].astype(np.int64) - FREQUENT if any_word else codes
                spread = np.where(in_tail >= 0, (w["log"][codes] if any_word else 0) - tail_log[np.maximum(in_tail, 0)], 0.0)
                n_tokens[i:j] = sizes + 1
                known[i:j] = np.bincount(owner, w["head"][codes] if any_word else None, j - i) + (model.ends > 0)
                base[i:j] = np.bincount(owner, w["log"][codes] if any_word else None, j - i) + end_log - (sizes + 1) * model.base_log
                part[i:j] = logs / np.log(10) + np.bincount(owner, spread, j - i)
                # words outside the head meet their counts in a join
                out = ~w["head"][codes] if any_word else np.zeros(0, bool)
                pair, tf = np.unique(owner[out] * max(len(words), 1) + codes[out], return_counts=True)
                which = pair % max(len(words), 1)
                there, nth = np.unique(which, return_inverse=True)
                second = second_hashes([words[x] for x in there.tolist()])[nth]
                for held, x in ((rare_h, w["h"][which] if any_word else which), (rare_h2, second), (rare_tf, tf), (rare_n, np.bincount(pair // max(len(words), 1), minlength=j - i))):
                    held.append(x)
            edges = np.concatenate([[0], np.cumsum(np.concatenate(rare_n))]).astype(np.int32)
            pairs = pa.StructArray.from_arrays([pa.array(np.concatenate(rare_h), pa.int64()), pa.array(np.concatenate(rare_h2), pa.int32()), pa.array(np.concatenate(rare_tf), pa.int64())], names=["h", "h2", "tf"])
            rest = [b.column(k) for k in range(1, b.num_columns)]
            yield pa.RecordBatch.from_arrays([*rest, pa.array(n_tokens), pa.array(known), pa.array(base), pa.array(part), pa.ListArray.from_arrays(edges, pairs)], names=["_u1", "_u2", "_held", *keep, "n_tokens", "head_known", "base_part", "part", "rare"])

    scored = materialize(source.mapInArrow(tidy(run), schema), "lm-scores")
    # one entry more a document, without occurrences, tells how often it is there; its own id spreads it
    uid = ["_u1", "_u2"]
    own = F.array(F.struct(F.col("_u1").alias("h"), F.lit(0).alias("h2"), F.lit(0).cast("long").alias("tf")))
    found = scored.select(*uid, F.explode(F.concat("rare", own)).alias("r")).select(*uid, "r.h", "r.h2", "r.tf")
    found = found.join(counts.select("h", "h2", "c"), ["h", "h2"], "left") if counts is not None else found.withColumn("c", F.lit(0).cast("long"))
    c = F.coalesce("c", F.lit(0))
    rare = found.groupBy(*uid).agg(F.count(F.when(F.col("tf") == 0, 1)).alias("rows"), F.sum(F.col("tf") * F.log10(c + ALPHA)).alias("rare_log"), F.sum(F.when(c > 0, F.col("tf")).otherwise(0)).alias("rare_known"))
    rare = rare.select(*uid, (F.col("rare_log") / F.col("rows")).alias("rare_log"), (F.col("rare_known") / F.col("rows")).cast("long").alias("rare_known"))
    out = scored.join(rare, uid, "left")
    rare_log, rare_known = F.coalesce("rare_log", F.lit(0.0)), F.coalesce("rare_known", F.lit(0))
    return out.select(*keep, F.col("_held").alias("held_out"), "n_tokens", (F.col("head_known") + rare_known).alias("n_known"), F.lit(model.tokens).cast("long").alias("train_tokens"), (F.col("base_part") + rare_log).alias("base_score"), (F.col("part") + rare_log).alias("score"))
