"""Quality classifier: attention-based multiple-instance learning over passages.

A document is a bag of passages (``PASSAGE`` bytes each, the whole text).  A passage is described by
the square-rooted shares of hashed character trigrams and by shares of character kinds, encoded
into ``HIDDEN`` units.  Gated attention (a tanh gate times a sigmoid gate) weighs the passages, and
a logistic unit scores the weighted mean.  Encoder, gates and output are learnt together from
document labels with Adam.

Training takes a bounded sample of labelled rows outside the held-out part: those of least id hash, at
most ``sample_rows`` of them and as many as hold ``sample_passages`` passages, each with its whole
text.  The
positive class is far the larger one, so the loss weighs both kinds alike and the output is
shifted so that the share of positives is the sample's.

Defined cases: null and empty texts are one empty passage; without labelled rows every score is
0.5; rows repeating a doc_id are scored each on its own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, text_bytes, tidy
from .rules import labelled_sample

PASSAGE = 1024
BUCKETS = 256
HIDDEN = 24
GATES = 12
_KINDS = [bytes(range(65, 91)), bytes(range(97, 123)), bytes(range(48, 58)), b" ", b"\n", b"#*$%&|<>", b".,;:", b"!?", b"'\"()[]{}", bytes(range(128, 256))]
WIDTH = BUCKETS + len(_KINDS) + 4
_KIND = np.full(256, len(_KINDS), np.uint8)
for _k, _chars in enumerate(_KINDS):
    _KIND[list(_chars)] = _k


def passages(offsets: np.ndarray, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first passage of each text, features by passage) for texts given as one byte array."""
    sizes = np.diff(offsets)
    per = np.maximum(-(-sizes // PASSAGE), 1)
    first = np.concatenate([[0], np.cumsum(per)])
    owner = np.repeat(np.arange(len(sizes)), per)
    begin = offsets[:-1][owner] + (np.arange(first[-1]) - first[:-1][owner]) * PASSAGE
    span = np.minimum(PASSAGE, offsets[1:][owner] - begin)
    of = np.repeat(np.arange(len(owner), dtype=np.int64), span)
    wide = raw.astype(np.uint32)
    tri = np.zeros(len(wide), np.int64)
    if len(wide) > 2:
        tri[:-2] = ((wide[:-2] * np.uint32(0x9E3779B1) + wide[1:-1] * np.uint32(0x85EBCA77) + wide[2:] * np.uint32(0xC2B2AE3D)) >> np.uint32(24)).astype(np.int64)
    begins, ends = offsets[:-1][sizes > 0], offsets[1:][sizes > 0]
    tri[ends - 1] = tri[np.maximum(ends - 2, begins)] = 0  # no trigram reaches into the next text
    n = np.maximum(span, 1)[:, None]
    share = np.bincount(of * BUCKETS + tri, minlength=len(owner) * BUCKETS).reshape(len(owner), BUCKETS) / n
    kinds = np.bincount(of * (len(_KINDS) + 1) + _KIND[raw], minlength=len(owner) * (len(_KINDS) + 1)).reshape(len(owner), -1)[:, : len(_KINDS)] / n
    same = np.zeros(len(raw), np.int64)
    same[1:] = raw[1:] == raw[:-1]
    same[begins] = 0
    extra = np.stack([np.log1p(span) / 7, (share**2).sum(axis=1) * 10, np.bincount(of, same, len(owner)) / n[:, 0], (share > 0).sum(axis=1) / BUCKETS], axis=1)
    return first, np.concatenate([np.sqrt(share), kinds * 3, extra], axis=1).astype(np.float32)


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class GatedAttention:
    """Weights of the encoder, both gates, the attention vector and the output."""

    def __init__(self, weights: dict[str, np.ndarray]):
        self.w = weights

    @classmethod
    def fresh(cls, seed: int = 5) -> GatedAttention:
        r = np.random.default_rng(seed)
        draw = lambda *shape: (r.normal(size=shape) / np.sqrt(shape[0])).astype(np.float32)
        return cls({"E": draw(WIDTH, HIDDEN), "e": np.zeros(HIDDEN, np.float32), "V": draw(HIDDEN, GATES), "U": draw(HIDDEN, GATES), "a": draw(GATES), "o": draw(HIDDEN), "b": np.zeros(1, np.float32), "mean": np.zeros(WIDTH, np.float32), "scale": np.ones(WIDTH, np.float32)})

    def forward(self, x: np.ndarray, first: np.ndarray) -> dict:
        w, heads = self.w, first[:-1]
        z = (x - w["mean"]) * w["scale"]
        h = np.tanh(z @ w["E"] + w["e"])
        t, s = np.tanh(h @ w["V"]), _sigmoid(h @ w["U"])
        logit = (t * s) @ w["a"]
        per = np.diff(first)
        top = np.maximum.reduceat(logit, heads)
        q = np.exp(logit - np.repeat(top, per))
        alpha = q / np.repeat(np.add.reduceat(q, heads), per)
        doc = np.add.reduceat(alpha[:, None] * h, heads, axis=0)
        return {"z": z, "h": h, "t": t, "s": s, "alpha": alpha, "doc": doc, "p": _sigmoid(doc @ w["o"] + w["b"][0]), "per": per}

    def gradients(self, f: dict, first: np.ndarray, err: np.ndarray) -> dict:
        """Gradients of the summed loss; ``err`` is its derivative by each document's logit."""
        w, per, heads = self.w, f["per"], first[:-1]
        doc_err = err[:, None] * w["o"]
        d_doc = np.repeat(doc_err, per, axis=0)
        pull = (d_doc * f["h"]).sum(axis=1)
        d_logit = f["alpha"] * (pull - np.repeat(np.add.reduceat(f["alpha"] * pull, heads), per))
        d_ts = d_logit[:, None] * w["a"]
        d_t, d_s = d_ts * f["s"] * (1 - f["t"] ** 2), d_ts * f["t"] * f["s"] * (1 - f["s"])
        d_h = (f["alpha"][:, None] * d_doc + d_t @ w["V"].T + d_s @ w["U"].T) * (1 - f["h"] ** 2)
        return {"E": f["z"].T @ d_h, "e": d_h.sum(axis=0), "V": f["h"].T @ d_t, "U": f["h"].T @ d_s, "a": (f["t"] * f["s"]).T @ d_logit, "o": f["doc"].T @ err, "b": err.sum(keepdims=True)}

    def train(self, bags: list[np.ndarray], labels: np.ndarray, epochs: int = 12, size: int = 64, rate: float = 0.004, decay: float = 1e-4, seed: int = 3) -> GatedAttention:
        every = np.concatenate(bags)
        self.w["mean"], self.w["scale"] = every.mean(axis=0), 1 / np.maximum(every.std(axis=0), 1e-2)
        r, step = np.random.default_rng(seed), 0
        m = {k: np.zeros_like(v) for k, v in self.w.items()}
        v2 = {k: np.zeros_like(v) for k, v in self.w.items()}
        share = min(max(labels.mean(), 0.01), 0.99)
        weight = np.where(labels == 1, 0.5 / share, 0.5 / (1 - share))
        for _ in range(epochs):
            order = r.permutation(len(bags))
            for i in range(0, len(order), size):
                take = order[i : i + size]
                x = np.concatenate([bags[k] for k in take])
                first = np.concatenate([[0], np.cumsum([len(bags[k]) for k in take])])
                f = self.forward(x, first)
                g = self.gradients(f, first, ((f["p"] - labels[take]) * weight[take] / len(take)).astype(np.float32))
                step += 1
                for k, d in g.items():
                    d = d + decay * self.w[k]
                    m[k] = 0.9 * m[k] + 0.1 * d
                    v2[k] = 0.999 * v2[k] + 0.001 * d * d
                    self.w[k] = (self.w[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v2[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        self.w["b"] = self.w["b"] + np.float32(np.log(share / (1 - share)))  # back to the sample's share of positives
        return self


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", sample_rows: int = 5000, sample_passages: int = 60_000) -> GatedAttention | None:
    """Learn from a bounded sample of rows, each whole."""
    sample = labelled_sample(docs, labels, label, sample_rows).select("doc_id", "text", "_label")
    order = F.shiftrightunsigned(F.xxhash64("doc_id"), 1)
    size = F.greatest(F.ceil(F.octet_length(F.coalesce("text", F.lit(""))) / PASSAGE), F.lit(1))
    last, have = None, 0
    for h, n in sorted((r[0], r[1]) for r in sample.select(order, size).collect()):  # sample_rows rows
        have += n
        if have > sample_passages:
            break
        last = h
    if last is None:
        return None
    sample = sample.where(order <= last)

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(1))
            rows = []
            for i, j in slices(offsets, 1 << 19):
                first, x = passages(offsets[i : j + 1] - offsets[i], raw[offsets[i] : offsets[j]])
                for k in range(j - i):
                    rows.append(x[first[k] : first[k + 1]].astype(np.float16).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), b.column(2).cast(pa.int32()), pa.array(rows, pa.binary())], names=["doc_id", "y", "x"])

    got = sorted(sample.mapInArrow(tidy(run), "doc_id long, y int, x binary").collect(), key=lambda r: (r["doc_id"], bytes(r["x"])))  # sample_rows rows, sample_passages passages
    y = np.array([1 if r["y"] == 1 else 0 for r in got])
    if len(got) == 0 or y.min() == y.max():
        return None
    return GatedAttention.fresh().train([np.frombuffer(r["x"], np.float16).reshape(-1, WIDTH).astype(np.float32) for r in got], y)


def score(docs: DataFrame, model: GatedAttention | None, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns, score, n_passages, and top_passage: the passage of largest attention."""
    keep = keep or ["doc_id"]
    source = docs.select(F.col("text").cast("string").alias("_text"), *keep)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[1:]) + ", score double, n_passages int, top_passage int"

    def run(batches):
        for b in batches:
            offsets, raw = text_bytes(b.column(0))
            n = len(offsets) - 1
            p, count, top = np.full(n, 0.5), np.ones(n, np.int32), np.zeros(n, np.int32)
            for i, j in slices(offsets, 1 << 19):
                first, x = passages(offsets[i : j + 1] - offsets[i], raw[offsets[i] : offsets[j]])
                count[i:j] = np.diff(first)
                if model is not None:
                    f = model.forward(x, first)
                    p[i:j] = f["p"]
                    best = np.maximum.reduceat(f["alpha"], first[:-1])
                    at = np.flatnonzero(f["alpha"] == np.repeat(best, f["per"]))
                    top[i:j] = at[np.searchsorted(at, first[:-1])] - first[:-1]
            rest = [b.column(k) for k in range(1, b.num_columns)]
            yield pa.RecordBatch.from_arrays([*rest, pa.array(p, pa.float64()), pa.array(count, pa.int32()), pa.array(top, pa.int32())], names=[*keep, "score", "n_passages", "top_passage"])

    return source.mapInArrow(tidy(run), schema)
