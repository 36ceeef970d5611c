"""Language identification by cross-parsing against suffix automata of labelled text.

Training.  For every label value a bounded sample of labelled rows (``rows_per_language`` rows of
smallest id hash, ``chars_per_language`` code points in all, less where many languages share
``chars_in_all``) is turned into a suffix automaton: it accepts exactly the substrings of the sample.
A row longer than its share gives pieces from its beginning, middle and end.

Prediction.  The text is parsed greedily into phrases, each the longest match from its position
that occurs in the language's sample.  ``phrases * log2(sample size) / length`` estimates the cross
entropy in bits a symbol; the language with the least wins.

Symbols are the bytes of lower-case letters in UTF-8, and one blank for every run of anything else;
so every letter of every alphabet keeps an identity of its own in tables of at most 256 columns.  A
symbol that the sample lacks opens a phrase, which the next ones continue.

The automata are laid out as dense transition tables whose missing edges already hold the restart
(the root's edge with a phrase mark), so one symbol costs one table look-up.  Texts are cut into
lanes of ``LANE`` symbols that advance in step.  A lane goes on past its end until one of its phrases
begins where a phrase of the next lane's own parse does; from there on both parses agree, so the
counts are those of one greedy walk over the whole text.  Tables are built in each worker from the
sample (a few hundred kB travel, whatever the corpus holds).

Defined cases: null text, a text without letters, or no labelled rows: ``und`` with score 0.  Ties
go to the alphabetically first language.  Rows repeating a doc_id are judged each on its own.
"""

from __future__ import annotations

from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import held_out, slices, text_bytes, tidy, worker_state

LANE = 1024
UNKNOWN = "und"
_MARK = np.uint32(1 << 31)
_LAST_LETTER = 0x323AF  # no code point beyond it is a letter


def letter_tables() -> tuple[np.ndarray, np.ndarray]:
    """By code point: whether it is a letter, and its lower case where that is one code point."""
    is_letter, lower = np.zeros(0x110000, bool), np.arange(0x110000, dtype=np.uint32)
    for c in range(_LAST_LETTER + 1):
        x = chr(c)
        if x.isalpha():
            is_letter[c] = True
            low = x.lower()
            if len(low) == 1:
                lower[c] = ord(low)
    return is_letter, lower


def _heads(amounts: np.ndarray, kind) -> np.ndarray:
    """0 and the running sums of ``amounts``, in one array."""
    out = np.zeros(len(amounts) + 1, kind)
    np.cumsum(amounts, dtype=kind, out=out[1:])
    return out


def letter_bytes(points: np.ndarray, starts: np.ndarray, tables: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(symbols, where each text starts among them, letters of each text) for texts as code points."""
    kind = np.int32 if 4 * len(points) < 1 << 31 else np.int64  # an array a code point weighs in a worker's memory
    letter = tables[0][points]
    n_letters = np.diff(_heads(letter, kind)[starts].astype(np.int64))
    keep = letter.copy()
    keep[1:] |= letter[:-1]  # the first of a run of others stays, as its blank
    keep[starts[:-1][starts[:-1] < starts[1:]]] = True
    p = np.where(letter[keep], tables[1][points[keep]], np.uint32(32))
    kept = _heads(keep, kind)[starts]
    width = 1 + (p >= 0x80).astype(np.uint8) + (p >= 0x800) + (p >= 0x10000)
    at = _heads(width, kind)[kept].astype(np.int64)
    return np.frombuffer(str(p.astype("<u4", copy=False), "utf-32-le").encode(), np.uint8), at, n_letters


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), "<u4")


class SuffixAutomaton:
    """Suffix automaton of a symbol sequence, as a dense table of next states; states are numbered
    from ``base`` on, in steps of the alphabet's size."""

    def __init__(self, symbols: list[int], alphabet: int, base: int = 0):
        k = alphabet
        # at most two states a symbol, as rows of one flat table; -1 is a missing edge
        edges, link, length = array("i", [-1]) * (k * (2 * len(symbols) + 1)), [-1], [0]
        last = 0
        for c in symbols:
            new = len(link)
            length.append(length[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and edges[p * k + c] < 0:
                edges[p * k + c] = new
                p = link[p]
            if p >= 0:
                q = edges[p * k + c]
                if length[p] + 1 == length[q]:
                    link[new] = q
                else:
                    copy = len(link)
                    edges[copy * k : (copy + 1) * k] = edges[q * k : (q + 1) * k]
                    length.append(length[p] + 1)
                    link.append(link[q])
                    while p >= 0 and edges[p * k + c] == q:
                        edges[p * k + c] = copy
                        p = link[p]
                    link[q] = link[new] = copy
            last = new
        # a missing edge restarts at the root with the same symbol and counts a phrase
        state = np.frombuffer(edges, np.int32)[: len(link) * k].reshape(-1, k)
        root = (np.maximum(state[0], 0).astype(np.uint32) * np.uint32(k) + np.uint32(base)) | _MARK
        table = np.empty(state.shape, np.uint32)
        for i in range(0, len(state), 4096):  # some rows at a time, so that temporaries stay small
            some = state[i : i + 4096]
            table[i : i + 4096] = np.where(some < 0, root, some.astype(np.uint32) * np.uint32(k) + np.uint32(base))
        self.table, self.size = table.ravel(), len(symbols)


class CrossParser:
    """The automata of all languages in one table, and the parse of texts against each."""

    def __init__(self, samples: dict[str, str]):
        self.languages, self.tables = sorted(samples), letter_tables()
        raw = [letter_bytes(_points(samples[x]), np.array([0, len(samples[x])]), self.tables)[0] for x in self.languages]
        used = np.unique(np.concatenate(raw))
        self.code = np.full(256, len(used), np.uint8)  # the last symbol stands for bytes that no sample holds
        self.code[used] = np.arange(len(used))
        # each automaton goes to its place at once, so no second copy of all is held; pages beyond the last stay unused
        room = (len(used) + 1) * sum(2 * len(r) + 1 for r in raw)
        self.table, end, bases, sizes = np.empty(room, np.uint32), 0, [], []
        for r in raw:
            bases.append(end)
            one = SuffixAutomaton(self.code[r].tolist(), len(used) + 1, end)
            end += len(one.table)
            if end >= 1 << 31:
                raise ValueError("the samples are too large for one table: lower chars_in_all")
            self.table[bases[-1] : end] = one.table
            sizes.append(one.size)
            del one
        self.bases, self.table, self.log_size = np.array(bases, np.uint32), self.table[:end], np.log2(np.array(sizes) + 2.0)

    def phrases(self, raw: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Phrases of the greedy parse, by text and language."""
        k, sizes = len(self.languages), np.diff(starts)
        lanes = -(-sizes // LANE)
        first = np.concatenate([[0], np.cumsum(lanes)])
        owner = np.repeat(np.arange(len(sizes)), lanes)
        begin = starts[:-1][owner] + (np.arange(len(owner)) - first[:-1][owner]) * LANE
        span = np.minimum(LANE, starts[1:][owner] - begin)
        order = np.argsort(-span, kind="stable")
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        at, live = begin[order], np.searchsorted(-span[order], -np.arange(LANE), side="left")  # lanes with more than t symbols
        symbols = self.code[raw].astype(np.uint32)
        state = np.repeat(self.bases[:, None], len(order), axis=1)
        marks = np.zeros((min(LANE, int(span.max(initial=0))), k, len(order)), bool)  # a phrase begins there
        for t in range(len(marks)):
            n = int(live[t])
            v = self.table[state[:, :n] + symbols[at[:n] + t]]
            marks[t, :, :n] = v >> np.uint32(31)
            state[:, :n] = v & ~_MARK
        marks[:1] = True
        count = marks.sum(axis=0, dtype=np.int64)
        out = np.zeros((len(sizes), k), np.int64)
        one = lanes == 1
        out[one] = count[:, rank[first[:-1][one]]].T
        for text, lang, n in self._stitched(symbols, starts, first, begin, owner, rank, state, marks, count, lanes):
            out[text, lang] = n
        return out

    def _stitched(self, symbols, starts, first, begin, owner, rank, state, marks, count, lanes):
        """Phrases of the texts of several lanes."""
        on = np.flatnonzero(owner[:-1] == owner[1:]) if len(owner) else owner  # lanes that have a next one
        k = len(self.languages)
        lane, lang = np.repeat(on, k), np.tile(np.arange(k), len(on))
        more, meet = np.zeros((len(owner), k), np.int64), np.zeros((len(owner), k), np.int64)
        pos, s, stop = begin[lane] + LANE, state[lang, rank[lane]], starts[1:][owner[lane]]
        while len(lane):
            v = self.table[s + symbols[pos]]
            new = (v >> np.uint32(31)).astype(bool)
            inside = pos - starts[owner[lane]]
            met = new & marks[inside % LANE, lang, rank[first[owner[lane]] + inside // LANE]]
            more[lane, lang] += new & ~met
            meet[lane, lang] = pos
            pos = pos + ~met
            over = pos == stop
            meet[lane[over], lang[over]] = stop[over]
            go = ~met & ~over
            lane, lang, pos, s, stop = lane[go], lang[go], pos[go], (v & ~_MARK)[go], stop[go]
        for text in np.flatnonzero(lanes > 1).tolist():
            lo, end = int(starts[text]), int(starts[text + 1])
            for g in range(k):
                total, place = 0, lo
                while place < end:
                    j = int(first[text]) + (place - lo) // LANE
                    skip = (place - lo) % LANE
                    total += int(marks[skip:, g, rank[j]].sum()) if skip else int(count[g, rank[j]])
                    if j + 1 == first[text + 1]:
                        break
                    total += int(more[j, g])
                    place = int(meet[j, g])
                yield text, g, total

    def bits(self, raw: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Bits a symbol, by text and language."""
        return self.phrases(raw, starts) * self.log_size / np.maximum(np.diff(starts), 1)[:, None]


def training_samples(docs: DataFrame, held_out_modulus: int | None = 5, rows_per_language: int = 64, chars_per_language: int = 60_000, chars_in_all: int = 480_000) -> dict[str, str]:
    """A bounded text by label value, from rows outside the held-out part."""
    labelled = docs.where("lang is not null and text is not null and doc_id is not null")
    if held_out_modulus:
        labelled = labelled.where(~held_out(held_out_modulus))
    labelled = labelled.select("doc_id", F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    # ids first: texts travel only for the sample
    first = W.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id")
    chosen = labelled.select("doc_id", "lang").withColumn("_r", F.row_number().over(first)).where(F.col("_r") <= rows_per_language)
    chosen = chosen.groupBy("doc_id", "lang").agg(F.min("_r").alias("_r")).collect()  # rows_per_language a label value
    if not chosen:
        return {}
    languages = len({r["lang"] for r in chosen})
    share = max(3, min(chars_per_language, chars_in_all // languages) // rows_per_language)
    piece, n = share // 3, F.char_length("text")
    spread = F.concat_ws(" ", F.substring("text", 1, piece), F.substring("text", F.floor((n - piece) / 2).cast("int"), F.lit(piece)), F.substring("text", n - piece + 1, F.lit(piece)))
    picked = docs.sparkSession.createDataFrame(chosen, "doc_id long, lang string, _r int")
    rows = labelled.join(F.broadcast(picked), ["doc_id", "lang"]).select("lang", "_r", F.when(n <= share, F.col("text")).otherwise(spread).alias("text"))
    out: dict[str, str] = {}
    for r in sorted(rows.collect(), key=lambda r: (r["lang"], r["_r"], r["text"])):
        if len(out.get(r["lang"], "")) < share * rows_per_language:  # copies of one doc_id count as one row
            out[r["lang"]] = out.get(r["lang"], "") + " " + r["text"]
    return out


def identify(docs: DataFrame, samples: dict[str, str], keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (doc_id by default), lang_pred and score for every row of ``docs``."""
    keep = keep or ["doc_id"]
    # a kept text travels once
    source = docs.select(F.col("text").cast("string").alias("_text"), *(c for c in keep if c != "text"))
    kinds = {f.name: f.dataType.simpleString() for f in source.schema.fields} | {"text": "string"}
    place = {f.name: k for k, f in enumerate(source.schema.fields)} | {"text": 0}
    schema = ", ".join(f"`{c}` {kinds[c]}" for c in keep) + ", lang_pred string, score double"
    key = tuple(sorted(samples.items()))

    def run(batches):
        parser = worker_state(__name__, key, lambda: CrossParser(samples)) if samples else None
        for b in batches:
            offsets, raw = text_bytes(b.column(0))
            names, scores = [], np.zeros(len(offsets) - 1)
            for i, j in slices(offsets, 1 << 20):
                if parser is None:
                    names += [UNKNOWN] * (j - i)
                    continue
                part = raw[offsets[i] : offsets[j]]
                heads = _heads((part & 0xC0) != 0x80, np.int64)
                symbols, at, n_letters = letter_bytes(_points(part.tobytes().decode()), heads[offsets[i : j + 1] - offsets[i]], parser.tables)
                bits = parser.bits(symbols, at)
                best = bits.argmin(axis=1)
                odds = np.exp2(-np.minimum(np.diff(at), 40)[:, None] * (bits - bits.min(axis=1, keepdims=True)))
                scores[i:j] = np.where(n_letters > 0, 1 / odds.sum(axis=1), 0.0)
                names += [parser.languages[k] if ok else UNKNOWN for k, ok in zip(best, n_letters > 0)]
            yield pa.RecordBatch.from_arrays([*(b.column(place[c]) for c in keep), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=[*keep, "lang_pred", "score"])

    return source.mapInArrow(tidy(run), schema)


def detect(docs: DataFrame, held_out_modulus: int | None = 5, keep: list[str] | None = None) -> DataFrame:
    """Learn from the labelled rows of ``docs`` and judge all of its rows."""
    return identify(docs, training_samples(docs, held_out_modulus), keep)
