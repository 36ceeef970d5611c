"""Best-fit packing of tokenized documents into sequences of fixed capacity.

Method.  Items (documents, or pieces of those over the capacity) longer than a third of the
capacity fit at most twice into a sequence, so they are matched in pairs, longest first, each with
the longest partner that fits.  The rest goes, longest first, into the tightest gap that holds it,
and opens a sequence where no gap does.

Items of one length are interchangeable, so the plan is made from the histogram of lengths alone:
at most ``capacity`` counts reach the driver whatever the corpus size, and the plan is a short list
of *segments* (length, ranks, first sequence, items per sequence, first offset).  Each item finds
its place from its rank among the items of its length; that rank is computed with a salted window,
whose salts grow with the most frequent length, so one length holding most items is still spread
over many tasks of a bounded size.

Defined cases: null or empty text is a document of the end id alone; rows with the same doc_id are
packed each on its own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import base64
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import batch, materialize, slices, text_bytes, tidy, worker_state

CAPACITY = 2048
#: Items that one window task ranks, about.
RANKED = 500_000
#: Token split pattern of the 50k byte-level vocabulary (fixed value).
BYTE_BPE_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


class ByteBpe:
    """Ids of the tokenizer file ``json_path``; ``ranks_path`` is the same vocabulary as ranks.

    The rank form gives equal ids several times faster.  A text that spells a special token goes
    through the tokenizer file itself, which alone knows those.
    """

    def __init__(self, json_path: str, ranks_path: str | None):
        from tokenizers import Tokenizer

        self._full = Tokenizer.from_file(json_path)
        self._special = [t.content for t in self._full.get_added_tokens_decoder().values()]
        self._fast = None
        if ranks_path:
            import tiktoken

            with open(ranks_path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self._fast = tiktoken.Encoding("byte_bpe", pat_str=BYTE_BPE_PATTERN, mergeable_ranks=ranks, special_tokens={})

    def encode(self, text: str) -> list[int]:
        if self._fast is None or any(s in text for s in self._special):
            return self._full.encode(text, add_special_tokens=False).ids
        return self._fast.encode_ordinary(text)


def pieces(docs: DataFrame, json_path: str, ranks_path: str | None = None, capacity: int = CAPACITY, end_id: int = 0, with_ids: bool = False) -> DataFrame:
    """Token pieces of every document: doc_id, piece, start, length, ids_crc32 (and ids)."""
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else "")

    def run(batches):
        tok = worker_state(__name__, (json_path, ranks_path), lambda: ByteBpe(json_path, ranks_path))
        for b in batches:
            offsets, _ = text_bytes(b.column(1))
            for i, j in slices(offsets, 1 << 20):
                rows = ([], [], [], [], [], [])
                for doc_id, text in zip(b.column(0).slice(i, j - i).to_pylist(), b.column(1).slice(i, j - i)):
                    ids = np.array([*tok.encode(text.as_py() or ""), end_id], "<u4")
                    cuts = [0, *range(len(ids) % capacity or capacity, len(ids) + 1, capacity)]
                    for k, (lo, hi) in enumerate(zip(cuts, cuts[1:])):
                        part = ids[lo:hi]
                        for out, v in zip(rows, (doc_id, k, lo, hi - lo, zlib.crc32(part.tobytes()), part.astype(np.int32) if with_ids else None)):
                            out.append(v)
                cols = {"doc_id": (rows[0], pa.int64()), "piece": (rows[1], pa.int32()), "start": (rows[2], pa.int64()), "length": (rows[3], pa.int64()), "ids_crc32": (rows[4], pa.int64())}
                if with_ids:
                    cols["ids"] = (rows[5], pa.list_(pa.int32()))
                yield batch(cols)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), schema)


@dataclass(frozen=True)
class Plan:
    """Segments sorted by (length, rank): items of ``length`` with ranks from ``rank`` on go
    ``per_bin`` to a sequence, from sequence ``first`` and offset ``offset`` on."""

    length: np.ndarray
    rank: np.ndarray
    first: np.ndarray
    per_bin: np.ndarray
    offset: np.ndarray
    sequences: int

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        # ranks stay below 2^48, lengths below 2^15: one sortable key
        key = (self.length.astype(np.int64) << 48) + self.rank
        at = np.searchsorted(key, (length.astype(np.int64) << 48) + rank, side="right") - 1
        over = rank - self.rank[at]
        return self.first[at] + over // self.per_bin[at], self.offset[at] + over % self.per_bin[at] * length


def plan_packing(counts: dict[int, int], capacity: int = CAPACITY) -> Plan:
    """Large-item matching, then best fit decreasing, on the counts of each length."""
    left = np.zeros(capacity + 1, np.int64)
    for length, n in counts.items():
        left[length] = n
    used = np.zeros(capacity + 1, np.int64)
    segments: list[tuple[int, int, int, int, int]] = []
    runs: list[tuple[int, int, int]] = []  # gap, first sequence, number of sequences
    sequences = 0

    def put(length: int, n: int, first: int, per_bin: int, offset: int) -> None:
        segments.append((length, int(used[length]), first, per_bin, offset))
        used[length] += n
        left[length] -= n

    third = capacity // 3
    for length in range(capacity, third, -1):
        while left[length]:
            mate = min(capacity - length, length)
            while mate > third and (left[mate] == 0 or (mate == length and left[mate] < 2)):
                mate -= 1
            if mate <= third:  # no partner is left: alone
                n = int(left[length])
                put(length, n, sequences, 1, 0)
                gap = capacity - length
            elif mate == length:
                n = int(left[length]) // 2
                put(length, 2 * n, sequences, 2, 0)
                gap = capacity - 2 * length
            else:
                n = int(min(left[length], left[mate]))
                put(length, n, sequences, 1, 0)
                put(mate, n, sequences, 1, length)
                gap = capacity - length - mate
            if gap:
                runs.append((gap, sequences, n))
            sequences += n

    by_gap: dict[int, list[tuple[int, int]]] = {}
    for gap, first, n in runs:
        by_gap.setdefault(gap, []).append((first, n))
    for length in range(third, 0, -1):
        gap = length
        while left[length]:
            while gap <= capacity and not by_gap.get(gap):
                gap += 1
            if gap > capacity:  # nothing holds it: open as many sequences as needed
                per = capacity // length
                n = -(-int(left[length]) // per)
                by_gap.setdefault(capacity, []).append((sequences, n))
                sequences += n
                gap = capacity
            first, n = by_gap[gap].pop()
            per = gap // length
            full = min(n, int(left[length]) // per)
            if full:
                put(length, full * per, first, per, capacity - gap)
                if gap - per * length:
                    by_gap.setdefault(gap - per * length, []).append((first, full))
            if full < n:
                rest = int(left[length])  # fewer than a sequence takes
                if rest:
                    put(length, rest, first + full, rest, capacity - gap)
                    by_gap.setdefault(gap - rest * length, []).append((first + full, 1))
                    full += 1
                if full < n:
                    by_gap.setdefault(gap, []).append((first + full, n - full))
    table = np.array(sorted(segments), np.int64).reshape(-1, 5)
    return Plan(*table.T, sequences)


def pack(items: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Adds sequence_id and offset to ``items`` (doc_id, piece, start, length, ids_crc32), which is
    read several times: pass a materialised table."""
    counts = {r["length"]: r["n"] for r in items.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most capacity rows
    plan = plan_packing(counts, capacity)
    salts = max(256, -(-max(counts.values(), default=0) // RANKED))  # the most frequent length decides
    salted = items.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)).cast("int"))
    before = salted.groupBy("length", "_salt").agg(F.count(F.lit(1)).alias("_n"))
    before = before.select("length", "_salt", (F.sum("_n").over(W.partitionBy("length").orderBy("_salt")) - F.col("_n")).alias("_before"))
    ranked = salted.withColumn("_in", F.row_number().over(W.partitionBy("length", "_salt").orderBy("doc_id", "piece", "ids_crc32")) - 1)
    ranked = ranked.join(before, ["length", "_salt"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("_before") + F.col("_in")).alias("_rank"))
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"

    def run(batches):
        for b in batches:
            seq, off = plan.place(b.column("length").to_numpy(), b.column("_rank").to_numpy())
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")), pa.array(seq, pa.int64()), pa.array(off, pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(run, schema)


def pack_documents(docs: DataFrame, json_path: str, ranks_path: str | None = None, capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """Tokenize ``docs``, cut what exceeds the capacity, and place every piece."""
    return pack(materialize(pieces(docs, json_path, ranks_path, capacity, end_id), "pieces"), capacity)
