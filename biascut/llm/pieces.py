"""SentencePiece encoding and decoding with a streaming Viterbi.

The lattice of vocabulary pieces over the text is walked left to right.  Each position keeps one
surviving backpointer: for unigram models that of the best score; for merge (BPE) models that of
the one piece whose neighbours are compatible (an encoding is the model's own exactly when every
adjacent pair of pieces encodes to itself), so the ids are those of the model's merge order.  Only
a window behind the current position can still change, bounded by the longest piece.  Whenever the
surviving paths converge on one boundary, the ids before it are committed and forgotten: at once
where no piece reaches beyond the current position, and by a walk back through the window where it
has grown long.

Every text goes through this one walk.  Boundaries that no piece can span (before a run of space
marks, around characters that stand in no longer piece) are convergence points known in advance, so
what the walk commits between two of them depends on that stretch alone; a bounded memory by stretch
spares walking a word again.

Normalisation: ``identity`` models with a dummy prefix (spaces become the mark U+2581).  Characters
outside the vocabulary become their UTF-8 bytes' pieces where the model has them, else its unknown id.

Defined cases: null and empty texts have no ids and decode to the empty text; rows repeating a
doc_id are encoded each on its own.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidy, worker_state

MARK = "▁"
_MEMO = 350_000
_PAIRS = 1_000_000


class Generations(dict):
    """A bounded memory in two generations: what the older one still knows is taken over on use, and
    what neither knows is made."""

    def __init__(self, most: int, make):
        super().__init__()
        self.most, self.make, self.old = most, make, {}

    def __missing__(self, key):
        got = self.old.get(key)
        if got is None:
            got = self.make(key)
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        self[key] = got
        return got


class PieceModel:
    """Pieces, scores and kinds of a serialised model file."""

    def __init__(self, path: str):
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        with open(path, "rb") as f:
            proto.ParseFromString(f.read())
        if proto.normalizer_spec.name != "identity" or proto.normalizer_spec.remove_extra_whitespaces:
            raise ValueError("only identity normalisation is supported")
        self.prefix = proto.normalizer_spec.add_dummy_prefix
        self.merges = proto.trainer_spec.model_type == 2
        self.piece = [p.piece for p in proto.pieces]
        kind = [p.type for p in proto.pieces]
        self.control = {k for k, t in enumerate(kind) if t == 3}
        self.unknown = next(k for k, t in enumerate(kind) if t == 2)
        self.bytes = {int(p[3:5], 16): k for k, (p, t) in enumerate(zip(self.piece, kind)) if t == 6}
        self.byte_of = {k: b for b, k in self.bytes.items()}
        self.ids = {p: k for k, (p, t) in enumerate(zip(self.piece, kind)) if t in (1, 4)}
        self.score = {p: proto.pieces[k].score for p, k in self.ids.items()}
        self.id_score = [p.score for p in proto.pieces]
        self.unknown_score = min(self.score.values(), default=0.0) - 10
        self.longest = max(map(len, self.ids), default=1)
        #: pieces by characters: a node is (id or -1, its next characters)
        self.trie: dict = {}
        for p, k in self.ids.items():
            at, node = self.trie, None
            for c in p:
                node = at.setdefault(c, [-1, {}])
                at = node[1]
            node[0] = k
        #: each id's text, where it does not depend on its neighbours
        self.text = [None if k in self.byte_of and self.byte_of[k] > 127 else chr(self.byte_of[k]) if k in self.byte_of else "" if k in self.control else " ⁇ " if k == self.unknown else p.replace(MARK, " ") for k, p in enumerate(self.piece)]
        joined = {c for p in self.ids if len(p) > 1 for c in p}
        alone = "".join(c for c in "\n\t\r" if c not in joined)
        self.splits = all(MARK not in p.lstrip(MARK) for p in self.ids)
        gap = re.escape(alone)
        self.stretch = re.compile(f"{MARK}+[^{MARK}{gap}]*|[^{MARK}{gap}]+|[{gap or MARK}]") if self.splits else re.compile(r"(?s).+")

    def char_ids(self, char: str) -> list[int]:
        """Ids of a character outside the vocabulary."""
        if self.bytes:
            return [self.bytes[b] for b in char.encode("utf-8")]
        return [self.unknown]


class Encoder:
    """Streaming Viterbi over one model; keeps bounded memories of stretches and piece pairs."""

    def __init__(self, model: PieceModel, check_every: int = 64):
        self.m, self.check_every = model, check_every
        self._memo = Generations(_MEMO, lambda part: self.short(part) if model.merges and len(part) <= check_every else [k for ids in self.stream(part) for k in ids])
        self._pairs = Generations(_PAIRS, lambda pair: self.keeps(*pair))
        self._joints = Generations(_PAIRS, lambda ids: self.keeps(model.piece[ids >> 20], model.piece[ids & 0xFFFFF]))
        self.widest = 0  # the largest window so far
        self.walked = 0  # characters that the walk went over

    def merge(self, text: str) -> list[str]:
        """Pieces of a short text by the merge order itself: best score first, then leftmost."""
        parts = list(text)
        return parts if self._merged(parts, 0) else []

    def keeps(self, left: str, right: str) -> bool:
        """Whether the merge order leaves two pieces side by side as they are."""
        parts = list(left + right)
        return self._merged(parts, len(left)) and len(parts) == 2

    def _merged(self, parts: list[str], border: int) -> bool:
        """Merges ``parts`` in place; false as soon as a merge crosses the border before part ``border`` (0: none)."""
        get, none = self.m.score.get, float("-inf")
        scores = [get(a + b, none) for a, b in zip(parts, parts[1:])]
        while scores and (best := max(scores)) > none:
            at = scores.index(best)  # the leftmost
            if at < border:
                border -= 1
                if at == border:
                    return False
            parts[at] += parts.pop(at + 1)
            del scores[at]
            if at:
                scores[at - 1] = get(parts[at - 1] + parts[at], none)
            if at < len(scores):
                scores[at] = get(parts[at] + parts[at + 1], none)
        return True

    def compatible(self, left: str, right: str) -> bool:
        return self._pairs[left, right]

    def _joins(self, before: int, begin: int, piece: int, text: str, j: int, k: int) -> bool:
        """Whether a merge model puts the piece at [j, k) after the one at [begin, j)."""
        if before >= 0 and piece >= 0:
            return self._joints[before << 20 | piece]
        return self._pairs[text[begin:j], text[j:k]]

    def stream(self, text: str):
        """Yields lists of committed ids; the window behind the last commit stays short.

        back[p] = (where the surviving piece that ends at p begins, its id or -1 for a character
        outside the vocabulary); far is the furthest end of any piece so far."""
        m, n, trie = self.m, len(text), self.m.trie
        merges, score, worst, joints = m.merges, m.id_score, m.unknown_score, self._joints
        back: dict[int, tuple[int, int]] = {}
        value = {0: 0.0}
        committed, far, due = 0, 0, self.check_every
        self.walked += n
        for j in range(n):
            if j == far and j:  # no piece reaches further: all paths pass here
                yield self._path(text, back, committed, j)
                back, committed, due = {j: back[j]}, j, j + self.check_every
                if not merges:
                    value = {j: value[j]}
            got = back.get(j)
            if got is None and j:
                continue
            begin, before = got or (0, -1)
            node, k = trie.get(text[j]), j + 1
            t = node[0] if node is not None else -1
            while True:
                if t >= 0 or k == j + 1:
                    if merges:
                        if k not in back and (not j or (joints[before << 20 | t] if before >= 0 and t >= 0 else self._joins(before, begin, t, text, j, k))):
                            back[k] = j, t
                            far = k if k > far else far
                    else:
                        v = value[j] + (score[t] if t >= 0 else worst)
                        if k not in back or v > value[k]:
                            back[k], value[k] = (j, t), v
                            far = k if k > far else far
                if node is None or k == n:
                    break
                node = node[1].get(text[k])
                if node is None:
                    break
                t, k = node[0], k + 1
            if j >= due:
                self.widest = max(self.widest, len(back))
                meet = self._meeting(back, committed, j + 1)
                if meet > committed:
                    yield self._path(text, back, committed, meet)
                    back = {p: x for p, x in back.items() if p >= meet}
                    value = {p: v for p, v in value.items() if p >= meet}
                    committed = meet
                due = j + 16
        if n > committed:
            yield self._path(text, back, committed, n)

    def short(self, text: str) -> list[int]:
        """``stream`` of a merge model over a stretch that its window holds whole: nothing is committed before
        the end, so backpointers stand in two lists."""
        n, trie, joints = len(text), self.m.trie, self._joints
        start, piece = [-1] * (n + 1), [-1] * (n + 1)
        start[0] = 0
        self.walked += n
        for j in range(n):
            begin = start[j]
            if begin < 0:
                continue
            before, k, node = piece[j], j + 1, trie.get(text[j])
            t = node[0] if node is not None else -1
            # one character alone always counts, in the vocabulary or not
            if start[k] < 0 and (not j or (joints[before << 20 | t] if before >= 0 and t >= 0 else self._joins(before, begin, t, text, j, k))):
                start[k], piece[k] = j, t
            if node is None:
                continue
            if j and before >= 0:
                high = before << 20
                while k < n:
                    node = node[1].get(text[k])
                    if node is None:
                        break
                    t, k = node[0], k + 1
                    if t >= 0 and start[k] < 0 and joints[high | t]:
                        start[k], piece[k] = j, t
            else:
                while k < n:
                    node = node[1].get(text[k])
                    if node is None:
                        break
                    t, k = node[0], k + 1
                    if t >= 0 and start[k] < 0 and (not j or self._joins(before, begin, t, text, j, k)):
                        start[k], piece[k] = j, t
        out, end = [], n
        while end > 0:
            begin, t = start[end], piece[end]
            if t >= 0:
                out.append(t)
            else:
                out += self.m.char_ids(text[begin:end])[::-1]
            end = begin
        out.reverse()
        return out

    def _meeting(self, back: dict[int, tuple[int, int]], committed: int, now: int) -> int:
        """The boundary that every surviving path from positions at or after ``now`` passes."""
        # positions up to now may still start pieces: they are alive as well
        alive = {p for p in back if now - self.m.longest < p}
        while len(alive) > 1:
            p = max(alive)
            alive.discard(p)
            alive.add(back[p][0] if p > committed else committed)
        return max(alive.pop() if alive else committed, committed)

    def _path(self, text: str, back: dict[int, tuple[int, int]], start: int, end: int) -> list[int]:
        out: list[int] = []
        while end > start:
            begin, t = back[end]
            out += (t,) if t >= 0 else self.m.char_ids(text[begin:end])[::-1]
            end = begin
        return out[::-1]

    def marked(self, text: str) -> str:
        text = text.replace(" ", MARK)
        return MARK + text if self.m.prefix else text

    def encode(self, text: str | None) -> list[int]:
        if not text:
            return []
        parts = self.m.stretch.findall(self.marked(text))
        memo = self._memo.__getitem__
        if len(max(parts, key=len)) > 64:  # long stretches do not repeat: they are not memorised
            return [k for p in parts for k in (memo(p) if len(p) <= 64 else chain.from_iterable(self.stream(p)))]
        return list(chain.from_iterable(map(memo, parts)))

    def decode(self, ids) -> str:
        """Pieces joined, byte runs as UTF-8 (invalid ones as U+FFFD), the dummy prefix removed."""
        try:
            text = "".join(map(self.m.text.__getitem__, ids))
            return text[1:] if self.m.prefix and text.startswith(" ") else text
        except TypeError:  # a byte of a longer character: bytes have to be gathered
            pass
        out, held = [], bytearray()
        for k in ids:
            b = self.m.byte_of.get(k)
            if b is not None:
                held.append(b)
                continue
            if held:
                out.append(held.decode("utf-8", "replace"))
                held = bytearray()
            if k not in self.m.control:
                out.append(" ⁇ " if k == self.m.unknown else self.m.piece[k])
        if held:
            out.append(held.decode("utf-8", "replace"))
        text = "".join(out).replace(MARK, " ")
        return text[1:] if self.m.prefix and text.startswith(" ") else text


def encoder(path: str) -> Encoder:
    return worker_state(__name__, path, lambda: Encoder(PieceModel(path)))


def encode(docs: DataFrame, path: str, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (doc_id by default) and ids array<int>."""
    keep = keep or ["doc_id"]
    source = docs.select(F.col("text").cast("string").alias("_text"), *keep)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[1:]) + ", ids array<int>"

    def run(batches):
        e = encoder(path)
        for b in batches:
            for s in range(0, b.num_rows, 256):
                c = b.slice(s, 256)
                yield pa.RecordBatch.from_arrays([*(c.column(k) for k in range(1, c.num_columns)), pa.array([e.encode(t) for t in c.column(0).to_pylist()], pa.list_(pa.int32()))], names=[*keep, "ids"])

    return source.mapInArrow(tidy(run), schema)


def decode(encoded: DataFrame, path: str, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns (doc_id by default) and text, from ids."""
    keep = keep or ["doc_id"]
    source = encoded.select(F.col("ids").cast("array<int>").alias("_ids"), *keep)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[1:]) + ", text string"

    def run(batches):
        e = encoder(path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(1, b.num_columns)), pa.array([e.decode(x or []) for x in b.column(0).to_pylist()], pa.string())], names=[*keep, "text"])

    return source.mapInArrow(tidy(run), schema)


def codec_report(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_ids, ids_crc32 (little-endian unsigned 32-bit ids), decoded_sha256, round_trip:
    whole texts encoded and decoded in one pass, without the ids travelling further."""

    def run(batches):
        e = encoder(path)
        for b in batches:
            texts = b.column(1).to_pylist()
            n, crc, sha, same = [], [], [], []
            for t in texts:
                ids = e.encode(t)
                back = e.decode(ids)
                n.append(len(ids))
                crc.append(zlib.crc32(np.array(ids, "<u4").tobytes()))
                sha.append(hashlib.sha256(back.encode()).hexdigest())
                same.append(back == (t or ""))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(crc, pa.int64()), pa.array(sha, pa.string()), pa.array(same, pa.bool_())], names=["doc_id", "n_ids", "ids_crc32", "decoded_sha256", "round_trip"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), "doc_id long, n_ids long, ids_crc32 long, decoded_sha256 string, round_trip boolean")
