"""Replay-stable randomness: 4-wise independent vertex hashes and mixing coins of edges."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


def coefficients(seed: int, layer: int, shared: bool = False) -> tuple[int, int, int, int]:
    """Four field elements from the seed and the layer (one set for all layers if ``shared``)."""
    name = f"{seed}:{0 if shared else layer}"
    return tuple(int.from_bytes(hashlib.sha256(f"{name}:{j}".encode()).digest()[:8], "big") % PRIME for j in range(4))  # type: ignore[return-value]


def poly4(vid: Column, c0: Column | int, c1: Column | int, c2: Column | int, c3: Column | int) -> Column:
    """A cubic over the field of 2^31 - 1 elements; every product stays below 2^62."""
    p = F.lit(PRIME).cast("long")
    lit = lambda c: c.cast("long") if isinstance(c, Column) else F.lit(c).cast("long")
    x = vid.cast("long") % p
    h = (lit(c3) * x + lit(c2)) % p
    h = (h * x + lit(c1)) % p
    return (h * x + lit(c0)) % p


def poly4_int(vid: int, c: tuple[int, int, int, int]) -> int:
    x = vid % PRIME
    return (((c[3] * x + c[2]) % PRIME * x + c[1]) % PRIME * x + c[0]) % PRIME


def edge_word(eid: Column, tag: Column, kind: str = "md5") -> Column:
    """32 uniform bits of (edge, tag) as a long: md5 (portable) or xxhash64 (fast)."""
    if kind == "md5":
        return F.conv(F.substring(F.md5(F.concat_ws(":", eid, tag.cast("string"))), 1, 8), 16, 10).cast("long")
    return F.shiftrightunsigned(F.xxhash64(eid, tag), 32)


#: Coins of 32 bits that one digest holds.
DIGEST_WORDS = 4


def digest(eid: Column, block: int, seed: int) -> Column:
    """128 uniform bits of an edge as 32 hex digits: the coins of four layers at once."""
    return F.md5(F.concat_ws(":", eid, F.lit(block), F.lit(seed)))


def digest_word(digest: Column, slot: int) -> Column:
    """One of the digest's words, as hex digits: comparing them compares the numbers."""
    return F.substring(digest, 8 * slot + 1, 8)


def hex_threshold(probability: float) -> str:
    """What a word must stay below for a coin of that probability (below one)."""
    return f"{int(probability * (1 << 32)):08x}"


def below(word: Column, probability: Column) -> Column:
    """A coin of the given probability from 32 bits."""
    return word.cast("double") < probability * float(1 << 32)


def hash01(vid: Column, seed: int) -> Column:
    """A uniform number in [0, 1) of a vertex."""
    return edge_word(vid.cast("string"), F.lit(seed)).cast("double") / float(1 << 32)


def randomness_bits(layers: int) -> int:
    """Random bits of the vertex hashes of one sketch."""
    return layers * 4 * 31
