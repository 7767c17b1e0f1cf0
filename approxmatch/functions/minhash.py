"""Min-wise hashing of gram sets, with hash functions that any SQL engine with md5 can repeat."""

from __future__ import annotations

from hashlib import md5

from pyspark.sql import Column
from pyspark.sql import functions as F

from .text import let

PRIME = (1 << 31) - 1


def coefficients(hashes: int = 5, seed: int = 42) -> list[tuple[int, int]]:
    """(a, b) of each hash function, from md5 of the seed."""

    def draw(name: str, i: int, least: int) -> int:
        return least + int(md5(f"{seed}|{name}|{i}".encode(), usedforsecurity=False).hexdigest()[:8], 16) % (PRIME - least)

    return [(draw("a", i, 1), draw("b", i, 0)) for i in range(hashes)]


def gram_hash(gram: Column) -> Column:
    """The first 32 bits of md5 modulo the prime, so that products stay below 2^62."""
    return F.conv(F.substring(F.md5(gram.cast("binary")), 1, 8), 16, 10).cast("long") % PRIME


def minhash_signature(grams: Column, hashes: int = 5, seed: int = 42) -> Column:
    """array<bigint> of the least hash of the grams under each function; null for no grams."""
    hashed = F.transform(grams, gram_hash)
    return F.when(F.size(grams) > 0, let(hashed, lambda hs: F.array(*(F.array_min(_affine(hs, a, b)) for a, b in coefficients(hashes, seed)))))


def _affine(hs: Column, a: int, b: int) -> Column:
    return F.transform(hs, lambda h: (h * a + b) % PRIME)


def minhash_similarity(x: Column, y: Column) -> Column:
    """Share of agreeing positions."""
    same = F.zip_with(x, y, lambda a, b: (a == b).cast("int"))
    return F.aggregate(same, F.lit(0), lambda t, v: t + v).cast("double") / F.size(x)
