"""Hash families for MinHash: an affine one that SQL engines can reproduce, and the engine's own 64-bit hash."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


def affine_constants(m: int, seed: int = 1) -> list[tuple[int, int]]:
    """(a, b) with 0 < a < PRIME, from a multiplicative generator, so both engines can state them."""
    out, x = [], (seed * 48_271) % PRIME or 1
    for _ in range(m):
        pair = []
        for _ in range(2):
            x = x * 48_271 % PRIME
            pair.append(x)
        out.append((pair[0], pair[1]))
    return out


def hash_columns(member: Column, m: int, seed: int = 1, family: str = "affine") -> list[Column]:
    if family == "affine":
        return [F.pmod(F.lit(a) * F.pmod(member, F.lit(PRIME)) + F.lit(b), F.lit(PRIME)) for a, b in affine_constants(m, seed)]
    if family == "xx":
        return [F.xxhash64(F.lit(seed * 1_000 + i), member) for i in range(m)]
    raise ValueError(f"unknown hash family {family}")
