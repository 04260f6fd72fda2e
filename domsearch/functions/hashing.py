"""Families of min-wise hash functions.

``Portable`` can be recomputed by any SQL engine: a 31-bit hash from md5, then
affine maps modulo 2**31 - 1.  ``Native`` uses xxhash64 with a seed for each
function: 64 bits and no string digest, for production.
"""

from __future__ import annotations

import random
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2**31 - 1


def coefficients(m: int, seed: int = 1) -> list[tuple[int, int]]:
    draw = random.Random(seed)
    return [(draw.randrange(1, PRIME), draw.randrange(PRIME)) for _ in range(m)]


@dataclass(frozen=True)
class Portable:
    m: int = 64
    seed: int = 1
    low: int = 0
    span: int = PRIME

    def base(self, value: Column) -> Column:
        return F.conv(F.substring(F.md5(value.cast("string")), 1, 15), 16, 10).cast("bigint") % F.lit(PRIME)

    def functions(self, base: Column) -> list[Column]:
        return [(F.lit(a) * base + F.lit(b)) % F.lit(PRIME) for a, b in coefficients(self.m, self.seed)]


@dataclass(frozen=True)
class Native:
    m: int = 256
    seed: int = 1
    low: int = -(2**63)
    span: int = 2**64

    def base(self, value: Column) -> Column:
        return F.xxhash64(F.lit(self.seed), value.cast("string"))

    def functions(self, base: Column) -> list[Column]:
        return [F.xxhash64(base, F.lit(k)) for k in range(self.m)]


P1, P2, P3, P4, P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turned(x: np.ndarray, k: int) -> np.ndarray:
    return (x << np.uint64(k)) | (x >> np.uint64(64 - k))


def _ended(x: np.ndarray, spare: np.ndarray | None = None) -> np.ndarray:
    """The last step of xxhash64, in place."""
    x ^= np.right_shift(x, np.uint64(33), out=spare)
    x *= P2
    x ^= np.right_shift(x, np.uint64(29), out=spare)
    x *= P3
    x ^= np.right_shift(x, np.uint64(32), out=spare)
    return x


def hashed_int(k: int, seed: np.ndarray, out: np.ndarray | None = None, spare: np.ndarray | None = None) -> np.ndarray:
    """Spark's xxhash64 of one 32-bit number under many seeds."""
    x = np.add(seed, P5 + np.uint64(4), out=out)
    x ^= np.array([k & 0xFFFFFFFF], np.uint64) * P1
    y = np.right_shift(x, np.uint64(41), out=spare)
    x <<= np.uint64(23)
    x |= y
    x *= P2
    x += P3
    return _ended(x, y)


def hashed_long(values: np.ndarray, seed: int = 42) -> np.ndarray:
    """Spark's xxhash64 of 64-bit numbers."""
    x = _turned(values.astype(np.int64).view(np.uint64) * P2, 31) * P1 ^ (np.uint64(seed) + P5 + np.uint64(8))
    return _ended(_turned(x, 27) * P1 + P4)


def hashed_digits(values: np.ndarray, seed: np.uint64) -> np.ndarray:
    """Spark's xxhash64 of whole numbers as text, which has less than 32 bytes."""
    text = values.astype(np.int64).astype("S24")
    held = text.view(np.uint8).reshape(len(text), 24)
    width = (held != 0).sum(axis=1)
    out = np.empty(len(text), np.uint64)
    for n in np.unique(width).tolist():
        own = np.flatnonzero(width == n)
        some = np.ascontiguousarray(held[own])
        x = np.full(len(own), seed + P5 + np.uint64(n), np.uint64)
        at = 0
        while at + 8 <= n:
            x ^= _turned(np.ascontiguousarray(some[:, at : at + 8]).view(np.uint64).ravel() * P2, 31) * P1
            x = _turned(x, 27) * P1 + P4
            at += 8
        if at + 4 <= n:
            x ^= np.ascontiguousarray(some[:, at : at + 4]).view(np.uint32).ravel().astype(np.uint64) * P1
            x = _turned(x, 23) * P2 + P3
            at += 4
        for k in range(at, n):
            x ^= some[:, k].astype(np.uint64) * P5
            x = _turned(x, 11) * P1
        out[own] = _ended(x)
    return out


@dataclass(frozen=True)
class Vector:
    """The range of the 63-bit functions that ``vector_signatures`` evaluates by numpy."""

    m: int = 256
    seed: int = 1
    low: int = 0
    span: int = 2**63
