"""Vectorised words, word hashes and shingle hashes over whole texts.

Texts are handled as UTF-8 bytes laid end to end.  A word is a maximal run of
bytes other than space and 0x09-0x0D, which is the same set of words that the
pattern ``[^\\x20\\x09-\\x0D]+`` finds in the decoded text.

A word's hash takes its bytes in lanes of eight, each followed by a bijective
scrambling: words of one length up to eight bytes never collide, longer ones
have no structure in which they do.  Words of more than ``LANES`` bytes are
hashed by blake2b.  Every hash has a ``key``; hashes of different keys are
independent, so two of them identify words by 128 bits.  All arithmetic is
modulo 2**64, so every function gives the same values on every machine.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np

PIECE = 1 << 19  # bytes hashed at once; longer texts are cut at white space
LANES = 64  # bytes of a word that are hashed by lanes
FIRST, SECOND = 0x243F6A8885A308D3, 0x13198A2E03707344  # keys of two independent hashes
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32

_BASES = {FIRST: 0x9E3779B97F4A7C15, SECOND: 0xBF58476D1CE4E5B9}  # odd, so they have inverses


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xC2B2AE3D27D4EB4F)
    x ^= x >> np.uint64(32)
    return x


_tables: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    have = _tables.get(base)
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        with np.errstate(over="ignore"):
            out = np.full(size, base, np.uint64)
            out[0] = 1
            np.multiply.accumulate(out, out=out)
        _tables[base] = have = out
    return have[:n]


def span_sums(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, key: int = FIRST) -> np.ndarray:
    """Position-free polynomial hash of ``values[start:end]`` for every span; each key has a base of its own."""
    n = len(values)
    base = _BASES[key]
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(values * _powers(base, n), out=total[1:])
    return (total[ends] - total[starts]) * _powers(pow(base, -1, 1 << 64), n + 1)[starts]


def find_words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of every word, and for every text the index of its first word (one more at the end)."""
    inside = ~_SPACE[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    cuts = offsets[:-1][offsets[:-1] < len(data)]
    first[cuts] = inside[cuts]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    back = offsets[1:][offsets[1:] > 0] - 1
    last[back] = inside[back]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def _pieces(data: np.ndarray) -> Iterator[np.ndarray]:
    """A long text in pieces that end at white space, or whole where it has none."""
    at = 0
    while at < len(data):
        end = min(len(data), at + PIECE)
        while end < len(data):
            spaces = np.flatnonzero(_SPACE[data[at:end]])
            if len(spaces):
                end = at + int(spaces[-1]) + 1
                break
            end = min(len(data), end + PIECE)
        yield data[at:end]
        at = end


def hash_words(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, key: int = FIRST) -> np.ndarray:
    """64-bit hashes of the words ``data[start:end]``."""
    size = (ends - starts).astype(np.int64)
    lanes = np.ndarray(len(data) + 1, "<u8", np.concatenate([data, np.zeros(8, np.uint8)]).tobytes(), strides=(1,))
    out = mix(size.astype(np.uint64) * np.uint64(0x9FB21C651E98DF25) + np.uint64(key))
    todo, at = np.arange(len(size)), starts
    for k in range(0, LANES, 8):
        left = size[todo] - k
        lane = lanes[at[todo] + k]
        short = np.maximum(8 - left, 0).astype(np.uint64) * np.uint64(8)
        lane &= np.uint64(0xFFFFFFFFFFFFFFFF) >> short
        out[todo] = mix(out[todo] ^ lane)
        todo = todo[left > 8]
        if not len(todo):
            break
    for k in np.flatnonzero(size > LANES).tolist():
        raw = hashlib.blake2b(data[starts[k] : ends[k]].tobytes(), digest_size=8, key=key.to_bytes(8, "little")).digest()
        out[k] = int.from_bytes(raw, "little")
    return out


def word_hashes(texts: list, lower: bool = False, keys: tuple[int, ...] = (FIRST,)) -> Iterator[tuple]:
    """Blocks of texts as (first index, one past the last, hashes of all their words for each key, index of each text's first word).

    ``texts`` holds bytes or None (no words).  A block has about PIECE bytes, or one longer text.
    """
    at = 0
    while at < len(texts):
        end, size = at, 0
        while end < len(texts) and (end == at or size + len(texts[end] or b"") <= PIECE):
            size += len(texts[end] or b"")
            end += 1
        raw = [x or b"" for x in texts[at:end]]
        data = np.frombuffer(b"".join(raw), np.uint8)
        if lower:
            data = _LOWER[data]
        if end - at == 1 and size > PIECE:
            parts: list[list[np.ndarray]] = [[np.zeros(0, np.uint64)] for _ in keys]
            for piece in _pieces(data):
                s, e, _ = find_words(piece, np.array([0, len(piece)]))
                for part, key in zip(parts, keys, strict=True):
                    part.append(hash_words(piece, s, e, key))
            hashes = [np.concatenate(p) for p in parts]
            yield at, end, *hashes, np.array([0, len(hashes[0])])
        else:
            offsets = np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)
            s, e, bounds = find_words(data, offsets)
            yield at, end, *(hash_words(data, s, e, key) for key in keys), bounds
        at = end


def gram_hashes(words: np.ndarray, n: int, key: int = FIRST) -> np.ndarray:
    """Hash of every n consecutive words (over all of ``words``: the caller drops those that cross texts)."""
    if len(words) < n:
        return np.zeros(0, np.uint64)
    out = np.zeros(len(words) - n + 1, np.uint64)
    for k in range(n):
        out *= np.uint64(_BASES[key])
        out ^= out >> np.uint64(29)
        out += words[k : len(words) - n + 1 + k]
    return mix(out)


def shingle_sets(words: np.ndarray, bounds: np.ndarray, n: int = 5) -> Iterator[np.ndarray]:
    """For every text its sorted distinct n-word shingles; with fewer words the whole sequence as one, with none an empty set."""
    grams = gram_hashes(words, n)
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a >= n:
            yield np.unique(grams[a : b - n + 1])
        elif b > a:
            yield mix(span_sums(words[a:b], np.array([0]), np.array([b - a])) + np.uint64(b - a))
        else:
            yield np.zeros(0, np.uint64)


def shingle_digests(words: np.ndarray, others: np.ndarray, bounds: np.ndarray, n: int = 5) -> Iterator[tuple[np.ndarray, int, int]]:
    """The sets of ``shingle_sets`` from the words' first hashes, each with two 64-bit digests of it under independent keys."""
    one, two = gram_hashes(words, n), gram_hashes(others, n, SECOND)
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a >= n:
            found, at = np.unique(one[a : b - n + 1], return_index=True)
            second = two[a : b - n + 1][at]
        else:
            at, size = np.arange(1 if b > a else 0), np.uint64(b - a)
            found, second = (mix(span_sums(w[a:b], at, at + (b - a), key) + size) for w, key in ((words, FIRST), (others, SECOND)))
        yield found, int(found.sum(dtype=np.uint64).view(np.int64)), int(np.bitwise_xor.reduce(second * (second | np.uint64(1)), initial=np.uint64(0)).view(np.int64))
