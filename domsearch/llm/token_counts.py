"""Token counts by a compiled finite-state tokenizer.

Two transducers work one after the other:

* a splitter over character classes marks where pre-tokens begin.  Its rule
  looks one character back and one ahead, so it is evaluated for all
  characters of a block at once;
* a byte-pair automaton, determinised on demand, runs over the bytes of every
  pre-token.  A state keeps, for each suffix of the bytes read that can still
  grow into a longer token, which token ended before that suffix and how many
  tokens fewer that prefix had.  A transition is annotated with the number of
  tokens that it adds (negative where bytes join into a longer token).  All
  pre-tokens of a block run side by side, one table lookup per byte.

Texts are cut into chunks, all of which run side by side.  What a chunk does is
a map from the state in which a pre-token stands at its begin to the state at
its end and the tokens emitted: the transitions up to its first pre-token, then
a count and a state that no longer depend on what came before.  Maps compose
associatively and are combined by a prefix scan, level by level.  A pre-token
of more than ``LONG`` bytes is encoded in pieces whose seams are mended: a
segmentation is the encoding if all neighbours in it can stand side by side.
"""

from __future__ import annotations

import json
import sys
import types
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .frames import batches, documents_only

BLOCK = 1 << 19  # characters run at once
CHUNK = 1 << 12  # characters of a chunk, which has a map of its own
CONTEXT = 8  # characters around a block that the splitter may look at
LONG = 96  # bytes of a pre-token beyond which it is encoded in pieces
PIECE = 32  # bytes of such a piece
MOST_STATES = 300_000  # compiled at most, which bounds the automaton's memory
_BIAS, _BITS = 96, 7


def _cache() -> dict:
    """A dictionary that outlives a task in a reused Python worker."""
    return sys.modules.setdefault("_domsearch_worker_cache", types.ModuleType("_domsearch_worker_cache")).__dict__


def byte_alphabet() -> dict[str, int]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


class PairAutomaton:
    """Deterministic transducer of a byte-pair vocabulary.

    A transition (state, byte) is a row of an open-addressing table; its value packs the next state and the emitted
    count.  Once MOST_STATES are compiled, no more are added: pre-tokens that leave the compiled part are counted by
    plain merging, so memory is bounded and counts stay exact (the same at every bound).
    """

    def __init__(self, merges: list[tuple[bytes, bytes]], alphabet: list[bytes]):
        self.rank = {pair: k for k, pair in enumerate(merges)}
        self.names = list(dict.fromkeys([*alphabet, *(a + b for a, b in merges)]))
        self.tokens = {t: k for k, t in enumerate(self.names)}
        self.stems = list(dict.fromkeys([b"", *(t[:k] for t in self.names for k in range(1, len(t)))]))
        self.inner = {t: k for k, t in enumerate(self.stems)}
        self.pairs: dict[int, bool] = {}
        self.merged: dict[bytes, int] = {}
        self.pieces: dict[bytes, list[bytes]] = {}
        self.states: dict[bytes, int] = {}
        self.packed: list[bytes] = []
        self.size, self.used = 1 << 18, 0
        self.cells, self.values = np.full(self.size, -1, np.int64), np.zeros(self.size, np.int32)
        self.start = self._id(((0, -1, 0),))

    def _id(self, key: tuple) -> int:
        raw = np.array(key, np.int32).tobytes()
        if (k := self.states.get(raw)) is None:
            k = self.states[raw] = len(self.packed)
            self.packed.append(raw)
        return k

    def encode(self, raw: bytes) -> list[bytes]:
        """The tokens of one pre-token by plain merging, lowest rank first."""
        parts = [raw[k : k + 1] for k in range(len(raw))]
        rank, none = self.rank, 1 << 60
        while len(parts) > 1:
            ranks = [rank.get(p, none) for p in zip(parts, parts[1:])]  # noqa: B905
            best = min(ranks)
            if best == none:
                break
            at = ranks.index(best)
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _follows(self, left: int, token: bytes, number: int) -> bool:
        """Whether plain merging can leave token ``left`` (-1: none) and ``token`` side by side."""
        key = (left + 1) << 32 | number
        if (ok := self.pairs.get(key)) is None:
            before = [self.names[left]] if left >= 0 else []
            ok = self.encode(b"".join(before) + token) == [*before, token]
            if len(self.pairs) > 500_000:
                self.pairs.clear()
            self.pairs[key] = ok
        return ok

    def _hash(self, cells: np.ndarray) -> np.ndarray:
        return ((cells.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(65 - self.size.bit_length())).astype(np.int64)

    def _put(self, cell: int, value: int) -> None:
        if 3 * self.used > self.size:
            old, values = self.cells, self.values
            self.size, self.used = 2 * self.size, 0
            self.cells, self.values = np.full(self.size, -1, np.int64), np.zeros(self.size, np.int32)
            for k in np.flatnonzero(old >= 0).tolist():
                self._put(int(old[k]), int(values[k]))
        at = int(self._hash(np.array([cell]))[0])
        while self.cells[at] >= 0:
            at = (at + 1) % self.size
        self.cells[at], self.values[at] = cell, value
        self.used += 1

    def look_up(self, cells: np.ndarray) -> np.ndarray:
        """Packed values of transitions, -1 where one isn't compiled."""
        at = self._hash(cells)
        found = self.cells.take(at)
        out = self.values.take(at)
        wrong = np.flatnonzero(found != cells)
        while wrong.size:
            out[wrong] = -1
            wrong = wrong[found[wrong] >= 0]
            at[wrong] = (at[wrong] + 1) % self.size
            found[wrong] = self.cells.take(at[wrong])
            hit = wrong[found[wrong] == cells[wrong]]
            out[hit] = self.values.take(at[hit])
            wrong = wrong[found[wrong] != cells[wrong]]
        return out

    def step(self, cell: int) -> int:
        """Compile one transition."""
        c, grown, last, more = bytes([cell & 255]), [], None, 0
        for stem, left, less in np.frombuffer(self.packed[cell >> 8], np.int32).reshape(-1, 3).tolist():
            longer = self.stems[stem] + c
            number = self.tokens.get(longer)
            if number is not None and last is None and self._follows(left, longer, number):
                last, more = number, less + 1
            if (k := self.inner.get(longer)) is not None:
                grown.append((k, left, less))
        if last is None or not -_BIAS <= more < (1 << _BITS) - _BIAS:
            raise ValueError("not a byte-pair vocabulary over all bytes")
        key = ((0, last, 0), *sorted((s, left, less - more) for s, left, less in grown))
        value = (self._id(key) << _BITS) | (more + _BIAS)
        self._put(cell, value)
        return value

    def _plain(self, raw: bytes) -> int:
        if (n := self.merged.get(raw)) is None:
            n = len(self.encode(raw))
            if len(self.merged) > 200_000:
                self.merged.clear()
            self.merged[raw] = n
        return n

    def long(self, raw: bytes) -> int:
        """Number of tokens of a long pre-token: pieces are encoded by themselves and mended where they meet."""
        out: list[bytes] = []
        fits = lambda a, b: self._follows(self.tokens[a], b, self.tokens[b])
        for k in range(0, len(raw), PIECE):
            piece = self._tokens(raw[k : k + PIECE])
            reach = 2
            while out and not fits(out[-1], piece[0]):
                left, right = out[-reach:], piece[:reach]
                middle = self.encode(b"".join(left + right))
                whole = (len(out) <= reach or fits(out[-reach - 1], middle[0])) and (len(piece) <= reach or fits(middle[-1], piece[reach]))
                if whole or (len(out) <= reach and len(piece) <= reach):
                    piece = middle + piece[reach:]
                    del out[-reach:]
                    break
                reach *= 2
            out += piece
        return len(out)

    def _tokens(self, raw: bytes) -> list[bytes]:
        if (found := self.pieces.get(raw)) is None:
            if len(self.pieces) > 50_000:
                self.pieces.clear()
            found = self.pieces[raw] = self.encode(raw)
        return list(found)

    def number_of(self, raw: bytes) -> int:
        return self.long(raw) if len(raw) > LONG else self._plain(raw)

    def walk(self, state: int, raw: bytes) -> tuple[int, int]:
        """State and tokens emitted after the bytes, or state -1 where the automaton is full."""
        total = 0
        for byte in raw:
            cell = state << 8 | byte
            v = int(self.look_up(np.array([cell]))[0])
            if v < 0:
                if len(self.packed) >= MOST_STATES:
                    return -1, 0
                v = self.step(cell)
            state, total = v >> _BITS, total + (v & ((1 << _BITS) - 1)) - _BIAS
        return state, total

    def run(self, data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Number of tokens of every pre-token ``data[start:start + size]`` and the state after it.

        The state is -1 for pre-tokens that are too long or left the automaton; those that are too long aren't counted.
        """
        out, after = np.zeros(len(starts), np.int64), np.full(len(starts), -1, np.int64)
        lanes = np.flatnonzero(sizes <= LONG)
        lanes = lanes[np.argsort(LONG - sizes[lanes].astype(np.uint8), kind="stable")]
        begin, size = starts[lanes], sizes[lanes]
        active = np.searchsorted(-size, -np.arange(LONG), side="left")
        state = np.full(len(lanes), self.start, np.int64)
        total = np.zeros(len(lanes), np.int32)
        plain = np.zeros(len(lanes), bool)
        for k, n in enumerate(active.tolist()):
            if not n:
                break
            cells = (state[:n] << 8) | data[begin[:n] + k]
            value = self.look_up(cells)
            if (missing := np.flatnonzero(value < 0)).size:
                for cell in np.unique(cells[missing]).tolist():
                    if len(self.packed) >= MOST_STATES:
                        break
                    self.step(cell)
                value[missing] = self.look_up(cells[missing])
                lost = missing[value[missing] < 0]
                plain[lost] = True
                value[lost] = self.start << _BITS | _BIAS
            state[:n] = value >> _BITS
            total[:n] += (value & ((1 << _BITS) - 1)) - _BIAS
        for k in np.flatnonzero(plain).tolist():
            total[k] = self._plain(data[begin[k] : begin[k] + size[k]].tobytes())
        out[lanes] = total
        after[lanes] = np.where(plain, -1, state)
        return out, after


_SPACE, _LETTER, _NUMBER, _OTHER, _NONE = range(5)


def character_classes() -> np.ndarray:
    """White space, letter, number or other, for every code point."""
    out = np.full(0x110000, _OTHER, np.uint8)
    for k in range(0x110000):
        kind = unicodedata.category(chr(k))[0]
        if kind in "LN":
            out[k] = _LETTER if kind == "L" else _NUMBER
    # fixed values: the code points with the property White_Space
    out[[*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]] = _SPACE
    return out


def pretoken_starts(points: np.ndarray, bounds: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """Mask of the code points at which a pre-token begins; texts are ``points[bounds[k]:bounds[k + 1]]``."""
    c = classes[points]
    first = bounds[:-1][np.diff(bounds) > 0]
    last = bounds[1:][np.diff(bounds) > 0] - 1
    before, after = np.empty_like(c), np.empty_like(c)
    before[1:], after[:-1] = c[:-1], c[1:]
    before[first], after[last] = _NONE, _NONE
    blank = points == 32
    joined = np.zeros(len(c), bool)
    joined[1:] = blank[:-1]
    joined[first] = False
    space = c == _SPACE
    out = np.where(space, (before != _SPACE) | ((after != _SPACE) & (after != _NONE)), (c != before) & ~joined)
    quote = np.flatnonzero(out & (points == 39))
    if len(quote):
        end = bounds[np.searchsorted(bounds, quote, side="right")]
        p = np.concatenate([points, np.zeros(3, points.dtype)])
        a, b = p[quote + 1], p[quote + 2]
        # fixed values: the contractions are 's 't 'm 'd and 're 've 'll
        one = np.isin(a, [ord(x) for x in "stmd"]) & (quote + 1 < end)
        two = (((b == ord("e")) & ((a == ord("r")) | (a == ord("v")))) | ((a == ord("l")) & (b == ord("l")))) & (quote + 2 < end)
        for hit, n in ((one, 1), (two & ~one, 2)):
            q, e = quote[hit], end[hit]
            out[q + 1] = False
            nxt = q + 1 + n
            nxt = nxt[nxt < e]
            out[nxt[c[nxt] != _SPACE]] = True
    return out


class ChunkMap:
    """What a chunk does: its transitions before the first pre-token that begins in it (``head``), and from there on,
    whatever came before, the tokens of whole pre-tokens and the last pre-token's bytes with state and tokens so far.

    Without a pre-token that begins in it (``count`` is None), a chunk is all head.
    """

    __slots__ = ("head", "count", "tail", "state", "open")

    def __init__(self, head: bytes, count: int | None = None, tail: bytes = b"", state: int = -1, open_: int = 0):
        self.head, self.count, self.tail, self.state, self.open = head, count, tail, state, open_

    def applied(self, automaton: PairAutomaton, tail: bytes, state: int, open_: int) -> tuple[bytes, int, int]:
        """The map of the head: an open pre-token after it, as (bytes, state, tokens so far)."""
        if not self.head:
            return tail, state, open_
        whole = tail + self.head
        if state >= 0 and len(whole) <= LONG:
            state, more = automaton.walk(state, self.head)
            return whole, state, open_ + more
        return whole, -1, 0

    def then(self, other: ChunkMap, automaton: PairAutomaton) -> ChunkMap:
        if self.count is None:
            return ChunkMap(self.head + other.head, other.count, other.tail, other.state, other.open)
        tail, state, open_ = other.applied(automaton, self.tail, self.state, self.open)
        if other.count is None:
            return ChunkMap(self.head, self.count, tail, state, open_)
        done = open_ if state >= 0 else automaton.number_of(tail)
        return ChunkMap(self.head, self.count + done + other.count, other.tail, other.state, other.open)

    def total(self, automaton: PairAutomaton) -> int:
        """Tokens of a whole text, whose first character begins a pre-token."""
        return self.count + (self.open if self.state >= 0 else automaton.number_of(self.tail)) if self.count is not None else 0


def scanned(maps: list[ChunkMap], automaton: PairAutomaton) -> ChunkMap:
    """All maps of a text as one, combined in pairs, level by level."""
    while len(maps) > 1:
        maps = [maps[k].then(maps[k + 1], automaton) if k + 1 < len(maps) else maps[k] for k in range(0, len(maps), 2)]
    return maps[0]


class Tokenizer:
    """Counts tokens as the vocabulary's own library does, special strings included."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_alphabet()
        raw = lambda s: bytes(letters[x] for x in s)
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in spec["model"]["merges"]]
        self.automaton = PairAutomaton([(raw(a), raw(b)) for a, b in pairs], [bytes([b]) for b in range(256)])
        self.special = [x["content"] for x in spec.get("added_tokens", [])]
        self.classes = character_classes()

    @classmethod
    def at(cls, path: str) -> Tokenizer:
        key = f"tokenizer:{path}"
        if key not in _cache():
            _cache()[key] = cls(path)
        return _cache()[key]

    def maps(self, windows: list[tuple[str, int, int]]) -> list[list[ChunkMap]]:
        """Maps of the chunks of some windows ``text[a:b]``, all run side by side."""
        texts = [t[max(a - CONTEXT, 0) : b + CONTEXT] for t, a, b in windows]
        points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
        data = np.frombuffer("".join(texts).encode("utf-8", "surrogatepass"), np.uint8)
        bounds = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
        begins = pretoken_starts(points, bounds, self.classes)
        if len(data) == len(points):
            place = np.arange(len(points) + 1)
        else:
            width = (1 + (points >= 0x80) + (points >= 0x800) + (points >= 0x10000)).astype(np.int64)
            place = np.concatenate([[0], np.cumsum(width)])
        low, high, owner = [], [], []
        for k, (_, a, b) in enumerate(windows):
            first = int(bounds[k]) + a - max(a - CONTEXT, 0)
            cuts = list(range(first, first + b - a, CHUNK))
            low += cuts
            high += [*cuts[1:], first + b - a]
            owner += [k] * len(cuts)
        low_, high_ = np.array(low, np.int64), np.array(high, np.int64)
        start = np.flatnonzero(begins)
        chunk = np.searchsorted(low_, start, side="right") - 1
        inside = (chunk >= 0) & (start < high_[np.maximum(chunk, 0)])  # the rest are context
        start, chunk = start[inside], chunk[inside]
        # a pre-token ends where the next begins, or is open at the end of its chunk
        last = np.append(chunk[1:] != chunk[:-1], True) if len(chunk) else np.zeros(0, bool)
        end = np.where(last, high_[chunk], np.append(start[1:], 0)) if len(chunk) else start
        at, size = place[start], place[end] - place[start]
        n, state = self.automaton.run(data, at, size)
        for k in np.flatnonzero(~last & (size > LONG)).tolist():
            n[k] = self.automaton.long(data[at[k] : at[k] + size[k]].tobytes())
        total = np.concatenate([[0], np.cumsum(np.where(last, 0, n))])
        edges = np.searchsorted(chunk, np.arange(len(low) + 1))
        out: list[list[ChunkMap]] = [[] for _ in windows]
        for k, (i, j) in enumerate(zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)):
            begin, stop = int(place[low_[k]]), int(place[high_[k]])
            if i == j:
                out[owner[k]].append(ChunkMap(data[begin:stop].tobytes()))
                continue
            head = data[begin : at[i]].tobytes()
            out[owner[k]].append(ChunkMap(head, int(total[j] - total[i]), data[at[j - 1] : stop].tobytes(), int(state[j - 1]), int(n[j - 1])))
        return out

    def counts(self, texts: list[str | None]) -> np.ndarray:
        out = np.zeros(len(texts), np.int64)
        parts: list[tuple[int, str]] = []
        for k, text in enumerate(texts):
            pieces = [text or ""]
            for s in self.special:
                if s in pieces[0] or len(pieces) > 1:
                    split = [p.split(s) for p in pieces]
                    out[k] += sum(len(p) - 1 for p in split)
                    pieces = [x for p in split for x in p]
            parts += [(k, p) for p in pieces if p]
        held: list[tuple[int, str, int, int]] = []
        found: list[list[ChunkMap]] = [[] for _ in parts]

        def flush() -> None:
            for (k, *_), maps in zip(held, self.maps([w[1:] for w in held]), strict=True):
                found[k] += maps
            held.clear()

        size = 0
        for k, (_, p) in enumerate(parts):
            for a in range(0, len(p), BLOCK):
                b = min(a + BLOCK, len(p))
                if held and size + b - a > BLOCK:
                    flush()
                    size = 0
                held.append((k, p, a, b))
                size += b - a
        flush()
        for (k, _), maps in zip(parts, found, strict=True):
            out[k] += scanned(maps, self.automaton).total(self.automaton)
        return out


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 512) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every row with a doc_id; an empty table gives none.

    ``vocabulary`` is the path of a byte-level byte-pair file that every executor can open.  A null text counts as
    empty (no bytes, no tokens); repeated rows are counted each for itself; extra columns play no part.  Very long
    texts are counted whole, chunk by chunk.
    """

    def run(rows):
        tokenizer = Tokenizer.at(vocabulary)
        for batch in batches(rows, 1024):
            texts = batch.column(1).to_pylist()
            n = tokenizer.counts(texts)
            size = np.array([len((t or "").encode()) for t in texts], np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size), pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return documents_only(docs).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
