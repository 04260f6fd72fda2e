"""Document quality by a linear-chain conditional random field over lines.

Every line is good or bad.  A line's potential is linear in its own features
and those of the lines before and after it; a 2 x 2 table scores neighbouring
labels.  Forward-backward gives each line's chance of being good, and a
document's quality is their mean weighted by line length, rescaled so that
0.5 separates the labels best.  Labels exist for documents only: in training a
line has its document's label.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .frames import batches, documents_only, written
from .text_arrays import find_words, hash_words, mix

SAMPLE = 4000  # labelled rows that the model is fitted on at most; the bound of what the driver gathers
LIMIT = 0.7
_KINDS = 6
_CLASS = np.full(256, 5, np.uint8)  # other bytes: letters beyond ASCII
_CLASS[: 128] = 3
_CLASS[[9, 10, 11, 12, 13, 32]] = 4
_CLASS[65:91], _CLASS[97:123], _CLASS[48:58] = 0, 1, 2
_COMMON = np.zeros(256, bool)
_COMMON[[ord(c) for c in ".,;:?'-\"()"]] = True
N_OWN = 12


def line_features(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Features of every line of a text (lines x N_OWN) and the lines' lengths in bytes.  Blank lines are left out."""
    data = np.frombuffer(raw, np.uint8)
    cuts = np.flatnonzero(data == 10)
    begin, end = np.concatenate([[0], cuts + 1]), np.concatenate([cuts, [len(data)]])
    starts, ends, _ = find_words(data, np.array([0, len(data)]))
    first, last = np.searchsorted(starts, begin), np.searchsorted(starts, end)
    full = last > first
    begin, end, first, last = begin[full], end[full], first[full], last[full]
    if not len(begin):
        return np.zeros((0, N_OWN)), np.zeros(0)
    kind = _CLASS[data]
    share = []
    size = (end - begin).astype(float)
    for mask in (kind == 0, kind == 2, (kind == 3) & ~_COMMON[data], data == ord("|"), _COMMON[data]):
        total = np.concatenate([[0], np.cumsum(mask)])
        share.append((total[end] - total[begin]) / size)
    n = (last - first).astype(float)
    h = hash_words(data, starts, ends)
    at = np.zeros(len(h), bool)
    at[np.unique(h, return_index=True)[1]] = True
    fresh = np.concatenate([[0], np.cumsum(at)])
    new = (fresh[last] - fresh[first]) / n
    total = np.concatenate([[0], np.cumsum(ends - starts)])
    mean = (total[last] - total[first]) / n
    line = mix(np.add.reduceat(h, first))
    seen = np.ones(len(line))
    seen[np.unique(line, return_index=True)[1]] = 0
    whole = float(at.mean())
    stops = np.isin(data[end - 1], [ord("."), ord("?"), ord("!"), 13]).astype(float)
    columns = [*share, new, seen, np.log1p(size) / 8, np.log1p(n) / 6, np.log1p(mean) / 4, np.full(len(n), whole), stops]
    return np.stack(columns, axis=1), size


def with_neighbours(x: np.ndarray) -> np.ndarray:
    """A line's features, those of the line before and after (zero at the ends), and a constant."""
    zero = np.zeros((1, x.shape[1]))
    return np.concatenate([x, np.concatenate([zero, x[:-1]]), np.concatenate([x[1:], zero]), np.ones((len(x), 1))], axis=1)


def marginals(scores: np.ndarray, sizes: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Chances of good for all lines of many texts laid end to end, and expected counts of neighbouring labels.

    ``scores`` is the potential of good over bad for each line, ``table[a, b]`` that of label a before label b.
    Texts run side by side, the longest first.
    """
    order = np.argsort(-sizes, kind="stable")
    starts = (np.cumsum(sizes) - sizes)[order]
    size = sizes[order]
    longest = int(size[0]) if len(size) else 0
    active = np.searchsorted(-size, -np.arange(longest), side="left") if longest else np.zeros(0, int)
    e = np.exp(table)
    fwd, bwd = np.zeros(len(scores)), np.zeros(len(scores))  # log odds of good
    for t in range(longest):
        k = starts[: active[t]] + t
        if t == 0:
            fwd[k] = scores[k]
        else:
            g = 1 / (1 + np.exp(-np.clip(fwd[k - 1], -50, 50)))
            fwd[k] = scores[k] + np.log((g * e[1, 1] + (1 - g) * e[0, 1]) / (g * e[1, 0] + (1 - g) * e[0, 0]))
    for t in range(longest - 2, -1, -1):
        k = starts[: active[t + 1]] + t
        g = 1 / (1 + np.exp(-np.clip(bwd[k + 1] + scores[k + 1], -50, 50)))
        bwd[k] = np.log((g * e[1, 1] + (1 - g) * e[1, 0]) / (g * e[0, 1] + (1 - g) * e[0, 0]))
    p = 1 / (1 + np.exp(-np.clip(fwd + bwd, -50, 50)))
    pairs = np.zeros((2, 2))
    inner = np.ones(len(scores), bool)
    inner[np.cumsum(sizes)[sizes > 0] - 1] = False
    k = np.flatnonzero(inner)
    if len(k):
        a = 1 / (1 + np.exp(-np.clip(fwd[k], -50, 50)))
        b = 1 / (1 + np.exp(-np.clip(bwd[k + 1] + scores[k + 1], -50, 50)))
        m = np.stack([(1 - a) * (1 - b) * e[0, 0], (1 - a) * b * e[0, 1], a * (1 - b) * e[1, 0], a * b * e[1, 1]])
        pairs = (m / m.sum(axis=0)).sum(axis=1).reshape(2, 2)
    return p, pairs


def fit_chain(x: np.ndarray, sizes: np.ndarray, good: np.ndarray, ridge: float = 1.0, steps: int = 250) -> tuple[np.ndarray, np.ndarray]:
    """Weights and transition table by gradient steps on the penalised likelihood."""
    y = np.repeat(good, sizes).astype(float)
    w, table = np.zeros(x.shape[1]), np.zeros((2, 2))
    inner = sizes.astype(float) - 1
    seen = np.diag([inner[good == 0].clip(0).sum(), inner[good == 1].clip(0).sum()])
    n = max(len(y), 1)
    m = [np.zeros_like(w), np.zeros_like(w), np.zeros_like(table), np.zeros_like(table)]
    for step in range(1, steps + 1):
        p, pairs = marginals(x @ w, sizes, table)
        grads = (x.T @ (y - p) / n - ridge * w / n, (seen - pairs) / n - 0.02 * table)
        for k, (value, g) in enumerate(zip((w, table), grads, strict=True)):
            m[2 * k] = 0.9 * m[2 * k] + 0.1 * g
            m[2 * k + 1] = 0.999 * m[2 * k + 1] + 0.001 * g * g
            value += 0.1 * (m[2 * k] / (1 - 0.9**step)) / (np.sqrt(m[2 * k + 1] / (1 - 0.999**step)) + 1e-9)
    return w, table


def _weighted(p: np.ndarray, length: np.ndarray, sizes: np.ndarray, empty: float) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(p * length)])
    weight = np.concatenate([[0], np.cumsum(length)])
    end = np.cumsum(sizes)
    at = end - sizes
    span = weight[end] - weight[at]
    return np.where(span > 0, (total[end] - total[at]) / np.where(span > 0, span, 1), empty)


class LineQuality:
    def __init__(self, weights: np.ndarray, table: np.ndarray, scale: tuple[float, float], empty: float):
        self.weights, self.table, self.scale, self.empty = weights, table, scale, empty

    @classmethod
    def fit(cls, docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> LineQuality:
        """Fit on at most ``sample`` labelled rows, chosen by a hash of doc_id.  Without both labels the prior is all it knows.

        Rows that repeat a doc_id count once, with the least of their texts and the highest of their labels.
        """
        chosen = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where("doc_id is not null and quality is not null")
        chosen = chosen.groupBy("doc_id").agg(F.max("quality").alias("quality")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
        chosen = written(chosen, "labels")
        rows = documents_only(docs).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "quality").agg(F.min("text").cast("binary").alias("text"))

        def run(rows_):
            for batch in batches(rows_, 512):
                out = [line_features(t or b"") for t in batch.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([x.tobytes() for x, _ in out], pa.binary()), pa.array([s.tobytes() for _, s in out], pa.binary())], ["doc_id", "quality", "x", "length"])

        got = rows.mapInArrow(run, "doc_id long, quality int, x binary, length binary").orderBy("doc_id").collect()
        good = np.array([int(r["quality"] > 0) for r in got], int)
        prior = float(good.mean()) if len(good) else 0.5
        if len(set(good.tolist())) < 2:
            return cls(np.zeros(3 * N_OWN + 1), np.zeros((2, 2)), (0.0, 0.0), prior)
        lines = [np.frombuffer(r["x"]).reshape(-1, N_OWN) for r in got]
        length = np.concatenate([np.frombuffer(r["length"]) for r in got])
        sizes = np.array([len(v) for v in lines])
        x = np.concatenate([with_neighbours(v) for v in lines])
        w, table = fit_chain(x, sizes, good)
        mean = _weighted(marginals(x @ w, sizes, table)[0], length, sizes, prior)
        z = np.log((mean + 1e-3) / (1 - mean + 1e-3))
        a, b = 1.0, 0.0  # logistic rescaling of the weighted marginals
        for _ in range(50):
            p = 1 / (1 + np.exp(-(a * z + b)))
            g = np.array([((good - p) * z).sum() - 0.1 * (a - 1), (good - p).sum()])
            v = p * (1 - p)
            hess = np.array([[(v * z * z).sum() + 0.1, (v * z).sum()], [(v * z).sum(), v.sum() + 1e-6]])
            step = np.linalg.solve(hess, g)
            a, b = a + step[0], b + step[1]
        return cls(w, table, (float(max(a, 1e-3)), float(b)), prior)

    def score_texts(self, texts: list[bytes | None]) -> np.ndarray:
        parts = [line_features(t or b"") for t in texts]
        sizes = np.array([len(x) for x, _ in parts], int)
        x = np.concatenate([with_neighbours(v) if len(v) else np.zeros((0, len(self.weights))) for v, _ in parts]) if len(parts) else np.zeros((0, len(self.weights)))
        length = np.concatenate([s for _, s in parts]) if len(parts) else np.zeros(0)
        mean = _weighted(marginals(x @ self.weights, sizes, self.table)[0], length, sizes, self.empty)
        z = np.log((mean + 1e-3) / (1 - mean + 1e-3))
        return np.where(sizes > 0, 1 / (1 + np.exp(-(self.scale[0] * z + self.scale[1]))), self.empty)

    def score(self, docs: DataFrame, limit: float = LIMIT) -> DataFrame:
        """(doc_id, score, predicted) for every row with a doc_id; a null, empty or blank text gets the share of good labels.

        Repeated rows are scored each for itself, very long texts whole; extra columns play no part.
        """
        model = self

        def run(rows):
            for batch in batches(rows, 1024):
                s = model.score_texts(batch.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s), pa.array((s >= limit).astype(np.int32))], ["doc_id", "score", "predicted"])

        return documents_only(docs).select("doc_id", F.col("text").cast("binary").alias("text")).mapInArrow(run, "doc_id long, score double, predicted int")


def held_out(doc_id: str):
    return F.crc32(F.col(doc_id).cast("string")) % 4 == 2
