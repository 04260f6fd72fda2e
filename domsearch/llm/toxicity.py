"""Toxicity severity by cumulative-link ordinal regression over sparse text features.

Features are words and word beginnings, counted per document.  Grades 0 to 3
share one weight vector; ordered thresholds separate them:
P(grade <= k) = 1 / (1 + exp(w.x - t_k)).  The given labels only say toxic or
not, so toxic training rows are graded 1 to 3 by terciles of the mean evidence
of all their words, learned from the other half of the training rows: a grade
is no function of the features that the model gets, which are chosen on all
rows and lean to either side.  The output is the expected grade.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .frames import batches, documents_only, written

SAMPLE = 8000  # labelled rows that the model is fitted on at most; the bound of what the driver gathers
FEATURES = 600  # that lean to toxic rows; a sixth as many lean to the others
CLEAN_ROWS = 300  # clean rows that hold a feature of the latter kind at least
GRADES = 4
_WORD = re.compile(r"[^\W\d_]+")
_BEGINNINGS = (3, 4, 5, 6)


def features_of(word: str) -> list[str]:
    return [f"={word}", *(f"^{word[:n]}" for n in _BEGINNINGS if len(word) > n)]


class Counts:
    """Counts of the selected features in a text; remembers which words carry any."""

    def __init__(self, names: list[str], marking: int | None = None):
        self.index = {f: k for k, f in enumerate(names)}
        self.marking = len(names) if marking is None else marking  # of the features, the first ones mark toxic rows
        self.words: dict[str, tuple[int, ...]] = {}

    def __call__(self, text: str) -> tuple[dict[int, int], int, int]:
        """Counts by feature, words that carry a marking feature, all words."""
        out: dict[int, int] = {}
        words = Counter(_WORD.findall(text.lower()))
        hits = total = 0
        known = self.words
        for word, n in words.items():
            total += n
            found = known.get(word)
            if found is None:
                found = tuple(k for f in features_of(word) if (k := self.index.get(f)) is not None)
                if len(known) > 50_000:
                    known.clear()
                known[word] = found
            if found:
                hits += n * (min(found) < self.marking)
                for k in found:
                    out[k] = out.get(k, 0) + n
        return out, hits, total


def design(rows: list[tuple[dict[int, int], int, int]], n: int) -> np.ndarray:
    """Log counts of the features, of all words that carry a marking one, and of their density."""
    x = np.zeros((len(rows), n + 2))
    for k, (counts, hits, total) in enumerate(rows):
        if counts:
            x[k, list(counts)] = np.log1p(list(counts.values()))
            x[k, n:] = np.log1p(hits), np.log1p(1000 * hits / max(total, 1))
    return x


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def grade_chances(x: np.ndarray, weights: np.ndarray, thresholds: np.ndarray) -> np.ndarray:
    below = np.concatenate([np.zeros((len(x), 1)), _sigmoid(thresholds[None, :] - (x @ weights)[:, None]), np.ones((len(x), 1))], axis=1)
    return np.diff(below, axis=1)


def ordinal_gradient(weights: np.ndarray, first: float, gaps: np.ndarray, x: np.ndarray, y: np.ndarray, ridge: float) -> tuple[float, list[np.ndarray]]:
    """Mean penalised log likelihood of the grades, and its gradient.  Thresholds are ``first`` plus sums of exp(gaps)."""
    n, grades = max(len(y), 1), len(gaps) + 2
    thresholds = first + np.concatenate([[0.0], np.cumsum(np.exp(gaps))])
    edges = np.concatenate([[-np.inf], thresholds, [np.inf]])
    z = x @ weights
    upper, lower = _sigmoid(edges[y + 1] - z), _sigmoid(edges[y] - z)
    upper[y == grades - 1], lower[y == 0] = 1.0, 0.0
    p = np.maximum(upper - lower, 1e-12)
    du, dl = upper * (1 - upper) / p, lower * (1 - lower) / p
    to_t = np.array([du[y == k].sum() - dl[y == k + 1].sum() for k in range(grades - 1)])
    value = np.log(p).sum() / n - ridge * (weights @ weights) / 2 / n
    return value, [x.T @ (dl - du) / n - ridge * weights / n, to_t.sum() / n, np.array([to_t[k + 1 :].sum() * np.exp(gaps[k]) for k in range(grades - 2)]) / n]


def fit_ordinal(x: np.ndarray, y: np.ndarray, grades: int = GRADES, ridge: float = 1.0, steps: int = 400) -> tuple[np.ndarray, np.ndarray]:
    """Weights and ordered thresholds by gradient steps on the penalised likelihood; the same input gives the same model."""
    params = [np.zeros(x.shape[1]), np.array(0.0), np.zeros(grades - 2)]
    moments = [[np.zeros_like(p), np.zeros_like(p)] for p in params]
    for step in range(1, steps + 1):
        _, grad = ordinal_gradient(*params, x, y, ridge)
        for k, (m, v), g in zip(range(3), moments, grad, strict=True):
            m *= 0.9
            m += 0.1 * g
            v *= 0.999
            v += 0.001 * g * g
            params[k] = params[k] + 0.05 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-9)
    return params[0], params[1] + np.concatenate([[0.0], np.cumsum(np.exp(params[2]))])


class ToxicityModel:
    def __init__(self, names: list[str], marking: int, weights: np.ndarray, thresholds: np.ndarray):
        self.names, self.marking, self.weights, self.thresholds = names, marking, weights, thresholds

    @classmethod
    def fit(cls, docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, features: int = FEATURES) -> ToxicityModel:
        """Fit on at most ``sample`` labelled rows, chosen by a hash of doc_id.  Without toxic labels every grade is 0.

        Rows that repeat a doc_id count once, with the least of their texts and the highest of their labels.
        """
        chosen = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic is not null")
        chosen = chosen.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
        chosen = written(chosen, "labels")
        rows = documents_only(docs).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))
        rows = written(rows.select("doc_id", "text", "toxic"), "sample")

        rows = rows.withColumn("fold", (F.crc32(F.col("doc_id").cast("string")) % 2).cast("int"))

        def held(batch_rows):
            for batch in batches(batch_rows, 256):
                out = [[], [], [], []]
                for doc, text, t, fold in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                    found = {f for w in set(_WORD.findall((text or "").lower())) for f in features_of(w)}
                    for column, v in zip(out, (found, *([x] * len(found) for x in (int(t > 0), doc, fold))), strict=True):
                        column += v
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.string()), *(pa.array(x, pa.int64()) for x in out[1:])], ["feature", "toxic", "doc_id", "fold"])

        totals = {r["fold"]: (r["n"], r["t"]) for r in rows.groupBy("fold").agg(F.count("*").alias("n"), F.sum((F.col("toxic") > 0).cast("long")).alias("t")).collect()}
        n_all, n_toxic = (sum(v[k] for v in totals.values()) for k in (0, 1))
        if not n_toxic:
            return cls([], 0, np.zeros(2), np.arange(10.0, 10.0 + GRADES - 1))
        held_rows = written(rows.select("doc_id", "text", "toxic", "fold").mapInArrow(held, "feature string, toxic long, doc_id long, fold long"), "features")
        by_fold = held_rows.groupBy("feature", "fold").agg(F.sum("toxic").alias("t"), F.sum(1 - F.col("toxic")).alias("c"))
        seen = by_fold.groupBy("feature").agg(F.sum("t").alias("t"), F.sum("c").alias("c"))
        evidence = lambda n, t: F.log((F.col("t") + 0.5) / (t + 1)) - F.log((F.col("c") + 0.5) / (n - t + 1))
        odds = evidence(n_all, n_toxic)
        # a row's severity comes from the other half: mean evidence of its words there
        other = F.when(F.col("fold") == 0, evidence(*totals.get(0, (0, 0)))).otherwise(evidence(*totals.get(1, (0, 0))))
        other = by_fold.where("feature like '=%'").select("feature", (1 - F.col("fold")).alias("fold"), other.alias("e"))
        severity = held_rows.where("toxic > 0").join(other, ["feature", "fold"]).groupBy("doc_id").agg(F.avg("e").alias("severity"))
        # features that lean to toxic rows, then fewer and better known ones that lean to the others, by their evidence
        share = {1: F.col("t") / F.lit(n_toxic), -1: F.col("c") / F.lit(max(n_all - n_toxic, 1))}
        names, marking = [], 0
        for side, most, least in ((1, features, "t >= 3"), (-1, features // 6, f"c >= {CLEAN_ROWS}")):
            best = seen.withColumn("score", side * odds * share[side]).where(f"{least} and score > 0").orderBy(F.desc("score"), "feature").limit(most)
            names += [r["feature"] for r in best.select("feature").collect()]
            marking = marking or len(names)
        counts = Counts(names, marking)

        def counted(batch_rows):
            for batch in batches(batch_rows, 1024):
                out = [[], [], [], [], []]
                for text, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    c, hits, total = counts(text or "")
                    for column, v in zip(out, (int(t > 0), list(c), list(c.values()), hits, total), strict=True):
                        column.append(v)
                lists = (pa.array(x, pa.list_(pa.int64())) for x in out[1:3])
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), *lists, *(pa.array(x, pa.int64()) for x in out[3:]), batch.column(2)], ["toxic", "ids", "counts", "hits", "total", "severity"])

        graded = rows.join(severity, "doc_id", "left").orderBy("doc_id").select("text", "toxic", "severity")
        got = graded.mapInArrow(counted, "toxic long, ids array<long>, counts array<long>, hits long, total long, severity double").collect()
        data = [(dict(zip(r["ids"], r["counts"], strict=True)), r["hits"], r["total"]) for r in got]
        toxic = np.array([r["toxic"] for r in got])
        severities = np.array([-100.0 if r["severity"] is None else r["severity"] for r in got])
        cuts = np.quantile(severities[toxic > 0], [1 / 3, 2 / 3])
        grade = np.where(toxic > 0, 1 + np.searchsorted(cuts, severities, side="left"), 0)
        weights, thresholds = fit_ordinal(design(data, len(names)), grade)
        return cls(names, marking, weights, thresholds)

    def score(self, docs: DataFrame) -> DataFrame:
        """(doc_id, severity, chance, grade, toxic) for every row with a doc_id; a null or empty text counts as no words.

        Repeated rows are scored each for itself, very long texts whole; extra columns play no part.
        """
        names, marking, weights, thresholds = self.names, self.marking, self.weights, self.thresholds

        def run(rows):
            counts = Counts(names, marking)
            for batch in batches(rows, 1024):
                x = design([counts(t or "") for t in batch.column(1).to_pylist()], len(names))
                p = grade_chances(x, weights, thresholds)
                chance = 1 - p[:, 0]
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p @ np.arange(p.shape[1])), pa.array(chance), pa.array(p.argmax(axis=1).astype(np.int32)), pa.array(chance >= 0.5)], ["doc_id", "severity", "chance", "grade", "toxic"])

        return documents_only(docs).mapInArrow(run, "doc_id long, severity double, chance double, grade int, toxic boolean")
