"""Substring dedup over a log-structured fingerprint index.

A window is ``width`` consecutive words of one document.  Windows are grouped
under anchors: the smallest hash among the grams of ``gram`` words inside the
window.  A stretch of consecutive windows with one anchor is a single row
(anchor, content, check, doc_id, first window, number of windows), about one
row for eight words.  ``content`` and ``check`` are hashes of the stretch's
words under independent keys.  Two equal windows always have equal anchors, so
nothing is lost:

* stretches with equal anchor, content and check (128 bits) hold the same windows;
* a stretch in which its anchor stands twice is cut into single windows, so no
  stretch repeats itself;
* stretches with equal anchor and different content may share some windows.
  Only for these are the single windows hashed, from the text, with two
  independent 64-bit fingerprints, and compared one by one (the verification);
* an anchor with more than ``HOT`` contents in one block of texts is hot.  Its
  stretches are known to need comparing, so all but two of a block go there
  without meeting under the anchor: no task holds a common phrase's contexts.

The index is a sequence of immutable runs, written once, bucketed by anchor and
sorted by (anchor, content).  A new batch is dealt to the same buckets and
merged there with the runs, which are read in place: an append shuffles the
batch and never the history.  Of what it brings, only stretches that the
history lacks enter the index.  ``compact`` merges the runs into one, bucket by
bucket, and deletes the old ones.
"""

from __future__ import annotations

import hashlib
import uuid
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .frames import as_bytes, batches, delete, documents_only, new_path, partitions, written
from .text_arrays import FIRST, SECOND, gram_hashes, mix, span_sums, word_hashes

BOTH = (FIRST, SECOND)
HOT = 8  # contents of one anchor in one block of texts beyond which they don't meet under the anchor
NEW, KNOWN, LOOSE = 0, 1, 2  # a stretch to be looked up, one seen before in its block, one under a hot anchor
ROW = "anchor long, content long, check long, doc_id long, start int, n int, kind byte"
RUN = f"{ROW}, old int, whole boolean, compare boolean"
ROW_COLUMNS, RUN_COLUMNS = ([c.split()[0] for c in x.split(", ")] for x in (ROW, RUN))
MARKS = "doc_id long, start int, n int, whole boolean"


def _spread(doc: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Keys that deal out rows which no other row is to meet."""
    return mix(doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + start.astype(np.uint64))


def _stretches(words: np.ndarray, others: np.ndarray, bounds: np.ndarray, width: int, gram: int):
    """For all texts of a block: text number, first window in the text, number of windows, anchor, content and check."""
    grams = gram_hashes(words, gram)
    span = width - gram + 1
    none = np.zeros(0, np.int64)
    nothing = none, none, none, none.astype(np.uint64), none.astype(np.uint64), none.astype(np.uint64)
    if len(grams) < span:
        return nothing
    low, have = grams, 1
    while have < span:
        step = min(have, span - have)
        low = np.minimum(low[:-step], low[step:])
        have += step
    text = np.searchsorted(bounds, np.arange(len(low)), side="right") - 1
    whole = np.arange(len(low)) + width <= bounds[text + 1]
    at = np.flatnonzero(whole)
    low, text = low[at], text[at]
    if not len(at):
        return nothing
    new = np.ones(len(at), bool)
    new[1:] = (low[1:] != low[:-1]) | (text[1:] != text[:-1])
    first = np.flatnonzero(new)
    n = np.diff(np.append(first, len(at)))
    begin = at[first]
    # where the anchor stands twice in a stretch, some of its windows may be equal: each is a row of its own
    reach = n + span - 1
    offset = np.cumsum(reach) - reach
    place = np.arange(int(reach.sum())) + np.repeat(begin - offset, reach)
    twice = np.add.reduceat((grams[place] == np.repeat(low[first], reach)).astype(np.int64), offset) > 1
    copies = np.where(twice, n, 1)
    first = np.repeat(first, copies)
    begin = np.repeat(begin, copies) + np.arange(len(first)) - np.repeat(np.cumsum(copies) - copies, copies)
    n = np.repeat(np.where(twice, 1, n), copies)
    end = begin + n + width - 1
    content = mix(span_sums(words, begin, end) + n.astype(np.uint64))
    check = mix(span_sums(others, begin, end, SECOND) + n.astype(np.uint64))
    return text[first], begin - bounds[text[first]], n, low[first], content, check


class FingerprintIndex:
    """Runs of window fingerprints of all documents added so far; documents are to come in ascending doc_id.

    Rows without doc_id are left out; null texts have no windows.  Rows that share a doc_id are pooled: what is
    marked in one is marked at the same places in the other, and none of them counts as earlier than the other.
    ``buckets`` is the number of buckets of a run, fixed for the life of the index (default: the shuffle partitions).
    """

    def __init__(self, spark: SparkSession, width: int = 20, gram: int = 6, buckets: int | None = None):
        self.spark, self.width, self.gram = spark, width, gram
        self.buckets = buckets or partitions(spark)
        self.runs: list[tuple[str, str]] = []  # table and path of what the index holds, oldest first
        self.marks: list[DataFrame] = []

    def history(self) -> DataFrame | None:
        """What the index holds, read bucket by bucket."""
        runs = [self.spark.table(name).where(f"old = 0 and not whole and kind = {NEW}").select(*ROW_COLUMNS) for name, _ in self.runs]
        return reduce(DataFrame.unionByName, runs) if runs else None

    def _write_run(self, rows: DataFrame) -> tuple[str, str]:
        name, path = f"fingerprints_{uuid.uuid4().hex}", new_path(self.spark, "fingerprints")
        rows.select(*RUN_COLUMNS).write.bucketBy(self.buckets, "anchor").sortBy("anchor", "content").option("path", path).saveAsTable(name)
        return name, path

    def _fingerprints(self, docs: DataFrame) -> DataFrame:
        width, gram = self.width, self.gram

        def run(rows):
            for batch in batches(rows, 1024):
                ids = batch.column(0).to_numpy(zero_copy_only=False)
                for a, _, words, others, bounds in word_hashes(batch.column(1).to_pylist(), keys=BOTH):
                    text, start, n, anchor, content, check = _stretches(words, others, bounds, width, gram)
                    if not len(text):
                        continue
                    doc = ids[a + text]
                    # a stretch seen before in this block is settled here, so a hot passage sends one row for a block
                    order = np.lexsort((start, doc, check, content, anchor))
                    same = (anchor[order][1:] == anchor[order][:-1]) & (content[order][1:] == content[order][:-1]) & (check[order][1:] == check[order][:-1])
                    head = np.flatnonzero(np.append(True, ~same))
                    lead = order[np.repeat(head, np.diff(np.append(head, len(order))))]
                    kind = np.zeros(len(order), np.int8)
                    kind[order] = np.where((doc[order] != doc[lead]) | (start[order] != start[lead]), KNOWN, NEW)
                    # contents of one anchor stand side by side: beyond HOT of them, all but two are loose
                    above = anchor[order[head]]
                    first = np.flatnonzero(np.append(True, above[1:] != above[:-1]))
                    several = np.diff(np.append(first, len(above)))
                    place = np.arange(len(above)) - np.repeat(first, several)
                    loose = np.repeat((np.repeat(several, several) > HOT) & (place > 1), np.diff(np.append(head, len(order))))
                    loose &= kind[order] == NEW
                    kind[order[loose]] = LOOSE
                    anchor = np.where(kind == NEW, anchor, _spread(doc, start))
                    columns = [pa.array(x.view(np.int64)) for x in (anchor, content, check)]
                    yield pa.RecordBatch.from_arrays([*columns, pa.array(doc), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(kind)], ROW_COLUMNS)

        return docs.select("doc_id", as_bytes("text").alias("text")).mapInArrow(run, ROW)

    def merged(self, docs: DataFrame) -> DataFrame:
        """The rows of a new run: the batch's stretches, and those of the history that are to be compared with them."""
        rows = self._fingerprints(documents_only(docs)).repartition(self.buckets, "anchor").withColumn("old", F.lit(0))
        if (history := self.history()) is not None:
            rows = rows.unionByName(history.withColumn("old", F.lit(1)))
        rows = rows.sortWithinPartitions("anchor", "content", "check")
        same, alike = Window.partitionBy("anchor", "content", "check"), Window.partitionBy("anchor")
        place = F.struct((F.lit(1) - F.col("old")).alias("late"), "doc_id", "start")
        new = F.col("kind") == NEW
        differ = (F.min("content").over(alike) != F.max("content").over(alike)) | (F.min("check").over(alike) != F.max("check").over(alike))
        rows = rows.withColumn("head", F.min(F.when(new, place)).over(same)).withColumn("several", differ & (F.min("old").over(alike) == 0))
        whole = (F.col("old") == 0) & ((F.col("kind") == KNOWN) | (new & (place > F.col("head"))))
        compare = (F.col("kind") == LOOSE) | (F.col("several") & new & (place == F.col("head")))
        return rows.select(*ROW_COLUMNS, "old", whole.alias("whole"), compare.alias("compare")).where("old = 0 or compare")

    def append(self, docs: DataFrame) -> DataFrame:
        """Merge a batch with the history and keep it as a new run.

        Returns (doc_id, start, n, whole): the batch's stretches that are repeats as a whole, and the stretches
        (of batch or history) that are to be compared window by window.  Read it before the next ``compact``.
        """
        name, path = self._write_run(self.merged(docs))
        marks = self.spark.read.schema(RUN).parquet(path).where("whole or compare").select("doc_id", "start", "n", "whole")
        self.runs.append((name, path))
        self.marks.append(marks)
        return marks

    def compact(self) -> None:
        """One sorted run instead of many, and the marks in a table of their own; the old runs go.

        Runs are free of repeats already, so this merges and drops nothing.
        """
        if len(self.runs) > 1:
            marks = written(reduce(DataFrame.unionByName, self.marks), "marks")
            rows = self.history().withColumns({"old": F.lit(0), "whole": F.lit(False), "compare": F.lit(False)})
            fresh = self._write_run(rows)
            self._drop()
            self.runs, self.marks = [fresh], [marks]

    def _drop(self) -> None:
        for name, path in self.runs:
            self.spark.sql(f"drop table if exists {name}")
            delete(self.spark, path)

    def repeated_windows(self, corpus: DataFrame) -> DataFrame:
        """(doc_id, spans): for every document with repeats the window ranges [start, start + n) that also start earlier.

        ``corpus`` gives the texts of all documents added; it is read for the stretches that need comparing.
        """
        marks = reduce(DataFrame.unionByName, self.marks)
        corpus = documents_only(corpus)
        width = self.width
        needed = marks.where("not whole").select("doc_id", "start", "n").distinct()
        needed = needed.groupBy("doc_id").agg(F.collect_list(F.struct("start", "n")).alias("spans"))
        texts = corpus.join(needed, "doc_id").select("doc_id", as_bytes("text").alias("text"), "spans")

        def windows(rows):
            for batch in batches(rows, 1024):
                ids, spans = batch.column(0).to_pylist(), batch.column(2).to_pylist()
                for a, b, words, others, bounds in word_hashes(batch.column(1).to_pylist(), keys=BOTH):
                    doc, at = [], []
                    for k in range(a, b):
                        lo, hi = int(bounds[k - a]), int(bounds[k - a + 1])
                        for s in spans[k]:
                            begin = np.arange(s["start"], s["start"] + s["n"]) + lo
                            begin = begin[begin + width <= hi]
                            at.append(begin)
                            doc.append(np.full(len(begin), ids[k], np.int64))
                    if not at:
                        continue
                    begin, doc = np.concatenate(at), np.concatenate(doc)
                    if not len(begin):
                        continue
                    one = mix(span_sums(words, begin, begin + width))
                    two = mix(span_sums(others, begin, begin + width, SECOND))
                    start = begin - bounds[np.searchsorted(bounds, begin, side="right") - 1]
                    # of equal windows of this block only the first is still in question
                    order = np.lexsort((start, doc, two, one))
                    same = np.append(False, (one[order][1:] == one[order][:-1]) & (two[order][1:] == two[order][:-1]))
                    head = np.flatnonzero(~same)
                    lead = order[np.repeat(head, np.diff(np.append(head, len(order))))]
                    known = np.zeros(len(order), bool)
                    known[order] = (doc[order] != doc[lead]) | (start[order] != start[lead])
                    one = np.where(known, _spread(doc, start), one)
                    yield pa.RecordBatch.from_arrays([pa.array(one.view(np.int64)), pa.array(two.view(np.int64)), pa.array(doc), pa.array(start.astype(np.int32)), pa.array(known)], ["one", "two", "doc_id", "start", "known"])

        single = texts.mapInArrow(windows, "one long, two long, doc_id long, start int, known boolean").withColumn("place", F.struct("doc_id", "start"))
        head = F.min(F.when(~F.col("known"), F.col("place"))).over(Window.partitionBy("one", "two"))
        later = single.withColumn("head", head).where("known or place > head")
        spans = marks.where("whole").select("doc_id", "start", "n").unionByName(later.select("doc_id", "start", F.lit(1).alias("n")))
        return spans.groupBy("doc_id").agg(F.collect_list(F.struct("start", "n")).alias("spans"))


def remove_repeats(corpus: DataFrame, repeated: DataFrame, width: int = 20, texts: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256[, text]): every word under a repeated window goes; kept words are joined by one space."""
    rows = documents_only(corpus).join(repeated, "doc_id", "left").select("doc_id", as_bytes("text").alias("text"), "spans")

    def run(rows):
        for batch in batches(rows, 1024):
            ids, n, gone, sha, kept = batch.column(0), [], [], [], []
            spans = batch.column(2)
            values = spans.flatten()
            begin, size = values.field("start").to_numpy(), values.field("n").to_numpy()
            counts = np.array([0 if x is None else x for x in pa.compute.list_value_length(spans).to_pylist()], np.int64)
            cuts = np.concatenate([[0], np.cumsum(counts)])
            for k, raw in enumerate(batch.column(1).to_pylist()):
                words = (raw or b"").split()
                n.append(len(words))
                if counts[k]:
                    s, m = begin[cuts[k] : cuts[k + 1]], size[cuts[k] : cuts[k + 1]]
                    step = np.zeros(len(words) + 1, np.int32)
                    ok = s < len(words)
                    np.add.at(step, s[ok], 1)
                    np.add.at(step, np.minimum(s[ok] + m[ok] + width - 1, len(words)), -1)
                    stay = np.cumsum(step[:-1]) == 0
                    words = [words[j] for j in np.flatnonzero(stay).tolist()]
                gone.append(n[-1] - len(words))
                text = b" ".join(words)
                sha.append(hashlib.sha256(text).hexdigest())
                if texts:
                    kept.append(text)
            columns = [ids, pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(sha, pa.string())]
            yield pa.RecordBatch.from_arrays(columns + ([pa.array(kept, pa.binary()).cast(pa.string())] if texts else []), ["doc_id", "n_words", "n_removed", "kept_sha256", "text"][: 4 + texts])

    return rows.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", text string" * texts)


def dedup_substrings(docs: DataFrame, width: int = 20, shares: tuple[float, ...] = (0.1, 0.2), texts: bool = False) -> DataFrame:
    """Remove repeated windows from a whole corpus, added to the index in batches cut at the given shares of the doc_ids.

    Returns one row per row with a doc_id; an empty table gives none.  Null and empty texts and texts of fewer than
    ``width`` words lose nothing.  Rows that repeat a doc_id don't remove each other's words.  Very long texts are
    hashed piece by piece, whole.  Extra columns play no part.
    """
    spark = docs.sparkSession
    docs = documents_only(docs)
    cuts = sorted(set(docs.approxQuantile("doc_id", list(shares), 0.01))) if shares else []
    index = FingerprintIndex(spark, width)
    edges = [None, *cuts, None]
    for k, (low, high) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
        batch = docs
        if low is not None:
            batch = batch.where(F.col("doc_id") > F.lit(int(low)))
        if high is not None:
            batch = batch.where(F.col("doc_id") <= F.lit(int(high)))
        if k == len(edges) - 2:
            index.compact()
        index.append(batch)
    return remove_repeats(docs, index.repeated_windows(docs), width, texts)
