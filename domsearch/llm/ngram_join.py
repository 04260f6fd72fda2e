"""N-gram Jaccard join by vertical partitioning.

The global order of shingle hashes is cut into fragments.  A first pass over
the fragments counts, for every document, how many of its shingles occur
anywhere else; a document below the threshold share can have no partner and
leaves.  What stays is collapsed to one representative for each distinct set,
candidates are gathered by a prefix filter (rarest shingles first), and then
every fragment counts the partial overlaps of the candidates by itself.  The
partial counts are summed per pair and compared exactly with the threshold.
No step is approximate: shingles are told apart by 64-bit hashes, equal sets by
two independent digests of 64 bits.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .frames import as_bytes, batches, by_key, documents_only, with_ids, written
from .text_arrays import FIRST, SECOND, mix, shingle_digests, shingle_sets, word_hashes

BLOCK = 512  # representatives compared at once
SLICE_BITS = 23  # a slice holds about 2 million shingles, 2**23 at most
FRAGMENT_BYTES = 12_000_000  # text bytes whose shingles make up one fragment (about 2 million)


def _fragment_of(h: np.ndarray, n: int) -> np.ndarray:
    return ((h >> np.uint64(32)) * np.uint64(n)) >> np.uint64(32)


def _packed(h: np.ndarray) -> bytes:
    """The low 40 bits of each hash."""
    return (h & np.uint64(0xFFFFFFFF)).astype(np.uint32).tobytes() + ((h >> np.uint64(32)) & np.uint64(255)).astype(np.uint8).tobytes()


def _unpacked(raw: bytes) -> np.ndarray:
    n = len(raw) // 5
    return np.frombuffer(raw, np.uint32, n).astype(np.uint64) | (np.frombuffer(raw, np.uint8, n, 4 * n).astype(np.uint64) << np.uint64(32))


def _narrow(codes: np.ndarray, width: int) -> bytes:
    """The low ``width`` bytes of each code."""
    return codes.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def _wide(raw: bytes, width: int) -> np.ndarray:
    out = np.zeros((len(raw) // width, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(-1, width)
    return out.reshape(-1).view("<u8")


def _block_of(ids: np.ndarray) -> int:
    """A 64-bit name for the batch that holds these rows."""
    return int(mix(mix(ids.view(np.uint64)) + np.arange(len(ids), dtype=np.uint64)).sum(dtype=np.uint64).view(np.int64)) if len(ids) else 0


def _sets(texts, n_words):
    out = []
    for _, _, words, bounds in word_hashes(texts, lower=True):
        out += list(shingle_sets(words, bounds, n_words))
    return out


def shared_counts(docs: DataFrame, n_words: int = 5, fragments: int | None = None) -> DataFrame:
    """(doc_id, n_shingles, n_shared) for distinct doc_ids: n_shared counts the shingles that another row has too (never too few)."""
    docs = documents_only(docs)
    if fragments is None:
        size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        fragments = max(4, -(-size // FRAGMENT_BYTES))
    fields = [pa.field("fragment", pa.int32()), pa.field("block", pa.int64()), pa.field("ids", pa.binary()), pa.field("rows", pa.binary()), pa.field("sizes", pa.binary()), pa.field("hashes", pa.binary())]

    def cut(rows):
        for batch in batches(rows):
            sets = _sets(batch.column(1).to_pylist(), n_words)
            ids = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            flat = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
            owner = np.repeat(np.arange(len(sets), dtype=np.int32), [len(s) for s in sets])
            of = _fragment_of(flat, fragments)
            order = np.argsort(of, kind="stable")
            flat, owner, of = flat[order], owner[order], of[order]
            cuts = np.searchsorted(of, np.arange(fragments + 1, dtype=np.uint64))
            block = _block_of(ids)
            out = [(block % fragments, block, ids.tobytes(), None, None, None)]
            for f in np.flatnonzero(np.diff(cuts)).tolist():
                who, sizes = np.unique(owner[cuts[f] : cuts[f + 1]], return_counts=True)
                out.append((f, block, None, who.tobytes(), sizes.astype(np.int32).tobytes(), _packed(flat[cuts[f] : cuts[f + 1]])))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], x.type) for k, x in enumerate(fields)], schema=pa.schema(fields))

    def count(_, table):
        blocks, ids, who, sizes, raw = (table[x].to_pylist() for x in ("block", "ids", "rows", "sizes", "hashes"))
        h = np.concatenate([np.zeros(0, np.uint64), *(_unpacked(x) for x in raw if x is not None)])
        del raw
        order = np.argsort(h)
        h = h[order]
        again = np.zeros(len(h) + 1, bool)
        again[1:-1] = h[1:] == h[:-1]
        shared = np.zeros(len(h), bool)
        shared[order] = again[:-1] | again[1:]
        total, at = np.concatenate([[0], np.cumsum(shared)]), 0
        out = []
        for x in sizes:
            if x is None:
                out.append(None)
                continue
            n = np.frombuffer(x, np.int32)
            ends = at + np.cumsum(n)
            out.append((total[ends] - total[ends - n]).astype(np.int32).tobytes())
            at = int(ends[-1])
        yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int64()), *(pa.array(x, pa.binary()) for x in (ids, who, sizes, out))], ["block", "ids", "rows", "sizes", "shared"])

    def gather(_, table):
        ids = np.frombuffer(next(x for x in table["ids"].to_pylist() if x is not None), np.int64)
        n, s = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
        for who, sizes, shared in zip(*(table[x].to_pylist() for x in ("rows", "sizes", "shared")), strict=True):
            if who is not None:
                k = np.frombuffer(who, np.int32)
                n[k] += np.frombuffer(sizes, np.int32)
                s[k] += np.frombuffer(shared, np.int32)
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(n), pa.array(s)], ["doc_id", "n", "s"])

    pieces = docs.select("doc_id", as_bytes("text").alias("text")).mapInArrow(cut, "fragment int, block long, ids binary, rows binary, sizes binary, hashes binary")
    counted = by_key(pieces, ["fragment"], count, "block long, ids binary, rows binary, sizes binary, shared binary", fragments)
    return by_key(counted, ["block"], gather, "doc_id long, n long, s long").toDF("doc_id", "n_shingles", "n_shared")


def numbered(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """Rows whose doc_id is distinct, and the given ids of these (None: the ids were distinct already).

    Where ids repeat, each distinct text of an id becomes a row with a number of its own, in a written table.
    """
    if docs.groupBy("doc_id").count().where("count > 1").isEmpty():
        return docs, None
    rows = written(docs.dropDuplicates(["doc_id", "text"]).withColumn("row", F.monotonically_increasing_id()), "rows")
    return rows.select(F.col("row").alias("doc_id"), "text"), rows.select("row", "doc_id")


def _overlaps(segments_a, segments_b):
    """Sizes of all intersections between two lists of sorted arrays, by products of 0/1 matrices."""
    na, nb = len(segments_a), len(segments_b)
    out = np.zeros((na, nb), np.float32)
    flat = np.concatenate([*segments_a, *segments_b]) if na + nb else np.zeros(0, np.uint64)
    if not len(flat):
        return out.astype(np.uint32)
    row = np.repeat(np.arange(na + nb), [len(s) for s in [*segments_a, *segments_b]])
    order = np.argsort(flat, kind="stable")
    flat, row = flat[order], row[order]
    starts = np.flatnonzero(np.concatenate([[True], flat[1:] != flat[:-1]]))
    sizes = np.diff(np.concatenate([starts, [len(flat)]]))
    keep = np.repeat(sizes > 1, sizes)
    column = (np.cumsum(sizes > 1) - 1).repeat(sizes)[keep]
    row = row[keep]
    step = 2048
    cuts = np.searchsorted(column, np.arange(0, (int(column[-1]) if len(column) else -1) + 1 + step, step))
    for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
        if a == b:
            continue
        m = np.zeros((na + nb, step), np.float32)
        m[row[a:b], column[a:b] % step] = 1
        out += m[:na] @ m[na:].T
    return out.astype(np.uint32)


def jaccard_links(reps: DataFrame, percent: int = 80, fragments: int = 4) -> DataFrame:
    """Edges (a, b) that connect exactly the documents which links of Jaccard >= percent/100 connect.

    ``reps`` holds (doc_id, shingles: the set as sorted 64-bit values in a
    binary).  Sets are distinct.  Every link between two different sets is
    found; of each group of linked sets a spanning forest is returned.
    """
    spark = reps.sparkSession

    # 1. how many sets hold each shingle, slice by slice of the hash order; shingles of one set only are dropped,
    #    the others get a code: the slice and the rank in it, so codes are as distinct as hashes and in their order
    size = reps.agg(F.sum(F.octet_length("shingles"))).first()[0] or 0
    slices = max(16, -(-size // (8 * 2_000_000)))
    width = -(-((slices - 1).bit_length() + SLICE_BITS) // 8)
    fields = [pa.field("slice", pa.int32()), pa.field("block", pa.int64()), *(pa.field(x, pa.binary()) for x in ("ids", "lengths", "rows", "sizes", "values"))]

    def recut(rows):
        for batch in batches(rows):
            ids = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            if not len(ids):
                continue
            sets = [np.frombuffer(x, np.uint64) for x in batch.column(1).to_pylist()]
            lengths = np.array([len(x) for x in sets], np.int64)
            flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets), dtype=np.int32), lengths)
            of = _fragment_of(flat, slices)
            order = np.argsort(of, kind="stable")
            flat, owner, of = flat[order], owner[order], of[order]
            cuts = np.searchsorted(of, np.arange(slices + 1, dtype=np.uint64))
            block = _block_of(ids)
            out = [(block % slices, block, ids.tobytes(), lengths.tobytes(), None, None, None)]
            for f in np.flatnonzero(np.diff(cuts)).tolist():
                who, sizes = np.unique(owner[cuts[f] : cuts[f + 1]], return_counts=True)
                out.append((f, block, None, None, who.tobytes(), sizes.astype(np.int32).tobytes(), flat[cuts[f] : cuts[f + 1]].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], x.type) for k, x in enumerate(fields)], schema=pa.schema(fields))

    def frequencies(key, table):
        raw = table["values"].to_pylist()
        h = np.concatenate([np.zeros(0, np.uint64), *(np.frombuffer(x, np.uint64) for x in raw if x is not None)])
        _, rank, n = np.unique(h, return_inverse=True, return_counts=True)
        if len(n) >> SLICE_BITS:  # four times what a slice holds on average; hashes are uniform
            raise OverflowError("a slice of the hash order holds too many shingles")
        code = rank.astype(np.uint64) | np.uint64(key[0] << SLICE_BITS)
        # an eighth of a doubling is fine enough to order by; ties stand in the order of codes
        commonness = np.minimum(8 * np.log2(n), 255).astype(np.uint8)[rank]
        keep = n[rank] > 1
        total, at = np.concatenate([[0], np.cumsum(keep)]), 0
        sizes, known = [], []
        for x in table["sizes"].to_pylist():
            if x is None:
                sizes.append(None)
                known.append(None)
                continue
            ends = at + np.cumsum(np.frombuffer(x, np.int32), dtype=np.int64)
            starts = np.concatenate([[at], ends[:-1]])
            mine = keep[at : ends[-1]]
            sizes.append((total[ends] - total[starts]).astype(np.int32).tobytes())
            known.append(_narrow(code[at : ends[-1]][mine], width) + commonness[at : ends[-1]][mine].tobytes())
            at = int(ends[-1])
        yield pa.RecordBatch.from_arrays([table["block"].combine_chunks(), *(table[x].combine_chunks() for x in ("ids", "lengths", "rows")), pa.array(sizes, pa.binary()), pa.array(known, pa.binary())], ["block", "ids", "lengths", "rows", "sizes", "known"])

    def gather(_, table):
        ids = np.frombuffer(next(x for x in table["ids"].to_pylist() if x is not None), np.int64)
        lengths = np.frombuffer(next(x for x in table["lengths"].to_pylist() if x is not None), np.int64)
        owner, code, common = [np.zeros(0, np.int32)], [np.zeros(0, np.uint64)], [np.zeros(0, np.uint8)]
        for who, sizes, known in zip(*(table[x].to_pylist() for x in ("rows", "sizes", "known")), strict=True):
            if known:
                k = len(known) // (width + 1)
                owner.append(np.repeat(np.frombuffer(who, np.int32), np.frombuffer(sizes, np.int32)))
                code.append(_wide(known[: k * width], width))
                common.append(np.frombuffer(known, np.uint8, k, k * width))
        owner, code, common = np.concatenate(owner), np.concatenate(code), np.concatenate(common)
        order = np.lexsort((code, owner))
        code, common = code[order], common[order]
        cuts = np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=len(ids)))])
        live = np.flatnonzero(100 * np.diff(cuts) >= percent * lengths)
        raw = [_narrow(code[cuts[k] : cuts[k + 1]], width) + common[cuts[k] : cuts[k + 1]].tobytes() for k in live.tolist()]
        yield pa.RecordBatch.from_arrays([pa.array(ids[live]), pa.array(lengths[live]), pa.array(raw, pa.binary())], ["doc_id", "n", "known"])

    pieces = reps.select("doc_id", "shingles").mapInArrow(recut, "slice int, block long, ids binary, lengths binary, rows binary, sizes binary, values binary")
    known = by_key(pieces, ["slice"], frequencies, "block long, ids binary, lengths binary, rows binary, sizes binary, known binary", slices)
    live = written(by_key(known, ["block"], gather, "doc_id long, n long, known binary"), "candidates")

    def prefixes(rows):
        for batch in batches(rows):
            ids, token = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for doc, n, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                k = len(raw) // (width + 1)
                code, common = _wide(raw[: k * width], width), np.frombuffer(raw, np.uint8, k, k * width)
                alone = n - k  # shingles that no other set has stand first in the order
                size = n - -(-percent * n // 100) + 1 - alone
                chosen = np.lexsort((code, common))[: max(size, 0)]
                ids.append(np.full(len(chosen), doc, np.int64))
                token.append(code[chosen].view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(ids)), pa.array(np.concatenate(token))], ["doc_id", "token"])

    # 2. clusters: sets that share a shingle of their prefixes, directly or through others
    tokens = live.select("doc_id", "n", "known").mapInArrow(prefixes, "doc_id long, token long")
    tokens = written(tokens, "prefixes")
    stars = tokens.join(tokens.groupBy("token").agg(F.min("doc_id").alias("first"), F.count("*").alias("k")).where("k > 1"), "token")
    clusters = connected_components(stars.select("doc_id", "first").where("doc_id <> first").distinct(), "doc_id", "first")
    clusters = written(clusters.select(F.col("node").alias("doc_id"), F.col("component").alias("cluster")), "clusters")

    # 3. blocks of a cluster meet in pairs; partial overlaps by fragment, then summed per pair
    sizes = clusters.groupBy("cluster").agg(F.count("*").alias("m")).where("m > 1").withColumn("blocks", F.ceil(F.col("m") / BLOCK).cast("int"))
    member = clusters.join(sizes, "cluster").withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
    member = member.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    member = member.select("doc_id", "cluster", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block")
    sets = live.select("doc_id", F.col("n").alias("size"), F.expr(f"substr(known, 1, {width} * (octet_length(known) div {width + 1}))").alias("values"))
    parts = member.join(sets, "doc_id").select("cluster", "i", "j", "block", "doc_id", "size", "values")

    def split(rows):
        for batch in batches(rows, 1024):
            raw = [_wide(x, width) for x in batch.column(6).to_pylist()]
            picks, frags, out = [], [], []
            for k, h in enumerate(raw):
                of = (h >> np.uint64(SLICE_BITS)) * np.uint64(fragments) // np.uint64(slices)
                cuts = np.searchsorted(of, np.arange(fragments + 1, dtype=np.uint64))
                for f in range(fragments):
                    picks.append(k)
                    frags.append(f)
                    out.append(_narrow(h[cuts[f] : cuts[f + 1]], width))
            kept = pa.RecordBatch.from_arrays(batch.columns[:6], ["cluster", "i", "j", "block", "doc_id", "size"]).take(pa.array(picks, pa.int32()))
            yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(frags, pa.int32()), pa.array(out, pa.binary())], ["cluster", "i", "j", "block", "doc_id", "size", "fragment", "values"])

    def sides(key, table):
        _, i, j, *_ = key
        docs, blocks = table["doc_id"].to_numpy(), table["block"].to_numpy()
        order = np.argsort(docs, kind="stable")
        return docs, order[blocks[order] == i], order[blocks[order] == j]

    def partial(key, table):
        docs, a, b = sides(key, table)
        size = table["size"].to_numpy()
        segments = [_wide(x, width) for x in table["values"].to_pylist()]
        counts = _overlaps([segments[k] for k in a], [segments[k] for k in b])
        counts[docs[a][:, None] == docs[b][None, :]] = 0
        if not counts.any():
            return  # nothing shared in this fragment
        row = [[key[0]], [key[1]], [key[2]], [docs[a].tobytes()], [docs[b].tobytes()], [size[a].tobytes()], [size[b].tobytes()], [zlib.compress(counts.tobytes(), 1)]]
        yield pa.RecordBatch.from_arrays([pa.array(row[0], pa.int64()), pa.array(row[1], pa.int32()), pa.array(row[2], pa.int32()), *(pa.array(x, pa.binary()) for x in row[3:])], ["cluster", "i", "j", "docs_a", "docs_b", "size_a", "size_b", "counts"])

    def total(key, table):
        docs_a, docs_b, na, nb = (np.frombuffer(table[c][0].as_py(), np.int64) for c in ("docs_a", "docs_b", "size_a", "size_b"))
        overlap = np.zeros((len(docs_a), len(docs_b)), np.int64)
        for raw in table["counts"].to_pylist():
            overlap += np.frombuffer(zlib.decompress(raw), np.uint32).reshape(overlap.shape)
        linked = 100 * overlap >= percent * (na[:, None] + nb[None, :] - overlap)
        linked &= docs_a[:, None] != docs_b[None, :]
        names = np.unique(np.concatenate([docs_a, docs_b]))
        pa_, pb = np.searchsorted(names, docs_a), np.searchsorted(names, docs_b)
        x, y = np.nonzero(linked)
        parent = np.arange(len(names))

        def root(k):
            while parent[k] != k:
                parent[k] = parent[parent[k]]
                k = parent[k]
            return k

        ea, eb = [], []
        for p, q in zip(pa_[x].tolist(), pb[y].tolist(), strict=True):
            p, q = root(p), root(q)
            if p != q:
                parent[max(p, q)] = min(p, q)
                ea.append(names[p])
                eb.append(names[q])
        if ea:
            yield pa.RecordBatch.from_arrays([pa.array(ea, pa.int64()), pa.array(eb, pa.int64())], ["a", "b"])

    parts = parts.mapInArrow(split, "cluster long, i int, j int, block int, doc_id long, size long, fragment int, values binary")
    counted = by_key(parts, ["cluster", "i", "j", "fragment"], partial, "cluster long, i int, j int, docs_a binary, docs_b binary, size_a binary, size_b binary, counts binary")
    return by_key(counted, ["cluster", "i", "j"], total, "a long, b long")


def jaccard_components(docs: DataFrame, n_words: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every document; component_id is the smallest doc_id that links reach.

    Nulls: a row without an id is left out; a null or empty text, or one of white space, has no shingles and
    links with nothing.  Rows that repeat an id and text are one document.  Differing texts under one id are compared
    each for itself; they are one document, which has the links of all of them and the size of its largest set.
    An empty table gives no rows.  Extra columns play no part.  Very long texts are hashed piece by piece, whole.
    """
    docs, ids = numbered(documents_only(docs))
    counts = written(shared_counts(docs, n_words), "counts")
    candidates = counts.where(F.col("n_shared") * 100 >= F.col("n_shingles") * percent).where("n_shingles > 0").select("doc_id")
    near = with_ids(docs, candidates, "doc_id", "left_semi").select("doc_id", as_bytes("text").alias("text"))

    def sets(rows):
        for batch in batches(rows, 1024):
            found = []
            for _, _, words, others, bounds in word_hashes(batch.column(1).to_pylist(), lower=True, keys=(FIRST, SECOND)):
                found += list(shingle_digests(words, others, bounds, n_words))
            columns = [pa.array([len(h) for h, _, _ in found], pa.int64()), *(pa.array([x[k] for x in found], pa.int64()) for k in (1, 2)), pa.array([h.tobytes() for h, _, _ in found], pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column(0), *columns], ["doc_id", "n", "k1", "k2", "shingles"])

    schema = "doc_id long, n long, k1 long, k2 long, shingles binary"
    classes = written(near.mapInArrow(sets, schema).where("n > 0"), "sets")
    rep = classes.groupBy("n", "k1", "k2").agg(F.min("doc_id").alias("rep"))
    member = written(classes.select("doc_id", "n", "k1", "k2").join(rep, ["n", "k1", "k2"]).select("doc_id", "rep"), "classes")
    # sets stay where they are while the representatives' ids are small
    reps = with_ids(classes, member.where("doc_id = rep").select("doc_id"), "doc_id", "left_semi").select("doc_id", "shingles")
    edges = written(jaccard_links(reps, percent), "edges")
    if ids is None:
        merged = connected_components(edges)
        label = member.join(merged, member.rep == merged.node, "left").select("doc_id", F.coalesce("component", "rep").alias("component_id"))
        return counts.join(label, "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
    # rows of one id hang together, whatever they hold
    own = ids.join(ids.groupBy("doc_id").agg(F.min("row").alias("first")), "doc_id").select(F.col("row").alias("a"), F.col("first").alias("b"))
    merged = connected_components(edges.unionByName(member.toDF("a", "b")).unionByName(own))
    rows = ids.join(counts.withColumnRenamed("doc_id", "row"), "row").join(merged.withColumnRenamed("node", "row"), "row", "left")
    rows = rows.withColumn("component", F.coalesce("component", "row"))
    least = rows.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    per = rows.groupBy("doc_id").agg(F.max("n_shingles").alias("n_shingles"), F.min("component").alias("component"))
    return per.join(least, "component").select("doc_id", "n_shingles", "component_id")
