"""Headline timings: index building and query time of plain MinHash LSH and of the size-partitioned index.

Prints one JSON line.  BENCH_SF_DIR names the tables, BENCH_CPUS the local threads.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import functions as F

from domsearch.functions.hashing import Vector
from domsearch.functions.minhash import vector_signatures
from domsearch.operators import extract, search, spci
from domsearch.session import session
from domsearch.store import fresh, materialise

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
M, K, T = 256, 100, [0.5]


def main() -> None:
    spark = session(f"local[{CPUS}]", 16, spark__driver__memory="16g", spark__ui__showConsoleProgress="false")
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name, function):
        began = time.time()
        out = function()
        took[name] = round(time.time() - began, 3)
        print(name, took[name], file=sys.stderr, flush=True)
        return out

    entries = timed("extract", lambda: materialise(extract.slice_entries(spark, SF), "entries"))
    exact_sizes = materialise(extract.sizes(entries), "sizes")
    n_domains, queries = exact_sizes.count(), materialise(search.query_sample(exact_sizes, K), "queries")
    # one pass for the sketches, shared by all settings: only part_id differs between them
    signed = timed("sketch_m256", lambda: materialise(vector_signatures(entries, M).where(F.col("size") >= extract.MIN_SIZE), "signed"))
    candidates = {}
    for n in (1, 8, 16, 32):

        def build(n=n):
            path = fresh(spark, f"index-{n}")
            spci.save(spci.build(signed, n, M, native=True, family=Vector(M)), path, None)
            return spci.load(spark, path)

        index = timed(f"index_n{n}", build)
        candidates[f"n{n}"] = timed(f"query_n{n}", lambda i=index: spci.search(i, queries, T).count())
    # buckets written once, in a layout of trees, and searches that read only them; then over a fifth of the domains
    asked = materialise(signed.join(queries, F.col("domain_id") == F.col("query_id")).select("query_id", "q", "sig"), "asked")
    growth = {}
    for share in (20, 100):
        kept = signed.where(F.pmod(F.xxhash64("domain_id"), F.lit(100)) < share)
        index = timed(f"buckets_share_{share}", lambda kept=kept: spci.stored(spci.build(kept, 32, M, native=True, family=Vector(M), layout=(32, 8)), T))
        growth[share] = timed(f"query_buckets_share_{share}", lambda i=index: spci.search(i, asked, T).count())
    pairs = timed("exact_search", lambda: search.exact(search.overlaps(entries, exact_sizes, queries), T[0]).count())
    for name in ("lsh_static", "partition_costs"):
        from domsearch.plans.catalog import QUERIES

        timed(name, lambda name=name: QUERIES[name](spark, SF).write.format("noop").mode("overwrite").save())
    print(json.dumps({
        "metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF.rstrip("/").rsplit("sf", 1)[-1],
        "n_domains": n_domains, "index_domains_per_s": round(n_domains / (took["sketch_m256"] + took["index_n32"]), 1),
        "mean_query_s": {k: round(took[f"query_{k}"] / K, 4) for k in candidates}, "candidates": candidates, "candidates_by_share": growth, "exact_answers": pairs,
    }))


if __name__ == "__main__":
    main()
