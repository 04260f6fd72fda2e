"""Distributed connected components over an edge list."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .frames import delete, new_path, written


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for every node of ``edges``; component is the smallest node that it reaches.

    Each round hooks every node's neighbours onto the smallest of them and then
    replaces chains by stars, so rounds grow with the logarithm of the longest
    path.  A round writes its edges to the shared folder, never to one task: the
    aggregates combine before the shuffle, and a node with very many neighbours
    takes part through joins whose large partitions can be split.
    """
    spark = edges.sparkSession
    pair = edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u <> v")
    links = pair.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    paths = [new_path(spark, "links")]
    links = written(links, "links", paths[0])
    seen = None
    while True:
        # large star: neighbours above a node go to its smallest neighbour
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        # small star: a node's smaller neighbours and itself go to the smallest of them
        large = large.where("u <> v").distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.*")
        paths.append(new_path(spark, "links"))
        links = written(small.where("u <> v").distinct(), "links", paths[-1])
        now = links.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.max(F.lit(1))).first()
        if len(paths) > 2:
            delete(spark, paths.pop(0))
        if seen == now:
            break
        seen = now
    stars = links.select(F.col("u").alias("node"), F.col("v").alias("component"))
    roots = links.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return stars.unionByName(roots)
