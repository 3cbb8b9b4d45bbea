"""Connected components of a link table, by alternating star contractions.

Each round rewires links towards the smallest known node: the large-star step
hangs every larger neighbour of a node on its smallest neighbour, the small-star
step does the same for its smaller ones. Rounds end when the table no longer
changes; every link then joins a node to the smallest node of its component.
All state stays in written tables, so a lost executor costs one round at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def components(links: DataFrame, first: str = "a", second: str = "b") -> DataFrame:
    """(node, root) for every node that has a link to another; nulls and loops are ignored."""
    edges = links.select(F.greatest(first, second).alias("a"), F.least(first, second).alias("b")).where(F.col("a") != F.col("b")).distinct()
    edges = written(edges, "links")
    mark = _mark(edges)
    while mark[0]:
        edges = written(_small_star(_large_star(edges)), "links")
        mark, before = _mark(edges), mark
        if mark == before:
            break
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))


def _mark(edges: DataFrame):
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.bit_xor(F.hash("b", "a").cast("long"))).first())


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    rewired = edges.join(least, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("x")).select("x.*")
    return rewired.where(F.col("a") != F.col("b")).distinct()
