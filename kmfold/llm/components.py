"""Connected components of a link table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.staging import discard, stage


def _clean(edges: DataFrame) -> DataFrame:
    return edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def _fingerprint(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)")).alias("s")).first()
    return row["n"], row["s"]


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """Least node reachable from each node that has a link: ``node, component``.

    ``links`` has long columns ``a`` and ``b``; self-links and null ends are ignored.
    In each round every node hands its larger neighbours to its least one, then its
    smaller ones: the number of rounds grows with the logarithm of the longest path.
    Minima are pre-aggregated, so a node with very many links is no bottleneck, and
    each round is written to the shared folder.
    """
    edges = stage(_clean(links.filter("a is not null and b is not null")), "links")
    seen = _fingerprint(edges)
    for _ in range(most_rounds):
        if not seen[0]:
            break
        both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(least, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = _clean(large)
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b")))
        new = stage(_clean(small), "links")
        told = _fingerprint(new)
        discard(edges)
        edges = new
        if told == seen:
            break
        seen = told
    else:
        raise RuntimeError("components did not settle")
    leaves = edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
    roots = edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return leaves.unionByName(roots)
