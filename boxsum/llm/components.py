"""Connected components of a table of links, by alternating star contractions.

Each round hangs every node's larger neighbours on its least one (large star), then its smaller ones (small
star). The links never grow in number beyond one per node and round, and the end is a star per component around
its least node. Each round is cut off in the shared folder.

A node's least neighbour comes from a pre-aggregated minimum, which a task reads at most one row a node and map
task of. It is joined back in two ways: the nodes with more than a share of 2 / `HEAVY_NODES` of the links, of
which there can't be more than `HEAVY_NODES`, are broadcast, so their links stay where they are; the others are
dealt by node, so no task gets more links of one node than that share (or `LIGHT`, if that is more).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import cut

#: The most nodes that are broadcast, and the links up to which a node is never one of them.
HEAVY_NODES, LIGHT = 2000, 32


def _with_least(ends: DataFrame, bound: int) -> DataFrame:
    """ends (a, b) with the least b of their a; nodes with more than `bound` rows are joined where the rows are."""
    least = ends.groupBy("a").agg(F.min("b").alias("least"), F.count("*").alias("n"))
    heavy = least.where(F.col("n") > bound).select("a", F.col("least").alias("of_heavy"))
    light = least.where(F.col("n") <= bound).select("a", "least")
    marked = ends.join(F.broadcast(heavy), "a", "left")
    known = marked.where("of_heavy is not null").select("a", "b", F.col("of_heavy").alias("least"))
    return known.unionByName(marked.where("of_heavy is null").select("a", "b").join(light, "a").select("a", "b", "least"))


def _large_star(links: DataFrame, bound: int) -> DataFrame:
    both = links.select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("x")).select("x.*")
    return _with_least(both, bound).where("b > a").select(F.col("b").alias("a"), F.least("a", "least").alias("b"))


def _small_star(links: DataFrame, bound: int) -> DataFrame:
    return _with_least(links, bound).select(F.when(F.col("b") == F.col("least"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("least").alias("b"))


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): each linked node with the least node that it can reach.

    Links count in both directions; repeated ones, loops and nulls add nothing. No links: no rows.
    """
    links = cut(links.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).where("a > b").distinct())
    # xor of hashes and count: equal for equal sets of links
    mark = lambda df: tuple(df.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("a", "b")), F.lit(0))).first())
    before = mark(links)
    while before[0]:
        bound = max(LIGHT, 2 * before[0] // HEAVY_NODES)  # both stars have at most twice the links as rows
        links = cut(_small_star(_large_star(links, bound).distinct(), bound).distinct())
        now = mark(links)
        if now == before:
            break
        before = now
    roots = links.select(F.col("b").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return links.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots)
