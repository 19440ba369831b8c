"""Connected components of an edge table by alternating star contraction.

Each round points the neighbours of a node at the smallest of them: first the larger neighbours
(large star), then the smaller ones (small star). Stars merge in a number of rounds logarithmic in
the longest path. The driver sees one row of counts per round; edges never leave the executors. A
hub's minimum is a partial aggregate; it is written before its rows meet it, as Spark splits the large
partitions of a join only where both sides come straight from an exchange.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.staging import Staged

_MAX_ROUNDS = 60


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = Staged(both.groupBy("a").agg(F.min("b").alias("low")).withColumn("low", F.least("a", "low")), "star").df
    return both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("low").alias("b"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = down.groupBy("a").agg(F.min("b").alias("low"))
    moved = down.join(low, "a").where("b <> low").select(F.col("b").alias("a"), F.col("low").alias("b"))
    return moved.union(low.select("a", F.col("low").alias("b")))


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): the smallest node that each node with an edge can reach, itself included.

    Null ends and loops are ignored; repeated and reversed edges count once. No edges: no rows.
    """
    now = Staged(
        edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b"))
        .where("a is not null and b is not null and a <> b")
        .distinct(),
        "edges",
    )
    before = None
    for _ in range(_MAX_ROUNDS):
        grown = Staged(_small_star(_large_star(now.df)).distinct(), "edges")
        now.drop()
        now = grown
        seen = now.df.agg(
            F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))
        ).first()
        if tuple(seen) == before:
            break
        before = tuple(seen)
    else:
        raise RuntimeError("components did not settle")
    leaves = now.df.select(F.col("a").alias("node"), F.col("b").alias("component"))
    roots = now.df.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return leaves.union(roots)
