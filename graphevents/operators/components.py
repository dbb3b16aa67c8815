"""Connected components of an undirected graph, as DataFrame rounds."""

from __future__ import annotations

import gc
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def checkpointed(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the folder the session names; a temporary folder only where none is set (tests)."""
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="checkpoints-"))
    return df.checkpoint(eager=True)


def free_shuffles(spark: SparkSession) -> None:
    """Let the context cleaner drop shuffle files of finished jobs that nothing refers to."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``src, dst`` -> ``node, component``: the smallest node reachable from each node that has an edge.

    Alternating stars: every node hangs its larger neighbours (then its smaller ones) under its smallest neighbour, which keeps
    components and needs about log^2 of their size rounds. Each round is one aggregation of the current edges by node with
    combining before the shuffle (the minimum) and one join back, so a node with very many edges is no single task's work.
    Nulls and loops are ignored.
    """
    both = edges.select("src", "dst").filter("src <> dst")
    both = checkpointed(both.select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct())
    mark = None
    for _ in range(max_rounds):
        # Large star: neighbours above a node move to the least of the node and its neighbours.
        out = both.union(both.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = out.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("n"), F.least("a", "m").alias("m"))
        large = out.join(least, out.a == least.n).filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a > b").distinct()
        # Small star: neighbours below a node, and the node, move to the least of them.
        low = large.groupBy("a").agg(F.min("b").alias("m")).withColumnRenamed("a", "n")
        small = large.join(low, large.a == low.n).select(F.explode(F.array(F.struct(F.col("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e"))
        both = checkpointed(small.select("e.a", "e.b").filter("a > b").distinct())
        now = both.agg(F.count("*"), F.sum(F.hash("a", "b").cast("long")), F.sum(F.xxhash64("a", "b").bitwiseAND(F.lit((1 << 40) - 1)))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"components are not settled after {max_rounds} rounds: raise max_rounds")
    roots = both.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return both.select(F.col("a").alias("node"), F.col("b").alias("component")).union(roots)
