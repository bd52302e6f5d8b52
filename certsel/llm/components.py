"""Connected components by alternating star contraction, as DataFrame joins over edges only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, staged


def _outward(edges: DataFrame) -> DataFrame:
    """Every node above its smallest neighbour hands its larger neighbours to the smallest of them all."""
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("n")).select("u", F.least("u", "n").alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()


def _inward(edges: DataFrame) -> DataFrame:
    """edges hold u > v: u and all its smaller neighbours go to the smallest one."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def components(edges: DataFrame, a: str, b: str, max_rounds: int = 60) -> DataFrame:
    """(node, root) for each node that has an edge; root is the smallest node of its component.

    Self loops and null ends are ignored; repeated and reversed edges count once; no edges give no rows.
    Each round is written to the shared folder, so a lost executor costs one round at most.
    """
    spark = edges.sparkSession
    e = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v")
    e = e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    e, path = staged(e, "edges")
    seen = None
    for _ in range(max_rounds):
        nxt, new_path = staged(_inward(_outward(e)), "edges")
        discard(spark, path)
        e, path = nxt, new_path
        state = tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).union(
        e.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()
