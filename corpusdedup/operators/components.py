"""Connected components as DataFrame rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import drop_stage, stage


def _digest(edges: DataFrame) -> tuple:
    """Number of edges and an order-free checksum; two scalars reach the driver."""
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def connected_components(edges: DataFrame, left: str = "src", right: str = "dst", max_rounds: int = 50) -> DataFrame:
    """(node, component): the smallest node reachable from each node that has an edge.

    Alternates two star contractions: every node hands its larger neighbours to its
    smallest neighbour, then its smaller ones. The number of edges never grows and a
    logarithmic number of rounds suffices. A hub's edges are aggregated before the
    shuffle and joined back, so no task gathers them. Each round is written to the
    shared folder, which cuts the lineage and outlives lost executors.
    Null ends and loops are ignored; repeated edges count once.
    """
    a, b = F.col(left), F.col(right)
    e = stage(edges.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "cc")
    before = _digest(e)
    for _ in range(max_rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        big = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = big.groupBy("u").agg(F.min("v").alias("m"))
        small = big.join(low, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        new = stage(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct(), "cc")
        drop_stage(e)
        e, now = new, _digest(new)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError("components did not settle")
    roots = e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
