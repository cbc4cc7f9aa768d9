"""Jobs on a partitioned graph: PageRank, components, neighbour means, profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import materialise
from .components import connected_components

__all__ = ["connected_components", "neighbour_mean", "pagerank", "partition_profile"]


def pagerank(assignment: DataFrame, iterations: int = 100, reset: float = 0.15, undirected: bool = True, k: int | None = None, cut_every: int = 10) -> DataFrame:
    """``v, rank`` after static iterations from rank 1.

    Edges lie by partition once.  An iteration sends each vertex's rank to the partitions that hold
    it and sums messages inside a partition before they go back, so both exchanges carry one row for
    each replica: the replication factor is what they cost.
    """
    arcs = assignment.select("p", "src", "dst")
    if undirected:
        arcs = arcs.union(arcs.select("p", F.col("dst").alias("src"), F.col("src").alias("dst")))
    k = k or (arcs.agg(F.max("p")).first()[0] or 0) + 1
    arcs = materialise(arcs.repartition(k, "p"), "arcs").repartition(k, "p").persist()
    out = arcs.groupBy("src").agg(F.count("*").alias("out_degree")).withColumnRenamed("src", "v")
    mirrors = materialise(arcs.select(F.col("src").alias("v"), "p").distinct(), "mirrors")
    vertices = materialise(arcs.select(F.explode(F.array("src", "dst")).alias("v")).distinct().join(out, "v", "left"), "vertices")
    ranks = vertices.select("v", "out_degree", F.lit(1.0).alias("rank"))
    for i in range(iterations):
        sent = ranks.where("out_degree > 0").select("v", (F.col("rank") / F.col("out_degree")).alias("share")).join(mirrors, "v").select(F.col("v").alias("src"), "p", "share")
        local = arcs.join(sent.repartition(k, "p"), ["p", "src"]).groupBy("p", "dst").agg(F.sum("share").alias("part"))
        gathered = local.groupBy("dst").agg(F.sum("part").alias("got")).withColumnRenamed("dst", "v")
        ranks = vertices.join(gathered, "v", "left").select("v", "out_degree", (F.lit(reset) + (1 - reset) * F.coalesce("got", F.lit(0.0))).alias("rank"))
        if (i + 1) % cut_every == 0 and i + 1 < iterations:
            ranks = materialise(ranks, "ranks")
    return ranks.select("v", "rank")


def neighbour_mean(edges: DataFrame, features: DataFrame) -> DataFrame:
    """``v, mean``: mean feature vector of a vertex's neighbours (``features`` has v and x)."""
    arcs = edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    # Whole vectors are dealt by the vertex they go to; the sums of their parts then need no exchange of their own.
    met = arcs.join(features.select(F.col("v").alias("dst"), "x"), "dst").repartition("src")
    parts = met.select("src", F.posexplode("x").alias("i", "y"))
    means = parts.groupBy("src", "i").agg(F.avg("y").alias("y"))
    return means.groupBy(F.col("src").alias("v")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "y"))), lambda s: s["y"]).alias("mean"))


def partition_profile(assignment: DataFrame) -> DataFrame:
    """``p, edges, vertices, mirrors`` for each partition and, with p null, for all."""
    ends = assignment.select(F.explode(F.array("src", "dst")).alias("v"), "p").distinct()
    shared = ends.groupBy("v").agg(F.count("*").alias("r"))
    sides = ends.join(shared, "v").groupBy("p").agg(F.count("*").alias("vertices"), F.sum((F.col("r") > 1).cast("long")).alias("mirrors"))
    both = assignment.groupBy("p").agg(F.count("*").alias("edges")).join(sides, "p")
    return both.rollup("p").agg(F.sum("edges").alias("edges"), F.sum("vertices").alias("vertices"), F.sum("mirrors").alias("mirrors"))
