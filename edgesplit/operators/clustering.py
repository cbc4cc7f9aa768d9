"""Phase 1: vertices drift into the larger of the clusters that their edges touch, in bulk rounds.

The stream is cut into batches by position.  Every edge of a batch sees the state at the batch's
start and proposes a move; one proposal for each vertex survives, a cluster either gives or takes
vertices within a batch, and arrivals are admitted in stream order while they fit the volume cap.  A
batch of one edge behaves as the sequential stream does.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.storage import materialise


def singletons(degrees: DataFrame) -> DataFrame:
    """Every vertex as a cluster of its own."""
    return degrees.select("v", F.col("v").alias("c"), "d")


def volumes(clusters: DataFrame) -> DataFrame:
    return clusters.groupBy("c").agg(F.sum("d").alias("vol"))


def propose(batch: DataFrame, clusters: DataFrame, cap: int | None, migration: str = "residual") -> DataFrame:
    """One move for each vertex: ``v, d, source, target, pos``."""
    if migration not in ("residual", "volume"):
        raise ValueError("migration is residual or volume")
    state = clusters.join(volumes(clusters), "c")
    ends = [state.select(F.col("v").alias(x), F.col("c").alias(f"c_{x}"), F.col("d").alias(f"d_{x}"), F.col("vol").alias(f"vol_{x}")) for x in ("src", "dst")]
    rows = batch.select("pos", "src", "dst").join(ends[0], "src").join(ends[1], "dst").where("c_src <> c_dst")
    if cap is not None:
        rows = rows.where((F.col("vol_src") <= cap) & (F.col("vol_dst") <= cap))
    own = (lambda x: F.col(f"vol_{x}") - F.col(f"d_{x}")) if migration == "residual" else (lambda x: F.col(f"vol_{x}"))
    first = own("src") <= own("dst")
    pick = lambda a, b: F.when(first, F.col(a)).otherwise(F.col(b))
    moves = rows.select(
        "pos", pick("src", "dst").alias("v"), pick("d_src", "d_dst").alias("d"), pick("c_src", "c_dst").alias("source"), pick("c_dst", "c_src").alias("target"), pick("vol_dst", "vol_src").alias("room")
    )
    if cap is not None:
        moves = moves.where(F.col("room") + F.col("d") <= cap)
    best = F.max_by(F.struct("d", "source", "target", "room", "pos"), F.struct("room", -F.col("pos")))
    return moves.groupBy("v").agg(best.alias("m")).select("v", "m.*")


def settle(moves: DataFrame, cap: int | None) -> DataFrame:
    """Moves that hold: roles by each cluster's earliest proposal, then admission in stream order."""
    roles = (
        moves.select(F.col("source").alias("c"), F.lit(0).alias("role"), "pos")
        .union(moves.select(F.col("target").alias("c"), F.lit(1).alias("role"), "pos"))
        .groupBy("c")
        .agg(F.min_by("role", F.struct("pos", "role")).alias("role"))
    )
    kept = moves.join(roles.where("role = 0").select(F.col("c").alias("source")), "source", "left_semi").join(roles.where("role = 1").select(F.col("c").alias("target")), "target", "left_semi")
    if cap is None:
        return kept.select("v", F.col("target").alias("to"))
    running = F.sum("d").over(Window.partitionBy("target").orderBy("pos", "v").rowsBetween(Window.unboundedPreceding, 0))
    return kept.withColumn("arrived", running).where(F.col("room") + F.col("arrived") <= cap).select("v", F.col("target").alias("to"))


def one_round(batch: DataFrame, clusters: DataFrame, cap: int | None, migration: str = "residual") -> DataFrame:
    """Clusters after one batch."""
    moved = settle(propose(batch, clusters, cap, migration), cap)
    return clusters.join(moved, "v", "left").select("v", F.coalesce("to", "c").alias("c"), "d")


def named_by_least(clusters: DataFrame) -> DataFrame:
    """Each cluster named by its least vertex, so that engines agree on names and ties."""
    names = clusters.groupBy("c").agg(F.min("v").alias("name"))
    return clusters.join(names, "c").select("v", F.col("name").alias("c"), "d")


def stream_cluster(edges: DataFrame, degrees: DataFrame, cap: int | None, total: int, passes: int = 1, batches: int = 4, migration: str = "residual", subrounds: int = 1, min_moved: float = 0.0) -> DataFrame:
    """CLUSTERS ``v, c, d`` after the given passes over ``edges`` (pos, src, dst); ``cap`` None means unbounded.

    State is cut to a table after each batch, so a lost executor costs one batch.
    """
    if cap is not None and cap < 1:
        raise ValueError("the volume cap must be at least 1")
    clusters = materialise(singletons(degrees), "clusters")
    for _ in range(passes):
        before = clusters
        for b in range(batches):
            low, high = b * total // batches, (b + 1) * total // batches
            if low == high:
                continue
            batch = edges.where((F.col("pos") >= low) & (F.col("pos") < high))
            for _ in range(subrounds):
                clusters = materialise(one_round(batch, clusters, cap, migration), "clusters")
        if min_moved > 0:
            moved = clusters.alias("a").join(before.alias("b"), "v").where("a.c <> b.c").count()
            if moved < min_moved * clusters.count():
                break
    return materialise(named_by_least(clusters), "clusters")
