"""Degree pass, positions and capacity."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import portable
from ..plans.storage import materialise


def compute(edges: DataFrame) -> DataFrame:
    """``v, d``: how often each vertex is an end of an edge; counted before the shuffle."""
    return edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count("*").alias("d"))


def check_known(edges: DataFrame, degrees: DataFrame) -> DataFrame:
    """Given degrees; raises if a vertex of the edges has none."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("v"))
    if ends.join(degrees, "v", "left_anti").limit(1).count():
        raise ValueError("degrees are given, but a vertex has none")
    return degrees.select(F.col("v").cast("long"), F.col("d").cast("long"))


def with_position(edges: DataFrame, order_by: tuple[str, ...] | None = None) -> DataFrame:
    """Edges with ``pos``, gapless from 0 in the given order, or without one in a hashed order.

    Streaming methods expect edges in no particular order; a table sorted by vertex is the worst case.

    A range sort, a count for each of its partitions and their running sum: no task sees all edges.
    """
    spark = edges.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    held = [c for c in edges.columns if c != "pos"]
    order = [F.col(c) for c in order_by] if order_by else [portable(portable(F.col("src")) + portable(F.col("dst"), 1)), F.col("src"), F.col("dst")]
    placed = edges.select(held).repartitionByRange(parts, *order).sortWithinPartitions(*order)
    local = F.monotonically_increasing_id()
    placed = materialise(placed.select(*held, F.shiftright(local, 33).alias("__part"), local.bitwiseAND((1 << 33) - 1).alias("__at")), "edges")
    sizes = sorted((r["__part"], r["n"]) for r in placed.groupBy("__part").agg(F.count("*").alias("n")).collect())
    starts, total = [], 0
    for part, n in sizes:
        starts.append((part, total))
        total += n
    table = spark.createDataFrame(starts, "__part long, __start long")
    return placed.join(F.broadcast(table), "__part").select((F.col("__start") + F.col("__at")).alias("pos"), *held)


def hard_cap(edges: int, k: int, alpha: float) -> int:
    """Most edges of a partition: the balance bound, or an even share where that is larger."""
    if k <= 1:
        raise ValueError("k must be greater than 1")
    if alpha < 1:
        raise ValueError("alpha must be at least 1")
    return max(math.floor(alpha * edges / k + 1e-9), -(-edges // k))


def volume_cap(edges: int, k: int, alpha: float, factor: float = 1.0) -> int:
    """Most volume of a cluster: by default what one partition holds."""
    return max(1, math.floor(factor * alpha * 2 * edges / k + 1e-9))
