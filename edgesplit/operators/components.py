"""Connected components by contraction: every round hooks each vertex to its least neighbour and shortcuts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import materialise


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60, shortcuts: int = 2) -> DataFrame:
    """``node, root`` for every vertex of an edge; ``root`` is the least vertex that it reaches.

    A round costs a constant number of joins whose keys are aggregated first, and at least halves the
    vertices that are left, so rounds grow with the logarithm of the graph; each ends in a table in
    the shared folder.  Self loops and duplicates are allowed; rows with a null end are ignored.
    """
    pairs = edges.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo"), F.col(a).isNotNull().alias("x"), F.col(b).isNotNull().alias("y")).where("x and y").select("hi", "lo")
    # Whatever made the edges runs once.
    pairs = materialise(pairs.distinct(), "cc-pairs")
    nodes = pairs.select(F.explode(F.array("hi", "lo")).alias("node")).distinct()
    live = pairs.where("hi <> lo")
    labels = materialise(nodes.select("node", F.col("node").alias("root")), "cc-labels")
    for _ in range(max_rounds):
        if live.isEmpty():
            return labels
        hooks = live.groupBy("hi").agg(F.min("lo").alias("up")).select(F.col("hi").alias("v"), "up")
        for _ in range(shortcuts):
            further = hooks.select(F.col("v").alias("mid"), F.col("up").alias("top"))
            hooks = hooks.join(further, hooks["up"] == further["mid"], "left").select("v", F.coalesce("top", "up").alias("up"))
        hooks = materialise(hooks, "cc-hooks")
        moved = labels.join(hooks, labels["root"] == hooks["v"], "left").select("node", F.coalesce("up", "root").alias("root"))
        left = hooks.select(F.col("v").alias("v1"), F.col("up").alias("u1"))
        right = hooks.select(F.col("v").alias("v2"), F.col("up").alias("u2"))
        mapped = (
            live.join(left, live["hi"] == left["v1"], "left").join(right, live["lo"] == right["v2"], "left").select(F.coalesce("u1", "hi").alias("p"), F.coalesce("u2", "lo").alias("q"))
        )
        labels = materialise(moved, "cc-labels")
        live = materialise(mapped.where("p <> q").select(F.greatest("p", "q").alias("hi"), F.least("p", "q").alias("lo")).distinct(), "cc-edges")
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
