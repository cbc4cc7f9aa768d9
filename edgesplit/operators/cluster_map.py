"""Phase 2, step 1: clusters to partitions by longest-first list scheduling."""

from __future__ import annotations

import heapq
from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import partition_of

DRIVER_CLUSTERS = 200_000
POLICIES = ("lpt", "lpt_hist", "hash", "round_robin", "unsorted_list")


def list_schedule(jobs: Iterable[tuple[int, int]], k: int) -> tuple[list[int], list[int]]:
    """Partition of each (volume, id) job in the given order, each to the least loaded; and the loads."""
    heap = [(0, p) for p in range(k)]
    out = []
    for vol, _ in jobs:
        load, p = heapq.heappop(heap)
        out.append(p)
        heapq.heappush(heap, (load + vol, p))
    return out, [load for load, _ in sorted(heap, key=lambda x: x[1])]


def assign(volumes: DataFrame, k: int, policy: str = "lpt", driver_limit: int = DRIVER_CLUSTERS) -> DataFrame:
    """CLUSTER_MAP ``c, vol, p``.

    ``lpt`` sorts by volume (ties: smaller c; equal loads: smaller p).  Up to ``driver_limit`` clusters
    it runs over the clusters themselves; beyond, over the histogram of volumes, which moves equal
    clusters among their partitions and leaves the loads as they are.
    """
    if policy not in POLICIES:
        raise ValueError(f"unknown policy {policy!r}")
    spark = volumes.sparkSession
    if policy == "hash":
        return volumes.select("c", "vol", partition_of(F.col("c"), k).alias("p"))
    if policy == "round_robin":
        turn = F.row_number().over(Window.partitionBy(F.pmod(F.xxhash64("c"), F.lit(64))).orderBy("c"))
        return volumes.select("c", "vol", F.pmod(turn + F.pmod(F.xxhash64("c"), F.lit(64)), F.lit(k)).cast("int").alias("p"))
    if policy == "lpt_hist" or (policy == "lpt" and volumes.limit(driver_limit + 1).count() > driver_limit):
        return by_histogram(volumes, k)
    order = (lambda r: (-r["vol"], r["c"])) if policy == "lpt" else (lambda r: r["c"])
    rows = sorted(volumes.select("c", "vol").limit(driver_limit + 1).collect(), key=order)
    if len(rows) > driver_limit:
        raise ValueError(f"{policy} runs on the driver and takes at most {driver_limit} clusters")
    placed, _ = list_schedule([(r["vol"], r["c"]) for r in rows], k)
    return spark.createDataFrame([(r["c"], r["vol"], p) for r, p in zip(rows, placed, strict=True)], "c long, vol long, p int")


def by_histogram(volumes: DataFrame, k: int, head: int = 100_000) -> DataFrame:
    """LPT over (volume, count) groups; inside a volume clusters are dealt by quota.

    The driver holds the groups; there are at most as many as distinct volumes, which the largest
    cluster bounds.  Of more than ``head`` groups the ``head`` largest volumes are dealt exactly; the
    smaller ones share one group each power of two, at its upper bound.
    """
    spark = volumes.sparkSession
    groups = volumes.groupBy("vol").agg(F.count("*").alias("n"))
    if groups.limit(head + 1).count() > head:
        least = groups.orderBy(F.desc("vol")).limit(head).agg(F.min("vol")).first()[0]
        power = F.least(F.pow(F.lit(2.0), F.ceil(F.log2("vol"))).cast("long"), F.lit(least - 1))
        rounded = volumes.withColumn("key", F.when(F.col("vol") >= least, F.col("vol")).otherwise(power))
    else:
        rounded = volumes.withColumn("key", F.col("vol"))
    counted = sorted(((r["key"], r["n"]) for r in rounded.groupBy("key").agg(F.count("*").alias("n")).collect()), reverse=True)
    loads, quotas = [0] * k, []
    for vol, n in counted:
        given = _deal(loads, vol, n)
        at = 0
        for p, take in enumerate(given):
            if take:
                quotas.append((vol, at, at + take, p))
                loads[p] += take * vol
                at += take
    table = spark.createDataFrame(quotas, "key long, low long, high long, p int")
    # Numbers inside a volume by hash range: two levels, so no volume's clusters meet in one task.
    part = F.pmod(F.xxhash64("c"), F.lit(256)).cast("int")
    parted = rounded.withColumn("part", part)
    sizes = parted.groupBy("key", "part").agg(F.count("*").alias("n"))
    starts = sizes.select("key", "part", F.coalesce(F.sum("n").over(Window.partitionBy("key").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    inside = F.row_number().over(Window.partitionBy("key", "part").orderBy("c")) - 1
    numbered = parted.withColumn("i", inside).join(starts, ["key", "part"]).withColumn("i", F.col("i") + F.col("start"))
    return numbered.join(table, "key").where((F.col("i") >= F.col("low")) & (F.col("i") < F.col("high"))).select("c", "vol", "p")


def _deal(loads: list[int], vol: int, n: int) -> list[int]:
    """How many of n equal jobs each partition gets if each goes to the least loaded."""
    out = [0] * len(loads)
    if n <= 4 * len(loads):
        heap = [(load, p) for p, load in enumerate(loads)]
        heapq.heapify(heap)
        for _ in range(n):
            load, p = heapq.heappop(heap)
            out[p] += 1
            heapq.heappush(heap, (load + vol, p))
        return out
    # All but the last rounds are found by their level at once.
    low, high = min(loads), max(loads) + vol * n
    while low < high:
        mid = (low + high + 1) // 2
        if sum(max(0, -(-(mid - load) // vol)) for load in loads) <= n:
            low = mid
        else:
            high = mid - 1
    out = [max(0, -(-(low - load) // vol)) for load in loads]
    rest = _deal([load + vol * m for load, m in zip(loads, out, strict=True)], vol, n - sum(out))
    return [a + b for a, b in zip(out, rest, strict=True)]


def makespan_ratio(cluster_map: DataFrame, k: int) -> DataFrame:
    """``max_volume, ratio``: the fullest partition over the lower bound max(mean, largest job)."""
    per = cluster_map.groupBy("p").agg(F.sum("vol").alias("v"), F.max("vol").alias("m"))
    top = per.agg(F.max("v").alias("max_volume"), (F.sum("v") / k).alias("mean"), F.max("m").alias("largest"))
    return top.select("max_volume", (F.col("max_volume") / F.greatest("mean", "largest")).alias("ratio"))
