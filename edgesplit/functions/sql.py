"""SQL surface: functions and table functions for a session."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .hashing import _SHIFT, FIRST, MODULUS, SECOND


def register(spark: SparkSession) -> None:
    """Create ``portable_hash``, ``pair_score`` and the table functions ``edge_partition_candidates`` and ``lpt``."""
    once = f"pmod(pmod(v + seed, {MODULUS}) * {FIRST}, {MODULUS})"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION portable_hash(v BIGINT, seed BIGINT) RETURNS BIGINT RETURN pmod((({once} ^ shiftright({once}, 9)) + {_SHIFT}) * {SECOND}, {MODULUS})")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION pair_score(du BIGINT, dv BIGINT, vu BIGINT, vv BIGINT, ru BOOLEAN, rv BOOLEAN, hu BOOLEAN, hv BOOLEAN) RETURNS DOUBLE RETURN "
        "CASE WHEN ru THEN 2 - du / (du + dv) ELSE 0D END + CASE WHEN rv THEN 2 - dv / (du + dv) ELSE 0D END + CASE WHEN hu THEN vu / (vu + vv) ELSE 0D END + CASE WHEN hv THEN vv / (vu + vv) ELSE 0D END"
    )
    spark.udtf.register("edge_partition_candidates", Candidates)
    spark.udtf.register("lpt", ListSchedule)


@udtf(returnType="p int, is_home boolean")
class Candidates:
    """All k partitions of an edge, its ends' homes marked."""

    def eval(self, p_u: int, p_v: int, k: int) -> Iterator[tuple]:
        for p in range(k):
            yield p, p in (p_u, p_v)


@udtf(returnType="place int, vol long, p int")
class ListSchedule:
    """Longest-first list scheduling of an array of volumes."""

    def eval(self, volumes: list, k: int) -> Iterator[tuple]:
        heap = [(0, p) for p in range(k)]
        for i in sorted(range(len(volumes)), key=lambda i: (-volumes[i], i)):
            load, p = heapq.heappop(heap)
            heapq.heappush(heap, (load + volumes[i], p))
            yield i, volumes[i], p
