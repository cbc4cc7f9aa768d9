"""Stateless partitioners as pure expressions over edges (and, for DBH, degrees)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import partition_of, portable, portable_sql

# Perfect difference sets by number of partitions.
DIFFERENCE_SETS = {7: (0, 1, 3), 13: (0, 1, 3, 9), 21: (0, 1, 4, 14, 16), 31: (0, 1, 3, 8, 12, 18), 57: (0, 1, 3, 13, 32, 36, 43, 52)}
_PAIR = 2_147_483_629


def _edge_hash(seed: int) -> Column:
    return portable(portable(F.col("src"), seed) + portable(F.col("dst"), seed + 1), seed)


def edge_hash_sql(seed: int = 0) -> str:
    return portable_sql(f"{portable_sql('src', seed)} + {portable_sql('dst', seed + 1)}", seed)


def hash_edge(edges: DataFrame, k: int, seed: int = 0) -> DataFrame:
    return edges.withColumn("p", (_edge_hash(seed) % k).cast("int"))


def hash_src(edges: DataFrame, k: int, seed: int = 0) -> DataFrame:
    return edges.withColumn("p", partition_of(F.col("src"), k, seed))


def dbh(edges: DataFrame, degrees: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """Hash of the end with the lower degree; equal degrees: the smaller id."""
    du, dv = (degrees.select(F.col("v").alias(x), F.col("d").alias(n)) for x, n in (("src", "d_u"), ("dst", "d_v")))
    first = (F.col("d_u") < F.col("d_v")) | ((F.col("d_u") == F.col("d_v")) & (F.col("src") <= F.col("dst")))
    return edges.join(du, "src").join(dv, "dst").withColumn("p", partition_of(F.when(first, F.col("src")).otherwise(F.col("dst")), k, seed)).drop("d_u", "d_v")


def grid_shape(k: int) -> tuple[int, int]:
    """Rows and columns: the largest divisor of k up to its square root, and k over it."""
    rows = next(r for r in range(math.isqrt(k), 0, -1) if k % r == 0)
    return rows, k // rows


def grid(edges: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """Each end hashes to a cell; the edge takes one of the two cells where one end's row meets the other's column, by its own hash."""
    _, columns = grid_shape(k)
    a, b = partition_of(F.col("src"), k, seed), partition_of(F.col("dst"), k, seed)
    row = lambda x: F.floor(x / columns)
    one, two = row(a) * columns + b % columns, row(b) * columns + a % columns
    return edges.withColumn("p", F.when(_edge_hash(seed) % 2 == 0, one).otherwise(two).cast("int"))


def difference_sets(edges: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """Each end's set is the difference set shifted by its hash; two sets share one partition (equal ones: by the edge's hash)."""
    if k not in DIFFERENCE_SETS:
        raise ValueError(f"k must be one of {sorted(DIFFERENCE_SETS)}")
    base = F.array(*[F.lit(x) for x in DIFFERENCE_SETS[k]])
    own = lambda x: F.transform(base, lambda d: (d + partition_of(F.col(x), k, seed)) % k)
    shared = F.array_sort(F.array_intersect(own("src"), own("dst")))
    return edges.withColumn("p", F.element_at(shared, (_edge_hash(seed) % F.size(shared) + 1).cast("int")).cast("int"))
