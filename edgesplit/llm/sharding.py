"""Uniform shuffle into exact-size shards by a hypergeometric communication matrix.

Rows are dealt in three steps.  (1) Each logical source bucket (a hash range of the key) learns how
many of its rows go to each shard: one row of a matrix whose bucket sums are the bucket sizes and
whose shard sums are the exact shard sizes, drawn by the multivariate hypergeometric law.  (2) Each
bucket permutes its rows locally, so that the first a(b,0) go to shard 0, the next a(b,1) to shard 1.
(3) After the exchange each shard permutes again.  Buckets depend on the rows alone, so a task that is
run again deals the same rows to the same shards.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .columns import Packed

_ATOMIC = (T.NumericType, T.StringType, T.BooleanType, T.DateType, T.TimestampType, T.BinaryType)


def communication_matrix(sizes: list[int], shards: int, seed: int) -> np.ndarray:
    """Matrix (source bucket, shard) with the given row sums and shard sums that differ by one at most.

    The law is that of a uniform permutation of all rows that is cut into shards: bucket by bucket,
    its counts are multivariate hypergeometric in the shards' places that are still free.
    """
    total = int(sum(sizes))
    free = np.full(shards, total // shards, dtype=np.int64)
    free[: total % shards] += 1
    draw = np.random.default_rng(seed)
    out = np.zeros((len(sizes), shards), dtype=np.int64)
    for i, n in enumerate(sizes):
        if n:
            out[i] = _draw_counts(draw, free, int(n))
            free -= out[i]
    return out


def _draw_counts(draw: np.random.Generator, free: np.ndarray, n: int) -> np.ndarray:
    """Multivariate hypergeometric counts; numpy's sampler stops at a population of 10^9, the tabled law below does not."""
    total = int(free.sum())
    if total < 1_000_000_000:
        return draw.multivariate_hypergeometric(free, n, method="marginals")
    out, left, rest = np.zeros_like(free), n, total
    for j, places in enumerate(map(int, free)):
        rest -= places
        out[j] = _tabled_draw(draw, places, rest, left)
        left -= int(out[j])
    return out


def _tabled_draw(draw: np.random.Generator, good: int, bad: int, n: int) -> int:
    """One hypergeometric draw from the table of its probabilities around the mode, by ratios of neighbours."""
    low, high = max(0, n - bad), min(n, good)
    mode = min(high, max(low, (n + 1) * (good + 1) // (good + bad + 2)))
    reach = int(14 * (n * good / (good + bad) * bad / (good + bad)) ** 0.5) + 20
    x = np.arange(max(low, mode - reach), min(high, mode + reach) + 1, dtype=np.float64)
    step = np.log((good - x[:-1]) * (n - x[:-1])) - np.log((x[:-1] + 1) * (bad - n + x[:-1] + 1))
    weight = np.concatenate(([0.0], np.cumsum(step)))
    table = np.cumsum(np.exp(weight - weight.max()))
    return int(x[np.searchsorted(table, draw.random() * table[-1], side="right")])


def _range_of(hashed: Column, parts: int) -> Column:
    """Which of so many equal ranges of a uniform 64-bit hash."""
    return F.floor(F.shiftrightunsigned(hashed, 33) * F.lit(parts) / F.lit(float(1 << 31))).cast("int")


def shuffle_into_shards(
    rows: DataFrame, key: str = "doc_id", shards: int = 16, seed: int = 20_240, rows_per_bucket: int = 50_000, least_buckets: int = 256
) -> DataFrame:
    """All rows with ``shard`` (0 to shards-1) and ``slot`` (gapless from 0 in each shard).

    Every row is kept, once for each time it occurs; shard sizes differ by one at most; the order of
    slots is a pseudo-random permutation fixed by ``seed`` and the rows.  A null key is a key like
    any other; repeated rows take different slots; an empty table gives an empty result.  Columns
    named ``shard`` or ``slot`` in the input are replaced; other names are kept.
    """
    if shards < 1:
        raise ValueError("shards must be at least 1")
    spark = rows.sparkSession
    total = rows.count()
    buckets = max(least_buckets, -(-total // rows_per_bucket))
    parts = max(-(-least_buckets // 4), -(-total // (shards * rows_per_bucket)))
    atomic = [F.col(f"`{f.name}`") for f in rows.schema.fields if isinstance(f.dataType, _ATOMIC) and f.name not in ("shard", "slot")]
    own = Packed(rows, ("shard", "slot"), (key,), [(F.xxhash64(*atomic) if atomic else F.lit(0).cast("long")).alias("tie")])

    # The rest of the row takes part, so that rows without a key, or with one key, spread over all buckets.
    first = F.xxhash64(F.col(key), F.lit(seed), "tie")
    second = F.xxhash64(F.lit(seed + 1), F.col(key), F.lit("slot"), "tie")
    dealt = own.rows.withColumns({"first": first, "second": second, "bucket": _range_of(first, buckets)})

    counted = {r["bucket"]: r["n"] for r in own.rows.select(_range_of(first, buckets).alias("bucket")).groupBy("bucket").agg(F.count("*").alias("n")).collect()}
    matrix = communication_matrix([counted.get(b, 0) for b in range(buckets)], shards, seed)
    ends = np.cumsum(matrix, axis=1)
    table = spark.createDataFrame([(b, ends[b].tolist()) for b in range(buckets) if b in counted], "bucket int, ends array<bigint>")

    # Left joins, though every row has a match: an inner one would push a null check of the hashes below the caller's columns,
    # where planning can take time exponential in their number.
    local = Window.partitionBy("bucket").orderBy("first", "tie")
    dealt = dealt.withColumn("rank", F.row_number().over(local) - 1).join(table, "bucket", "left")
    dealt = dealt.withColumn("shard", F.size(F.filter("ends", lambda e: e <= F.col("rank"))).cast("int"))
    dealt = dealt.withColumn("part", _range_of(F.col("second"), parts)).drop("ends", "rank", "first", "bucket")

    sizes = dealt.groupBy("shard", "part").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("shard", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("begin"))
    within = Window.partitionBy("shard", "part").orderBy("second", "tie")
    placed = dealt.withColumn("place", F.row_number().over(within) - 1).join(starts, ["shard", "part"], "left")
    return placed.select(*own.back(), "shard", (F.col("begin") + F.col("place")).cast("long").alias("slot"))
