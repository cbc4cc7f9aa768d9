"""Edge lists: readers for text, CSV, JSON, ORC, Parquet, adjacency and binary files, and sinks."""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def normalise(edges: DataFrame, dedupe: bool = True, undirected: bool = True, drop_self_loops: bool = True) -> DataFrame:
    """Canonical edges: no null ends, least end first, no loops, no duplicates; other columns stay (of one duplicate)."""
    for c in ("src", "dst"):
        if c not in edges.columns:
            raise ValueError(f"edges need a column {c}")
        kind = dict(edges.dtypes)[c]
        if kind not in ("tinyint", "smallint", "int", "bigint"):
            raise ValueError(f"{c} must be an integer id, not {kind}; see functions.hashing.string_id")
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    checked = edges.select(F.assert_true(F.col("src").isNotNull() & F.col("dst").isNotNull(), F.lit("an edge has a null end")).alias("__ok"), F.col("src").cast("long"), F.col("dst").cast("long"), *rest)
    out = checked.where(F.col("__ok").isNull()).select("src", "dst", *rest)
    if undirected:
        out = out.withColumns({"src": F.least("src", "dst"), "dst": F.greatest("src", "dst")})
    if drop_self_loops:
        out = out.where("src <> dst")
    return out.dropDuplicates(["src", "dst"]) if dedupe else out


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", width: int = 4) -> DataFrame:
    """Edges ``src, dst`` of a file or folder in one of the formats above (``width``: bytes of a binary id)."""
    if fmt in ("parquet", "orc", "json"):
        return getattr(spark.read.schema("src long, dst long"), fmt)(path)
    if fmt in ("csv", "tsv", "text"):
        parts = F.split(F.trim("value"), "[,\\s]+")
        lines = spark.read.text(path).where("value not like '#%' and trim(value) <> ''")
        return lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    if fmt == "adjacency":
        parts = F.split(F.trim("value"), "[,\\s]+")
        lines = spark.read.text(path).where("value not like '#%' and trim(value) <> ''").select(parts.cast("array<bigint>").alias("p"))
        return lines.select(F.col("p")[0].alias("src"), F.explode(F.slice("p", 2, F.greatest(F.size("p") - 1, F.lit(0)))).alias("dst"))
    if fmt == "binary":
        return _read_binary(spark, path, width)
    raise ValueError(f"unknown edge format {fmt!r}")


def _read_binary(spark: SparkSession, path: str, width: int) -> DataFrame:
    """Pairs of little-endian ids; files are read by Spark whole, so keep them at the size of a split."""
    kind = {4: "<u4", 8: "<i8"}[width]

    def run(batches):
        for batch in batches:
            for body in batch.column("content"):
                pairs = np.frombuffer(body.as_py(), kind).astype(np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], names=["src", "dst"])

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, "src long, dst long")


def write_assignment(assignment: DataFrame, path: str, manifest: dict | None = None, fmt: str = "parquet") -> None:
    """One folder for each partition, and a manifest of measures beside them."""
    k = assignment.select(F.max("p")).first()[0]
    spread = assignment.repartition(max(1, (k or 0) + 1), "p")
    spread.sortWithinPartitions("p", "src", "dst").write.mode("overwrite").partitionBy("p").format(fmt).save(path)
    if manifest is not None:
        spark = assignment.sparkSession
        spark.createDataFrame([(json.dumps(manifest, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path.rstrip('/')}-manifest")


def write_state(state: DataFrame, path: str) -> None:
    """A snapshot of degrees or clusters for later runs."""
    state.write.mode("overwrite").parquet(path)
