"""Edge streams: stateless methods as plain projections, stateful ones by micro-batch with versioned tables."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import partition_of
from ..operators import clustering
from ..plans.storage import exists, materialise, prepare, remove


def event_stream(spark: SparkSession, folder: str, watermark: str = "1 hour") -> DataFrame:
    """The events table as a file stream, duplicates within the watermark dropped."""
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    return spark.readStream.schema(schema).parquet(folder).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def assign_live(edges: DataFrame, degrees: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """DBH on a live stream with a static table of degrees; vertices that it lacks count as degree 0."""
    d_u, d_v = (degrees.select(F.col("v").alias(x), F.col("d").alias(n)) for x, n in (("src", "d_u"), ("dst", "d_v")))
    rows = edges.join(d_u, "src", "left").join(d_v, "dst", "left").fillna(0, ["d_u", "d_v"])
    first = (F.col("d_u") < F.col("d_v")) | ((F.col("d_u") == F.col("d_v")) & (F.col("src") <= F.col("dst")))
    return rows.withColumn("p", partition_of(F.when(first, F.col("src")).otherwise(F.col("dst")), k, seed)).drop("d_u", "d_v")


def window_counts(events: DataFrame, width: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """Events and about how many active users, by tumbling or sliding window, on a stream or a table."""
    counts = events.groupBy(F.window("ts", width, slide or width).alias("w")).agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("users"))
    return counts.select(F.col("w.start").alias("start"), "n", "users")


def replica_counts(assigned: DataFrame, k: int) -> DataFrame:
    """``v, replicas``: after each micro-batch, how many partitions hold each vertex that it touched.

    The state of a vertex is its set of partitions as a bit mask, k bits at most.
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        mask = int(state.get[0]) if state.exists else 0
        for batch in batches:
            for p in batch["p"]:
                mask |= 1 << int(p)
        state.update((str(mask),))
        yield pd.DataFrame({"v": [key[0]], "replicas": [mask.bit_count()]})

    if not 1 < k <= 1 << 16:
        raise ValueError("k must be from 2 to 65536")
    ends = assigned.select(F.explode(F.array("src", "dst")).alias("v"), "p")
    return ends.groupBy("v").applyInPandasWithState(update, "v long, replicas int", "mask string", "update", GroupStateTimeout.NoTimeout)


class LiveClusters:
    """Clusters kept up to date by micro-batches, in a folder of their own.

    Each batch writes a new version there, then notes it; a batch that comes again is skipped.  An object
    on the same folder goes on from the last version noted, so a restarted stream, whose offsets lie there
    too, finds the clusters that belong to them.  Of older versions the last one is kept.
    """

    _SCHEMA = "v long, c long, d long"

    def __init__(self, spark: SparkSession, cap: int | None, state_dir: str) -> None:
        self.spark, self.cap, self.state_dir = prepare(spark), cap, state_dir.rstrip("/")
        self.version, self.clusters = -1, spark.createDataFrame([], self._SCHEMA)
        if exists(spark, f"{self.state_dir}/noted"):
            self.version = spark.read.schema("version long").parquet(f"{self.state_dir}/noted").agg(F.max("version")).first()[0]
            self.clusters = self._read(self.version)

    def _read(self, version: int) -> DataFrame:
        return self.spark.read.schema(self._SCHEMA).parquet(f"{self.state_dir}/version-{version}")

    def update(self, batch: DataFrame, version: int) -> None:
        """Degrees grow by the batch's edges, unseen vertices open clusters, then one bulk round runs."""
        if version <= self.version:
            return
        edges = materialise(batch.select("src", "dst", F.monotonically_increasing_id().alias("pos")), "live-edges")
        seen = edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count("*").alias("n"))
        grown = self.clusters.join(seen, "v", "full_outer").select("v", F.coalesce("c", "v").alias("c"), (F.coalesce("d", F.lit(0)) + F.coalesce("n", F.lit(0))).cast("long").alias("d"))
        grown = materialise(grown, "live-clusters")
        clustering.one_round(edges, grown, self.cap).write.mode("overwrite").parquet(f"{self.state_dir}/version-{version}")
        self.spark.createDataFrame([(version,)], "version long").write.mode("append").parquet(f"{self.state_dir}/noted")
        before, self.version, self.clusters = self.version, version, self._read(version)
        if before > 0:
            remove(self.spark, f"{self.state_dir}/version-{before - 1}")


def run(edges: DataFrame, state: LiveClusters, trigger: dict | None = None) -> StreamingQuery:
    """Feed a stream of ``src, dst`` to the clusters."""
    writer = edges.writeStream.foreachBatch(state.update).option("checkpointLocation", f"{state.state_dir}/log")
    return writer.trigger(**(trigger or {"availableNow": True})).start()


def session_counts(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Events of each user's session, on a stream or a table: a session ends when nothing follows within the gap."""
    counts = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return counts.select("user_id", F.col("w.start").alias("start"), "n")
