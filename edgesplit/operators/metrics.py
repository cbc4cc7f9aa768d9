"""Cost and accuracy measures of an assignment ``src, dst, p`` (and ``stage``)."""

from __future__ import annotations

import contextlib
import time
from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _covers(assignment: DataFrame) -> DataFrame:
    return assignment.select(F.explode(F.array("src", "dst")).alias("v"), "p").distinct()


def loads(assignment: DataFrame) -> DataFrame:
    return assignment.groupBy("p").agg(F.count("*").alias("n"))


def replication_factor(assignment: DataFrame) -> DataFrame:
    """``replicas, vertices, rf``: one row."""
    per_vertex = _covers(assignment).groupBy("v").agg(F.count("*").alias("r"))
    return per_vertex.agg(F.coalesce(F.sum("r"), F.lit(0)).alias("replicas"), F.count("*").alias("vertices")).withColumn("rf", F.col("replicas") / F.col("vertices"))


def replication_factor_estimate(assignment: DataFrame, k: int, rsd: float = 0.02) -> DataFrame:
    """The same from sketches: a distinct count for each partition and one for all."""
    ends = assignment.select(F.explode(F.array("src", "dst")).alias("v"), "p")
    per = ends.groupBy("p").agg(F.approx_count_distinct("v", rsd).alias("r")).agg(F.sum("r").alias("replicas"))
    return per.crossJoin(ends.agg(F.approx_count_distinct("v", rsd).alias("vertices"))).withColumn("rf", F.col("replicas") / F.col("vertices"))


def imbalance(assignment: DataFrame, k: int) -> DataFrame:
    """``edges, max_load, alpha``: one row."""
    return loads(assignment).agg(F.sum("n").alias("edges"), F.max("n").alias("max_load")).withColumn("alpha", F.col("max_load") * k / F.col("edges"))


def load_statistics(assignment: DataFrame) -> DataFrame:
    """``mean, sd, median, p90, slope`` of the partitions' loads (slope: against the partition's number): one row."""
    facts = {"mean": F.avg("n"), "sd": F.stddev_samp("n"), "median": F.percentile("n", 0.5), "p90": F.percentile("n", 0.9), "slope": F.regr_slope("n", "p")}
    return loads(assignment).agg(*[F.round(x, 6).alias(name) for name, x in facts.items()])


def check_balance(assignment: DataFrame, cap: int) -> DataFrame:
    return loads(assignment).agg((F.coalesce(F.max("n"), F.lit(0)) <= cap).alias("balanced"))


def check_exact_cover(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """``missing, extra``: edges without a place, and places without (or with a second) edge."""
    a, b = edges.select("src", "dst"), assignment.select("src", "dst")
    missing, extra = a.exceptAll(b).agg(F.count("*").alias("missing")), b.exceptAll(a).agg(F.count("*").alias("extra"))
    return missing.crossJoin(extra)


def replica_bitmaps(assignment: DataFrame, k: int) -> DataFrame:
    """``v, bits``: the partitions that hold each vertex as an array of words of 63 bits, for any k."""
    ends = assignment.select(F.explode(F.array("src", "dst")).alias("v"), "p")
    words = [F.bit_or(F.when(F.floor(F.col("p") / 63) == i, F.expr("shiftleft(1L, p % 63)")).otherwise(F.lit(0).cast("long"))) for i in range(-(-k // 63))]
    return ends.groupBy("v").agg(F.array(*words).alias("bits"))


def cover_sketches(assignment: DataFrame, lg_k: int = 14) -> DataFrame:
    """``p, sketch``: a mergeable distinct-count sketch of each partition's vertices."""
    ends = assignment.select(F.explode(F.array("src", "dst")).alias("v"), "p")
    return ends.groupBy("p").agg(F.hll_sketch_agg("v", lg_k).alias("sketch"))


def stage_mix(assignment: DataFrame) -> DataFrame:
    """``stage, n, share``: edges by how they were placed."""
    counts = assignment.groupBy("stage").agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy()))


def sync_messages(assignment: DataFrame) -> DataFrame:
    """``messages``: replicas beyond the first, each synchronised once an iteration of a job."""
    return _covers(assignment).groupBy("v").agg((F.count("*") - 1).alias("m")).agg(F.coalesce(F.sum("m"), F.lit(0)).alias("messages"))


def state_size(clusters: DataFrame, assignment: DataFrame, k: int) -> DataFrame:
    """``dense_bits, sparse_rows``: the replication matrix, and the pairs that are set."""
    return clusters.agg((F.count("*") * k).alias("dense_bits")).crossJoin(_covers(assignment).agg(F.count("*").alias("sparse_rows")))


def cluster_quality(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """``clusters, largest_volume, median_volume, inside_share, modularity``: one row."""
    a, b = (clusters.select(F.col("v").alias(x), F.col("c").alias(f"c_{x}")) for x in ("src", "dst"))
    inside = edges.join(a, "src").join(b, "dst").agg(F.avg((F.col("c_src") == F.col("c_dst")).cast("double")).alias("inside_share"))
    vol = clusters.groupBy("c").agg(F.sum("d").alias("vol"))
    shape = vol.agg(F.count("*").alias("clusters"), F.max("vol").alias("largest_volume"), F.percentile_approx("vol", 0.5).alias("median_volume"), F.sum("vol").alias("total"), F.sum(F.col("vol").cast("double") ** 2).alias("squares"))
    return shape.crossJoin(inside).withColumn("modularity", F.col("inside_share") - F.col("squares") / F.col("total") ** 2).drop("total", "squares")


def evaluate(assignment: DataFrame, k: int, alpha: float) -> DataFrame:
    """``metric, value`` rows."""
    rf, bal = replication_factor(assignment), imbalance(assignment, k)
    one = rf.crossJoin(bal).crossJoin(sync_messages(assignment))
    pairs = [(n, F.col(c).cast("double")) for n, c in (("replication_factor", "rf"), ("vertices", "vertices"), ("edges", "edges"), ("max_load", "max_load"), ("measured_alpha", "alpha"), ("sync_messages", "messages"))]
    return one.select(F.explode(F.array(*[F.struct(F.lit(n).alias("metric"), v.alias("value")) for n, v in pairs])).alias("r")).select("r.*")


def normalise(report: DataFrame, by: str, base) -> DataFrame:
    """Values over those of the row where ``by`` equals ``base``, metric by metric."""
    ref = report.where(F.col(by) == base).select("metric", F.col("value").alias("__base"))
    return report.join(ref, "metric").withColumn("ratio", F.col("value") / F.col("__base")).drop("__base")


class Timer:
    """Seconds by phase."""

    def __init__(self) -> None:
        self.seconds: dict[str, float] = {}

    @contextlib.contextmanager
    def phase(self, name: str) -> Iterator[None]:
        begin = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - begin
