"""Approximate nearest neighbours by collision counting.

Every vector is projected on many single lines; each line keeps its projected values in sorted order.
A query opens a window around its own value on every line, and a vector that lies in enough windows is
verified by its true distance.  Windows are as wide as the query's search radius, one radius for all
rows: a first round at a radius guessed from a bounded sample gives the query its k-th verified
distance over the whole table; where that lies beyond the radius, virtual rehashing widens all its
windows to that distance, and the round that follows is the last.  Lines come in orthogonal groups, so
that a group's squared differences add up to the squared distance and counts tell near from far with
few lines.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.storage import materialise
from .vectors import matrix, usable

NEIGHBOURS = 10
PROJECTIONS = 128
BLOCK_ROWS = 4096
QUERY_ROWS = 4096
#: Rows (fewer for long vectors) from which the first radius is guessed.
SAMPLE_ROWS, SAMPLE_VALUES = 1024, 1 << 20
#: Half a window over the radius, and how far below its mean a vector at the radius may count (in standard deviations).
HALF_WIDTH, SLACK = 1.3, 0.6
_FOUND = "query_id long, vec_id long, score double, verified long"


def lines(dimension: int, projections: int, seed: int = 17) -> np.ndarray:
    """Columns to project on: random orthogonal bases one after the other, scaled as independent normal columns are."""
    draw = np.random.default_rng([seed, dimension])
    bases = [np.linalg.qr(draw.normal(size=(dimension, dimension)))[0] for _ in range(-(-projections // dimension))]
    return np.concatenate(bases, axis=1)[:, :projections] * math.sqrt(dimension)


def least_collisions(projections: int) -> int:
    """The collision threshold: a little under the mean count of a vector at the radius."""
    inside = math.erf(HALF_WIDTH / math.sqrt(2))
    return math.floor(projections * inside - SLACK * math.sqrt(projections * inside * (1 - inside)))


class Block:
    """Sorted projections of one block of vectors."""

    def __init__(self, vectors: np.ndarray, projections: int) -> None:
        self.vectors, self.n = vectors, len(vectors)
        self.lines = lines(vectors.shape[1], projections)
        projected = np.ascontiguousarray((vectors @ self.lines).T)
        self.order = np.argsort(projected, axis=1, kind="stable")
        self.sorted = np.take_along_axis(projected, self.order, axis=1)
        self.least = least_collisions(projections)

    def windows(self, queries: np.ndarray, radius: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First and last place (exclusive) of each query's window on each line."""
        at, half = (queries @ self.lines).T, HALF_WIDTH * radius + 1e-9 * np.abs(queries).max(axis=1, initial=0)
        low = np.stack([np.searchsorted(s, x - half) for s, x in zip(self.sorted, at, strict=True)], axis=1)
        high = np.stack([np.searchsorted(s, x + half, side="right") for s, x in zip(self.sorted, at, strict=True)], axis=1)
        return low, high

    def collisions(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """In how many of one query's windows each vector lies; of a wide window its outside is read."""
        wide = high - low > self.n // 2
        inner = [o[i:j] for o, i, j, w in zip(self.order, low.tolist(), high.tolist(), wide.tolist(), strict=True) if not w]
        outer = [part for o, i, j, w in zip(self.order, low.tolist(), high.tolist(), wide.tolist(), strict=True) if w for part in (o[:i], o[j:])]
        counts = np.full(self.n, int(wide.sum()))
        if inner:
            counts += np.bincount(np.concatenate(inner), minlength=self.n)
        if outer:
            counts -= np.bincount(np.concatenate(outer), minlength=self.n)
        return counts

    def search(self, queries: np.ndarray, radius: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """For each query places and distances of the verified vectors."""
        low, high = self.windows(queries, radius)
        for i, query in enumerate(queries):
            places = np.flatnonzero(self.collisions(low[i], high[i]) >= self.least)
            yield places, np.sqrt(((self.vectors[places] - query) ** 2).sum(axis=1))


def first_radius(queries: np.ndarray, sample: np.ndarray, rows: int, k: int) -> np.ndarray:
    """The k-th distance to a sample of the rows, shrunk as it does in a uniform cloud when ``rows`` fill it."""
    if not len(sample):
        return np.ones(len(queries))
    squares = (queries**2).sum(axis=1)[:, None] + (sample**2).sum(axis=1)[None, :] - 2 * queries @ sample.T
    rank = min(k, len(sample) - 1)
    distance = np.sqrt(np.maximum(np.partition(squares, rank, axis=1)[:, rank], 0))
    return np.maximum(distance * (len(sample) / max(rows, len(sample))) ** (1 / queries.shape[1]), 1e-6 * np.abs(queries).max(axis=1))


def nearest(rows: DataFrame, is_query: Column, k: int = NEIGHBOURS, projections: int = PROJECTIONS, block_rows: int = BLOCK_ROWS, query_rows: int = QUERY_ROWS) -> DataFrame:
    """``query_id, rank, vec_id, score, verified``: for each query the ``k`` nearest rows found, by Euclidean distance.

    ``rows`` has vec_id and embedding; ``is_query`` picks the queries.  ``verified`` is the number of
    rows whose distance to the query was computed in its last round.  Candidates are all rows but
    those with the query's own vec_id; ties go to the smaller vec_id.  A vector that is null, empty,
    zero or holds null or non-finite components takes no part, nor do rows with a null vec_id; rows
    that repeat a vec_id count once, by their smallest vector; vectors of another length than the
    query's are not compared.  An empty table gives an empty result.  Queries meet the table block by
    block: a task holds one block of rows and one of queries, however large both are.
    """
    clean = rows.where(F.col("vec_id").isNotNull() & usable(F.col("embedding"))).select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>").alias("embedding"), is_query.alias("q"))
    clean = clean.groupBy("vec_id").agg(F.min("embedding").alias("embedding"), F.max("q").alias("q"))
    clean = materialise(clean.withColumn("dim", F.size("embedding")), "nearest-rows")
    # One row for each length of vectors.
    known = {r["dim"]: (r["n"], r["wanted"]) for r in clean.groupBy("dim").agg(F.count("*").alias("n"), F.count(F.when(F.col("q"), 1)).alias("wanted")).collect()}
    samples = {d: _sample(clean, d, n) for d, (n, wanted) in known.items() if wanted}
    total, wanted = sum(n for n, _ in known.values()), sum(w for _, w in known.values())
    blocks, query_blocks = max(1, -(-total // block_rows)), max(1, -(-wanted // query_rows))
    data = clean.select("vec_id", "embedding", "dim", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("long").alias("block"), F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))).alias("query_block"))

    def guess(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims = np.asarray(batch.column("dim"))
            for d in np.unique(dims).tolist():
                part = batch.filter(pa.array(dims == d))
                radius = first_radius(matrix(part.column("embedding")), samples[d], known[d][0], k)
                yield pa.RecordBatch.from_arrays([part.column("vec_id"), part.column("embedding"), part.column("dim"), pa.array(radius)], names=["vec_id", "embedding", "dim", "radius"])

    asked = materialise(clean.where("q").select("vec_id", "embedding", "dim").mapInArrow(guess, "vec_id long, embedding array<double>, dim int, radius double"), "nearest-queries")

    def run(own: pa.Table, queries: pa.Table) -> pa.Table:
        ids, vectors = own.column("vec_id").to_numpy(), matrix(own.column("embedding"))
        out: list[list] = [[], [], [], []]
        if len(ids) and queries.num_rows:
            names = queries.column("vec_id").to_pylist()
            for q, (places, distance) in zip(names, Block(vectors, projections).search(matrix(queries.column("embedding")), queries.column("radius").to_numpy()), strict=True):
                if not len(places):
                    continue
                others = ids[places] != q
                places, distance = places[others], distance[others]
                best = np.lexsort((ids[places], distance))[:k]
                out[0].append(np.full(len(best), q))
                out[1].append(ids[places][best])
                out[2].append(distance[best])
                out[3].append(np.where(np.arange(len(best)) == 0, len(places), 0))
        kinds = (np.int64, np.int64, np.float64, np.int64)
        return pa.Table.from_arrays([pa.array(np.concatenate(x).astype(t) if x else np.zeros(0, t)) for x, t in zip(out, kinds, strict=True)], names=["query_id", "vec_id", "score", "verified"])

    keys = ("block", "query_block", "dim")
    settled, at_most = [], F.create_map(*[F.lit(x) for d, (n, _) in known.items() for x in (d, min(k, n - 1))]) if known else None
    while True:  # a radius settles its query or at least doubles, so windows hold everything in the end
        spread = asked.select(
            "vec_id", "embedding", "dim", "radius", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("block"), F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(query_blocks)).cast("int").alias("query_block")
        )
        met = data.groupBy(*keys).cogroup(spread.groupBy(*keys)).applyInArrow(run, _FOUND)
        by_query = Window.partitionBy("query_id")
        ranked = met.withColumns({"rank": F.row_number().over(by_query.orderBy("score", "vec_id")), "verified": F.sum("verified").over(by_query)}).where(F.col("rank") <= k)
        ranked = materialise(ranked, "nearest-found")
        settled.append(ranked)
        if at_most is None:
            break
        reached = ranked.groupBy("query_id").agg(F.count("*").alias("n"), F.max("score").alias("furthest"))
        again = asked.join(reached, asked["vec_id"] == reached["query_id"], "left").withColumn("wanted", F.element_at(at_most, F.col("dim")))
        full = F.coalesce(F.col("n"), F.lit(0)) >= F.col("wanted")
        again = again.where((F.col("wanted") > 0) & ~(full & (F.coalesce("furthest", F.lit(0.0)) <= F.col("radius"))))
        wider = F.when(full, F.col("furthest")).otherwise(F.col("radius") * 2)
        again = materialise(again.select("vec_id", "embedding", "dim", wider.alias("radius")), "nearest-queries")
        if again.isEmpty():
            break
        settled[-1] = ranked.join(again.select(F.col("vec_id").alias("query_id")), "query_id", "left_anti")
        asked = again
    out = settled[0]
    for x in settled[1:]:
        out = out.unionByName(x)
    return out.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score", "verified")


def _sample(clean: DataFrame, dimension: int, rows: int) -> np.ndarray:
    """A sample, bounded in expectation, of the vectors of one length: those whose hash falls on a share of its values."""
    n = max(64, min(SAMPLE_ROWS, SAMPLE_VALUES // dimension))
    chosen = (F.col("dim") == dimension) & (F.pmod(F.xxhash64("vec_id", F.lit(5)), F.lit(rows)) < n)
    found = clean.where(chosen).select("vec_id", "embedding").toArrow().sort_by("vec_id")
    return matrix(found.column("embedding"))
