"""Graphs derived from the given tables; each is one SELECT that Spark and DuckDB both run.

A vertex id is ``key * 8 + kind`` (0 order, 1 part, 2 supplier, 3 customer, 4 user, 5 document,
6 page, 7 string), so that ids of different tables never meet.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import string_id

_SPARK_STRING, _DUCK_STRING = "CAST(conv(substr(md5(CAST({0} AS BINARY)), 1, 14), 16, 10) AS BIGINT) * 8 + 7", "('0x' || substr(md5({0}), 1, 14))::BIGINT * 8 + 7"
_SPARK_WORDS = "SELECT doc_id, explode(split(text, '[ \\n\\t\\r]+')) AS w FROM documents"
_DUCK_WORDS = "SELECT doc_id, unnest(regexp_split_to_array(text, '[ \\n\\t\\r]+')) AS w FROM documents"
_SPARK_LINES = "SELECT doc_id, explode(split(text, '\\n')) AS w FROM documents"
_DUCK_LINES = "SELECT doc_id, unnest(string_split(text, chr(10))) AS w FROM documents"

#: Name of the graph -> SELECT of distinct (src, dst); {S} is the engine's string id, {words} and {lines} its tokens.
GRAPHS: dict[str, str] = {
    "cust_part": "SELECT DISTINCT o_custkey * 8 + 3 AS src, l_partkey * 8 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "order_part": "SELECT DISTINCT l_orderkey * 8 AS src, l_partkey * 8 + 1 AS dst FROM lineitem",
    "order_supp": "SELECT DISTINCT l_orderkey * 8 AS src, l_suppkey * 8 + 2 AS dst FROM lineitem",
    "part_supp": "SELECT DISTINCT l_partkey * 8 + 1 AS src, l_suppkey * 8 + 2 AS dst FROM lineitem",
    "cust_order": "SELECT DISTINCT o_custkey * 8 + 3 AS src, o_orderkey * 8 AS dst FROM orders",
    "nation_planted": (
        "SELECT DISTINCT o_custkey * 8 + 3 AS src, (l_partkey - l_partkey % 25 + CASE WHEN l_linenumber <= 6 THEN c_nationkey ELSE l_partkey % 25 END) * 8 + 1 AS dst "
        "FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey"
    ),
    "doc_token": "SELECT DISTINCT doc_id * 8 + 5 AS src, {S} AS dst FROM ({words}) t WHERE w <> ''",
    "doc_line": "SELECT DISTINCT doc_id * 8 + 5 AS src, {S} AS dst FROM ({lines}) t WHERE w <> ''",
    "user_next": (
        "SELECT DISTINCT least(a, b) * 8 + 4 AS src, greatest(a, b) * 8 + 4 AS dst FROM "
        "(SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events) t WHERE a <> b"
    ),
}


def graph_sql(name: str, engine: str = "spark") -> str:
    spark = engine == "spark"
    return GRAPHS[name].replace("{S}", (_SPARK_STRING if spark else _DUCK_STRING).format("w")).replace("{words}", _SPARK_WORDS if spark else _DUCK_WORDS).replace("{lines}", _SPARK_LINES if spark else _DUCK_LINES)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Edges ``src, dst`` of a named graph."""
    if name == "page_link":
        return page_links(spark, sf_dir)
    if name == "embed_knn":
        return knn(table(spark, sf_dir, "embeddings"))
    if name not in GRAPHS:
        raise ValueError(f"unknown graph {name!r}")
    text = graph_sql(name)
    views = {t: table(spark, sf_dir, t) for t in ("orders", "lineitem", "customer", "documents", "events") if t in text}
    # Views get names of their own, so that two folders never mix in one session.
    for t, df in views.items():
        view = f"es_{t}_{abs(hash(sf_dir)) % 10**9}"
        df.createOrReplaceTempView(view)
        text = text.replace(f"FROM {t}", f"FROM {view} AS {t}").replace(f"JOIN {t} ", f"JOIN {view} AS {t} ")
    return spark.sql(text)


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the targets of their links."""
    pages = table(spark, sf_dir, "pages")
    links = pages.select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)")).alias("w"))
    return links.select((F.col("page_id") * 8 + 6).alias("src"), (string_id(F.col("w")) * 8 + 7).alias("dst")).distinct()


PAGE_LINK_SQL = (
    "SELECT DISTINCT page_id * 8 + 6 AS src, ('0x' || substr(md5(w), 1, 14))::BIGINT * 8 + 7 AS dst FROM "
    "(SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS w FROM pages) t"
)


def knn(vectors: DataFrame, neighbours: int = 8, values: int = 1 << 21) -> DataFrame:
    """Edges to the nearest rows by cosine, least id first; all rows meet all, block by block, in matrix products.

    A block holds about ``values`` numbers, so there are more of them, not larger ones, as the table grows; cosines
    are equal if they agree in 12 digits.  Vectors that are null, zero or hold null or non-finite values take no part.
    """
    from pyspark.sql import Window

    odd = lambda y: y.isNull() | F.isnan(y) | (F.abs(y) == float("inf"))
    x = F.col("embedding")
    clean = vectors.where(F.col("vec_id").isNotNull() & x.isNotNull() & ~F.exists(x, odd) & F.exists(x, lambda y: y != 0)).select("vec_id", "embedding")
    held = clean.agg(F.sum(F.size("embedding").cast("long"))).first()[0] or 0
    blocks = max(4, -(-held // values))
    clean = clean.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    left = clean.withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = clean.withColumn("o", F.col("b")).withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        i, j, c = nearest_of_block(*_unit(a), *_unit(b), neighbours)
        return pa.Table.from_arrays([pa.array(i, pa.int64()), pa.array(j, pa.int64()), pa.array(c, pa.float64())], names=["i", "j", "c"])

    met = left.groupBy("b", "o").cogroup(right.groupBy("b", "o")).applyInArrow(run, "i long, j long, c double")
    top = met.withColumn("r", F.row_number().over(Window.partitionBy("i").orderBy(F.desc("c"), "j"))).where(F.col("r") <= neighbours)
    return top.select(F.least("i", "j").alias("src"), F.greatest("i", "j").alias("dst")).distinct()


def _unit(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids in order and their vectors at length 1."""
    rows = rows.sort_by("vec_id").combine_chunks()
    if not rows.num_rows:
        return np.zeros(0, np.int64), np.zeros((0, 0))
    flat = pa.concat_arrays([c.flatten() for c in rows.column("embedding").chunks]).to_numpy(zero_copy_only=False)
    x = flat.astype(np.float64).reshape(rows.num_rows, -1)
    x /= np.abs(x).max(axis=1, keepdims=True)
    return rows.column("vec_id").to_numpy(), x / np.linalg.norm(x, axis=1, keepdims=True)


def nearest_of_block(i: np.ndarray, x: np.ndarray, j: np.ndarray, y: np.ndarray, n: int, tall: int = 1024, wide: int = 4096) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each i its n largest cosines among other ids j (ascending), ties to the least; products are cut to ``tall`` by ``wide``."""
    out = []
    for top in range(0, len(i), tall):
        ids, own = i[top : top + tall], np.arange(min(tall, len(i) - top))
        row, col, best = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        least = np.full(len(ids), -np.inf)
        for at in range(0, len(j), wide):
            near = j[at : at + wide]
            cos = x[top : top + tall] @ y[at : at + wide].T
            begin, end = np.searchsorted(near, ids), np.searchsorted(near, ids, "right")
            for r in own[begin < end].tolist():
                cos[r, begin[r] : end[r]] = -np.inf
            bound = np.maximum(least, np.partition(cos, -n, axis=1)[:, -n]) if not at and len(near) > n else least
            r, c = np.nonzero(cos > (bound - 1e-11)[:, None])
            row, col, best = np.concatenate((row, r)), np.concatenate((col, c + at)), np.concatenate((best, np.round(cos[r, c], 12)))
            order = np.lexsort((col, -best, row))
            row, col, best = row[order], col[order], best[order]
            counts = np.bincount(row, minlength=len(ids))
            starts = np.cumsum(counts) - counts
            keep = np.arange(len(row)) - starts[row] < n
            row, col, best = row[keep], col[keep], best[keep]
            full = counts >= n
            counts = np.minimum(counts, n)
            least[full] = best[(np.cumsum(counts) - 1)[full]]
        out.append((ids[row], j[col], best))
    return tuple(np.concatenate(parts) for parts in zip(*out, strict=True)) if out else (i[:0], j[:0], np.zeros(0))
