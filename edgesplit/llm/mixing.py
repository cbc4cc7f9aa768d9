"""Mixing sources to target weights by weighted fair queueing.

Every copy of a document gets a virtual finish time: the words its source has sent up to and
including it, in shuffled order, divided by the source's target.  Copies are range-sorted by it.  The
targets add up to the total budget, so all sources together have sent the budget at virtual time 1:
the mix is truncated there, and a copy that is being sent at that time is cut.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.storage import materialise
from .columns import Packed

WORD = r"[^\x20\x09-\x0D]+"
#: Hash ranges of a source at least, and about how many rows one may hold.
BUCKETS, ROWS_AT_ONCE = 1024, 100_000


def word_count(text):
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def source_targets(sizes: DataFrame, most_repeats: int = 3) -> DataFrame:
    """One row for each source: ``source, source_size, weight, target``.

    ``sizes`` has ``source`` and ``size``.  Weights 1, 2, 3 repeat in code-point order, null last.
    All words are shared by weight; a target stops at ``most_repeats`` times its source's size and
    the excess is shared again by weight.  In order of cap over weight the sources that stop are a
    prefix, so running sums find the water level without a loop.  One row for each source meets in
    one task here: a catalogue of sources, never documents.
    """
    per = sizes.groupBy("source").agg(F.sum("size").cast("decimal(38,0)").alias("source_size"))
    ranked = per.withColumn("weight", (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % 3 + 1)
    caps = ranked.withColumn("cap", (F.col("source_size") * most_repeats).cast("decimal(38,0)")).withColumn("w", F.col("weight").cast("decimal(10,0)"))
    order = Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy()
    levels = caps.withColumns(
        {
            "total": F.sum("source_size").over(whole),
            "capped_before": F.coalesce(F.sum("cap").over(before), F.lit(0)),
            "weight_left": F.sum("w").over(after),
        }
    )
    levels = levels.withColumn("stops", F.col("cap").cast("double") * F.col("weight_left").cast("double") < (F.col("total") - F.col("capped_before")).cast("double") * F.col("weight"))
    shared = levels.withColumns(
        {
            "rest": F.col("total") - F.coalesce(F.sum(F.when(F.col("stops"), F.col("cap"))).over(whole), F.lit(0)),
            "weights": F.sum(F.when(~F.col("stops"), F.col("w"))).over(whole),
        }
    )
    target = F.when(F.col("stops"), F.col("cap").cast("double")).otherwise(F.col("rest").cast("double") * F.col("weight") / F.col("weights").cast("double"))
    return shared.select("source", F.col("source_size").cast("long").alias("source_size"), F.col("weight").cast("int").alias("weight"), target.alias("target"))


def _place(rows: DataFrame, most_repeats: int) -> DataFrame:
    """``rows`` (doc_id, source, size and more) and ``source_size, target, start``: the words that a row's source sends before it.

    A source's rows are in the order of a hash of their doc_id.  Running sums take two levels: ranges of
    that hash, as many as the rows need, then rows inside a range; no source's rows meet in one task.
    """
    buckets = max(BUCKETS, -(-rows.count() // ROWS_AT_ONCE))
    digest = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))
    bucket = F.floor(F.conv(F.substring("digest", 1, 8), 16, 10).cast("long") * buckets / F.lit(float(1 << 32))).cast("int")
    dealt = rows.withColumn("digest", digest).withColumn("bucket", bucket)
    per_bucket = materialise(dealt.groupBy("source", "bucket").agg(F.sum("size").alias("size")), "mix-buckets")
    targets = source_targets(per_bucket, most_repeats)
    before = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = per_bucket.select("source", "bucket", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("offset"))
    facts = offsets.alias("o").join(targets.alias("t"), F.col("o.source").eqNullSafe(F.col("t.source"))).select(
        F.col("o.source").alias("of_source"), F.col("bucket").alias("of_bucket"), "offset", "source_size", "target"
    )
    inside = Window.partitionBy("source", "bucket").orderBy("digest", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    run = dealt.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    joined = run.join(facts, F.col("source").eqNullSafe(F.col("of_source")) & (F.col("bucket") == F.col("of_bucket")), "left")
    return joined.withColumn("start", F.col("offset") + F.col("inside")).select(*rows.columns, "source_size", "target", "start")


def _copies(placed: DataFrame) -> DataFrame:
    """A row for each copy that starts before the budget's virtual time, and one at least for each row, in the order of
    ``virtual_finish``; ``words`` are those that it sends before that time."""
    budget = F.floor(F.col("target") + 0.5).cast("long")
    rounds = F.when(F.col("source_size") > 0, F.greatest(F.lit(1), F.ceil((budget - F.col("start")) / F.col("source_size")))).otherwise(F.lit(1))
    rows = placed.select("*", F.explode(F.sequence(F.lit(0), rounds.cast("int") - 1)).alias("copy"))
    begin = F.col("copy") * F.col("source_size") + F.col("start")
    finish = F.when(F.col("target") > 0, (begin + F.col("size")) / F.col("target"))
    rows = rows.withColumns({"virtual_finish": finish, "words": F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), budget - begin))})
    return rows.repartitionByRange("virtual_finish", "doc_id").sortWithinPartitions("virtual_finish", "doc_id", "copy")


def plan_mix(docs: DataFrame, most_repeats: int = 3) -> DataFrame:
    """``doc_id, source, size, source_size, target, start, taken`` for every row of ``docs``.

    ``start`` is the number of words that the source sends before this row in its shuffled order;
    ``taken`` the words of all its copies that the mix sends before it is truncated, never over
    ``most_repeats`` times size.  A null text has size 0, a null source is a source like any other and
    comes last, repeated rows are dealt one by one, an empty table gives an empty result.  Other
    columns are left out.
    """
    sized = materialise(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "mix-sizes")
    row = ["doc_id", "source", "size", "source_size", "target", "start"]
    served = _copies(_place(sized, most_repeats))
    # Rows that agree in all of this send no words; they come back as often as they came.
    taken = served.groupBy(*row).agg(F.sum("words").alias("taken"), F.sum((F.col("copy") == 0).cast("int")).alias("times"))
    return taken.select(*row, "taken", F.explode(F.sequence(F.lit(1), F.col("times").cast("int")))).drop("col")


def take_copies(docs: DataFrame, most_repeats: int = 3) -> DataFrame:
    """The mix itself: ``docs`` with a row for each copy taken, cut to its first words where the mix is truncated.

    Adds ``size, source_size, target, start, copy`` (from 0), ``virtual_finish`` and ``words`` (those of
    the copy); columns of these names are replaced.  Rows are range-sorted by ``virtual_finish``, so a
    reader of the files in order sees every source at its target rate.  Odd rows are dealt with as in
    ``plan_mix``; rows of size 0 are in no mix.
    """
    made = ["size", "source_size", "target", "start", "copy", "virtual_finish", "words"]
    own = Packed(docs, made, ("doc_id", "source", "text"))
    placed = _place(own.rows.withColumn("size", word_count(F.col("text"))), most_repeats)
    served = _copies(placed.where("size > 0")).where("words > 0")
    cut = served.mapInArrow(_cut_texts, served.schema)
    return cut.select(*own.back(), *made)


_SPAN = re.compile(WORD)


def first_words(text: str, n: int) -> str:
    """The text up to the end of its n-th word."""
    end = 0
    for i, m in enumerate(_SPAN.finditer(text), 1):
        end = m.end()
        if i >= n:
            break
    return text[:end] if n > 0 else ""


def _cut_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if not batch.num_rows:
            continue
        at = batch.schema.get_field_index("text")
        size, keep = batch.column("size").to_pylist(), batch.column("words").to_pylist()
        if any(s != k for s, k in zip(size, keep, strict=True)):
            texts = [t if s == k or t is None else first_words(t, k) for t, s, k in zip(batch.column(at).to_pylist(), size, keep, strict=True)]
            batch = batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type))
        yield batch


#: The mix in DuckDB's SQL, for any table expression with doc_id, source and text.
MIX_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS digest,
         CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size
  FROM {docs}),
per AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size,
         (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS weight
  FROM sized GROUP BY source),
lv AS (
  SELECT source, source_size, weight, 3 * source_size AS cap,
         sum(source_size) OVER () AS total,
         coalesce(sum(3 * source_size) OVER (ORDER BY 3.0 * source_size / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS capped_before,
         sum(weight) OVER (ORDER BY 3.0 * source_size / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS weight_left
  FROM per),
st AS (SELECT *, CAST(cap AS DOUBLE) * CAST(weight_left AS DOUBLE) < CAST(total - capped_before AS DOUBLE) * weight AS stops FROM lv),
tg AS (
  SELECT source, source_size,
         CASE WHEN stops THEN CAST(cap AS DOUBLE)
              ELSE CAST(total - coalesce(sum(CASE WHEN stops THEN cap END) OVER (), 0) AS DOUBLE) * weight
                   / CAST(sum(CASE WHEN NOT stops THEN weight END) OVER () AS DOUBLE) END AS target
  FROM st),
run AS (
  SELECT s.*, coalesce(sum(size) OVER (PARTITION BY source ORDER BY digest, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start
  FROM sized s),
j AS (
  SELECT r.doc_id, r.size, t.source_size, t.target, r.start, CAST(floor(t.target + 0.5) AS BIGINT) AS budget
  FROM run r JOIN tg t ON r.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
       CAST(CASE WHEN source_size > 0 THEN budget // source_size ELSE 0 END * size
            + greatest(0, least(size, budget - CASE WHEN source_size > 0 THEN budget // source_size ELSE 0 END * source_size - start)) AS BIGINT) AS taken
FROM j
"""
