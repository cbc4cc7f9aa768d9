"""Phase 2 in bulk: pre-partitioning, two-candidate scoring, admission under the hard cap, overflow."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import partition_of
from ..functions.scoring import balance_term, first_candidate_wins, pair_score
from ..plans.storage import materialise

_CHUNK_BITS = 14


def vertex_plan(clusters: DataFrame, cluster_map: DataFrame) -> DataFrame:
    """VERTEX_PLAN ``v, d, c, vol, p``: all that phase 2 joins to edges."""
    return clusters.join(cluster_map, "c").select("v", "d", "c", "vol", "p")


def enrich(edges: DataFrame, plan: DataFrame) -> DataFrame:
    """Edges with both ends' degree, cluster, volume and home partition (suffixes _u and _v)."""
    ends = [plan.select(F.col("v").alias(x), *[F.col(c).alias(f"{c}_{s}") for c in ("d", "c", "vol", "p")]) for x, s in (("src", "u"), ("dst", "v"))]
    return edges.join(ends[0], "src").join(ends[1], "dst")


class Loads:
    """Edges on each partition so far; k numbers on the driver."""

    def __init__(self, k: int, cap: int) -> None:
        self.n, self.cap = [0] * k, cap

    def add(self, placed: DataFrame) -> None:
        for r in placed.groupBy("p").agg(F.count("*").alias("n")).collect():
            self.n[r["p"]] += r["n"]

    def free(self) -> list[int]:
        return [max(0, self.cap - x) for x in self.n]


def admit(rows: DataFrame, loads: Loads) -> tuple[DataFrame, DataFrame | None]:
    """Rows with a target ``p``: those that fit, in stream order, and those refused (None: all fit).

    Only where a partition would overflow are rows ranked, in two levels: counts of position chunks
    first, then places inside a chunk.
    """
    wanted = {r["p"]: r["n"] for r in rows.groupBy("p").agg(F.count("*").alias("n")).collect()}
    free = loads.free()
    if all(n <= free[p] for p, n in wanted.items()):
        return rows, None
    chunk = F.shiftright("pos", _CHUNK_BITS)
    parted = rows.withColumn("__chunk", chunk)
    sizes = parted.groupBy("p", "__chunk").agg(F.count("*").alias("n"))
    starts = sizes.select("p", "__chunk", F.coalesce(F.sum("n").over(Window.partitionBy("p").orderBy("__chunk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__start"))
    place = F.row_number().over(Window.partitionBy("p", "__chunk").orderBy("pos"))
    ranked = parted.withColumn("__place", place).join(starts, ["p", "__chunk"]).withColumn("__rank", F.col("__place") + F.col("__start"))
    ranked = materialise(ranked.drop("__chunk", "__place", "__start"), "ranked")
    room = F.element_at(F.array(*[F.lit(x) for x in free]), F.col("p") + 1)
    return ranked.where(F.col("__rank") <= room).drop("__rank"), ranked.where(F.col("__rank") > room).drop("__rank")


def least_loaded_turns(loads: list[int], cap: int, n: int) -> list[tuple[int, int, list[int]]]:
    """Segments (first, last, partitions in turn) of n rows that each go to the least loaded partition."""
    out, at, now = [], 0, list(loads)
    while at < n:
        least = min(x for x in now if x < cap)
        turn = [p for p, x in enumerate(now) if x == least]
        above = min([x for x in now if x > least] + [cap])
        rounds = min(above - least, -(-(n - at) // len(turn)))
        rows = min(n - at, rounds * len(turn))
        out.append((at, at + rows, turn))
        for i, p in enumerate(turn):
            now[p] += rows // len(turn) + (i < rows % len(turn))
        at += rows
    return out


def overflow(rows: DataFrame, loads: Loads, seed: int = 0, which: str = "max", try_second: bool = False) -> list[DataFrame]:
    """Refused edges: to the hash of the endpoint of higher degree while that has room, then to the least loaded."""
    placed = []
    k = len(loads.n)
    if try_second:
        other = rows.withColumn("p", F.when(F.col("p") == F.col("p_u"), F.col("p_v")).otherwise(F.col("p_u")))
        good, rows = admit(other, loads)
        good = materialise(good.withColumn("stage", F.lit("scored")), "placed")
        loads.add(good)
        placed.append(good)
        if rows is None:
            return placed
    heavier = F.col("d_u") >= F.col("d_v") if which == "max" else F.col("d_u") <= F.col("d_v")
    hashed = rows.withColumn("p", partition_of(F.when(heavier, F.col("src")).otherwise(F.col("dst")), k, seed))
    good, rest = admit(hashed, loads)
    good = materialise(good.withColumn("stage", F.lit("hashed")), "placed")
    loads.add(good)
    placed.append(good)
    if rest is not None:
        rest = materialise(rest, "rest")
        total = rest.count()
        # Stream order, numbered by the two-level counts of their positions.
        chunk = F.shiftright("pos", _CHUNK_BITS)
        sizes = rest.groupBy(chunk.alias("__chunk")).agg(F.count("*").alias("n"))
        starts = sizes.select("__chunk", F.coalesce(F.sum("n").over(Window.orderBy("__chunk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__start"))
        numbered = rest.withColumn("__chunk", chunk).withColumn("__i", F.row_number().over(Window.partitionBy("__chunk").orderBy("pos")) - 1).join(starts, "__chunk")
        numbered = numbered.withColumn("__i", F.col("__i") + F.col("__start"))
        choice: Column = F.lit(None).cast("int")
        for first, last, turn in reversed(least_loaded_turns(loads.n, loads.cap, total)):
            ring = F.array(*[F.lit(p) for p in turn])
            choice = F.when((F.col("__i") >= first) & (F.col("__i") < last), F.element_at(ring, ((F.col("__i") - first) % len(turn) + 1).cast("int"))).otherwise(choice)
        last_resort = materialise(numbered.withColumn("p", choice).drop("__i", "__chunk", "__start").withColumn("stage", F.lit("least_loaded")), "placed")
        loads.add(last_resort)
        placed.append(last_resort)
    return placed


def replica_sets(placed: DataFrame) -> DataFrame:
    """``v, ps``: the partitions of each vertex; at most k of them."""
    return placed.select(F.explode(F.array("src", "dst")).alias("v"), "p").distinct().groupBy("v").agg(F.collect_set("p").alias("ps"))


def with_sets(batch: DataFrame, sets: DataFrame) -> DataFrame:
    empty = F.array().cast("array<int>")
    for x, s in (("src", "u"), ("dst", "v")):
        batch = batch.join(sets.select(F.col("v").alias(x), F.col("ps").alias(f"ps_{s}")), x, "left").withColumn(f"ps_{s}", F.coalesce(f"ps_{s}", empty))
    return batch


def choose_of_two(rows: DataFrame, terms: tuple[str, ...] = ("replica", "cluster")) -> DataFrame:
    """Edges with ``p``, the better of the two homes, and both scores; ties go to the first end's."""
    on = {f"{x}{y}": F.array_contains(f"ps_{x}", F.col(f"p_{y}")) for x in "uv" for y in "uv"}
    numbers = [F.col(c) for c in ("d_u", "d_v", "vol_u", "vol_v")]
    scores = [pair_score(*numbers, on[f"u{y}"], on[f"v{y}"], F.lit(y == "u"), F.lit(y == "v"), terms) for y in "uv"]
    if set(terms) == {"replica", "cluster"}:
        first = first_candidate_wins(*numbers, on["uu"], on["vu"], on["uv"], on["vv"])
    else:
        first = scores[0] >= scores[1]
    return rows.withColumns({"score_u": scores[0], "score_v": scores[1], "p": F.when(first, F.col("p_u")).otherwise(F.col("p_v"))})


def choose_of_all(rows: DataFrame, k: int, loads: Loads, lam: float, eps: float, batch: int = 0) -> DataFrame:
    """Edges with ``p`` of the best HDRF score over all partitions with room; scores compare after rounding, ties to the smaller.

    All edges of a batch see the loads at its start.  While a batch of ``batch`` edges (0: one batch alone) goes
    in, the least loaded partition changes with nearly every edge; each edge therefore sees every load raised by a
    hashed part of what the batch may add to it.
    """
    total = F.col("d_u") + F.col("d_v")
    step = batch / k
    seen = [F.lit(float(n)) + F.pmod(F.xxhash64("src", "dst", F.lit(p)), F.lit(4096)) * F.lit(step / 4096) if batch else F.lit(n) for p, n in enumerate(loads.n)]
    rows = rows.withColumn("seen", F.array(*seen))
    rows = rows.withColumns({"least": F.array_min("seen"), "most": F.array_max("seen")})
    options = []
    for p in range(k):
        if loads.n[p] >= loads.cap:
            continue
        part = F.when(F.array_contains("ps_u", p), F.lit(2.0) - F.col("d_u") / total).otherwise(F.lit(0.0)) + F.when(F.array_contains("ps_v", p), F.lit(2.0) - F.col("d_v") / total).otherwise(F.lit(0.0))
        score = part + balance_term(F.col("seen")[p], F.col("least"), F.col("most"), lam, eps)
        options.append(F.struct(F.round(score, 9).alias("s"), F.lit(-p).alias("q")))
    best = F.array_max(F.array(*options))
    return rows.withColumn("p", (-best["q"]).cast("int")).drop("seen", "least", "most")


def even_batches(total: int, batches: int) -> list[tuple[int, int]]:
    """Position ranges of so many batches."""
    return [(b * total // batches, (b + 1) * total // batches) for b in range(batches)]


def growing_batches(total: int, first: int = 256, growth: float = 0.5) -> list[tuple[int, int]]:
    """Position ranges that begin small: each holds at most ``growth`` times what came before it.

    All edges of a batch see one state, so a batch may not be large beside the state that guides it.
    """
    cuts = [0]
    while cuts[-1] < total:
        cuts.append(min(total, cuts[-1] + max(first, int(growth * cuts[-1]))))
    return list(zip(cuts, cuts[1:], strict=False))


def place_stream(rows: DataFrame, sets: DataFrame | None, loads: Loads, rounds: list[tuple[int, int]], choose, seed: int = 0, try_second: bool = False, stage: str = "scored", spread: bool = False) -> list[DataFrame]:
    """Edges in batches of positions; each batch sees the replicas of those before it.

    With ``spread`` a partition takes at most an even share of the batch above the least loaded one, and
    what it refuses chooses again among the others, against the loads and replicas as they are by then.
    """
    spark = rows.sparkSession
    sets = sets if sets is not None else spark.createDataFrame([], "v long, ps array<int>")
    out: list[DataFrame] = []
    kept = [c for c in rows.columns]
    for b, (low, high) in enumerate(rounds):
        if low == high:
            continue
        batch = rows.where((F.col("pos") >= low) & (F.col("pos") < high))
        new: list[DataFrame] = []
        for turn in range(2 if spread else 1):
            now = Loads(len(loads.n), loads.cap)
            now.n = list(loads.n)
            if spread and turn == 0:
                level = (sum(loads.n) + high - low) / len(loads.n)
                now.cap = min(loads.cap, max(int(1.1 * level) + 1, min(loads.n) + 1))
            chosen = materialise(choose(with_sets(batch, sets), now, high - low).select(*kept, "p"), "chosen")
            good, refused = admit(chosen, now)
            good = good.withColumn("stage", F.lit(stage))
            loads.add(good)
            new.append(good)
            last = turn == (1 if spread else 0)
            if last and refused is not None:
                new += overflow(refused, loads, seed, try_second=try_second)
            if last or refused is None:
                break
            sets = _with_new(sets, [good])
            batch = refused.drop("p")
        out += [x.select(*kept, "p", "stage") for x in new]
        if b + 1 < len(rounds):
            sets = _with_new(sets, new)
    return out


def _with_new(sets: DataFrame, placed: list[DataFrame]) -> DataFrame:
    """Replica sets after more edges were placed."""
    fresh = placed[0].select("src", "dst", "p")
    for x in placed[1:]:
        fresh = fresh.unionByName(x.select("src", "dst", "p"))
    return materialise(sets.unionByName(replica_sets(fresh)).groupBy("v").agg(F.array_distinct(F.flatten(F.collect_list("ps"))).alias("ps")), "replicas")
