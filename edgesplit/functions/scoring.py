"""Scores of the stateful methods as column expressions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType, LongType


def replica_term(replicated: Column, own_degree: Column, degree_sum: Column) -> Column:
    """Zero without a replica, else 2 - d/(d_u + d_v): a replica of the rarer vertex weighs more."""
    return F.when(replicated, F.lit(2.0) - own_degree / degree_sum).otherwise(F.lit(0.0))


def cluster_term(on_partition: Column, own_volume: Column, volume_sum: Column) -> Column:
    """The cluster's share of both volumes where its partition is the candidate."""
    return F.when(on_partition, own_volume / volume_sum).otherwise(F.lit(0.0))


def pair_score(du: Column, dv: Column, vol_u: Column, vol_v: Column, rep_u: Column, rep_v: Column, u_home: Column, v_home: Column, terms: tuple[str, ...] = ("replica", "cluster")) -> Column:
    """Score of one candidate partition for an edge."""
    score = F.lit(0.0)
    if "replica" in terms:
        score = score + replica_term(rep_u, du, du + dv) + replica_term(rep_v, dv, du + dv)
    if "cluster" in terms:
        score = score + cluster_term(u_home, vol_u, vol_u + vol_v) + cluster_term(v_home, vol_v, vol_u + vol_v)
    return score


def first_candidate_wins(du: Column, dv: Column, vol_u: Column, vol_v: Column, uu: Column, vu: Column, uv: Column, vv: Column) -> Column:
    """Whether u's candidate wins, in integers.  ``xy``: vertex x is replicated on y's partition.

    The candidate that holds more ends wins; equal counts are settled by products, ties go to u's.
    """
    wide = lambda x: x.cast("decimal(18,0)")
    on_u, on_v = uu.cast("int") + vu.cast("int"), uv.cast("int") + vv.cast("int")
    apart = wide(vol_u) * wide(dv) >= wide(vol_v) * wide(du)
    crossed = wide(du) * wide(vol_u) >= wide(dv) * wide(vol_v)
    even = F.when((on_u == 1) & uu & vv, apart).when((on_u == 1) & vu & uv, crossed).otherwise(vol_u >= vol_v)
    return F.when(on_u != on_v, on_u > on_v).otherwise(even)


def balance_term(load: Column, least: Column, most: Column, lam: float, eps: float) -> Column:
    return F.lit(lam) * (most - load) / (F.lit(eps) + most - least)


@pandas_udf(DoubleType())
def pair_score_arrow(du: pd.Series, dv: pd.Series, own: pd.Series, vol_u: pd.Series, vol_v: pd.Series, rep_u: pd.Series, rep_v: pd.Series) -> pd.Series:
    """The pair score by Arrow batches, where ``own`` is the volume at home on the candidate: to compare with the native one."""
    both = du + dv
    return rep_u * (2 - du / both) + rep_v * (2 - dv / both) + own / (vol_u + vol_v)


@pandas_udf(LongType())
def merge_masks(mask: pd.Series) -> int:
    """Bitwise or of a group's replica masks, as a user's own aggregate: to compare with the native one."""
    return int(np.bitwise_or.reduce(mask.to_numpy(np.int64)))
