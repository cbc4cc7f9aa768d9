"""Which variant to use."""

from __future__ import annotations


def choose(k: int, expected_job_seconds: float = 0.0, partition_seconds: float | None = None) -> str:
    """Full scan for few partitions, or where the job is so long that better quality repays scoring all k."""
    if k <= 4:
        return "cluster_guided_full"
    if partition_seconds is not None and expected_job_seconds > 20 * partition_seconds * k / 32:
        return "cluster_guided_full"
    return "cluster_guided"
