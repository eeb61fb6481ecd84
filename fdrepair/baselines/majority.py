"""The most frequent right side of each left side, each FD looked at on its own."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..operators import chase
from ..operators.chase import RepairResult


def majority(df: DataFrame, fds, tid: str, **options) -> RepairResult:
    return chase.repair(df, fds, tid, "greedy", score="freq", **options)
