"""What a plan must hold at scale, read from the executed plan's text."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().toString()


def explain_checks(df: DataFrame) -> dict[str, bool]:
    """Flags: broadcast join, pushed filters, partition filters, top-k node, cartesian product, row-at-a-time Python."""
    t = plan_text(df)
    physical = t[t.find("== Physical Plan ==") :]
    return {
        "broadcast_join": "BroadcastHashJoin" in physical or "BroadcastNestedLoopJoin" in physical, "pushed_filters": bool(re.search(r"PushedFilters: \[[^\]]+\]", physical)), "partition_filters": bool(re.search(r"PartitionFilters: \[[^\]]+\]", physical)),
        "top_k": "TakeOrderedAndProject" in physical, "cartesian": "CartesianProduct" in physical, "row_python": "BatchEvalPython" in physical,
    }
