"""What a plan does, for assertions and for reading."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def executed(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def facts(df: DataFrame) -> dict[str, object]:
    """Counts of exchanges, joins and Python steps of a plan, its pushed filters and the columns it reads."""
    plan = executed(df)
    count = lambda pattern: len(re.findall(pattern, plan))
    return {
        "exchanges": count(r"\bExchange "), "broadcasts": count(r"BroadcastExchange"), "sort_merge": count(r"SortMergeJoin"), "broadcast_join": count(r"Broadcast(?:Hash|NestedLoop)Join"),
        "python": count(r"ArrowEvalPython|MapInArrow|MapInPandas|BatchEvalPython"), "pushed": re.findall(r"PushedFilters: \[(.*?)\]", plan), "read": re.findall(r"ReadSchema: struct<(.*?)>", plan),
    }
