"""What a plan does: exchanges, joins, Python stages, pushed filters, read columns."""

import re

from pyspark.sql import DataFrame


def plan_text(df: DataFrame, mode: str = "formatted") -> str:
    return df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), mode)


def plan_report(df: DataFrame) -> dict:
    text = plan_text(df)
    tree = text.split("\n\n")[0]
    count = lambda p: len(re.findall(p, tree))
    return {
        "exchanges": count(r"\bExchange\b"), "broadcasts": count("BroadcastExchange"), "sort_merge_joins": count("SortMergeJoin"), "hash_joins": count("BroadcastHashJoin|ShuffledHashJoin"),
        "nested_loops": count("BroadcastNestedLoopJoin"), "cartesian": count("CartesianProduct"), "python": count("Python|Pandas|Arrow"), "read_schema": sorted(set(re.findall(r"ReadSchema: (.*)", text))), "pushed": sorted(set(re.findall(r"PushedFilters: (.*)", text))),
    }
