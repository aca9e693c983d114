"""Facts about a frame's physical plan, for tests and tuning."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def plan_facts(df: DataFrame) -> dict[str, object]:
    """Exchanges, aggregates, Python nodes and the columns each scan reads."""
    text = physical(df)
    return {
        "exchanges": len(re.findall(r"^\(\d+\) Exchange", text, re.M)),
        "hash_aggregates": len(re.findall(r"^\(\d+\) HashAggregate", text, re.M)),
        "object_aggregates": len(re.findall(r"^\(\d+\) ObjectHashAggregate", text, re.M)),
        "python": len(re.findall(r"^\(\d+\) \w*(?:Python|Arrow|Pandas)\w*", text, re.M)),
        "broadcasts": len(re.findall(r"^\(\d+\) BroadcastExchange", text, re.M)),
        "read": re.findall(r"ReadSchema: struct<(.*?)>$", text, re.M),
        "pushed": re.findall(r"PushedFilters: \[(.*?)\]$", text, re.M),
    }
