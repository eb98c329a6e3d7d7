"""Choice of plan for scoring, and checks of plans."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

#: Bytes of a label block's matrix that is broadcast at once, and of all matrices that a worker holds in one pass.
BLOCK_BYTES, PASS_BYTES = 128 << 20, 1 << 30


def block_size(n_tokens: int, n_labels: int, how: str = "best", most: int = BLOCK_BYTES) -> int:
    return max(1, min(n_labels, most // ((4 if how == "best" else 8) * (n_tokens + 2))))


def choose_engine(n_labels: int, n_tokens: int, how: str = "best", distinct_share: float | None = None) -> str:
    """map: one scan, no shuffle, a memory of chunks in each task. dictionary pays two shuffles and wins only where a chunk's kernel is dear (many
    labels) and chunks repeat much (a known share of distinct chunks)."""
    return "dictionary" if distinct_share is not None and distinct_share < 0.02 and n_labels > 200 else "map"


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def facts(df: DataFrame) -> dict:
    """What tests assert of a physical plan."""
    text = plan_text(df)
    tree = text.split("\n\n")[0]
    return {
        "exchanges": len(re.findall(r"\bExchange\b", tree)),
        "broadcasts": len(re.findall(r"BroadcastHashJoin", tree)),
        "cartesian": "CartesianProduct" in tree,
        "python": len(re.findall(r"Python|Pandas|Arrow", tree)),
        "pushed": re.findall(r"PushedFilters: \[(.*?)\]", text),
        "read": re.findall(r"ReadSchema: (.*)", text),
    }
