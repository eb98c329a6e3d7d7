"""Floors: the most frequent label, or one drawn by a digest."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..text import hash8


def majority(train: DataFrame, df: DataFrame, label_col: str = "label") -> DataFrame:
    top = train.groupBy(F.col(label_col).alias("label")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "label").limit(1).select("label")
    return df.drop("label").join(F.broadcast(top))  # one row


def uniform(labels: list[str], df: DataFrame, text_col: str = "text") -> DataFrame:
    pick = F.element_at(F.array(*map(F.lit, sorted(labels))), (F.pmod(hash8(F.col(text_col)), F.lit(len(labels))) + 1).cast("int"))
    return df.withColumn("label", pick)
