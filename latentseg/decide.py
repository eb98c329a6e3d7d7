"""From scores to labels, posteriors and margins."""

from __future__ import annotations

from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

if TYPE_CHECKING:
    from .model import SegmentModel


def predict(topk: Column) -> Column:
    return F.get(topk, F.lit(0))["label"]


def margin(topk: Column) -> Column:
    """Best score less the next; null with one label."""
    return F.get(topk, F.lit(0))["score"] - F.get(topk, F.lit(1))["score"]


def posterior(topk: Column, log_total: Column | None = None) -> Column:
    """Map label -> probability of the listed labels. log_total is the log of the sum of exponentials over all labels; without it the listed ones are all there are."""
    if log_total is None:
        top = F.array_max(F.transform(topk, lambda x: x["score"]))
        log_total = top + F.log(F.aggregate(topk, F.lit(0.0), lambda a, x: a + F.exp(x["score"] - top)))
    return F.map_from_entries(F.transform(topk, lambda x: F.struct(x["label"], F.exp(x["score"] - log_total))))


def decorate(scored: DataFrame) -> DataFrame:
    """Adds label, score, margin and posterior next to topk; takes log_total away."""
    top = F.col("topk")
    return scored.withColumns({"label": predict(top), "score": F.get(top, F.lit(0))["score"], "margin": margin(top), "posterior": posterior(top, F.col("log_total"))}).drop("log_total")


def from_rows(scores: DataFrame, keys: list[str], k: int = 5) -> DataFrame:
    """(keys, topk) from rows (keys, label, score): for scores that sit in SQL tables."""
    entries = F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), "label")))
    return scores.groupBy(*keys).agg(F.slice(F.transform(entries, lambda x: F.struct(x["label"].alias("label"), (-x["s"]).alias("score"))), 1, k).alias("topk"))


def hierarchical(df: DataFrame, model: SegmentModel, parents: DataFrame, text_col: str = "text", how: str = "best") -> DataFrame:
    """Family first, then inside: a family's distribution adds its members' counts; rows then meet only the labels of their family. An approximation that
    saves label work where families are many."""
    import dataclasses

    from . import em
    from .io import stash

    fam = {r[0]: r[1] for r in parents.select("label", "family").collect()}
    groups = sorted(set(fam.values()))
    pooled = model.theta.join(F.broadcast(parents.select("label", "family")), "label").groupBy(F.col("family").alias("label"), "token_id").agg(F.sum("c").alias("c"))
    final = em.m_step(pooled)
    samples = model.stats.join(parents.select("label", "family"), "label").groupBy(F.col("family").alias("label")).agg(F.sum("n_samples").alias("n_samples"))
    trace = df.sparkSession.createDataFrame([], "label string, round int, loglik double, tv double")
    theta, stats = em.finish(stash(final, "families"), samples, trace, seen=pooled.select("label", "token_id"))
    upper = dataclasses.replace(model, theta=stash(theta, "families"), stats=stash(stats, "families"))
    first = stash(upper.transform(df, text_col, how).withColumn("family", F.col("label")).drop("topk", "label", "score", "margin", "posterior"), "routed")
    out = None
    for g in groups:  # one scan of the rows of each family
        own = model.subset([x for x, f in fam.items() if f == g]).transform(first.where(F.col("family") == g), text_col, how)
        out = own if out is None else out.unionByName(own)
    lost = first.where("family is null")
    return out.unionByName(lost, allowMissingColumns=True)
