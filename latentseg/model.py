"""The classifier: one distribution a label over a shared vocabulary."""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import decide, em, lattice, planner, score
from .io import stash
from .text import chunk_counts, pretokenize


@dataclass
class SegmentModel:
    vocab: DataFrame
    theta: DataFrame  # label, token_id, logp, logp_fx, seen, c
    stats: DataFrame
    trace: DataFrame | None = None
    kind: str = "regex"
    prefix_space: bool = False
    unit: str = "codepoint"

    @classmethod
    def fit(cls, corpus: DataFrame, vocab: DataFrame, label_col: str = "label", text_col: str = "text", kind: str = "regex", prefix_space: bool = False, unit: str = "codepoint", chunks: DataFrame | None = None, **params) -> SegmentModel:
        """Fits all labels of a corpus in one job a round. n_samples of the statistics counts rows of the corpus. kind, prefix_space and unit say how text is cut (text.pretokenize);
        unit byte wants a vocabulary whose characters stand for bytes. chunks: the corpus cut and counted so already, if it is fitted several times."""
        if chunks is None:
            chunks = stash(chunk_counts(corpus, label_col, text_col, kind, prefix_space, unit), "chunks")
        fitted = em.fit(chunks, vocab, **params)
        rows = corpus.groupBy(F.col(label_col).alias("label")).agg(F.count(F.lit(1)).alias("n_samples"))
        stats = fitted.stats.drop("n_samples").join(rows, "label").select("label", "n_samples", "n_tokens", "floor", "entropy", "rounds", "tv")
        return cls(vocab, stash(fitted.theta, "theta"), stash(stats, "stats"), fitted.trace, kind, prefix_space, unit)

    def chunks(self, text: str | Column) -> Column:
        """How the model cuts a text."""
        return pretokenize(F.col(text) if isinstance(text, str) else text, self.kind, self.prefix_space, self.unit)

    def labels(self) -> list[str]:
        return sorted(r[0] for r in self.stats.select("label").collect())

    def subset(self, labels: list[str]) -> SegmentModel:
        """Restriction needs no fitting: on a saved model it is partition pruning."""
        keep = F.col("label").isin(labels)
        return replace(self, theta=self.theta.where(keep), stats=self.stats.where(keep))

    def without(self, labels: list[str]) -> SegmentModel:
        return self.subset([x for x in self.labels() if x not in labels])

    def merge(self, other: SegmentModel) -> SegmentModel:
        return replace(self, theta=self.theta.unionByName(other.theta), stats=self.stats.unionByName(other.stats))

    def add_label(self, corpus: DataFrame, label_col: str = "label", text_col: str = "text", **params) -> SegmentModel:
        """Fits the labels of `corpus` alone and appends their rows; old rows stay as they are."""
        return self.merge(SegmentModel.fit(corpus, self.vocab, label_col, text_col, self.kind, self.prefix_space, self.unit, **params))

    def cap_unseen(self, c: float = -17.0) -> SegmentModel:
        """Tokens that never occur in a label's corpus get min(value, c). They share one floor a label, so only the statistics change; tokens that occur have rows of their own in theta."""
        return replace(self, stats=self.stats.withColumn("floor", F.least("floor", F.lit(c))))

    def unseen(self) -> DataFrame:
        """(label, seen, unseen): tokens of the vocabulary that occur in a label's corpus, and that never do."""
        v = self.vocab.count()
        n = self.theta.groupBy("label").agg(F.count(F.lit(1)).alias("seen"))
        return n.withColumn("unseen", F.lit(v).cast("long") - F.col("seen"))

    def size(self) -> DataFrame:
        """One row: labels, tokens, dense cells, stored rows."""
        v, l = self.vocab.count(), self.stats.count()
        return self.theta.agg(F.lit(l).cast("long").alias("labels"), F.lit(v).cast("long").alias("tokens"), F.lit(v * l).cast("long").alias("dense"), F.count(F.lit(1)).alias("stored"))

    def save(self, path: str) -> str:
        """Writes a new version folder, then the pointer to it; readers never see half a model."""
        version = uuid.uuid4().hex
        spark = self.vocab.sparkSession
        self.vocab.write.parquet(f"{path}/{version}/vocab")
        self.theta.write.partitionBy("label").parquet(f"{path}/{version}/theta")
        self.stats.write.parquet(f"{path}/{version}/stats")
        meta = json.dumps({"version": version, "kind": self.kind, "prefix_space": self.prefix_space, "unit": self.unit})
        spark.createDataFrame([(meta,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/current")
        return version

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> SegmentModel:
        meta = json.loads(spark.read.text(f"{path}/current").first()[0])
        at = f"{path}/{meta['version']}"
        theta = spark.read.parquet(f"{at}/theta").withColumn("label", F.col("label").cast("string"))
        return cls(spark.read.parquet(f"{at}/vocab"), theta, spark.read.parquet(f"{at}/stats"), None, meta["kind"], meta["prefix_space"], meta["unit"])

    def transform(self, df: DataFrame, text_col: str = "text", how: str = "best", topk: int = 5, block: int | None = None, engine: str = "auto", prior: dict[str, float] | None = None, distinct_share: float | None = None) -> DataFrame:
        """Adds topk, label, score, margin and posterior. With a prior all of them are of score plus log prior, over all labels (one that the prior lacks gets 1e-300); else the prior is
        uniform. posterior holds the listed labels, normalised over all. Null or empty texts get nulls. engine: auto, dictionary (A), map (B) or native (C); distinct_share: distinct
        chunks over chunks, if known, lets auto weigh A."""
        if engine == "auto":
            engine = planner.choose_engine(self.stats.count(), self.vocab.count(), how, distinct_share)
        return decide.decorate(score.score_labels(df, self, text_col, how, topk, block, engine, prior))


def block_matrix(model: SegmentModel, labels: list[str], how: str) -> tuple[dict[str, int], np.ndarray]:
    """Dense values [tokens + 2, labels] of a block of labels: fixed point for best splits, logs for sums. The caller bounds the block."""
    ids = lattice.collect_vocab(model.vocab)
    col = {x: k for k, x in enumerate(labels)}
    floors = {r[0]: r[1] for r in model.stats.where(F.col("label").isin(labels)).select("label", "floor").collect()}
    fx = how == "best"
    out = np.empty((len(ids) + 2, len(labels)), np.int32 if fx else float)
    for x, k in col.items():
        out[:, k] = round(floors[x] * em.SCALE) if fx else floors[x]
    pdf = model.theta.where(F.col("label").isin(labels)).select("label", "token_id", "logp_fx" if fx else "logp").toPandas()
    out[pdf["token_id"].to_numpy(int), pdf["label"].map(col).to_numpy(int)] = pdf.iloc[:, 2].to_numpy()
    out[-2] = round(em.UNKNOWN * em.SCALE) if fx else em.UNKNOWN
    out[-1] = 0 if fx else -np.inf  # never read: a place without an edge is skipped
    return ids, out


def top_entries(theta: DataFrame, k: int = 10) -> DataFrame:
    """The k most probable tokens of each label."""
    return theta.withColumn("rank", F.row_number().over(Window.partitionBy("label").orderBy(F.desc("logp_fx"), "token_id"))).where(F.col("rank") <= k)
