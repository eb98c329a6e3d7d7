"""Token bigrams over text that the unigram model has split already, interpolated with its distributions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .io import join_frequent, stash
from .model import SegmentModel
from .score import segment, whole_chunks


@dataclass
class TokenBigram:
    model: SegmentModel
    pairs: DataFrame  # label, a, b, c
    firsts: DataFrame  # label, a, t
    weight: float

    @staticmethod
    def _pairs(df: DataFrame, model: SegmentModel, keys: list[str], own: bool) -> DataFrame:
        """(keys, label, a, b, m): pairs inside chunks, each distinct chunk split once per label. own: only under the row's own label."""
        chunks = df.select(*keys, F.explode(model.chunks("text")).alias("chunk")).where("chunk <> ''").groupBy(*keys, "chunk").agg(F.count(F.lit(1)).alias("m"))
        cut = segment(chunks.groupBy("chunk").agg(F.count(F.lit(1)).alias("f")), whole_chunks(model), "chunk")
        cut = stash(cut.groupBy("chunk").agg(F.max("f").alias("f"), F.collect_list(F.struct(F.col("label").alias("under"), "tokens")).alias("cuts")), "cuts")  # a row a label
        j = join_frequent(chunks, cut, "chunk").select(*keys, "m", F.explode("cuts").alias("x")).select(*keys, "m", "x.*")
        j = j.where(F.col("label") == F.col("under")) if own else j
        p = j.select(*keys, "under", "m", F.explode(F.expr("transform(sequence(1, size(tokens)), i -> struct(if(i = 1, '', tokens[i - 2]) as a, tokens[i - 1] as b))")).alias("p"))
        return p.groupBy(*keys, "under", "p.a", "p.b").agg(F.sum("m").alias("m"))

    @classmethod
    def fit(cls, df: DataFrame, model: SegmentModel, label_col: str = "label", text_col: str = "text", weight: float = 0.5) -> TokenBigram:
        src = df.select(F.col(label_col).alias("label"), F.col(text_col).alias("text"))
        pairs = stash(cls._pairs(src, model, ["label"], True).select("label", "a", "b", F.col("m").alias("c")), "pairs")
        return cls(model, pairs, stash(pairs.groupBy("label", "a").agg(F.sum("c").alias("t")), "firsts"), weight)

    def transform(self, df: DataFrame, key: str, text_col: str = "text") -> DataFrame:
        m = self.model
        p = stash(self._pairs(df.select(key, F.col(text_col).alias("text")), m, [key], False).withColumnRenamed("under", "label"), "test")
        cells = p.select("label", "a", "b").distinct().join(self.pairs, ["label", "a", "b"], "left").join(self.firsts, ["label", "a"], "left")
        cells = cells.join(m.vocab.select(F.col("token").alias("b"), "token_id"), "b", "left").join(m.theta.select("label", "token_id", "logp"), ["label", "token_id"], "left").join(F.broadcast(m.stats.select("label", "floor")), "label")
        uni = F.exp(F.coalesce("logp", "floor"))
        mixed = F.when(F.col("t") > 0, self.weight * F.coalesce("c", F.lit(0)) / F.col("t") + (1 - self.weight) * uni).otherwise(uni)
        value = cells.select("label", "a", "b", F.round(F.log(mixed) * 1_000_000).cast("long").alias("v"))
        s = p.join(value, ["label", "a", "b"]).groupBy(key, "label").agg(F.sum(F.col("m") * F.col("v")).alias("score"))
        best = s.groupBy(key).agg(F.min_by("label", F.struct((-F.col("score")).alias("s"), "label")).alias("label"))
        return df.drop("label").join(best, key, "left")
