"""Naive Bayes over one split for all labels: the same vocabulary, but the split comes from the pooled distribution. It isolates what splitting per label adds."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import em, lattice
from ..cluster import lean
from ..io import join_frequent, spread, stash
from ..model import SegmentModel, block_matrix
from ..score import SplitKernel, scan, segment, whole_chunks
from ..text import chunk_counts

#: Cells, tokens by labels, of the values that every worker holds; chunks that are split at a time.
HELD, CHUNKS = 8_000_000, 20_000


def fixed_point(c: Column, t: Column, k: float, v: int) -> Column:
    """The value of a token that a label has c times among its t, in millionths of nats."""
    return F.round(F.log((c + k) / (t + k * v)) * 1_000_000).cast("long")


def with_tokens(ids: dict[str, int], fx: np.ndarray, more: list[str]) -> tuple[dict[str, int], np.ndarray]:
    """Characters that the vocabulary lacks as tokens of their own, each with the score of the unknown token: no split changes."""
    new = [x for x in dict.fromkeys(more) if x not in ids]
    return ids | {x: len(ids) + i for i, x in enumerate(new)}, np.concatenate([fx[:-2], np.repeat(fx[-2:-1], len(new), axis=0), fx[-2:]])


def token_counts(chunks: DataFrame, pooled: SegmentModel) -> DataFrame:
    """(label, token, c) of chunks (label, chunk, n, split), split under the label `split` of the pooled model. Tasks add up what they have; the caller adds up tasks."""
    splits = pooled.labels()
    sent = chunks.sparkSession.sparkContext.broadcast((block_matrix(pooled, splits, "best"), {x: i for i, x in enumerate(splits)}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (known, matrix), col = sent.value
        for whole in batches:
            for at in range(0, whole.num_rows, CHUNKS):
                pdf = whole.slice(at, CHUNKS).to_pandas()
                ids, fx = with_tokens(known, matrix, list("".join(pdf["chunk"])))
                names, longest = np.array(list(ids), dtype=object), max(map(len, ids), default=1)
                names[list(ids.values())] = list(ids)
                for split, part in pdf.groupby("split"):
                    owner, labels = pd.factorize(part["label"])
                    n, c = part["n"].to_numpy(np.int64), np.zeros((len(labels), len(ids)), np.int64)
                    for rows, tok in lattice.tensors(part["chunk"].tolist(), ids, longest):
                        of, token = lattice.split_tokens(tok, fx[:, col[split]].astype(np.int64))
                        np.add.at(c, (owner[rows[of]], token), n[rows[of]])
                    i, j = np.nonzero(c)
                    yield pa.RecordBatch.from_arrays([pa.array(np.asarray(labels, object)[i], pa.string()), pa.array(names[j], pa.string()), pa.array(c[i, j], pa.int64())], names=["label", "token", "c"])

    return spread(chunks.select("label", "chunk", "n", "split")).mapInArrow(lean(run), "label string, token string, c long")


def kernel_of(pooled: SegmentModel, table: DataFrame, totals: DataFrame, v: int, k: float, split_of: dict[str, str]) -> tuple[list[str], tuple] | None:
    """The labels in order and what a SplitKernel takes, the labels of the pooled model being split_of each; None if its cells are too many to be sent."""
    labels, splits = sorted(r[0] for r in totals.select("label").collect()), pooled.labels()
    more = table.select("token").distinct().count()
    if not labels or (v + more) * (len(labels) + len(splits)) > HELD:
        return None
    cells = table.join(F.broadcast(totals), "label").select("label", "token", fixed_point(F.col("c"), F.col("t"), k, v).alias("v")).toArrow().to_pandas()  # totals: a row a label
    none = {r["label"]: r["v"] for r in totals.select("label", fixed_point(F.lit(0), F.col("t"), k, v).alias("v")).collect()}
    ids, fx = with_tokens(*block_matrix(pooled, splits, "best"), cells["token"].tolist())
    values = np.tile(np.array([none[x] for x in labels], np.int64), (len(fx), 1))
    values[cells["token"].map(ids).to_numpy(int), cells["label"].map({x: i for i, x in enumerate(labels)}).to_numpy(int)] = cells["v"]
    return labels, (ids, fx, values, np.array([splits.index(split_of[x]) for x in labels]))


@dataclass
class FixedSegNB:
    pooled: SegmentModel
    table: DataFrame  # label, token, c
    totals: DataFrame  # label, t
    v: int
    k: float

    @classmethod
    def fit(cls, df: DataFrame, vocab: DataFrame, label_col: str = "label", text_col: str = "text", k: float = 0.5, rounds: int = 5, chunks: DataFrame | None = None) -> FixedSegNB:
        """chunks: df cut and counted so already (text.chunk_counts), if it is there."""
        if chunks is None:
            chunks = stash(chunk_counts(df, label_col, text_col), "chunks")
        whole = stash(chunks.groupBy("chunk").agg(F.sum("n").alias("n")).select(F.lit("*").alias("label"), "chunk", "n"), "chunks")
        pooled = SegmentModel.fit(df.select(F.lit("*").alias("label")), vocab, rounds=rounds, chunks=whole)
        table = stash(token_counts(chunks.withColumn("split", F.lit("*")), pooled).groupBy("label", "token").agg(F.sum("c").alias("c")), "tokens")
        return cls(pooled, table, stash(table.groupBy("label").agg(F.sum("c").alias("t")), "totals"), vocab.count(), k)

    @staticmethod
    def _tokens(df: DataFrame, pooled: SegmentModel, keys: list[str]) -> DataFrame:
        """(keys, token, m): chunks are split once each and joined back."""
        chunks = df.select(*keys, F.explode(pooled.chunks("text")).alias("chunk")).where("chunk <> ''").groupBy(*keys, "chunk").agg(F.count(F.lit(1)).alias("m"))
        cut = segment(chunks.groupBy("chunk").agg(F.count(F.lit(1)).alias("f")), whole_chunks(pooled), "chunk").select("chunk", "tokens", "f")
        return join_frequent(chunks, stash(cut, "cuts"), "chunk").select(*keys, F.explode("tokens").alias("token"), "m").groupBy(*keys, "token").agg(F.sum("m").alias("m"))

    def transform(self, df: DataFrame, key: str, text_col: str = "text") -> DataFrame:
        """df with label: the best score, ties to the smaller label. key tells rows apart. Values that are few enough are sent, and texts meet them in one scan."""
        if (made := kernel_of(self.pooled, self.table, self.totals, self.v, self.k, {r[0]: "*" for r in self.totals.select("label").collect()})) is not None:
            df, sent, names = df.drop("label"), df.sparkSession.sparkContext.broadcast(made[1]), np.array(made[0], dtype=object)
            kind = T.StructType([T.StructField("row", df.schema), T.StructField("label", T.StringType())])
            said = lambda row, total, has: [row, pa.array(names[total.argmax(axis=1)], pa.string(), mask=~has)]
            return scan(df, F.filter(self.pooled.chunks(F.col(text_col)), lambda c: c != ""), lambda: [SplitKernel(*sent.value)], len(names), kind, said).select("row.*", "label")
        t = self._tokens(df.select(key, F.col(text_col).alias("text")), self.pooled, [key])
        t = stash(t, "tokens")
        cells = t.groupBy("token").agg(F.count(F.lit(1)).alias("f")).join(F.broadcast(self.totals)).join(self.table, ["label", "token"], "left")  # totals: a row a label
        value = fixed_point(F.coalesce("c", F.lit(0)), F.col("t"), self.k, self.v)
        cells = stash(cells.groupBy("token").agg(F.max("f").alias("f"), F.collect_list(F.struct("label", value.alias("v"))).alias("vs")), "cells")
        s = join_frequent(t, cells, "token").select(key, "m", F.explode("vs").alias("x")).groupBy(key, F.col("x.label").alias("label")).agg(F.sum(F.col("m") * F.col("x.v")).alias("score"))
        best = s.groupBy(key).agg(F.min_by("label", F.struct((-F.col("score")).alias("s"), "label")).alias("label"))
        return df.drop("label").join(best, key, "left")
