"""Exact length histogram: documents by encoded length, with suffix sums that answer every context limit.

A document's length is the number of tokens of its whole text under a byte-level merge vocabulary. One row per group and length that
occurs holds the documents of that length and, by sums over all longer lengths, how many documents and tokens a limit of that length keeps
whole, cuts or drops. Totals, quantiles and truncated totals for any limit come from that table alone. Suffix sums are taken within blocks of
lengths and then over blocks.

Defined cases: a null or empty text has 0 tokens; null group values form a group of their own; repeated rows count each; an empty table gives an empty
histogram; other columns are not read; a group may have any name but n_tokens and those of the columns that are added. Text that spells a special token counts as ordinary text.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window
from pyspark.sql import types as T

from ..io import read_table, spread, stash
from .common import named, whole

BLOCK = 256
_encoders: dict[str, object] = {}


def _encoder(digest: str, data: bytes, pattern: str):
    if digest not in _encoders:
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, data.splitlines())}
        _encoders[digest] = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    return _encoders[digest]


def token_lengths(docs: DataFrame, vocab_path: str, pattern: str, groups: list[str], text_col: str = "text") -> DataFrame:
    """(groups, n_tokens), one row per row of docs. The vocabulary is read on the driver and broadcast: a file of fixed size."""
    with open(vocab_path, "rb") as f:
        data = f.read()
    if len(data) > 64 << 20:
        raise ValueError("the vocabulary file is over 64 MB")
    digest, sent = hashlib.sha256(data).hexdigest(), docs.sparkSession.sparkContext.broadcast(data)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _encoder(digest, sent.value, pattern).encode_ordinary
        for b in batches:
            n = pa.array([len(encode(t)) for t in b.column(0).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(1), n], names=["row", "n_tokens"])

    if not groups:
        groups_of = F.struct(F.lit(0).alias("none")).alias("row")
    else:
        groups_of = F.struct(*[named(g) for g in groups]).alias("row")
    df = spread(docs.select(whole(text_col).alias("t"), groups_of))
    out = df.mapInArrow(run, T.StructType([df.schema["row"], T.StructField("n_tokens", T.LongType())]))
    return out.select(*[F.col("row")[g].alias(g) for g in groups], "n_tokens")


def histogram(lengths: DataFrame, groups: list[str]) -> DataFrame:
    """(groups, n_tokens, docs), exact and mergeable: histograms of parts add up."""
    return lengths.groupBy(*groups, "n_tokens").agg(F.count(F.lit(1)).alias("docs"))


def suffix_sums(hist: DataFrame, groups: list[str]) -> DataFrame:
    """Adds, for a limit of n_tokens: tokens (of exactly that length), longer_docs, longer_tokens, total_docs, total_tokens,
    truncated_tokens (all documents, each cut at the limit) and share_whole_ppm (documents that fit, per million)."""
    h = hist.withColumn("tokens", F.col("n_tokens") * F.col("docs")).withColumn("block_", F.floor(F.col("n_tokens") / BLOCK))
    after = lambda c, keys, by: F.coalesce(F.sum(c).over(Window.partitionBy(*keys).orderBy(F.desc(by)).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    blocks = h.groupBy(*groups, "block_").agg(F.sum("docs").alias("d_"), F.sum("tokens").alias("t_"))
    whole_group = Window.partitionBy(*groups)
    blocks = blocks.select(*groups, "block_", after("d_", groups, "block_").alias("ld_"), after("t_", groups, "block_").alias("lt_"), F.sum("d_").over(whole_group).alias("total_docs"), F.sum("t_").over(whole_group).alias("total_tokens"))
    a = h.withColumn("id_", after("docs", [*groups, "block_"], "n_tokens")).withColumn("it_", after("tokens", [*groups, "block_"], "n_tokens")).alias("a")
    b = blocks.alias("b")
    on = F.col("a.block_") == F.col("b.block_")
    for g in groups:
        on = on & F.col(f"a.{g}").eqNullSafe(F.col(f"b.{g}"))
    j = a.join(b, on)
    longer_d, longer_t = F.col("b.ld_") + F.col("a.id_"), F.col("b.lt_") + F.col("a.it_")
    return j.select(
        *[F.col(f"a.{g}").alias(g) for g in groups], "n_tokens", "docs", "tokens", longer_d.alias("longer_docs"), longer_t.alias("longer_tokens"), "total_docs", "total_tokens",
        (F.col("total_tokens") - longer_t + F.col("n_tokens") * longer_d).alias("truncated_tokens"),
        F.expr("((total_docs - (b.ld_ + a.id_)) * 1000000) div total_docs").alias("share_whole_ppm"),
    )


def at_limits(sums: DataFrame, groups: list[str], limits: list[int]) -> DataFrame:
    """What any context limits keep: the row of the longest length up to the limit answers; shorter limits than all lengths cut every document."""
    out = []
    for limit in limits:
        fit = sums.groupBy(*groups).agg(
            F.max("total_docs").alias("total_docs"), F.max("total_tokens").alias("total_tokens"),
            F.sum(F.when(F.col("n_tokens") > limit, F.col("docs")).otherwise(0)).alias("cut_docs"),
            F.sum(F.least(F.col("n_tokens"), F.lit(limit)) * F.col("docs")).alias("kept_tokens"),
        )
        out.append(fit.withColumn("context", F.lit(limit).cast("long")))
    df = out[0]
    for more in out[1:]:
        df = df.unionByName(more)
    return df


def quantiles(sums: DataFrame, groups: list[str], per_cent: list[int]) -> DataFrame:
    """Exact quantiles of length: the least length that at least the stated share of documents does not exceed."""
    upto = F.col("total_docs") - F.col("longer_docs")
    picks = [F.min(F.when(100 * upto >= q * F.col("total_docs"), F.col("n_tokens"))).alias(f"p{q}") for q in per_cent]
    return sums.groupBy(*groups).agg(*picks)


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = read_table(spark, sf_dir, "documents", ["lang", "source", "text"])
    lengths = token_lengths(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, ["lang", "source"])
    return suffix_sums(stash(histogram(lengths, ["lang", "source"]), "histogram"), ["lang", "source"])
