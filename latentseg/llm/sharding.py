"""Sharding by proportional stratified interleaving.

Rows are shuffled within their source by a seeded hash and ranked; a row's fractional rank is (rank + 1/2) / rows of the source. Sorted by
that fraction the sources lie interleaved in proportion to their sizes, so every stretch of the order has the mixture of the whole.
Cutting it into equal stretches gives shards whose counts differ by one at most, each with about the same share of every source.

Both rankings are distributed: rows fall into buckets by the leading bits of hash or fraction, bucket counts are added up
along the order, and only the rows of one bucket are ranked together. A source with a third of all rows is spread over its buckets like any other.
Only id, source, size and checksum are shuffled, never texts.

Defined cases: a null text has size 1 and checksum 0; a null source is a source of its own; a null id is placed by its text's checksum;
ties and repeated rows are ordered by id, checksum and size, and rows equal in these are interchangeable; fewer rows than shards leave shards
empty; an empty table gives an empty result; of other columns only those asked for in `keep` pass through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..io import join_small, read_table, stash
from .common import buckets_for, hex_digest, hex_to_long, identity_of, whole

SEED = "shard-1"


def _ranks(df: DataFrame, part: list[str], bucket: str, order: list[str], out: str) -> DataFrame:
    """Adds out: the rank from 0 within part, in the order of bucket, then order."""
    counts = stash(df.groupBy(*part, bucket).agg(F.count(F.lit(1)).alias("_n")), "counts")
    wide = counts.withColumn("_block", F.floor(F.col(bucket) / 64))
    blocks = wide.groupBy(*part, "_block").agg(F.sum("_n").alias("_m"))
    before = lambda n, keys, by: F.coalesce(F.sum(n).over(Window.partitionBy(*keys).orderBy(by).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    blocks = blocks.withColumn("_before", before("_m", part, "_block"))
    a, b = wide.withColumn("_inner", before("_n", [*part, "_block"], bucket)).alias("a"), blocks.alias("b")
    same = F.col("a._block") == F.col("b._block")
    for p in part:
        same = same & F.col(f"a.{p}").eqNullSafe(F.col(f"b.{p}"))
    starts = stash(a.join(b, same).select(*[F.col(f"a.{p}").alias(f"s_{p}") for p in part], F.col(f"a.{bucket}").alias("s_bucket"), (F.col("b._before") + F.col("a._inner")).alias("_start")), "starts")
    placed = df.withColumn("_rn", F.row_number().over(Window.partitionBy(*part, bucket).orderBy(*order)) - 1)
    on = placed[bucket] == starts["s_bucket"]
    for p in part:
        on = on & placed[p].eqNullSafe(starts[f"s_{p}"])
    return join_small(placed, starts, on).withColumn(out, F.col("_start") + F.col("_rn")).drop("_rn", "_start", "s_bucket", *[f"s_{p}" for p in part])


def interleave(docs: DataFrame, n_shards: int, seed: str = SEED, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """(id, source, keep..., size, text_crc32, position, shard, slot). shard = floor(position * n_shards / rows); slot counts from 0 within it."""
    text = F.encode(whole(text_col), "UTF-8")
    light = docs.select(
        F.col(id_col).alias("doc_id"),
        F.col(source_col).alias("source"),
        *(keep or []),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        hex_digest(seed, F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("text:"), F.crc32(text).cast("string")))).alias("_key"),
    )
    light = stash(light, "light")
    rows, largest = light.groupBy("source").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n"), F.max("n")).first()
    rows, largest = rows or 0, largest or 0
    per_source, overall = buckets_for(largest), buckets_for(rows, 1024)
    digits = (per_source.bit_length() + 2) // 4
    df = light.withColumn("_b", hex_to_long(F.col("_key"), 1, digits))
    ties = ["doc_id", "text_crc32", "size"]
    df = _ranks(df, ["source"], "_b", ["_key", *ties], "_rank").drop("_b")
    sizes = stash(light.groupBy(F.col("source").alias("z_source")).agg(F.count(F.lit(1)).alias("_of")), "sizes")
    df = join_small(df, sizes, df["source"].eqNullSafe(sizes["z_source"])).drop("z_source")
    df = df.withColumn("_frac", (F.col("_rank") + 0.5) / F.col("_of")).withColumn("_b", F.floor(F.col("_frac") * overall).cast("long")).drop("_of", "_rank")
    df = _ranks(df, [], "_b", ["_frac", "source", "_key", *ties], "position").drop("_b", "_frac", "_key")
    shard = F.floor(F.col("position") * n_shards / F.lit(max(rows, 1))) if rows * n_shards < 2**52 else F.expr(f"cast(position as decimal(28,0)) * {n_shards} div {rows}")
    df = df.withColumn("shard", shard.cast("int"))
    first = F.ceil(F.col("shard").cast("decimal(20,0)") * F.lit(rows) / F.lit(n_shards)).cast("long")
    return df.withColumn("slot", F.col("position") - first)


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "source", "text"])
    df = interleave(docs, 8)
    return df.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")
