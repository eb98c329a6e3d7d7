"""Mixing sources to target weights by Poisson replication.

A source with weight w and size n (in UTF-8 bytes or rows) is repeated w * budget / n times in the mean. Every document draws its own
count: a number in [0, 1) hashed from seed and row is put through the inverted Poisson distribution with that mean, so the
draw of a row depends on nothing but itself and its source's rate. Copies are exploded and shuffled globally by a second hash.

Defined cases: a null or empty text has size 1; a null source is a source of its own; a source without a stated weight gets 0 when
weights are given; repeated rows (equal id) draw alike and all their copies are kept; an empty table gives an empty result;
other columns pass through, whatever they are called, except those named (in any case) like a column that is added: n_copies by draw(), copy by
replicate(), copy and position by mix().
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..io import join_small, read_table, stash
from .common import beside, buckets_for, hex_to_long, identity_of, named, whole

SEED = "mix-1"
#: Production weights: a source of size n gets n ** TEMPERATURE, normalised, so large sources are damped and small ones repeated.
TEMPERATURE = 0.7
#: Fixed value: 12 hex digits make a number below 2 ** 48, which a double holds exactly.
DIGITS, SPAN = 12, 2.0**48


def size_of(text_col: str, unit: str = "bytes") -> Column:
    return (F.octet_length(whole(text_col)) + 1 if unit == "bytes" else F.lit(1)).cast("long")


def rates(docs: DataFrame, weights: dict[str, float] | None = None, source_col: str = "source", text_col: str = "text", unit: str = "bytes", epochs: float = 1.0) -> DataFrame:
    """(m_source, m_rows, m_size, rate). weights None: by TEMPERATURE. The budget is epochs times the size of all rows."""
    stats = docs.groupBy(F.col(source_col).alias("m_source")).agg(F.count(F.lit(1)).alias("m_rows"), F.sum(size_of(text_col, unit)).alias("m_size"))
    if weights is None:
        raw = F.round(F.pow(F.col("m_size").cast("double"), F.lit(TEMPERATURE)), 3)
    else:
        raw = F.coalesce(F.create_map(*[F.lit(x) for kv in weights.items() for x in (kv[0], float(kv[1]))])[F.col("m_source")], F.lit(0.0)) if weights else F.lit(0.0)
    stats = stats.withColumn("raw", raw.cast("decimal(30,3)"))
    total = stats.agg(F.sum("raw").alias("all_raw"), F.sum("m_size").alias("all_size"))
    mean = F.col("raw").cast("double") / F.col("all_raw").cast("double") * F.col("all_size").cast("double") * F.lit(float(epochs)) / F.col("m_size").cast("double")
    return stats.join(F.broadcast(total)).select("m_source", "m_rows", "m_size", F.coalesce(mean, F.lit(0.0)).alias("rate"))  # total is one row


def poisson_steps(rate: Column) -> Column:
    """The distribution function at 0, 1, 2, ... as thresholds on [0, SPAN), up to where it cannot be told from 1 at that resolution."""
    most = (F.ceil(rate + 10 * F.sqrt(rate)) + 20).cast("int")
    start = F.struct(F.exp(-rate).alias("p"), F.exp(-rate).alias("cdf"), F.array(F.exp(-rate)).alias("steps"))

    def step(acc: Column, k: Column) -> Column:
        p = acc["p"] * rate / k
        return F.struct(p.alias("p"), (acc["cdf"] + p).alias("cdf"), F.concat(acc["steps"], F.array(acc["cdf"] + p)).alias("steps"))

    steps = F.aggregate(F.sequence(F.lit(1), most), start, step)["steps"]
    return F.transform(steps, lambda x: F.floor(x * F.lit(SPAN)).cast("long"))


def _drawn(rows: DataFrame, rate_table: DataFrame, seed: str) -> DataFrame:
    """Adds n_copies to rows with m_ident and m_from: how many thresholds of its source's distribution a row's hashed number reaches. Rates over some hundreds
    would underflow; they are split into equal parts, whose draws add up to the same distribution."""
    steps = stash(rate_table.withColumn("m_parts", F.greatest(F.lit(1), F.ceil(F.col("rate") / 256)).cast("int")).withColumn("m_steps", poisson_steps(F.col("rate") / F.col("m_parts"))).select("m_source", "m_parts", "m_steps"), "steps")
    joined = join_small(rows, steps, F.col("m_from").eqNullSafe(F.col("m_source")))

    def one(k: Column) -> Column:
        u = hex_to_long(F.md5(F.concat(F.lit(f"{seed}:"), k.cast("string"), F.lit(":"), F.col("m_ident"))), 1, DIGITS)
        return F.size(F.filter(F.col("m_steps"), lambda x: x <= u)).cast("long")

    n = F.aggregate(F.sequence(F.lit(1), F.col("m_parts")), F.lit(0).cast("long"), lambda acc, k: acc + one(k))
    return joined.withColumn("n_copies", n).drop("m_source", "m_parts", "m_steps")


def draw(docs: DataFrame, rate_table: DataFrame, seed: str = SEED, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text") -> DataFrame:
    """Adds n_copies."""
    rows = docs.select(beside(docs, {"n_copies"}), identity_of(id_col, text_col).alias("m_ident"), named(source_col).alias("m_from"))
    return _drawn(rows, rate_table, seed).select("row.*", "n_copies")


def replicate(drawn: DataFrame) -> DataFrame:
    """One row per copy, numbered from 1; n_copies goes."""
    rows = drawn.where("n_copies > 0").select(beside(drawn, {"copy", "n_copies"}), F.explode(F.sequence(F.lit(1).cast("long"), F.col("n_copies"))).alias("copy"))
    return rows.select("row.*", "copy")


def mix(docs: DataFrame, weights: dict[str, float] | None = None, seed: str = SEED, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", unit: str = "bytes", epochs: float = 1.0, texts: bool = True) -> DataFrame:
    """The mixture in its global order: the columns of docs (without the text if texts is False), copy, and position from 0 without
    gaps. A copy belongs to the bucket that its order hash names; rows are placed within buckets, and buckets by a running sum of
    their counts, so the texts move once and no task sees more than a bucket."""
    table = stash(rates(docs, weights, source_col, text_col, unit, epochs), "rates")
    rows = table.agg(F.ceil(F.sum(F.col("m_rows") * F.col("rate")))).first()[0] or 0
    n = buckets_for(rows, 1024, 20_000)
    digits = (n.bit_length() + 2) // 4
    key = F.md5(F.concat(F.lit(f"{seed}:order:"), F.col("copy").cast("string"), F.lit(":"), F.col("m_ident")))

    def copies(*kept: Column) -> DataFrame:
        light = docs.select(*kept, identity_of(id_col, text_col).alias("m_ident"), named(source_col).alias("m_from"))
        each = replicate(_drawn(light, table, seed)).withColumn("m_key", key)
        return each.withColumn("m_bucket", hex_to_long(F.col("m_key"), 1, digits))

    starts = stash(_running(copies().groupBy(F.col("m_bucket").alias("bucket")).agg(F.count(F.lit(1)).alias("n")), n), "starts").select(F.col("bucket").alias("m_at"), F.col("start").alias("m_start"))
    out = copies(beside(docs, {"copy", "position"} | (set() if texts else {text_col})), named(id_col).alias("m_id"))
    slot = F.row_number().over(Window.partitionBy("m_bucket").orderBy("m_key", "m_id", "copy")) - 1
    placed = join_small(out.withColumn("m_slot", slot), starts, F.col("m_bucket") == F.col("m_at"))
    return placed.select("row.*", "copy", (F.col("m_start") + F.col("m_slot")).alias("position"))


def _running(counts: DataFrame, n: int) -> DataFrame:
    """Where each bucket starts. Buckets (about sqrt(n) at a time) are summed in blocks, then blocks."""
    width = 1 << (n.bit_length() // 2)
    counts = counts.withColumn("block", F.floor(F.col("bucket") / width))
    blocks = counts.groupBy("block").agg(F.sum("n").alias("m")).withColumn("before", F.coalesce(F.sum("m").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    inner = F.coalesce(F.sum("n").over(Window.partitionBy("block").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return counts.withColumn("inner", inner).join(blocks, "block").select("bucket", (F.col("before") + F.col("inner")).alias("start"))


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole mixture, texts included."""
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "source", "text"])
    return mix(docs).select("doc_id", "source", "text", "copy", "position")


OP1_SQL = f"""
with recursive s as (select source, sum(strlen(coalesce(text, '')) + 1)::double as size, round(pow(sum(strlen(coalesce(text, '')) + 1)::double, {TEMPERATURE}), 3)::decimal(30,3) as raw
           from documents group by source),
r as (select source, raw::double / (select sum(raw) from s)::double * (select sum(size) from s) / size as rate from s),
p as (select source, rate, 0 as k, exp(-rate) as p, exp(-rate) as cdf from r
      union all select source, rate, k + 1, p * rate / (k + 1), cdf + p * rate / (k + 1) from p where k + 1 <= ceil(rate + 10 * sqrt(rate)) + 20),
steps as (select source, list(floor(cdf * {SPAN:.0f})::bigint order by k) as steps from p group by source),
d as (select doc_id, source, text, ('0x' || substr(md5('{SEED}:1:' || doc_id), 1, {DIGITS}))::bigint as u from documents),
c as (select doc_id, source, text, len(list_filter(steps, lambda x: x <= u)) as n from d join steps using (source)),
e as (select doc_id, source, text, unnest(range(1, n + 1))::bigint as copy from c where n > 0)
select doc_id, source, text, copy, row_number() over (order by md5('{SEED}:order:' || copy || ':' || doc_id), doc_id, copy) - 1 as position from e
"""
