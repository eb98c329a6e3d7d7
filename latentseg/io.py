"""Scans, sinks and the shared work area."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a side of a join may be broadcast: with a few hundred bytes a row this stays under 100 MB.
BROADCAST_ROWS = 200_000


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """One of the given tables; only `columns` reach the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int, mode: str = "overwrite") -> None:
    """A table whose files are dealt by a key: joins and sums on it later need no shuffle."""
    df.write.bucketBy(buckets, by).sortBy(by).mode(mode).saveAsTable(table)


def fingerprint(spark: SparkSession, path: str) -> str:
    """Names, sizes and times of the files of a table, from the file system's listing."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    fs = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return ";".join(sorted(f"{x.getPath().getName()}:{x.getLen()}:{x.getModificationTime()}" for x in fs.listStatus(at)))


def read_text(spark: SparkSession, path: str, fmt: str = "text", **options) -> DataFrame:
    """Corpora and token lists: fmt is text, json, csv, orc, parquet or binaryFile."""
    return spark.read.options(**options).format(fmt).load(path)


def write_labeled(df: DataFrame, path: str, label_col: str = "label", fmt: str = "parquet", mode: str = "overwrite") -> None:
    """Rows laid out by label, so that a subset of labels is a matter of partition pruning."""
    df.write.partitionBy(label_col).format(fmt).mode(mode).save(path)


def spread(df: DataFrame) -> DataFrame:
    """At least one partition per core before CPU-bound work. Files of a few partitions are dealt out; what has been through a shuffle, or comes from more files than
    there are cores, is left alone. Only the plan and the list of files are looked at: nothing runs."""
    if df.isStreaming:
        return df
    sc = df.sparkSession.sparkContext
    cores = sc.defaultParallelism
    plan = df._jdf.queryExecution().optimizedPlan()
    if any(x in plan.toString() for x in ("Repartition", "Aggregate", "Join", "Window", "Sort ", "Distinct")):
        return df
    files = df.inputFiles()
    if len(files) >= cores:
        return df
    size = int(str(plan.stats().sizeInBytes()))
    step = _bytes(df.sparkSession.conf.get("spark.sql.files.maxPartitionBytes"))
    return df if size // step >= cores else df.repartition(cores)


def _bytes(text: str) -> int:
    """A size as Spark writes it: 134217728, 134217728b, 16m, 1g."""
    t = text.strip().lower().removesuffix("b")
    unit = {"k": 10, "m": 20, "g": 30, "t": 40}.get(t[-1:], 0)
    return int(t[:-1] if unit else t) << unit


def work_dir(spark: SparkSession) -> str:
    """The folder that all executors share. It is the cluster's spark.checkpoint.dir; only where that is unset
    (tests, local runs) a temporary one is made and put into the context. On a cluster an unset folder is an error: executors share no temporary one."""
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not base:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        own = tempfile.mkdtemp(prefix="latentseg-")
        atexit.register(shutil.rmtree, own, True)
        sc.setCheckpointDir(f"file://{own}")
        base = sc.getCheckpointDir()
    return base.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{work_dir(spark)}/latentseg/{uuid.uuid4().hex}/{name}"


def stash(df: DataFrame, name: str = "table") -> DataFrame:
    """Write a frame to the shared folder and read it back: cuts the lineage, and what is read again survives the
    loss of any executor."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def side_by_side(*jobs: Callable, most: int = 4) -> list:
    """What the jobs give, `most` of them at a time. One that waits for small steps leaves cores to the others."""
    with ThreadPoolExecutor(most) as pool:
        return [x.result() for x in [pool.submit(f) for f in jobs]]


def join_small(big: DataFrame, small: DataFrame, on, how: str = "left", bound: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast `small` only if it has at most `bound` rows, counted up to that bound; else leave the join to a
    shuffle, whose skewed partitions are split at run time. `small` should be stashed: it is read twice."""
    fits = small.limit(bound + 1).count() <= bound
    return big.join(F.broadcast(small) if fits else small, on, how)


def join_spread(big: DataFrame, small: DataFrame, key: str, small_key: str, by: str, how: str = "left", salts: int = 64, bound: int = BROADCAST_ROWS) -> DataFrame:
    """Joins `big`, in which a key may hold a third of all rows, with `small`, which has one row a key and is stashed. Up to `bound` rows `small` is broadcast; beyond, each of its
    rows meets `salts` salts, and rows of `big` take the salt that their column `by` hashes to, so that no key lands in one task. The key of `small` is dropped."""
    if small.limit(bound + 1).count() <= bound:
        return big.join(F.broadcast(small), big[key] == small[small_key], how).drop(small_key)
    many = small.withColumn("_salt_b", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    salted = big.withColumn("_salt_a", F.pmod(F.xxhash64(by), F.lit(salts)).cast("int"))
    return salted.join(many, (F.col(key) == F.col(small_key)) & (F.col("_salt_a") == F.col("_salt_b")), how).drop(small_key, "_salt_a", "_salt_b")


def join_frequent(big: DataFrame, small: DataFrame, key: str, freq: str = "f", bound: int = BROADCAST_ROWS) -> DataFrame:
    """Inner join of `big`, whose keys follow words and so are very uneven, with `small`, one stashed row a key, that says in `freq` how many rows of big have it. Keys of at least
    1 / bound of all rows, fewer than `bound` by arithmetic, are broadcast; all others are joined by a shuffle in which none is large. The column `freq` goes."""
    total = small.agg(F.sum(freq)).first()[0] or 0
    cut = total // bound + 1
    if small.limit(bound + 1).count() <= bound:
        return big.join(F.broadcast(small.drop(freq)), key)
    head, tail = small.where(F.col(freq) >= cut), small.where(F.col(freq) < cut).drop(freq)
    rest = big.join(F.broadcast(head.select(key)), key, "left_anti").join(tail, key)
    return big.join(F.broadcast(head.drop(freq)), key).unionByName(rest)
