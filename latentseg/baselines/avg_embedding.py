"""Averaged hashed n-gram embeddings with a linear softmax. In a round every partition runs some epochs of mini-batch steps on its rows from the common parameters, and the
partitions' parameters are averaged by their row counts. What travels is the sums of parameters: (buckets + labels) * dim numbers for each core, whatever the corpus."""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..cluster import lean
from ..io import side_by_side, stash

BATCH = 16
#: Epochs of a partition between two averages.
LOCAL = 10
#: Partitions of the rows of many runs.
RUN_PARTS = 64


def features(texts: list[str], low: int, high: int, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """(bucket of every n-gram, number of n-grams of each text). A text is lower-cased and put between < and >; all texts are hashed at once, from their code points."""
    marked = [f"<{t.lower()}>" for t in texts]
    size = np.fromiter(map(len, marked), np.int64, len(marked))
    points = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    left = np.repeat(np.cumsum(size), size) - np.arange(len(points))  # characters from here to the text's end
    owner = np.repeat(np.arange(len(texts)), size)
    h = np.zeros(len(points), np.uint64)
    found, whose = [], []
    for n in range(1, high + 1):
        shifted = np.zeros_like(points)
        shifted[: len(points) - n + 1] = points[n - 1 :]
        h = (h ^ (shifted + np.uint64(1))) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        if n >= low:
            ok = left >= n
            found.append((h[ok] % np.uint64(buckets)).astype(np.int64))
            whose.append(owner[ok])
    f, w = np.concatenate(found), np.concatenate(whose)
    order = np.argsort(w, kind="stable")
    return f[order], np.bincount(w, minlength=len(texts))


def means(x: np.ndarray, f: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Mean of the rows of each text; texts without any n-gram have zeros."""
    out = np.zeros((len(size), x.shape[1]), x.dtype)
    has = size > 0
    if has.any():
        first = np.cumsum(size) - size
        out[has] = np.add.reduceat(x[f], first[has], axis=0) / size[has, None].astype(x.dtype)
    return out


Batch = tuple[np.ndarray, np.ndarray, np.ndarray]


def batches_of(texts: list[str], low: int, high: int, buckets: int) -> list[Batch]:
    """(buckets that occur, how often in each text, n-grams of each text) for BATCH texts at a time. Counts are kept in as few bytes as hold them."""
    out = []
    for at in range(0, len(texts), BATCH):
        f, size = features(texts[at : at + BATCH], low, high, buckets)
        n = np.bincount(np.repeat(np.arange(len(size)), size) * buckets + f, minlength=len(size) * buckets).reshape(len(size), buckets)
        rows = np.flatnonzero(n.any(axis=0))
        n = n[:, rows]
        out.append((rows, n.astype(np.min_scalar_type(n.max(initial=0))), size))
    return out


def pack(batch: Batch, gold: np.ndarray) -> bytes:
    rows, n, size = batch
    head = np.array([len(size), len(rows), n.itemsize], np.int64)
    return pa.compress(b"".join(m.tobytes() for m in (head, gold, size.astype(np.int64), rows.astype(np.int64), n)), codec="zstd", asbytes=True) + np.int64(8 * (3 + 2 * len(size) + len(rows)) + n.nbytes).tobytes()


def unpack(packed: pa.Buffer) -> tuple[Batch, np.ndarray]:
    raw = pa.decompress(packed[:-8], int(np.frombuffer(packed[-8:], np.int64)[0]), codec="zstd")
    texts, buckets, width = np.frombuffer(raw, np.int64, 3)
    gold, size, rows = np.split(np.frombuffer(raw, np.int64, 2 * texts + buckets, 24), [texts, 2 * texts])
    return (rows, np.frombuffer(raw, f"u{width}", offset=8 * (3 + 2 * texts + buckets)).reshape(texts, buckets), size), gold


def train(texts: list[str], gold: np.ndarray, x: np.ndarray, y: np.ndarray, low: int, high: int, rates: list[float]) -> None:
    """One epoch a rate, in place."""
    descend(batches_of(texts, low, high, len(x)), gold, x, y, rates)


def descend(batches: list[Batch], gold: np.ndarray, x: np.ndarray, y: np.ndarray, rates: list[float]) -> None:
    """One epoch a rate, in place. A text's n-grams meet the embeddings as counts of buckets: two small matrix products a batch."""
    steps = [(rows, n, 1 / np.maximum(size, 1)[:, None].astype(x.dtype), np.arange(len(size)), gold[k * BATCH : k * BATCH + len(size)]) for k, (rows, n, size) in enumerate(batches)]
    whole = np.dtype((np.void, x.itemsize * x.shape[1]))  # an embedding is written as one item
    to = x.view(whole).ravel()
    for rate in rates:
        for rows, n, share, own, g in steps:
            n, e = n.astype(x.dtype), x.take(rows, axis=0)
            h = n @ e
            h *= share
            p = h @ y.T
            p -= p.max(axis=1, keepdims=True)
            np.exp(p, out=p)
            p /= p.sum(axis=1, keepdims=True)
            p[own, g] -= 1
            p *= x.dtype.type(rate)
            back = p @ y
            back *= share
            y -= p.T @ h
            e -= n.T @ back
            np.put(to, rows, e.view(whole).ravel())


def start(buckets: int, labels: int, dim: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    return np.random.default_rng(seed).uniform(-1 / dim, 1 / dim, (buckets, dim)).astype(np.float32), np.zeros((labels, dim), np.float32)


def _descended(src: DataFrame, first: tuple[np.ndarray, np.ndarray], lr: float, epochs: int, local: int) -> tuple[np.ndarray, np.ndarray]:
    """The parameters after all epochs over src (packed batches), averaged over partitions every `local` epochs."""
    (a, b), spark = first, src.sparkSession
    rates = [lr * (1 - e / epochs) for e in range(epochs)]
    sizes = a.size, b.size
    for at in range(0, epochs, local):
        sent = spark.sparkContext.broadcast((a, b))

        def run(batches: Iterator[pa.RecordBatch], sent=sent, own=rates[at : at + local]) -> Iterator[pa.RecordBatch]:
            made = [unpack(x.as_buffer()) for batch in batches for x in batch.column("batch")]
            if made:
                gold = np.concatenate([g for _, g in made])
                x, y = (m.copy() for m in sent.value)
                descend([m for m, _ in made], gold, x, y, own)
                yield pa.RecordBatch.from_arrays([pa.array([len(gold)], pa.int64()), pa.array([x.tobytes()], pa.binary()), pa.array([y.tobytes()], pa.binary())], names=["n", "x", "y"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            n, x, y = 0, np.zeros(sizes[0]), np.zeros(sizes[1])
            for batch in batches:
                for k, u, v in zip(*(batch.column(c) for c in ("n", "x", "y")), strict=True):
                    n += k.as_py()
                    x += np.frombuffer(u.as_buffer(), np.float32) * float(k.as_py())
                    y += np.frombuffer(v.as_buffer(), np.float32) * float(k.as_py())
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([x.tobytes()], pa.binary()), pa.array([y.tobytes()], pa.binary())], names=["n", "x", "y"])

        # all partitions side by side, summed by task, whatever the number of partitions
        kind = "n long, x binary, y binary"
        sums = stash(src.mapInArrow(lean(run), kind).coalesce(spark.sparkContext.defaultParallelism).mapInArrow(lean(add), kind), "parameters")
        total, x, y = 0, np.zeros(a.shape), np.zeros(b.shape)
        for r in sums.toLocalIterator():
            total += r["n"]
            x += np.frombuffer(r["x"]).reshape(a.shape)
            y += np.frombuffer(r["y"]).reshape(b.shape)
        if total:
            a, b = (x / total).astype(np.float32), (y / total).astype(np.float32)
    return a, b


@dataclass
class AvgEmbedding:
    inputs: np.ndarray
    outputs: np.ndarray
    labels: list[str]
    low: int
    high: int

    @classmethod
    def fit(cls, df: DataFrame, label_col: str = "label", text_col: str = "text", low: int = 1, high: int = 3, buckets: int = 4096, dim: int = 16, lr: float = 0.5, epochs: int = 100, seed: int = 7) -> AvgEmbedding:
        return cls.fit_each(df, (epochs,), label_col, text_col, low, high, buckets, dim, lr, seed)[0]

    @classmethod
    def fit_each(cls, df: DataFrame, epochs: tuple[int, ...], label_col: str = "label", text_col: str = "text", low: int = 1, high: int = 3, buckets: int = 4096, dim: int = 16, lr: float = 0.5, seed: int = 7) -> list[AvgEmbedding]:
        """A fit for each number of epochs, each as by itself; n-grams are counted once for all. Two go side by side, the longest first: one that waits for its last partition leaves cores to the other."""
        src = df.select(F.col(label_col).alias("label"), F.col(text_col).alias("text")).where("label is not null and text is not null")
        labels = sorted(r[0] for r in src.select("label").distinct().collect())
        col = {v: k for k, v in enumerate(labels)}
        cores = src.sparkSession.sparkContext.defaultParallelism
        n = src.count()
        # a partition has enough rows of its own to learn from
        parts = max(1, min(max(cores, n // 50_000), n // 500))

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            texts, gold = [], []
            for batch in itertools.chain(batches, [None]):
                if batch is not None:
                    texts += batch.column("text").to_pylist()
                    gold += [col[v] for v in batch.column("label").to_pylist()]
                whole = len(texts) if batch is None else len(texts) // BATCH * BATCH
                made = [pack(x, np.array(gold[k * BATCH : (k + 1) * BATCH], np.int64)) for k, x in enumerate(batches_of(texts[:whole], low, high, buckets))]
                texts, gold = texts[whole:], gold[whole:]
                if made:
                    yield pa.RecordBatch.from_arrays([pa.array(made, pa.binary())], names=["batch"])

        # every partition keeps its rows and their order
        src = src.repartition(parts, F.md5("text")).sortWithinPartitions(F.md5("text")).mapInArrow(lean(count), "batch binary").persist()
        own = lambda n: cls(*_descended(src, start(buckets, len(labels), dim, seed), lr, n, n if parts == 1 else LOCAL), labels, low, high)
        order = sorted(range(len(epochs)), key=lambda k: -epochs[k])
        out = dict(zip(order, side_by_side(*[lambda k=k: own(epochs[k]) for k in order], most=2), strict=True))
        src.unpersist()
        return [out[k] for k in range(len(epochs))]

    def predict(self, texts: list[str | None]) -> list[str | None]:
        f, size = features([t or "" for t in texts], self.low, self.high, len(self.inputs))
        s = means(self.inputs, f, size) @ self.outputs.T
        return [self.labels[int(k)] if t else None for k, t in zip(s.argmax(axis=1), texts, strict=True)]

    def transform(self, df: DataFrame, key: str | None = None, text_col: str = "text") -> DataFrame:
        df = df.drop("label")
        sent = df.sparkSession.sparkContext.broadcast(self)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for at in range(0, whole.num_rows, 500):
                    b = whole.slice(at, 500)
                    yield pa.RecordBatch.from_arrays([*b.columns, pa.array(sent.value.predict(b.column(text_col).to_pylist()), pa.string())], names=[*b.schema.names, "label"])

        return df.mapInArrow(lean(run), T.StructType([*df.schema.fields, T.StructField("label", T.StringType())]))


class Held:
    """Test rows whose n-grams are counted when they are first asked for, and kept."""

    def __init__(self, gold: np.ndarray, texts: np.ndarray, low: int, high: int, buckets: int) -> None:
        self.gold, self.texts, self.bounds, self.parts = gold, texts, (low, high, buckets), None

    def predict(self, x: np.ndarray, y: np.ndarray, labels: list[str]) -> list[str | None]:
        if self.parts is None:
            texts = [t or "" for t in self.texts]
            self.parts = [(f.astype(np.int32), size.astype(np.int32)) for f, size in (features(texts[k : k + 500], *self.bounds) for k in range(0, len(texts), 500))]
        best = [k for f, size in self.parts for k in (means(x, f, size) @ y.T).argmax(axis=1).tolist()]
        return [labels[k] if t else None for k, t in zip(best, self.texts, strict=True)]


def fit_runs(train_rows: DataFrame, test: DataFrame, run_cols: list[str], epochs: int = 100, low: int = 1, high: int = 3, buckets: int = 4096, dim: int = 16, lr: float = 0.5, seed: int = 7) -> DataFrame:
    """(run_cols, gold, label): many small training sets side by side, scored on the same test rows (gold, text), which are broadcast: the caller bounds them. A run's rows are few, so that
    they are dealt to a fixed number of partitions, which Spark does not join to larger ones; n-grams of the test rows are counted once a worker."""
    held = train_rows.sparkSession.sparkContext.broadcast(Held(*test.select("gold", "text").toPandas()[["gold", "text"]].to_numpy(object).T, low, high, buckets))
    kinds = dict(train_rows.dtypes)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("text")
        labels = sorted(pdf["label"].unique())
        x, y = start(buckets, len(labels), dim, seed)
        order = np.random.default_rng(seed).permutation(len(pdf))
        train(pdf["text"].to_numpy()[order].tolist(), np.searchsorted(labels, pdf["label"].to_numpy()[order]), x, y, low, high, [lr * (1 - e / epochs) for e in range(epochs)])
        return pd.DataFrame({**{c: pdf[c].iloc[0] for c in run_cols}, "gold": held.value.gold, "label": held.value.predict(x, y, labels)})

    return train_rows.repartition(RUN_PARTS, *run_cols).groupBy(*run_cols).applyInPandas(run, ", ".join(f"{c} {kinds[c]}" for c in run_cols) + ", gold string, label string")
