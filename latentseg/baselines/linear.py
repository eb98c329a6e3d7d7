"""Discriminative baselines on hashed character n-grams, by pyspark.ml: multinomial regression on TF-IDF, linear SVM inside a family, and a shallow
feed-forward net on normalised frequencies."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.ml import Pipeline, PipelineModel
from pyspark.ml.classification import LinearSVC, LogisticRegression, MultilayerPerceptronClassifier, OneVsRest
from pyspark.ml.feature import IDF, IndexToString, Normalizer, StringIndexer
from pyspark.ml.linalg import VectorUDT
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..cluster import lean
from ..io import spread, stash


def char_grams(text: Column, low: int = 1, high: int = 3) -> Column:
    """Every character n-gram of the lower-cased text between two spaces. The characters are bound once: a text inside a lambda would be lower-cased and walked again for each gram."""

    def grams(c: Column) -> Column:
        # a lambda with a default would take the index as its second argument
        of = lambda n: F.transform(F.sequence(F.lit(1), F.greatest(F.size(c) - n + 1, F.lit(1))), lambda i: F.array_join(F.slice(c, i, F.lit(n)), ""))
        return F.flatten(F.array(*[of(n) for n in range(low, high + 1)]))

    return F.get(F.transform(F.array(F.split(F.concat(F.lit(" "), F.lower(text), F.lit(" ")), "")), grams), F.lit(0))


def murmur3(data: bytes, seed: int = 42) -> int:
    """Spark's hash of a term, as a signed 32-bit number."""
    h, mask = seed, 0xFFFFFFFF
    mix = lambda k: ((k * 0xCC9E2D51 & mask) << 15 | (k * 0xCC9E2D51 & mask) >> 17) * 0x1B873593 & mask
    for at in range(0, len(data) - 3, 4):
        h ^= mix(int.from_bytes(data[at : at + 4], "little"))
        h = ((h << 13 | h >> 19) * 5 + 0xE6546B64) & mask
    if len(data) % 4:
        h ^= mix(int.from_bytes(data[len(data) // 4 * 4 :], "little"))
    h ^= len(data)
    h = (h ^ h >> 16) * 0x85EBCA6B & mask
    h = (h ^ h >> 13) * 0xC2B2AE35 & mask
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


#: Code points, plus one, that a gram's number holds: 21 bits each.
MOST_GRAM, BITS = 3, 21


def frequencies(texts: list[str], low: int, high: int, features: int, known: dict[int, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, index, count) of what HashingTF gives over char_grams, in the order of texts and indices. Only distinct grams are hashed; known holds their indices."""
    marked = [f" {t.lower()} " for t in texts]
    size = np.fromiter(map(len, marked), np.int64, len(marked))
    points = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64) + 1
    owner = np.repeat(np.arange(len(texts)), size)
    left = np.repeat(np.cumsum(size), size) - np.arange(len(points))
    code, found, whose = np.zeros(len(points), np.int64), [], []
    for n in range(1, high + 1):
        inside = left >= n
        code[inside] |= points[np.flatnonzero(inside) + n - 1] << BITS * (n - 1)
        if n >= low:
            ok = inside | ((left == size[owner]) & (left < n))  # a shorter text is one gram
            found.append(code[ok])
            whose.append(owner[ok])
    grams, which = np.unique(np.concatenate(found), return_inverse=True)
    index = np.empty(len(grams), np.int64)
    for k, g in enumerate(grams.tolist()):
        if (i := known.get(g)) is None:
            chars = [g >> BITS * j & (1 << BITS) - 1 for j in range(MOST_GRAM)]
            i = known[g] = murmur3("".join(chr(c - 1) for c in chars if c).encode("utf-8", "replace")) % features
        index[k] = i
    cells = np.bincount(np.concatenate(whose) * features + index[which], minlength=len(texts) * features)
    at = np.flatnonzero(cells)
    return at // features, at % features, cells[at]


def term_frequencies(df: DataFrame, text: str, low: int, high: int, features: int) -> DataFrame:
    """Adds _tf, a sparse vector. Null texts count as empty."""
    if high > MOST_GRAM:
        raise ValueError(f"grams of over {MOST_GRAM} characters")
    vector = VectorUDT()
    kind = pa.struct([("type", pa.int8()), ("size", pa.int32()), ("indices", pa.list_(pa.int32())), ("values", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, int] = {}
        for whole in batches:
            for at in range(0, whole.num_rows, 64):
                b = whole.slice(at, 64)
                row, index, count = frequencies([t or "" for t in b.column(text).to_pylist()], low, high, features, known)
                ends = pa.array(np.concatenate([[0], np.cumsum(np.bincount(row, minlength=b.num_rows))]).astype(np.int32))
                lists = [pa.ListArray.from_arrays(ends, pa.array(v)) for v in (index.astype(np.int32), count.astype(float))]
                made = pa.StructArray.from_arrays([pa.array([0] * b.num_rows, pa.int8()), pa.array([features] * b.num_rows, pa.int32()), *lists], fields=list(kind))
                yield pa.RecordBatch.from_arrays([*b.columns, made], names=[*b.schema.names, "_tf"])

    return df.mapInArrow(lean(run), T.StructType([*df.schema.fields, T.StructField("_tf", vector)]))


@dataclass
class Linear:
    model: PipelineModel
    text_col: str
    low: int
    high: int
    features: int

    def transform(self, df: DataFrame, key: str | None = None, text_col: str | None = None) -> DataFrame:
        out = self.model.transform(term_frequencies(df.drop("label"), text_col or self.text_col, self.low, self.high, self.features))
        return out.drop("_tf", "_x", "rawPrediction", "probability", "prediction").withColumnRenamed("_said", "label")


def _fit(df: DataFrame, label_col: str, text_col: str, low: int, high: int, features: int, middle: list, classifier) -> Linear:
    src = df.select(F.col(label_col).alias("_gold"), F.col(text_col).alias("_text"))
    src = stash(term_frequencies(spread(src), "_text", low, high, features).drop("_text"), "tf")  # vectors are a fraction of their grams, and made once
    indexer = StringIndexer(inputCol="_gold", outputCol="_y", stringOrderType="alphabetAsc").fit(src)
    front = Pipeline(stages=middle).fit(src)
    model = classifier(len(indexer.labels)).fit(front.transform(indexer.transform(src)))
    back = IndexToString(inputCol="prediction", outputCol="_said", labels=indexer.labels)
    return Linear(PipelineModel(stages=[front, model, back]), text_col, low, high, features)


def tfidf_linear(df: DataFrame, label_col: str = "label", text_col: str = "text", features: int = 1 << 12, iters: int = 15) -> Linear:
    return _fit(df, label_col, text_col, 1, 3, features, [IDF(inputCol="_tf", outputCol="_x")], lambda n: LogisticRegression(featuresCol="_x", labelCol="_y", family="multinomial", maxIter=iters, regParam=1e-4))


def svm_family(df: DataFrame, label_col: str = "label", text_col: str = "text", features: int = 1 << 12, iters: int = 15) -> Linear:
    return _fit(df, label_col, text_col, 1, 3, features, [IDF(inputCol="_tf", outputCol="_x")], lambda n: OneVsRest(classifier=LinearSVC(maxIter=iters, regParam=1e-4), featuresCol="_x", labelCol="_y"))


def shallow_ffn(df: DataFrame, label_col: str = "label", text_col: str = "text", features: int = 1 << 9, hidden: int = 32, iters: int = 40) -> Linear:
    """Trained on some labels only, it shows what partial coverage costs."""
    return _fit(df, label_col, text_col, 1, 3, features, [Normalizer(inputCol="_tf", outputCol="_x", p=1.0)], lambda n: MultilayerPerceptronClassifier(featuresCol="_x", labelCol="_y", layers=[features, hidden, n], maxIter=iters, seed=7))
