"""Character n-gram language model per label: add-k, interpolated or stupid-backoff smoothing. Joins and sums; add-k scores texts in one scan where its values are few enough to be sent."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..cluster import lean
from ..io import join_frequent, spread, stash

#: Characters that are counted at a time; a longer text is counted by itself.
WINDOW = 1 << 20
#: Grams of up to so many numbers are counted and looked up in a table of all numbers, others by sorting.
NUMBERS = 1 << 22
#: Cells, contexts and grams by labels, of the values that every worker holds, and of an intermediate sum.
HELD, CELLS = 8_000_000, 1 << 22


def grams(df: DataFrame, keys: list[str], text_col: str, n: int) -> DataFrame:
    """(keys, ctx, ch): every character with the n-1 before it; the text is preceded by n-1 spaces. A text is taken apart once and dropped before its grams are listed."""
    chars = F.regexp_extract_all(F.concat(F.lit(" " * (n - 1)), F.lower(text_col)), F.lit("(?s)."), 0)
    at = F.expr(f"transform(sequence(1, size(_c) - {n - 1}), i -> struct(array_join(slice(_c, i, {n - 1}), '') as ctx, element_at(_c, i + {n - 1}) as ch))")
    return df.select(*keys, chars.alias("_c")).where(f"size(_c) >= {n}").select(*keys, F.explode(at).alias("_g")).select(*keys, "_g.ctx", "_g.ch")


def places(texts: list[str], n: int) -> tuple[str, np.ndarray, np.ndarray, np.ndarray]:
    """(all texts, each after n-1 spaces; their code points; where the n characters of each gram begin; the text of each gram)."""
    whole = "".join(" " * (n - 1) + t for t in texts)
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    first = np.cumsum(size + n - 1) - size - n + 1  # where each text's spaces begin
    at = np.arange(size.sum()) + np.repeat(first - np.cumsum(size) + size, size)
    return whole, np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), np.uint32), at, np.repeat(np.arange(len(texts)), size)


def windows(column: pa.StringArray) -> Iterator[tuple[int, int]]:
    """(begin, length) of runs of texts that have WINDOW characters, or are one longer text. Null texts have none."""
    ends = np.cumsum(pa.compute.fill_null(pa.compute.utf8_length(column), 0).to_numpy(zero_copy_only=False)) if len(column) else []
    at = 0
    while at < len(column):
        upto = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + WINDOW, "right")))
        yield at, upto - at
        at = upto


def counted(owner: np.ndarray, texts: list[str], n: int) -> tuple[np.ndarray, list[str], list[str], np.ndarray]:
    """(owner, ctx, ch, times) of every different gram of each owner's texts, by arrays. Grams are numbered by the characters that occur; a number that could pass 63 bits is replaced by its rank."""
    whole, points, at, _ = places(texts, n)
    present = np.zeros(int(points.max(initial=0)) + 1, bool)
    present[points] = True
    alphabet, place = int(present.sum()), (np.cumsum(present) - 1)[points]
    code, bound = np.repeat(owner, [len(t) for t in texts]), int(owner.max(initial=0)) + 1
    for k in range(n):
        if bound * alphabet >= 1 << 63:
            seen, code = np.unique(code, return_inverse=True)
            bound = len(seen)
        code, bound = code * alphabet + place[at + k], bound * alphabet
    if bound <= NUMBERS:
        times = np.bincount(code, minlength=bound)
        one, some = np.zeros(bound, np.int64), np.flatnonzero(times)
        one[code] = np.arange(len(code))  # any of the places of a gram
        one, times = one[some], times[some]
    else:
        _, one, times = np.unique(code, return_index=True, return_counts=True)
    starts = at[one].tolist()
    return np.repeat(owner, [len(t) for t in texts])[one], [whole[i : i + n - 1] for i in starts], [whole[i + n - 1] for i in starts], times


def gram_counts(df: DataFrame, key: str, text_col: str, n: int) -> DataFrame:
    """(key, ctx, ch, m): the grams of grams(), counted by an Arrow kernel. A key has a row for each window of texts that it occurs in: the caller adds them up."""
    rows = spread(df.select(key, F.lower(text_col).alias("_text")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(batch.column("_text").is_valid())
            for at, many in windows(batch.column("_text")):
                b = batch.slice(at, many)
                coded = b.column(key).dictionary_encode(null_encoding="encode")
                owner, ctx, ch, m = counted(coded.indices.to_numpy().astype(np.int64), b.column("_text").to_pylist(), n)
                yield pa.RecordBatch.from_arrays([coded.dictionary.take(pa.array(owner)), pa.array(ctx, pa.string()), pa.array(ch, pa.string()), pa.array(m, pa.int64())], names=[key, "ctx", "ch", "m"])

    return rows.mapInArrow(lean(run), T.StructType([rows.schema[key], *T._parse_datatype_string("ctx string, ch string, m long").fields]))


class Values:
    """What a gram adds to a text's score under each label, in whole numbers: of the gram if a label has it, else of its context, else of neither. Grams are numbers in the
    alphabet of the training texts, of which 0 is any other character."""

    def __init__(self, labels: list[str], none: int, ctx: pd.DataFrame, gram: pd.DataFrame, n: int) -> None:
        self.labels, self.n = labels, n
        col = {x: k for k, x in enumerate(labels)}
        contexts, grams = (sorted(df.iloc[:, 0].unique()) for df in (ctx, gram))
        cut = [np.frombuffer("".join(x).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(x), -1) for x in (contexts, grams)]
        points = np.unique(np.concatenate([x.ravel() for x in cut]))
        self.points, self.base = points, len(points) + 1
        code = [self._number((np.searchsorted(points, x) + 1).T) for x in cut]
        order = [np.argsort(c) for c in code]
        self.contexts, self.grams = (c[o] for c, o in zip(code, order, strict=True))
        d = []
        for df, names, o in ((ctx, contexts, order[0]), (gram, grams, order[1])):
            at = {names[j]: i for i, j in enumerate(o.tolist())}
            cells = np.zeros((len(o), len(labels)), np.int64)
            cells[df.iloc[:, 0].map(at).to_numpy(int), df["label"].map(col).to_numpy(int)] = df["d"]
            d.append(cells)
        d[1] += d[0][np.searchsorted(self.contexts, self.grams // self.base)]
        self.values = np.concatenate([np.zeros((1, len(labels)), np.int64), *d]) + none  # of neither, of contexts, of grams
        self.table = None

    @staticmethod
    def fits(alphabet: int, n: int) -> bool:
        return (alphabet + 1) ** n < 1 << 62

    def _number(self, digits: np.ndarray) -> np.ndarray:
        out = np.zeros(digits.shape[1], np.int64)
        for d in digits:
            out = out * self.base + d
        return out

    def _rows(self, code: np.ndarray) -> np.ndarray:
        """Rows of `values` for numbers of grams."""
        if self.table is None and self.base**self.n <= NUMBERS:
            whole = np.zeros(self.base ** (self.n - 1), np.int32)
            whole[self.contexts] = 1 + np.arange(len(self.contexts))
            self.table = np.repeat(whole, self.base)
            self.table[self.grams] = 1 + len(self.contexts) + np.arange(len(self.grams))
        if self.table is not None:
            return self.table[code]

        def find(sorted_: np.ndarray, x: np.ndarray, before: int, other: np.ndarray | int) -> np.ndarray:
            at = np.minimum(np.searchsorted(sorted_, x), len(sorted_) - 1)
            return np.where(sorted_[at] == x, before + at, other)

        return find(self.grams, code, 1 + len(self.contexts), find(self.contexts, code // self.base, 1, 0))

    def scores(self, texts: list[str]) -> np.ndarray:
        """[texts, labels]."""
        total = np.zeros((len(texts), len(self.labels)), np.int64)
        _, points, at, owner = places(texts, self.n)
        if not len(at):
            return total
        digit = np.minimum(np.searchsorted(self.points, points), len(self.points) - 1)
        digit = np.where(self.points[digit] == points, digit + 1, 0)
        rows = self._rows(self._number(np.stack([digit[at + k] for k in range(self.n)])))
        step = max(1, CELLS // len(self.labels))
        for k in range(0, len(rows), step):
            own = owner[k : k + step]
            first = np.concatenate([[0], np.flatnonzero(np.diff(own)) + 1])
            total[own[first]] += np.add.reduceat(self.values[rows[k : k + step]], first, axis=0)
        return total


@dataclass
class NgramLM:
    counts: DataFrame  # label, ctx, ch, c
    contexts: DataFrame  # label, ctx, t
    labels: DataFrame
    n: int
    alphabet: int
    k: float = 0.5
    smooth: str = "add_k"
    weight: float = 0.6
    _known: list[Values | None] = field(default_factory=list, repr=False)

    @classmethod
    def fit(cls, df: DataFrame, label_col: str = "label", text_col: str = "text", n: int = 3, smooth: str = "add_k", k: float = 0.5, weight: float = 0.6) -> NgramLM:
        g = gram_counts(df.select(F.col(label_col).alias("label"), F.col(text_col).alias("text")), "label", "text", n)
        counts = stash(g.groupBy("label", "ctx", "ch").agg(F.sum("m").alias("c")), "counts")
        contexts = stash(counts.groupBy("label", "ctx").agg(F.sum("c").alias("t")), "contexts")
        alphabet = counts.agg(F.count_distinct("ch")).first()[0]
        return cls(counts, contexts, counts.select("label").distinct(), n, alphabet, k, smooth, weight)

    def scores(self, df: DataFrame, key: str, text_col: str = "text") -> DataFrame:
        """(key, label, score), scores in millionths of nats: whole numbers add up alike in any order."""
        g = stash(gram_counts(df, key, text_col, self.n).groupBy(key, "ctx", "ch").agg(F.sum("m").alias("m")), "grams")
        return self._sparse(g, key) if self.smooth == "add_k" else self._cells(g, key)

    def _added(self) -> tuple[Column, DataFrame, DataFrame]:
        """add_k, in whole numbers: the value of a gram whose context a label lacks, (ctx, label, d) of what the context adds to it, and (gram, label, d) of what the gram adds to that."""
        fx = lambda p: F.round(F.log(p) * 1_000_000).cast("long")
        none = fx(F.lit(0.0 + self.k) / (F.lit(0) + self.k * self.alphabet))
        total = F.col("t") + self.k * self.alphabet
        by_ctx = self.contexts.select("ctx", "label", (fx(F.lit(0.0 + self.k) / total) - none).alias("d"))
        both = self.counts.join(self.contexts, ["label", "ctx"])
        return none, by_ctx, both.select(F.concat("ctx", "ch").alias("gram"), "label", (fx((F.col("c") + self.k) / total) - fx(F.lit(0.0 + self.k) / total)).alias("d"))

    def values(self) -> Values | None:
        """The values that add_k scores with, gathered once; None if they are too many to be sent: then grams meet them by joins."""
        if self.smooth != "add_k":
            return None
        if not self._known:
            labels = sorted(r[0] for r in self.labels.collect())
            cells = (self.contexts.select("ctx").distinct().count() + self.counts.select("ctx", "ch").distinct().count()) * len(labels)
            made = None
            if labels and cells <= HELD and Values.fits(self.alphabet + 1, self.n):  # a space stands before every text
                none, *added = self._added()
                made = Values(labels, self.labels.limit(1).select(none.alias("v")).first()[0], *(x.toArrow().to_pandas() for x in added), self.n)
            self._known.append(made)
        return self._known[0]

    def _sparse(self, g: DataFrame, key: str) -> DataFrame:
        """add_k: every gram has the same value under a label that lacks its context, so only contexts and grams that a label has are joined, as what they add to that. A
        table has a row a key with all its labels, and frequent keys are broadcast."""
        packed = lambda df, key: df.groupBy(key).agg(F.collect_list(F.struct("label", "d")).alias("ds"))
        none, by_ctx, by_gram = self._added()
        by_ctx, by_gram = packed(by_ctx, "ctx"), packed(by_gram, "gram")
        g = g.withColumn("gram", F.concat("ctx", "ch"))
        adds = []
        for table, on in ((by_ctx, "ctx"), (by_gram, "gram")):
            often = stash(table.join(g.groupBy(on).agg(F.count(F.lit(1)).alias("f")), on), "table")
            hit = join_frequent(g.select(key, on, "m"), often, on).select(key, "m", F.explode("ds").alias("x"))
            adds.append(hit.groupBy(key, F.col("x.label").alias("label")).agg(F.sum(F.col("m") * F.col("x.d")).alias("score")))
        rows = g.groupBy(key).agg(F.sum("m").alias("m"))
        least = rows.join(F.broadcast(self.labels)).select(key, "label", (F.col("m") * none).alias("score"))  # label set: a row a label
        return least.unionByName(adds[0]).unionByName(adds[1]).groupBy(key, "label").agg(F.sum("score").alias("score"))

    def _cells(self, g: DataFrame, key: str) -> DataFrame:
        """Distinct grams meet the label set once, whatever the number of rows."""
        cells = g.groupBy("ctx", "ch").agg(F.count(F.lit(1)).alias("f")).join(F.broadcast(self.labels))  # label set: a row a label
        cells = cells.join(self.counts, ["label", "ctx", "ch"], "left").join(self.contexts, ["label", "ctx"], "left")
        p = self._prob(cells, F.coalesce("c", F.lit(0)), F.coalesce("t", F.lit(0)))
        values = p.groupBy(F.concat("ctx", "ch").alias("gram")).agg(F.max("f").alias("f"), F.collect_list(F.struct("label", F.round(F.log("p") * 1_000_000).cast("long").alias("v"))).alias("vs"))
        hit = join_frequent(g.select(key, F.concat("ctx", "ch").alias("gram"), "m"), stash(values, "table"), "gram").select(key, "m", F.explode("vs").alias("x"))
        return hit.groupBy(key, F.col("x.label").alias("label")).agg(F.sum(F.col("m") * F.col("x.v")).alias("score"))

    def _prob(self, cells: DataFrame, c: Column, t: Column) -> DataFrame:
        uni = self.counts.groupBy("label", "ch").agg(F.sum("c").alias("uc"))
        all_ = self.counts.groupBy("label").agg(F.sum("c").alias("ut"))
        cells = cells.join(uni, ["label", "ch"], "left").join(F.broadcast(all_), "label")
        low = (F.coalesce("uc", F.lit(0)) + self.k) / (F.col("ut") + self.k * self.alphabet)
        if self.smooth == "interp":
            return cells.withColumn("p", F.when(t > 0, self.weight * c / t + (1 - self.weight) * low).otherwise(low))
        return cells.withColumn("p", F.when(c > 0, c / t).otherwise(0.4 * low))

    def transform(self, df: DataFrame, key: str, text_col: str = "text") -> DataFrame:
        """df with label: the best score, ties to the smaller label. key tells rows apart. Texts without characters have none."""
        if (values := self.values()) is not None:
            kind = T.StructType([*df.drop("label").schema.fields, T.StructField("label", T.StringType())])
            names = np.array(values.labels, dtype=object)
            return map_scores(df.drop("label"), text_col, values, kind, lambda b, total, has: [*b.columns, pa.array(names[total.argmax(axis=1)], pa.string(), mask=~has)])
        s = self.scores(df, key, text_col)
        best = s.groupBy(key).agg(F.min_by("label", F.struct((-F.col("score")).alias("s"), "label")).alias("label"))
        return df.drop("label").join(best, key, "left")


def map_scores(df: DataFrame, text_col: str, values: Values, kind: T.StructType, said: Callable[[pa.RecordBatch, np.ndarray, np.ndarray], list]) -> DataFrame:
    """One scan: the columns, of the schema `kind`, that `said` makes of a batch of df's rows, their scores [rows, labels], and whether they have any character."""
    sent, names = df.sparkSession.sparkContext.broadcast(values), kind.names
    lower = "_lower"
    while lower in df.columns:
        lower += "_"
    most = max(1, CELLS // len(values.labels))  # rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at, many in windows(whole.column(lower)):
                for k in range(at, at + many, most):
                    b = whole.slice(k, min(most, at + many - k))
                    texts = [t or "" for t in b.column(lower).to_pylist()]
                    has = np.fromiter(map(bool, texts), bool, len(texts))
                    yield pa.RecordBatch.from_arrays(said(b.drop_columns([lower]), sent.value.scores(texts), has), names=names)

    return spread(df.withColumn(lower, F.lower(F.col(text_col)))).mapInArrow(lean(run), kind)


def runner_up(scores: DataFrame, key: str) -> DataFrame:
    """(key, label, margin)."""
    w = Window.partitionBy(key).orderBy(F.desc("score"), "label")
    r = scores.withColumn("r", F.row_number().over(w)).withColumn("next", F.lead("score").over(w)).where("r = 1")
    return r.select(key, "label", (F.col("score") - F.col("next")).alias("margin"))
