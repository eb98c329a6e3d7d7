"""Scores of texts under all labels, by three engines that agree exactly in fixed point."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import replace
from typing import TYPE_CHECKING

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import em, lattice, planner
from .cluster import lean
from .io import join_frequent, spread, stash
from .schemas import TOP

if TYPE_CHECKING:
    from .model import SegmentModel

#: Bytes of chunk scores that a worker remembers for a block of labels, and cells of an intermediate sum.
MEMORY, CELLS = 64 << 20, 1 << 22
ADDED = ("topk", "log_total")
_TOP_ARROW = pa.list_(pa.struct([("label", pa.string()), ("score", pa.float64())]))


class Kernel:
    """Scores of chunks for a block of labels, remembered up to a bound."""

    def __init__(self, ids: dict[str, int], matrix: np.ndarray, how: str) -> None:
        self.ids, self.matrix, self.how = ids, matrix, how
        self.longest = max(map(len, ids), default=1)
        self.row: dict[str, int] = {}
        self.table = np.empty((0, matrix.shape[1]), np.int64 if how == "best" else float)

    def rows(self, chunks: list[str]) -> np.ndarray:
        """Where the scores of different chunks stand in `table`, until the next call."""
        if 8 * len(self.row) * self.matrix.shape[1] > MEMORY:
            self.row = {}
        new = [c for c in chunks if c not in self.row]
        if new:
            at = len(self.row)
            if at + len(new) > len(self.table):
                grown = np.empty((max(at + len(new), 2 * at, 1024), self.table.shape[1]), self.table.dtype)
                grown[:at] = self.table[:at]
                self.table = grown
            for rows, tok in lattice.tensors(new, self.ids, self.longest):
                step = max(1, CELLS // self.matrix.shape[1])
                for k in range(0, len(rows), step):
                    part = tok[k : k + step]
                    self.table[at + rows[k : k + step]] = self.values(part)
            self.row |= {c: at + k for k, c in enumerate(new)}
        return np.fromiter(map(self.row.__getitem__, chunks), np.int64, len(chunks))

    def values(self, tok: np.ndarray) -> np.ndarray:
        return lattice.best_fx(tok, self.matrix) if self.how == "best" else lattice.marginal(tok, self.matrix)

    def scores(self, chunks: list[str]) -> np.ndarray:
        rows = self.rows(list(dict.fromkeys(chunks)))
        at = dict(zip(dict.fromkeys(chunks), rows.tolist(), strict=True))
        return self.table[[at[c] for c in chunks]]

    def sums(self, lists: pa.ListArray) -> np.ndarray:
        """[rows, labels]: the scores of each row's chunks added up."""
        total = np.zeros((len(lists), self.matrix.shape[1]), self.table.dtype)
        coded = lists.flatten().dictionary_encode()
        if not len(coded):
            return total
        at = self.rows(coded.dictionary.to_pylist())[coded.indices.to_numpy()]
        owner = np.repeat(np.arange(len(lists)), np.nan_to_num(pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False)).astype(np.int64))
        step = max(1, CELLS // total.shape[1])
        for k in range(0, len(at), step):
            own = owner[k : k + step]
            first = np.concatenate([[0], np.flatnonzero(np.diff(own)) + 1])
            total[own[first]] += np.add.reduceat(self.table[at[k : k + step]], first, axis=0)
        return total


class SplitKernel(Kernel):
    """Values of tokens, a row of `matrix` for each, added up over the best split under `fx`; split[column] says by which column of fx a column of the matrix is split."""

    def __init__(self, ids: dict[str, int], fx: np.ndarray, matrix: np.ndarray, split: np.ndarray) -> None:
        super().__init__(ids, matrix, "best")
        self.fx, self.split = fx, split

    def values(self, tok: np.ndarray) -> np.ndarray:
        return lattice.split_sums(tok, self.fx, self.matrix, self.split)


def scan(df: DataFrame, chunks: Column, kernels: Callable[[], list[Kernel]], width: int, kind: T.StructType, said: Callable[[pa.Array, np.ndarray, np.ndarray], list]) -> DataFrame:
    """One scan: the columns, of the schema `kind`, that `said` makes of some of df's rows (as structs), the sums of their chunks [rows, width] and whether they have any chunk."""
    work = spread(df.select(F.struct("*").alias("row"), chunks.alias("chunks")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, step = kernels(), max(1, CELLS // width)
        for whole in batches:
            for at in range(0, whole.num_rows, step):
                b = whole.slice(at, step)
                lists = b.column("chunks")
                has = pa.compute.fill_null(pa.compute.greater(pa.compute.list_value_length(lists), 0), False).to_numpy(zero_copy_only=False)
                yield pa.RecordBatch.from_arrays(said(b.column("row"), np.concatenate([k.sums(lists) for k in own], axis=1), has), names=kind.names)

    return work.mapInArrow(lean(run), kind)


def _top(s: np.ndarray, labels: np.ndarray, k: int) -> tuple[list[list[dict]], np.ndarray]:
    """Best k by score, ties by label (labels are in order and the sort is stable), and the log of the sum of all exponentials."""
    order = np.argsort(-s, axis=1, kind="stable")[:, :k]
    top = s[np.arange(len(s)), order[:, 0]]
    with np.errstate(invalid="ignore"):
        total = top + np.log(np.exp(s - top[:, None]).sum(axis=1))
    return [[{"label": labels[j], "score": float(s[i, j])} for j in row] for i, row in enumerate(order)], total


def _log_prior(labels: list[str], prior: dict[str, float] | None) -> np.ndarray:
    return np.array([math.log(max(prior.get(x, 0.0), 1e-300)) if prior else 0.0 for x in labels])


def score_labels(df: DataFrame, model: SegmentModel, text_col: str = "text", how: str = "best", topk: int = 5, block: int | None = None, engine: str = "map", prior: dict[str, float] | None = None) -> DataFrame:
    """Adds topk, an array of (label, score) in falling order, and log_total, over all labels; a prior is added to the scores before the best are taken. Matrices are broadcast in blocks of labels. A worker
    holds those of one pass, planner.PASS_BYTES at most; sets of labels that are wider take further passes over stored rows, and a row's passes are joined by its best entries."""
    labels = model.labels()
    if not labels:
        raise ValueError("a model without labels")
    n = model.vocab.count()
    block = block or planner.block_size(n, len(labels), how)
    groups = [labels[i : i + block] for i in range(0, len(labels), block)]
    base = df.drop(*ADDED)
    if engine != "map":
        return {"dictionary": _dictionary, "native": _native}[engine](base, model, groups, text_col, how, topk, prior)
    many = max(1, planner.PASS_BYTES // ((4 if how == "best" else 8) * (n + 2) * block))
    passes = [groups[i : i + many] for i in range(0, len(groups), many)]
    if len(passes) == 1:
        return _map(base, model, passes[0], text_col, how, topk, prior)
    out, before = None, "before"
    while before in base.columns:
        before += "_"
    for own in passes:
        found = _map(base if out is None else out.select("row.*", F.struct("so_far", "total").alias(before)), model, own, text_col, how, topk, prior)
        kept = F.struct(*[F.col(f"`{c}`") for c in base.columns]).alias("row")
        if out is None:
            out = found.select(kept, F.col("topk").alias("so_far"), F.col("log_total").alias("total"))
        else:
            both = F.concat(f"{before}.so_far", "topk")
            big = F.greatest(f"{before}.total", "log_total")
            out = found.select(kept, _best(both, topk).alias("so_far"), (big + F.log(F.exp(F.col(f"{before}.total") - big) + F.exp(F.col("log_total") - big))).alias("total"))
        out = stash(out, "pass")
    return out.select("row.*", F.col("so_far").alias("topk"), F.col("total").alias("log_total"))


def _best(entries: Column, k: int) -> Column:
    ordered = F.array_sort(F.transform(entries, lambda x: F.struct((-x["score"]).alias("s"), x["label"].alias("label"))))
    return F.slice(F.transform(ordered, lambda x: F.struct(x["label"].alias("label"), (-x["s"]).alias("score"))), 1, k)


def _cut(df: DataFrame, model: SegmentModel, text_col: str) -> Column:
    chunks = model.chunks(F.col(f"`{text_col}`"))
    return F.filter(chunks, lambda c: c != "") if model.kind == "none" else chunks


def _map(df: DataFrame, model: SegmentModel, groups: list[list[str]], text_col: str, how: str, topk: int, prior: dict[str, float] | None) -> DataFrame:
    """Engine B: one scan. Chunks are cut by built-in functions, scored in Arrow batches with a memory per task; a worker goes through the blocks of labels of a batch."""
    from .model import block_matrix

    sc = df.sparkSession.sparkContext
    sent = [sc.broadcast(block_matrix(model, g, how)) for g in groups]
    names = np.array([x for g in groups for x in g], dtype=object)
    unit, add = 1 / em.SCALE if how == "best" else 1.0, _log_prior(list(names), prior)
    order = np.argsort(names.astype(str), kind="stable")

    def said(row: pa.Array, total: np.ndarray, has: np.ndarray) -> list:
        tops, z = _top((total * unit + add)[:, order], names[order], topk)
        return [row, pa.array([t if h else None for t, h in zip(tops, has, strict=True)], _TOP_ARROW), pa.array(z, pa.float64(), mask=~has)]

    kind = T.StructType([T.StructField("row", df.select(F.struct("*").alias("row")).schema["row"].dataType), T.StructField("topk", T._parse_datatype_string(TOP)), T.StructField("log_total", T.DoubleType())])
    out = scan(df, _cut(df, model, text_col), lambda: [Kernel(*x.value, how) for x in sent], len(names), kind, said)
    return out.select("row.*", *ADDED)


def best_of_runs(df: DataFrame, model: SegmentModel, text_col: str, kind: T.StructType, said: Callable) -> DataFrame | None:
    """scan() of the best-split scores under all labels of the model, in order; None if they don't fit one pass."""
    from .model import block_matrix

    labels, n = model.labels(), model.vocab.count()
    block = planner.block_size(n, len(labels), "best")
    if 4 * (n + 2) * len(labels) > planner.PASS_BYTES:
        return None
    sent = [df.sparkSession.sparkContext.broadcast(block_matrix(model, labels[i : i + block], "best")) for i in range(0, len(labels), block)]
    return scan(df, _cut(df, model, text_col), lambda: [Kernel(*x.value, "best") for x in sent], len(labels), kind, said)


def chunk_scores(chunks: DataFrame, model: SegmentModel, labels: list[str], how: str) -> DataFrame:
    """(chunk, scores array, f) once per distinct chunk; f: rows that have it."""
    from .model import block_matrix

    sent = chunks.sparkSession.sparkContext.broadcast(block_matrix(model, labels, how))
    kind, value = ("long", pa.int64()) if how == "best" else ("double", pa.float64())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = Kernel(*sent.value, how)
        for whole in batches:
            step = max(1, CELLS // len(labels))
            for at in range(0, whole.num_rows, step):
                b = whole.slice(at, step)
                rows = kernel.rows(b.column("chunk").to_pylist())
                s = kernel.table[rows]
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(s) + 1) * s.shape[1], pa.int32()), pa.array(s.ravel(), value))
                yield pa.RecordBatch.from_arrays([b.column("chunk"), lists, b.column("f")], names=["chunk", "scores", "f"])

    distinct = chunks.groupBy("chunk").agg(F.count(F.lit(1)).alias("f"))
    return distinct.mapInArrow(run, f"chunk string, scores array<{kind}>, f long")


def _sum_top(parts: DataFrame, labels: list[str], topk: int, how: str, prior: dict[str, float] | None) -> DataFrame:
    """(at, topk, log_total) from rows (at, n, scores)."""
    sums = parts.groupBy("at").agg(*[F.sum(F.col("n") * F.col("scores")[k]).alias(f"s{k}") for k in range(len(labels))])
    unit = 1 / em.SCALE if how == "best" else 1.0
    value = [F.col(f"s{k}") * F.lit(unit) + F.lit(float(p)) for k, p in enumerate(_log_prior(labels, prior))]
    entries = F.array(*[F.struct(F.lit(x).alias("label"), v.alias("score")) for x, v in zip(labels, value, strict=True)])
    kept = sums.select("at", entries.alias("entries"))
    top = F.array_max(F.transform("entries", lambda x: x["score"]))
    return kept.select("at", _best(F.col("entries"), topk).alias("topk"), (top + F.log(F.aggregate("entries", F.lit(0.0), lambda a, x: a + F.exp(x["score"] - top)))).alias("log_total"))


def _rows(df: DataFrame, model: SegmentModel, text_col: str) -> tuple[DataFrame, DataFrame]:
    """(row, at) with a stable number, written once; and (at, chunk, n)."""
    base = stash(df.select(F.struct("*").alias("row"), F.monotonically_increasing_id().alias("at"), _cut(df, model, text_col).alias("chunks")), "rows")
    return base.drop("chunks"), base.select("at", F.explode("chunks").alias("chunk")).groupBy("at", "chunk").agg(F.count(F.lit(1)).alias("n"))


def _dictionary(df: DataFrame, model: SegmentModel, groups: list[list[str]], text_col: str, how: str, topk: int, prior: dict[str, float] | None) -> DataFrame:
    """Engine A: every distinct chunk of the input is scored once, then joined back; frequent chunks are broadcast, so no chunk is hot."""
    base, chunks = _rows(df, model, text_col)
    labels = sorted(x for g in groups for x in g)
    scored = stash(chunk_scores(chunks, model, labels, how), "scored")
    top = _sum_top(join_frequent(chunks, scored, "chunk"), labels, topk, how, prior)
    return base.join(top, "at", "left").select("row.*", *ADDED)


def _native(df: DataFrame, model: SegmentModel, groups: list[list[str]], text_col: str, how: str, topk: int, prior: dict[str, float] | None) -> DataFrame:
    """Engine C: the dynamic program as built-in array functions over a broadcast map; for small models and best splits."""
    if how != "best":
        raise ValueError("the native engine takes best splits")
    from .model import block_matrix

    labels = sorted(x for g in groups for x in g)
    ids, matrix = block_matrix(model, labels, how)
    if len(ids) * len(labels) > 50_000:
        raise ValueError("the native engine is for small models")
    spark, longest = df.sparkSession, max(map(len, ids), default=1)
    table = spark.createDataFrame([({t: matrix[i].tolist() for t, i in ids.items()},)], "m map<string,array<bigint>>")
    unknown = F.array(*[F.lit(int(x)).cast("long") for x in matrix[-2]])
    base, chunks = _rows(df, model, text_col)
    distinct = chunks.groupBy("chunk").agg(F.count(F.lit(1)).alias("f")).join(F.broadcast(table))  # the table is one row
    never = F.array(*[F.lit(lattice.NEVER) for _ in labels])
    zero = F.array(F.array(*[F.lit(0).cast("long") for _ in labels]))

    def value(s: Column, l: Column) -> Column:
        v = F.col("m")[F.substring(F.col("chunk"), s, l)]
        return F.coalesce(v, F.when(l == 1, unknown))

    def step(acc: Column, e: Column) -> Column:
        reach = F.sequence(F.lit(1), F.least(F.lit(longest), e))
        into = F.filter(F.transform(reach, lambda l: F.zip_with(F.element_at(acc, -l), value(e - l + 1, l), lambda a, b: a + b)), lambda x: x.isNotNull())
        now = F.array(F.aggregate(into, never, lambda a, b: F.zip_with(a, b, lambda x, y: F.greatest(x, y))))
        return F.concat(F.slice(acc, -F.least(F.lit(longest), F.size(acc)), longest), now)

    scored = distinct.select("chunk", F.element_at(F.aggregate(F.sequence(F.lit(1), F.length("chunk")), zero, step), -1).alias("scores"), "f")
    top = _sum_top(join_frequent(chunks, stash(scored, "scored"), "chunk"), labels, topk, how, prior)
    return base.join(top, "at", "left").select("row.*", *ADDED)


def whole_chunks(model: SegmentModel) -> SegmentModel:
    """The model for texts that are chunks already: they are not cut again."""
    return replace(model, kind="none", prefix_space=False, unit="codepoint")


def sequence_logp(tokens: DataFrame, theta: DataFrame, stats: DataFrame, vocab: DataFrame) -> DataFrame:
    """(id, label, logp) of token sequences (id, label, tokens): the sum of the tokens' values, floors for unseen ones."""
    t = tokens.select("id", "label", F.explode("tokens").alias("token")).join(vocab.select("token", "token_id"), "token", "left")
    t = t.join(theta.select("label", "token_id", "logp"), ["label", "token_id"], "left").join(F.broadcast(stats.select("label", "floor")), "label")
    value = F.when(F.col("token_id").isNull(), em.UNKNOWN).otherwise(F.coalesce("logp", "floor"))
    return t.groupBy("id", "label").agg(F.sum(value).alias("logp"))


def marginal_chunks(chunks: DataFrame, model: SegmentModel) -> DataFrame:
    """(chunk, label, logp): log of the sum over all splits."""
    return _per_label(chunks, model, "marginal")


def best_chunks(chunks: DataFrame, model: SegmentModel) -> DataFrame:
    """(chunk, label, score_fx)."""
    return _per_label(chunks, model, "best")


def _per_label(chunks: DataFrame, model: SegmentModel, how: str) -> DataFrame:
    labels = model.labels()
    s = chunk_scores(chunks, model, labels, how)
    return s.select("chunk", F.posexplode("scores").alias("k", "logp" if how != "best" else "score_fx")).withColumn("label", F.element_at(F.array(*map(F.lit, labels)), F.col("k") + 1)).drop("k")


def path_posterior(paths: DataFrame, model: SegmentModel) -> DataFrame:
    """(id, label, posterior) of token sequences given the string they spell."""
    p = sequence_logp(paths, model.theta, model.stats, model.vocab)
    whole = paths.select("id", "label", F.array_join("tokens", "").alias("chunk"))
    m = marginal_chunks(whole, model).withColumnRenamed("logp", "all")
    return p.join(whole, ["id", "label"]).join(m, ["chunk", "label"]).select("id", "label", F.exp(F.col("logp") - F.col("all")).alias("posterior"))


def segment(df: DataFrame, model: SegmentModel, text_col: str = "text", labels: list[str] | None = None) -> DataFrame:
    """Rows times labels with tokens and score_fx: how a text splits under each label."""
    from .model import block_matrix

    labels = labels or model.labels()
    sent = df.sparkSession.sparkContext.broadcast(block_matrix(model, labels, "best"))
    work = df.drop("label", "tokens", "score_fx").select(F.struct("*").alias("row"), _cut(df, model, text_col).alias("chunks"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, matrix = sent.value
        longest = max(map(len, ids), default=1)
        for b in batches:
            take, names, tokens, scores = [], [], [], []
            for i, chunks in enumerate(b.column("chunks").to_pylist()):
                for k, label in enumerate(labels):
                    said, total = [], 0
                    for c in chunks or []:
                        t, s = lattice.segment_one(c, ids, longest, matrix[:, k])
                        said += t
                        total += s
                    take.append(i)
                    names.append(label)
                    tokens.append(said)
                    scores.append(total)
            yield pa.RecordBatch.from_arrays([b.column("row").take(pa.array(take, pa.int64())), pa.array(names, pa.string()), pa.array(tokens, pa.list_(pa.string())), pa.array(scores, pa.int64())], names=["row", "label", "tokens", "score_fx"])

    out = work.mapInArrow(run, T.StructType([work.schema["row"], *T._parse_datatype_string("label string, tokens array<string>, score_fx long").fields]))
    return out.select("row.*", "label", "tokens", "score_fx")
