"""Expectation-maximisation of token distributions, for all labels in one job a round.

Chunks with their weights are placed once by (label, salt) and written. Labels never meet, so a label whose distinct chunks fit one task, `rows_per_task` at most, runs all its rounds there, one
task a label and one job for all of them. A larger label goes round by round, and labels that have converged leave. Its lattices are built once and written; a round sends the current
distributions to them and adds up counts. If those distributions are too many for the driver, chunks stay placed by (label, salt) and meet them as rows. All ways take the same steps."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import lattice
from .cluster import release
from .io import side_by_side, stash

#: Log-probability of a character that no token covers.
UNKNOWN = -40.0
SCALE = 1_000_000
#: Cells, larger labels by tokens, of the distributions that the driver holds between rounds.
DENSE_CELLS = 2_000_000
#: Distinct chunks and their characters that one task holds: as a trie about 10 bytes a character, and a few times that within a round.
TASK_ROWS, TASK_CHARS = 500_000, 5_000_000


@dataclass
class Fitted:
    theta: DataFrame  # label, token_id, logp, logp_fx, seen, c; tokens that occur in the lattices of the label, also those whose count has gone to nothing
    stats: DataFrame  # LABEL_STATS
    trace: DataFrame  # label, round, loglik, tv


def init_theta(vocab_size: int, how: str = "uniform", freq: dict[int, float] | None = None) -> np.ndarray:
    """Start values, with entries for the unknown token and 'no edge' at the end. A uniform start is never stored by label."""
    out = np.full(vocab_size + 2, -np.log(max(vocab_size, 1)))
    if how != "uniform" and freq:
        total = sum(freq.values()) + vocab_size
        for i in range(vocab_size):
            out[i] = np.log((freq.get(i, 0.0) + 1) / total)
    out[-2], out[-1] = UNKNOWN, -np.inf
    return out


def prepare(chunks: DataFrame, rows_per_task: int = TASK_ROWS, chars_per_task: int = TASK_CHARS) -> DataFrame:
    """(label, salt, chunk, n), written in its final placement: the last shuffle that moves chunks. Salts follow the number and the length of the distinct chunks of a label."""
    sizes = chunks.groupBy("label").agg(F.count(F.lit(1)).alias("u"), F.sum(F.length("chunk")).alias("chars"))
    salts = F.greatest(F.ceil(F.col("u") / rows_per_task), F.ceil(F.col("chars") / chars_per_task), F.lit(1)).cast("int")
    placed = chunks.join(F.broadcast(sizes), "label").select("label", F.pmod(F.xxhash64("chunk"), salts).cast("int").alias("salt"), "chunk", F.col("n").cast("double").alias("n"))
    return stash(placed.repartition("label", "salt"), "placed")


Parts = list[tuple[np.ndarray, "np.ndarray | lattice.Trie"]]


def _lattices(chunks: pd.DataFrame, ids: dict[str, int], longest: int, hard: bool, most: int = 4096) -> Parts:
    """(weight, lattice): one trie of all chunks, but tensors of at most `most` chunks of one length for those that are too long, and for best splits; in memory a tensor lies by place and token length, then chunk."""
    weight, size = chunks["n"].to_numpy(float), chunks["chunk"].str.len().to_numpy()
    short = np.flatnonzero((size > 0) & (size <= lattice.TRIE_CHARS) & (not hard))
    found: Parts = [(weight[short], lattice.Trie.of(chunks["chunk"].iloc[short].tolist(), lattice.Suffixes(ids)))] if len(short) else []
    rest = np.setdiff1d(np.arange(len(chunks)), short)
    aside = lambda tok: np.ascontiguousarray(tok.transpose(1, 2, 0)).transpose(2, 0, 1)
    return found + [(weight[rest[rows[k : k + most]]], aside(tok[k : k + most])) for rows, tok in lattice.tensors(chunks["chunk"].iloc[rest].tolist(), ids, longest) for k in range(0, len(rows), most)]


def _counts(parts: Parts, logp: np.ndarray, hard: bool) -> tuple[np.ndarray, float]:
    c, total = np.zeros(len(logp)), 0.0
    for weight, tok in parts:
        part, ll = tok.expected_counts(weight, logp) if isinstance(tok, lattice.Trie) else lattice.expected_counts(tok, weight, logp, hard)
        c += part
        total += ll
    return c, total


def _edges(parts: Parts, size: int) -> np.ndarray:
    """Which tokens have an edge in some lattice."""
    out = np.zeros(size, bool)
    for _, part in parts:
        tok = part.tok if isinstance(part, lattice.Trie) else part
        out[tok[tok >= 0]] = True
    return out


def e_step(placed: DataFrame, vocab: DataFrame | dict[str, int], theta: DataFrame | None = None, kind: str = "soft", default: float | None = None, occurring: bool = False) -> DataFrame:
    """(label, token_id, c, loglik): expected counts, summed in the task; loglik sits on rows with token -1. occurring: also rows of count 0 for tokens that have an edge in some lattice.
    theta is (label, token_id, logp); tokens it lacks have `default`, and without it the start is uniform."""
    ids = vocab if isinstance(vocab, dict) else lattice.collect_vocab(vocab)
    sent = placed.sparkSession.sparkContext.broadcast(ids)
    size, longest = len(ids), max(map(len, ids), default=1)
    schema = "label string, token_id int, c double, loglik double"

    def counts(label: str, chunks: pd.DataFrame, logp: np.ndarray) -> pd.DataFrame:
        parts = _lattices(chunks, sent.value, longest, kind == "hard")
        c, total = _counts(parts, logp, kind == "hard")
        some = np.flatnonzero((c[:size] > 0) | _edges(parts, size) if occurring else c[:size] > 0)
        return pd.DataFrame({"label": label, "token_id": np.append(some, -1).astype(np.int32), "c": np.append(c[some], 0.0), "loglik": np.append(np.zeros(len(some)), total)})

    if theta is None:
        start = init_theta(size)
        return placed.groupBy("label", "salt").applyInPandas(lambda key, pdf: counts(key[0], pdf, start), schema)
    places = placed.select(F.col("label").alias("at_label"), F.col("salt").alias("at_salt")).distinct()
    salted = places.join(theta.select("label", "token_id", "logp"), F.col("at_label") == F.col("label")).select("at_label", "at_salt", "token_id", "logp")

    def run(key: tuple, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return counts(key[0], left, _dense(size, right, default)) if len(left) else pd.DataFrame({"label": [], "token_id": [], "c": [], "loglik": []})

    return placed.groupBy("label", "salt").cogroup(salted.groupBy("at_label", "at_salt")).applyInPandas(run, schema)


def _dense(size: int, theta: pd.DataFrame, default: float | None = None) -> np.ndarray:
    logp = np.full(size + 2, -np.inf if default is None else default)
    logp[-2], logp[-1] = UNKNOWN, -np.inf
    logp[theta["token_id"].to_numpy()] = theta["logp"].to_numpy()
    return logp


#: Smallest expected count that is kept as one.
TINY = 1e-12


def fit_in_task(placed: DataFrame, ids: dict[str, int], theta: DataFrame | None, rounds: int, tol: float, kind: str) -> DataFrame:
    """All rounds of labels that fit one task: (label, token_id, c, logp, total) with c null where a token occurs but its count has gone, and the trace on rows with token -1:
    round in `c`, log-likelihood in `logp`, total variation in `total`."""
    sent = placed.sparkSession.sparkContext.broadcast(ids)
    size, longest = len(ids), max(map(len, ids), default=1)
    schema = "label string, token_id int, c double, logp double, total double"

    def run(label: str, chunks: pd.DataFrame, logp: np.ndarray, uniform: bool) -> pd.DataFrame:
        parts = _lattices(chunks, sent.value, longest, kind == "hard")
        trace = []
        for r in range(1, rounds + 1):
            c, ll = _counts(parts, logp, kind == "hard")
            c, before = c[:size], logp[:size]
            new = np.full(size + 2, -np.inf)
            new[-2] = UNKNOWN
            kept = c > TINY
            new[:size][kept] = np.log(c[kept] / c.sum())
            tv = 1.0 if r == 1 and uniform else float(np.abs(np.exp(new[:size]) - np.exp(before)).sum() / 2)
            trace.append((r, ll, tv))
            logp = new
            if tv < tol:
                break
        some = np.flatnonzero(_edges(parts, size) | kept)
        t = np.array(trace)
        del parts
        release()
        return pd.DataFrame({
            "label": label, "token_id": np.append(some, np.full(len(t), -1)).astype(np.int32), "c": np.append(np.where(kept[some], c[some], np.nan), t[:, 0]),
            "logp": np.append(np.where(kept[some], logp[some], np.nan), t[:, 1]), "total": np.append(np.full(len(some), c.sum()), t[:, 2]),
        })

    if theta is None:
        start = init_theta(size)
        return placed.groupBy("label").applyInPandas(lambda key, pdf: run(key[0], pdf, start, True), schema)
    start_of = theta.select(F.col("label").alias("at_label"), "token_id", "logp")
    return placed.groupBy("label").cogroup(start_of.groupBy("at_label")).applyInPandas(lambda key, a, b: run(key[0], a, _dense(size, b), False) if len(a) else pd.DataFrame({c: [] for c in ("label", "token_id", "c", "logp", "total")}), schema)


def rounds_of(chunks: list[str], n: np.ndarray, ids: dict[str, int], rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """(logp, c) after some rounds over chunks that fit one task, from a uniform start; c is 0 where nothing is kept."""
    parts, logp, c = _lattices(pd.DataFrame({"chunk": chunks, "n": n}), ids, max(map(len, ids)), False), init_theta(len(ids)), np.zeros(len(ids))
    for _ in range(rounds):
        c = _counts(parts, logp, False)[0][: len(ids)]
        kept, total = c > TINY, c.sum()
        logp = np.full(len(ids) + 2, -np.inf)
        logp[-2] = UNKNOWN
        logp[: len(ids)][kept] = np.log(c[kept] / total)
        c = np.where(kept, c, 0.0)
    return logp, c


def pack(placed: DataFrame, ids: dict[str, int], kind: str = "soft", chars_per_task: int = 2_000_000) -> DataFrame:
    """(label, size, m, weight, tok): lattices as bytes, written; a trie, with m 0, or a tensor. Chunks are dealt by their digest, whatever their label."""
    spark = placed.sparkSession
    sent, longest = spark.sparkContext.broadcast(ids), max(map(len, ids), default=1)
    chars = placed.agg(F.sum(F.length("chunk"))).first()[0] or 0
    names = ["label", "size", "m", "weight", "tok"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b.to_pandas() for b in batches]
        for label, own in pd.concat(got).groupby("label") if got else ():
            for length, group in own.groupby(own["chunk"].str.len().where(lambda x: (x > lattice.TRIE_CHARS) | (kind == "hard"), 0)):
                most = max(1, min(4096, 200_000 // length)) if length else len(group)
                for at in range(0, len(group), most):
                    for w, tok in _lattices(group.iloc[at : at + most], sent.value, longest, kind == "hard", most):
                        row = [label, 0, 0, w.tobytes(), tok.to_bytes()] if isinstance(tok, lattice.Trie) else [label, tok.shape[1], tok.shape[2], w.tobytes(), tok.transpose(1, 2, 0).tobytes()]
                        yield pa.RecordBatch.from_arrays([pa.array([x], of) for x, of in zip(row, (pa.string(), pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=names)

    parts = max(spark.sparkContext.defaultParallelism, -(-chars // chars_per_task))
    dealt = placed.select("label", "chunk", "n").repartition(parts, F.xxhash64("chunk", "label"))
    return stash(dealt.mapInArrow(run, "label string, size int, m int, weight binary, tok binary"), "lattices")


def fit_packed(packed: DataFrame, labels: list[str], size: int, theta: DataFrame | None, rounds: int, tol: float, kind: str) -> tuple[DataFrame, DataFrame, list[tuple]]:
    """All rounds of labels whose distributions the driver holds: (label, token_id, c, logp, total), (label, token_id) of the tokens that occur, and the trace (label, round, loglik, tv)."""
    spark = packed.sparkSession
    logp = {x: init_theta(size) for x in labels}
    if theta is not None:
        start = theta.where(F.col("label").isin(labels)).select("label", "token_id", "logp").toArrow().to_pandas()
        logp = {x: _dense(size, start[start["label"] == x]) for x in labels}
    done, seen, said, active = [], None, [], list(labels)
    for r in range(1, rounds + 1):
        sent = spark.sparkContext.broadcast({x: logp[x] for x in active})

        def run(batches: Iterator[pa.RecordBatch], sent=sent, first=r == 1) -> Iterator[pa.RecordBatch]:
            sums: dict[str, list] = {}
            for batch in batches:
                for row in batch.to_pylist():
                    mine = sent.value[row["label"]]
                    tok = np.frombuffer(row["tok"], np.int32).reshape(row["size"], row["m"], -1).transpose(2, 0, 1) if row["m"] else lattice.Trie.from_bytes(row["tok"])
                    part = [(np.frombuffer(row["weight"]), tok)]
                    c, ll = _counts(part, mine, kind == "hard")
                    at = sums.setdefault(row["label"], [np.zeros(len(mine)), 0.0, np.zeros(size, bool)])
                    at[0] += c
                    at[1] += ll
                    if first:
                        at[2] |= _edges(part, size)
            for label, (c, ll, edge) in sums.items():
                some = np.flatnonzero((c[:size] > 0) | edge)
                yield pa.RecordBatch.from_arrays([pa.array([label] * (len(some) + 1)), pa.array(np.append(some, -1).astype(np.int32)), pa.array(np.append(c[some], ll))], names=["label", "token_id", "c"])

        got = packed.where(F.col("label").isin(active)).mapInArrow(run, "label string, token_id int, c double").groupBy("label", "token_id").agg(F.sum("c").alias("c")).toArrow().to_pandas()
        sent.destroy()
        if r == 1:
            seen = got.loc[got["token_id"] >= 0, ["label", "token_id"]]
        for x, own in got.groupby("label"):
            of = own["token_id"].to_numpy()
            ll, c = float(own["c"].to_numpy()[of < 0][0]), np.zeros(size)
            c[of[of >= 0]] = own["c"].to_numpy()[of >= 0]
            new, kept = np.full(size + 2, -np.inf), c > TINY
            new[-2] = UNKNOWN
            new[:size][kept] = np.log(c[kept] / c.sum())
            tv = 1.0 if r == 1 and theta is None else float(np.abs(np.exp(new[:size]) - np.exp(logp[x][:size])).sum() / 2)
            said.append((x, r, ll, tv))
            logp[x] = new
            if tv < tol or r == rounds:
                some = np.flatnonzero(kept)
                done.append(pd.DataFrame({"label": x, "token_id": some.astype(np.int32), "c": c[some], "logp": new[some], "total": c.sum()}))
                active.remove(x)
        if not active:
            break
    frame = lambda pdf: stash(spark.createDataFrame(pa.Table.from_pandas(pdf, preserve_index=False)), "dense")
    return frame(pd.concat(done)), frame(seen), said


def sum_counts(parts: DataFrame) -> DataFrame:
    """(label, token_id, c): salts added up."""
    return parts.where("token_id >= 0").groupBy("label", "token_id").agg(F.sum("c").alias("c"))


def m_step(expected: DataFrame, tiny: float = TINY) -> DataFrame:
    """(label, token_id, c, logp): counts normalised within their label. Totals are one row a label."""
    totals = expected.groupBy("label").agg(F.sum("c").alias("total"))
    return expected.join(totals, "label").where(F.col("c") > tiny).select("label", "token_id", "c", F.log(F.col("c") / F.col("total")).alias("logp"), "total")


def total_variation(a: DataFrame, b: DataFrame) -> DataFrame:
    """(label, tv): half the sum of absolute differences; tokens that one side lacks have probability 0 there."""
    x = a.select("label", "token_id", F.exp("logp").alias("p"))
    y = b.select("label", "token_id", F.exp("logp").alias("q"))
    j = x.join(y, ["label", "token_id"], "full")
    return j.groupBy("label").agg((F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0)))) / 2).alias("tv"))


def corpus_loglik(parts: DataFrame) -> DataFrame:
    """(label, loglik) of the distribution that an E-step was run with."""
    return parts.where("token_id = -1").groupBy("label").agg(F.sum("loglik").alias("loglik"))


def floor_of(total: Column, least_seen: Column, how: str = "expected", min_expected: float = 0.5) -> Column:
    """Log-value of tokens that a label lacks: that of min_expected occurrences, or the least seen one."""
    return F.log(F.lit(min_expected) / total) if how == "expected" else least_seen


def fix(logp: Column) -> Column:
    """Fixed point: maxima and sums of whole numbers do not depend on their order."""
    return F.round(logp * SCALE).cast("long")


def start_theta(chunks: DataFrame, vocab: DataFrame, ids: dict[str, int], how: str) -> DataFrame | None:
    """(label, token_id, logp) to begin with: None for uniform, two rounds over all labels together (base), or the frequency of a token as a substring (freq)."""
    if how == "base":
        pooled = chunks.groupBy("chunk").agg(F.sum("n").alias("n")).select(F.lit("*").alias("label"), "chunk", "n")
        whole = fit(pooled, vocab, rounds=2).theta
        return stash(whole.crossJoin(F.broadcast(chunks.select("label").distinct().withColumnRenamed("label", "own"))).select(F.col("own").alias("label"), "token_id", "logp"), "start")  # label set x vocabulary
    if how == "freq":
        longest = max(map(len, ids))
        sub = chunks.select("label", "n", "chunk", F.explode(F.expr("sequence(1, length(chunk))")).alias("s"))
        sub = sub.select("label", "n", F.explode(F.expr(f"transform(sequence(1, least({longest}, length(chunk) - s + 1)), l -> substring(chunk, s, l))")).alias("token"))
        counts = sub.groupBy("label", "token").agg(F.sum("n").cast("double").alias("c"))
        return stash(m_step(counts.join(F.broadcast(vocab.select("token", "token_id")), "token").select("label", "token_id", "c")).select("label", "token_id", "logp"), "start")
    return None


def fit(chunks: DataFrame, vocab: DataFrame, rounds: int = 20, tol: float = 1e-6, init: str = "uniform", kind: str = "soft", floor: str = "expected", min_expected: float = 0.5, rows_per_task: int = TASK_ROWS) -> Fitted:
    """Rounds until every label's total variation is below tol. Floors come after the last round, so the likelihood never falls before."""
    spark = chunks.sparkSession
    ids = lattice.collect_vocab(vocab)
    placed = prepare(chunks, rows_per_task)
    start = start_theta(chunks, vocab, ids, init)
    wide = [r[0] for r in placed.where("salt > 0").select("label").distinct().collect()]  # labels
    own = F.col("label").isin(wide)
    dense = bool(wide) and rounds > 0 and len(wide) * len(ids) <= DENSE_CELLS
    within = lambda: stash(fit_in_task(placed.where(~own), ids, None if start is None else start.where(~own), rounds, tol, kind), "fitted") if placed.where(~own).limit(1).count() else None
    across = lambda: fit_packed(pack(placed.where(own), ids, kind), wide, len(ids), None if start is None else start.where(own), rounds, tol, kind) if dense else None
    got, packed = side_by_side(within, across)
    done, trace, seen, said = None, None, None, []
    if got is not None:
        trace = got.where("token_id = -1").select("label", F.col("c").cast("int").alias("round"), F.col("logp").alias("loglik"), F.col("total").alias("tv"))
        rows = got.where("token_id >= 0")
        seen = rows.select("label", "token_id")
        done = rows.where("not isnan(c)").select("label", "token_id", "c", "logp", "total")
    if packed is not None:
        over, more, said = packed
        done, seen = over if done is None else done.unionByName(over), more if seen is None else seen.unionByName(more)
    active, theta, still = placed.where(own), None if start is None else start.where(own), wide
    for r in range(1, rounds + 1) if wide and not dense else ():
        parts = stash(e_step(active, ids, theta, kind, occurring=r == 1), "counts")
        if r == 1:
            more = stash(parts.where("token_id >= 0").select("label", "token_id").distinct(), "seen")
            seen = more if seen is None else seen.unionByName(more)
        new = stash(m_step(sum_counts(parts)), "theta")
        loglik = corpus_loglik(parts)
        gap = total_variation(new, theta) if theta is not None else loglik.select("label", F.lit(1.0).alias("tv"))
        rows = loglik.join(gap, "label", "left").collect()  # a row a label
        said += [(x["label"], r, x["loglik"], x["tv"]) for x in rows]
        still = [x["label"] for x in rows if not (x["tv"] is not None and x["tv"] < tol)]
        over = new.where(~F.col("label").isin(still)) if still and r < rounds else new
        done = over if done is None else done.unionByName(over.select(*done.columns))
        theta = new
        if not still:
            break
        if len(still) < len(rows):
            active, theta = active.where(F.col("label").isin(still)), stash(new.where(F.col("label").isin(still)), "theta")
    final = stash(done, "final")
    if said:
        rest = spark.createDataFrame(said, "label string, round int, loglik double, tv double")
        trace = rest if trace is None else trace.unionByName(rest)
    samples = chunks.groupBy("label").agg(F.sum("n").cast("long").alias("n_samples"))
    return Fitted(*finish(final, samples, trace, floor, min_expected, seen), trace)


def finish(final: DataFrame, samples: DataFrame, trace: DataFrame, floor: str = "expected", min_expected: float = 0.5, seen: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """theta with floored values, and the statistics of each label. seen is (label, token_id) of the tokens that occur in a label's lattices: they keep the floor as a value of their own
    where their count has gone; all others share the floor in the statistics."""
    stats = final.groupBy("label").agg(F.sum("c").alias("n_tokens"), F.min("logp").alias("least"))
    stats = stats.withColumn("floor", floor_of(F.col("n_tokens"), F.col("least"), floor, min_expected))
    rows = final.select("label", "token_id", "logp", "c") if seen is None else seen.join(final.select("label", "token_id", "logp", "c"), ["label", "token_id"], "left")
    value = F.greatest(F.coalesce("logp", "floor"), F.col("floor"))
    theta = rows.join(F.broadcast(stats.select("label", "floor")), "label").select("label", "token_id", value.alias("logp"), fix(value).alias("logp_fx"), F.lit(True).alias("seen"), F.coalesce("c", F.lit(0.0)).alias("c"))
    h = final.groupBy("label").agg(F.sum(-F.exp("logp") * F.col("logp")).alias("entropy"))
    last = trace.groupBy("label").agg(F.max("round").alias("rounds"), F.max_by("tv", "round").alias("tv"))
    out = stats.join(samples, "label").join(h, "label").join(last, "label", "left").select("label", "n_samples", "n_tokens", "floor", "entropy", "rounds", "tv")
    return theta, out
