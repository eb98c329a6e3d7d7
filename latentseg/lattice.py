"""Lattices: all ways to split a chunk into vocabulary tokens, as edges (start, end, token)."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .schemas import EDGE

#: Vocabularies are broadcast to workers up to this many tokens.
MOST_TOKENS = 5_000_000


def collect_vocab(vocab: DataFrame) -> dict[str, int]:
    """The vocabulary as a dictionary on the driver; its size is bounded by MOST_TOKENS, checked here."""
    rows = vocab.select("token", "token_id").limit(MOST_TOKENS + 1).collect()
    if len(rows) > MOST_TOKENS:
        raise ValueError(f"over {MOST_TOKENS} tokens")
    return {r[0]: r[1] for r in rows}


def edges_of(chunk: str, ids: dict[str, int], longest: int, unk: int = -1) -> list[tuple[int, int, int]]:
    """Edges ordered by end, then start. A position that no token leaves gets an edge of one character to the unknown token."""
    out = []
    for s in range(len(chunk)):
        found = False
        for e in range(s + 1, min(len(chunk), s + longest) + 1):
            t = ids.get(chunk[s:e])
            if t is not None:
                out.append((e, s, t))
                found |= e == s + 1
        if not found:
            out.append((s + 1, s, unk))
    out.sort()
    return [(s, e, t) for e, s, t in out]


def build(chunks: DataFrame, vocab: DataFrame | dict[str, int]) -> DataFrame:
    """Adds edges to rows with a chunk column; matching is done once per distinct chunk, whatever the number of labels. Map-only."""
    ids = vocab if isinstance(vocab, dict) else collect_vocab(vocab)
    sent = chunks.sparkSession.sparkContext.broadcast(ids)
    longest = max(map(len, ids), default=1)
    cols = [c for c in chunks.columns if c != "edges"]
    df = chunks.select(*cols)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = sent.value
        kind = pa.list_(pa.struct([("s", pa.int32()), ("e", pa.int32()), ("t", pa.int32())]))
        for b in batches:
            made = [[{"s": s, "e": e, "t": t} for s, e, t in edges_of(c, table, longest)] for c in b.column("chunk").to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(made, kind)], names=[*cols, "edges"])

    from pyspark.sql import types as T

    return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField("edges", T._parse_datatype_string(f"array<{EDGE}>"))]))


def edges_sql(chunks: DataFrame, vocab: DataFrame) -> DataFrame:
    """(chunk, s, e, token_id, token) by an equi-join of substrings with the vocabulary; no Python."""
    longest = vocab.agg(F.max("token_len")).first()[0] or 1
    spans = chunks.select("chunk").distinct().select("chunk", F.explode(F.expr("sequence(1, length(chunk))")).alias("s0"))
    spans = spans.select("chunk", "s0", F.explode(F.expr(f"sequence(1, least({longest}, length(chunk) - s0 + 1))")).alias("l"))
    sub = spans.select("chunk", (F.col("s0") - 1).alias("s"), (F.col("s0") - 1 + F.col("l")).alias("e"), F.expr("substring(chunk, s0, l)").alias("token"))
    return sub.join(vocab.select("token", "token_id"), "token").select("chunk", "s", "e", "token_id", "token")


def count_paths(edges: Column) -> Column:
    """Number of splits, by adding up along the edges in their order; nothing is enumerated."""
    n = F.array_max(F.transform(edges, lambda x: x["e"]))
    start = F.concat(F.array(F.lit(1).cast("long")), F.array_repeat(F.lit(0).cast("long"), n))
    step = lambda acc, x: F.transform(acc, lambda v, i: F.when(i == x["e"], v + F.get(acc, x["s"])).otherwise(v))
    return F.element_at(F.aggregate(edges, start, step), -1)


def enumerate_segmentations(chunks: DataFrame, vocab: DataFrame, max_len: int = 10) -> DataFrame:
    """(chunk, tokens): every split of chunks of at most max_len characters, by repeated equi-joins on the position reached."""
    edges = edges_sql(chunks.where(F.length("chunk") <= max_len), vocab).select("chunk", "s", "e", "token").cache()
    paths = edges.where("s = 0").select("chunk", "e", F.array("token").alias("tokens"))
    done = paths.where("e = length(chunk)")
    for _ in range(max_len - 1):
        nxt = edges.select(F.col("chunk").alias("c"), F.col("s").alias("at"), F.col("e").alias("to"), F.col("token").alias("tok"))
        paths = paths.join(nxt, (F.col("chunk") == F.col("c")) & (F.col("e") == F.col("at"))).select("chunk", F.col("to").alias("e"), F.array_append("tokens", F.col("tok")).alias("tokens"))
        done = done.unionByName(paths.where("e = length(chunk)"))
    return done.select("chunk", "tokens")


def cost(lattices: DataFrame, n_labels: int) -> DataFrame:
    """One row: chunks, characters, edges, relaxations for n_labels, and branching in thousandths."""
    weight = F.col("n")
    e, t = F.sum(F.size("edges") * weight), F.sum(F.length("chunk") * weight)
    return lattices.agg(F.count(F.lit(1)).alias("chunks"), t.cast("long").alias("characters"), e.cast("long").alias("edges"), (e * n_labels).cast("long").alias("relaxations"), F.floor(e * 1000 / t).cast("long").alias("branching_milli"))


# --- kernels over many chunks of one length at a time


def tensors(chunks: list[str], ids: dict[str, int], longest: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each length T: (rows, tok[n, T, m]) with tok[., s, l-1] the token on characters s .. s+l-1, or -1; a place that no one-character
    token leaves holds -2 there, the unknown token."""
    by: dict[int, list[int]] = {}
    for k, c in enumerate(chunks):
        by.setdefault(len(c), []).append(k)
    for size, rows in by.items():
        m = min(longest, size)
        flat = [ids.get(chunks[k][s : s + l], -1) if s + l <= size else -1 for k in rows for s in range(size) for l in range(1, m + 1)]
        tok = np.array(flat, np.int32).reshape(len(rows), size, m) if size else np.empty((len(rows), 0, 1), np.int32)
        if size:
            tok[:, :, 0] = np.where(tok[:, :, 0] < 0, -2, tok[:, :, 0])
        yield np.array(rows), tok


NEVER = -(2**60)


def best_fx(tok: np.ndarray, fx: np.ndarray) -> np.ndarray:
    """Best-split scores [n, labels] in fixed point. fx[v, label]; row -1 (the last) is 'no edge', row -2 the unknown token.
    An edge relaxes all labels at once."""
    n, size, m = tok.shape
    best = deque([np.zeros((n, fx.shape[1]), np.int64)], maxlen=max(m, 1))  # the last m positions are all that is needed
    for e in range(1, size + 1):
        now = np.full((n, fx.shape[1]), NEVER, np.int64)
        for l in range(1, min(m, e) + 1):
            t = tok[:, e - l, l - 1]
            is_edge = t != -1
            if is_edge.all():
                np.maximum(now, best[-l] + fx[t], out=now)
            elif is_edge.any():
                now[is_edge] = np.maximum(now[is_edge], best[-l][is_edge] + fx[t[is_edge]])
        best.append(now)
    return best[-1]


def split_sums(tok: np.ndarray, fx: np.ndarray, values: np.ndarray, split: np.ndarray) -> np.ndarray:
    """[n, columns]: values[v, column] of the tokens of the best split added up, that under fx[v, split[column]]. Among equal splits that of segment_one."""
    n, size, m = tok.shape
    best = deque([np.zeros((n, fx.shape[1]), np.int64)], maxlen=max(m, 1))
    total = deque([np.zeros((n, values.shape[1]), np.int64)], maxlen=max(m, 1))
    for e in range(1, size + 1):
        now, added = np.full((n, fx.shape[1]), NEVER, np.int64), np.zeros((n, values.shape[1]), np.int64)
        for l in range(min(m, e), 0, -1):  # the token that starts first wins among equals
            t = tok[:, e - l, l - 1]
            some = np.flatnonzero(t != -1)
            if len(some):
                x = best[-l][some] + fx[t[some]]
                better = x > now[some]
                now[some] = np.where(better, x, now[some])
                added[some] = np.where(better[:, split], total[-l][some] + values[t[some]], added[some])
        best.append(now)
        total.append(added)
    return total[-1]


def split_tokens(tok: np.ndarray, fx: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, token) of all tokens of the best splits under fx[v], those of segment_one."""
    n, size, m = tok.shape
    best, last = np.full((size + 1, n), NEVER, np.int64), np.zeros((size + 1, n), np.int64)
    best[0] = 0
    for e in range(1, size + 1):
        for l in range(min(m, e), 0, -1):
            t = tok[:, e - l, l - 1]
            x = np.where(t != -1, best[e - l] + fx[t], NEVER)
            better = x > best[e]
            best[e][better], last[e][better] = x[better], l
    rows, tokens, own, at = [], [], np.arange(n), np.full(n, size)
    while len(own := own[at[own] > 0]):
        l = last[at[own], own]
        at[own] -= l
        rows.append(own)
        tokens.append(tok[own, at[own], l - 1])
    return np.concatenate([np.zeros(0, np.int64), *rows]), np.concatenate([np.zeros(0, np.int32), *tokens])


def marginal(tok: np.ndarray, logp: np.ndarray) -> np.ndarray:
    """Log of the sum over all splits, [n, labels]."""
    n, size, m = tok.shape
    out = deque([np.zeros((n, logp.shape[1]))], maxlen=max(m, 1))
    for e in range(1, size + 1):
        now = np.full((n, logp.shape[1]), -np.inf)
        for l in range(1, min(m, e) + 1):
            t = tok[:, e - l, l - 1]
            if (t != -1).any():
                now = np.logaddexp(now, out[-l] + logp[t])
        out.append(now)
    return out[-1]


#: Chunks less probable than this are summed in logs.
SMALL = 1e-200


def expected_counts(tok: np.ndarray, weight: np.ndarray, logp: np.ndarray, hard: bool = False) -> tuple[np.ndarray, float]:
    """Expected (or, if hard, best-split) token counts [len(logp)] over chunks with weights, and the weighted log-likelihood. logp is one label's; its last two entries are the unknown
    token and 'no edge'. Probabilities are summed as they are: no split of a chunk is less probable on the way than at its end. Chunks whose sum is under SMALL go through logs."""
    n, size, m = tok.shape
    if hard or not size:
        return _by_logs(tok, weight, logp, hard)
    t = np.ascontiguousarray(tok.transpose(1, 2, 0))  # as em keeps them, nothing is moved
    p = np.exp(logp)[t]
    f = np.empty((size + 1, n))
    f[0] = 1.0
    for e in range(1, size + 1):
        np.multiply(f[e - 1], p[e - 1, 0], out=f[e])
        for l in range(2, min(m, e) + 1):
            f[e] += f[e - l] * p[e - l, l - 1]
    low = f[size] < SMALL
    total = np.where(low, 1.0, f[size])
    b = np.empty((size + 1, n))
    b[size] = np.where(low, 0.0, weight) / total
    for s in range(size - 1, -1, -1):
        k = min(m, size - s)
        onward = p[s, :k] * b[s + 1 : s + k + 1]
        onward.sum(axis=0, out=b[s])
        np.multiply(onward, f[s], out=p[s, :k])
    found = np.bincount(np.add(t, 2, dtype=np.intp).ravel(), p.ravel(), len(logp))
    counts = np.concatenate([found[2:], found[:2]])
    counts[-1] = 0.0
    loglik = float(np.log(total) @ weight)
    if low.any():
        more, ll = _by_logs(tok[low], weight[low], logp, hard)
        counts, loglik = counts + more, loglik + ll
    return counts, loglik


#: Longest chunk that is put into a trie.
TRIE_CHARS = 64


def points_of(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """The code points of all texts, and where each begins (and the last ends)."""
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    return points, np.concatenate([[0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))])


def _levels(points: np.ndarray, at: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """For the prefixes of sorted texts, depth by depth: texts that reach it, the number of each one's prefix, whether it ends there, the first text of each new prefix, and the number of that one's own prefix. 0 is the empty one."""
    size = np.diff(at)
    rows, node, used = np.flatnonzero(size > 0), np.zeros(len(size), np.int64), 1
    d = 1
    while len(rows):
        parent, c = node[rows], points[at[rows] + d - 1]
        new = np.ones(len(rows), bool)
        new[1:] = (parent[1:] != parent[:-1]) | (c[1:] != c[:-1])
        node[rows] = used - 1 + np.cumsum(new)
        yield rows, node[rows], size[rows] == d, rows[new], parent[new]
        used += int(new.sum())
        rows = rows[size[rows] > d]
        d += 1


class Suffixes:
    """A vocabulary by its tokens' characters from the last to the first, to look up all tokens that end at a place for many places at once."""

    def __init__(self, ids: dict[str, int]) -> None:
        tokens = sorted((t[::-1], i) for t, i in ids.items() if 0 < len(t) <= TRIE_CHARS)
        points, at = points_of([t for t, _ in tokens])
        number = np.array([i for _, i in tokens], np.int32)
        keys, token = [np.zeros(0, np.int64)], [np.array([-1], np.int32)]
        for d, (rows, node, stops, firsts, parent) in enumerate(_levels(points, at), 1):
            keys.append((parent << 21) + points[at[firsts] + d - 1])
            found = np.full(len(firsts), -1, np.int32)
            found[node[stops] - node[0]] = number[rows[stops]]
            token.append(found)
        self.keys, self.token = np.concatenate(keys), np.concatenate([*token, [np.int32(-1)]])

    def step(self, state: np.ndarray, c: np.ndarray) -> np.ndarray:
        """The state after one more character, -1 where no token goes on so."""
        wanted = (state << 21) + c
        k = np.searchsorted(self.keys, wanted)
        if not len(self.keys):
            return np.full(len(state), -1)
        return np.where(self.keys[np.minimum(k, len(self.keys) - 1)] == wanted, k + 1, -1)


class Trie:
    """The lattices of many chunks as one: a place in a chunk is the prefix that ends there, so chunks that begin alike share places and edges. Places are numbered by depth from the root, 0, and
    within a depth in the order of the text. Edges stand twice, by the place where they end and by the one where they start; every place but the root has an edge of one character, its first."""

    def __init__(self, end: np.ndarray, level: np.ndarray, first: np.ndarray, start: np.ndarray, tok: np.ndarray, out: np.ndarray, child: np.ndarray, tok_out: np.ndarray) -> None:
        """end: place of each chunk; level: first place of each depth, and their number; first: of each place, its first edge among those by end, and the number of edges; start and tok of these edges.
        out, child and tok_out: the same of edges by start."""
        self.end, self.level, self.first, self.start, self.tok, self.out, self.child, self.tok_out = end, level, first, start, tok, out, child, tok_out
        n = np.diff(out)
        self.inner = [a + np.flatnonzero(n[a:b]) for a, b in zip(level[:-1], level[1:], strict=True)]

    @classmethod
    def of(cls, chunks: list[str], suffixes: Suffixes) -> Trie:
        """Of chunks of 1 to TRIE_CHARS characters."""
        order = sorted(range(len(chunks)), key=chunks.__getitem__)
        points, at = points_of([chunks[k] for k in order])
        end, up, level = np.zeros(len(chunks), np.int32), [np.zeros(1, np.int32)], [0, 1]
        starts, tokens, degree = [], [], [np.zeros(1, np.int64)]
        for d, (rows, node, stops, firsts, parent) in enumerate(_levels(points, at), 1):
            end[rows[stops]] = node[stops]
            up.append(parent.astype(np.int32))
            which, state, back = np.arange(len(firsts)), np.zeros(len(firsts), np.int64), up[d]
            own, far, tok = [], [], []
            for l in range(1, d + 1):
                state = suffixes.step(state, points[at[firsts[which]] + d - l])
                t = suffixes.token[state]  # state -1 is one past all, without a token
                if l == 1:
                    t = np.where(t < 0, -2, t)
                has, alive = t != -1, state >= 0
                own.append(which[has])
                far.append(back[has])
                tok.append(t[has])
                if l == d or not alive.any():
                    break
                which, state, back = which[alive], state[alive], up[d - l][back[alive] - level[d - l]]
            own = np.concatenate(own)
            by = np.argsort(own, kind="stable")
            starts.append(np.concatenate(far)[by])
            tokens.append(np.concatenate(tok)[by])
            degree.append(np.bincount(own, minlength=len(firsts)))
            level.append(level[-1] + len(firsts))
        back = np.empty(len(chunks), np.int32)
        back[order] = end
        join = lambda parts: np.concatenate([np.zeros(0, np.int32), *parts])
        n, start, tok = np.concatenate(degree), join(starts), join(tokens)
        by = np.argsort(start, kind="stable")
        out = np.cumsum(np.bincount(start, minlength=len(n)))
        return cls(back, np.array(level), np.concatenate([[0], np.cumsum(n)]), start, tok, np.concatenate([[0], out]), np.repeat(np.arange(len(n), dtype=np.int32), n)[by], tok[by])

    def to_bytes(self) -> bytes:
        parts = [x.astype(np.int32, copy=False) for x in (self.end, self.level, self.first, self.start, self.tok, self.out, self.child, self.tok_out)]
        return b"".join(x.tobytes() for x in (np.array([len(x) for x in parts], np.int32), *parts))

    @classmethod
    def from_bytes(cls, raw: bytes) -> Trie:
        whole = np.frombuffer(raw, np.int32)
        return cls(*np.split(whole[8:], np.cumsum(whole[:7])))

    def tensors(self, which: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(chunks, their lattices as tensors() has them), by length."""
        depth = np.searchsorted(self.level, self.end[which], "right") - 1
        for size in np.unique(depth):
            rows = which[depth == size]
            tok, at = np.full((len(rows), size, size), -1, np.int32), self.end[rows]
            for e in range(size, 0, -1):
                k, n = self.first[at], np.diff(self.first)[at]
                for j in range(n.max()):
                    some = np.flatnonzero(j < n)
                    s = np.searchsorted(self.level, self.start[k[some] + j], "right") - 1
                    tok[some, s, e - s - 1] = self.tok[k[some] + j]
                at = self.start[k]
            yield rows, tok

    def expected_counts(self, weight: np.ndarray, logp: np.ndarray) -> tuple[np.ndarray, float]:
        """As the function of this name. The probability of all ways to a place is summed once for all chunks through it; weights go back the same way."""
        p = np.exp(logp)
        f, by_end = np.empty(self.level[-1]), p[self.tok]
        f[0] = 1.0
        for a, b in zip(self.level[1:-1], self.level[2:], strict=True):
            i, j = self.first[a], self.first[b]
            f[a:b] = np.add.reduceat(f[self.start[i:j]] * by_end[i:j], self.first[a:b] - i)
        whole = f[self.end]
        low = whole < SMALL
        total = np.where(low, 1.0, whole)
        back = np.bincount(self.end, np.where(low, 0.0, weight) / total, len(f))
        onward = p[self.tok_out]
        for a, b, inner in zip(self.level[-2::-1], self.level[:0:-1], self.inner[::-1], strict=True):
            if len(inner):
                i, j = self.out[a], self.out[b]
                onward[i:j] *= back[self.child[i:j]]
                back[inner] += np.add.reduceat(onward[i:j], self.out[inner] - i)
        onward *= np.repeat(f, np.diff(self.out))
        found = np.bincount(self.tok_out + 2, onward, len(logp))
        counts = np.concatenate([found[2:], found[:2]])
        counts[-1] = 0.0
        loglik = float(np.log(total) @ weight)
        for rows, tok in self.tensors(np.flatnonzero(low)):
            more, ll = _by_logs(tok, weight[rows], logp, False)
            counts, loglik = counts + more, loglik + ll
        return counts, loglik

def _by_logs(tok: np.ndarray, weight: np.ndarray, logp: np.ndarray, hard: bool) -> tuple[np.ndarray, float]:
    n, size, m = tok.shape
    join = np.maximum if hard else np.logaddexp
    f = [np.zeros(n)]
    for e in range(1, size + 1):
        now = np.full(n, -np.inf)
        for l in range(1, min(m, e) + 1):
            now = join(now, f[e - l] + logp[tok[:, e - l, l - 1]])
        f.append(now)
    counts = np.zeros(len(logp))
    if hard:
        at = np.full(n, size)
        while (at > 0).any():
            moved = np.zeros(n, bool)
            for l in range(m, 0, -1):
                s = at - l
                ok = (~moved) & (s >= 0) & (at > 0)
                rows = np.flatnonzero(ok)
                t = tok[rows, s[rows], l - 1]
                F_ = np.stack(f, 1)
                hit = F_[rows, s[rows]] + logp[t] >= F_[rows, at[rows]] - 1e-12
                rows, t = rows[hit], t[hit]
                np.add.at(counts, t, weight[rows])
                at[rows] -= l
                moved[rows] = True
        return counts, float((f[size] * weight).sum())
    b = [np.zeros(n) for _ in range(size + 1)]
    for s in range(size - 1, -1, -1):
        now = np.full(n, -np.inf)
        for l in range(1, min(m, size - s) + 1):
            now = np.logaddexp(now, b[s + l] + logp[tok[:, s, l - 1]])
        b[s] = now
    for s in range(size):
        for l in range(1, min(m, size - s) + 1):
            t = tok[:, s, l - 1]
            p = np.exp(f[s] + logp[t] + b[s + l] - f[size])
            np.add.at(counts, t, np.where(t == -1, 0.0, p * weight))
    return counts, float((f[size] * weight).sum())


def segment_one(chunk: str, ids: dict[str, int], longest: int, fx: np.ndarray) -> tuple[list[str], int]:
    """Tokens of the best split and its score under one label; among equals the one whose last token starts first."""
    size = len(chunk)
    best, back = [0] + [NEVER] * size, [0] * (size + 1)
    for s, e, t in edges_of(chunk, ids, longest, -2):
        x = best[s] + int(fx[t])
        if x > best[e]:
            best[e], back[e] = x, s
    out, at = [], size
    while at:
        out.append(chunk[back[at] : at])
        at = back[at]
    return out[::-1], best[size]
