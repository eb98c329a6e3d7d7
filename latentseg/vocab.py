"""Vocabularies: seeded from substrings, learned by pruning, merged pairwise, or loaded."""

from __future__ import annotations

import base64
import itertools
import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import em, lattice
from .cluster import lean
from .io import spread, stash
from .text import hash8


def substrings(chunks: DataFrame, max_len: int, min_len: int = 1) -> DataFrame:
    """(token, c): weighted occurrences of every substring of the distinct chunks; summed before it is shuffled."""
    u = chunks.groupBy("chunk").agg(F.sum("n").alias("n"))
    spans = u.select("chunk", "n", F.explode(F.expr("sequence(1, length(chunk))")).alias("s"))
    spans = spans.select("chunk", "n", "s", F.explode(F.expr(f"sequence({min_len}, greatest({min_len}, least({max_len}, length(chunk) - s + 1)))")).alias("l")).where("s + l - 1 <= length(chunk)")
    return spans.select(F.expr("substring(chunk, s, l)").alias("token"), "n").groupBy("token").agg(F.sum("n").alias("c"))


def number(tokens: DataFrame) -> DataFrame:
    """Dense ids in the order of tokens. A vocabulary is bounded (lattice.MOST_TOKENS), so one window is fine."""
    t = tokens.select("token").distinct().withColumn("token_len", F.length("token")).withColumn("is_base", F.col("token_len") == 1)
    return t.withColumn("token_id", (F.row_number().over(Window.orderBy("token")) - 1).cast("int")).select("token_id", "token", "token_len", "is_base")


def base_topk(chunks: DataFrame, k: int = 500, min_len: int = 2, max_len: int = 4) -> DataFrame:
    """All characters and the k most frequent substrings of min_len to max_len characters; ties by token."""
    chars = substrings(chunks, 1).select("token")
    top = substrings(chunks, max_len, min_len).orderBy(F.desc("c"), "token").limit(k).select("token")
    return number(chars.unionByName(top))


def seed(chunks: DataFrame, size: int, max_len: int = 16, min_count: int = 2) -> DataFrame:
    """The oversized start: characters and the substrings of the largest count times length."""
    s = substrings(chunks, max_len)
    chars = s.where("length(token) = 1").select("token")
    top = s.where(f"length(token) > 1 and c >= {min_count}").orderBy(F.desc(F.col("c") * F.length("token")), "token").limit(size).select("token")
    return number(chars.unionByName(top))


#: Largest tokenizer file that is parsed, on the driver.
MOST_BYTES = 256 << 20


def load(spark: SparkSession, path: str, fmt: str = "text", base: DataFrame | None = None, unit: str = "codepoint") -> DataFrame:
    """A borrowed vocabulary. fmt: text or csv (a token a line), tsv (token and anything behind a tab), json (lines with a field token), tokenizer (a tokenizer's JSON: a model with a
    map or a list of tokens), or ranks (base64 tokens with ranks). With unit byte, tokens of the last two are bytes, one character each. Characters of `base` (token) that it lacks are added,
    so that every text has a split; coverage() says how many there were."""
    if fmt in ("tokenizer", "ranks"):
        size = spark.read.format("binaryFile").load(path).select("length").first()[0]
        if size > MOST_BYTES:
            raise ValueError(f"{path} has {size} bytes; {MOST_BYTES} are read")
        raw = bytes(spark.read.format("binaryFile").load(path).select("content").first()[0])
        tokens = _of_tokenizer(raw, unit) if fmt == "tokenizer" else _of_ranks(raw, unit)
        t = spark.createDataFrame([(x,) for x in tokens], "token string").where("token <> ''")
    elif fmt == "json":
        t = spark.read.json(path).select("token").where("token is not null and token <> ''")
    else:
        t = spark.read.text(path).select((F.split("value", "\t")[0] if fmt == "tsv" else F.col("value")).alias("token")).where("token <> ''")
    return number(t.unionByName(base.select("token")) if base is not None else t)


def byte_letters() -> dict[str, int]:
    """The printable stand-ins of bytes in byte-level tokenizers: printable Latin-1 characters stand for themselves, the others for 256, 257, ..."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


def _of_tokenizer(raw: bytes, unit: str) -> list[str]:
    model = json.loads(raw)["model"]
    tokens = list(model["vocab"]) if isinstance(model["vocab"], dict) else [x[0] for x in model["vocab"]]
    letters = byte_letters()
    if not all(c in letters for t in tokens[:1000] for c in t):  # not byte-level: tokens are text, with a mark for a space
        plain = [t.replace("\u2581", " ") for t in tokens]
        return [t.encode().decode("latin-1") for t in plain] if unit == "byte" else plain
    return _texts([bytes(letters[c] for c in t) for t in tokens if all(c in letters for c in t)], unit)


def _of_ranks(raw: bytes, unit: str) -> list[str]:
    return _texts([base64.b64decode(x.split()[0]) for x in raw.splitlines() if x], unit)


def _texts(tokens: list[bytes], unit: str) -> list[str]:
    """Tokens as characters: one a byte, or as the text they spell, without those that are parts of a character."""
    if unit == "byte":
        return [t.decode("latin-1") for t in tokens]
    out = []
    for t in tokens:
        try:
            out.append(t.decode())
        except UnicodeDecodeError:
            continue
    return out


def byte_alphabet(spark: SparkSession) -> DataFrame:
    """(token): the 256 characters that stand for bytes."""
    return spark.createDataFrame([(chr(b),) for b in range(256)], "token string")


def coverage(chunks: DataFrame, vocab: DataFrame) -> DataFrame:
    """One row: characters, and how many of them are tokens."""
    c = substrings(chunks, 1).join(vocab.select("token", F.lit(1).alias("known")), "token", "left")
    return c.agg(F.sum("c").alias("characters"), F.coalesce(F.sum(F.when(F.col("known") == 1, F.col("c"))), F.lit(0)).alias("covered"))


def sample_per_label(df: DataFrame, n: int = 1000, label_col: str = "label", text_col: str = "text") -> DataFrame:
    """n rows a label by the order of text digests, so the sample does not depend on the layout."""
    w = Window.partitionBy(label_col).orderBy("_h", text_col)
    return df.withColumn("_h", hash8(F.col(text_col))).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= n).drop("_h", "_r")


def prune_loss(chunks: DataFrame, vocab: DataFrame, mode: str = "resplit", rounds: int = 2) -> DataFrame:
    """(token_id, token, loss): what the corpus log-likelihood falls by, at the present estimate, if a token goes. exact takes the sum over all splits of every chunk that has the token, with and without
    it; resplit takes the token's expected count times the gap between its log-probability and that of its best other split. Characters are not listed: they stay. A token
    that nothing else spells has an infinite loss."""
    pooled = stash(chunks.groupBy("chunk").agg(F.sum("n").alias("n")).select(F.lit("all").alias("label"), "chunk", "n"), "pooled")
    fitted = em.fit(pooled, vocab, rounds=rounds)
    ids = lattice.collect_vocab(vocab)
    longest = max(map(len, ids))
    logp = np.full(len(ids) + 2, -np.inf)
    counts = np.zeros(len(ids))
    for r in fitted.theta.where("c > 0").select("token_id", "logp", "c").collect():  # a vocabulary's worth of rows
        logp[r[0]], counts[r[0]] = r[1], r[2]
    sent = chunks.sparkSession.sparkContext.broadcast((ids, logp, counts))

    def resplit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, value, c = sent.value
        for b in batches:
            tokens = b.column("token").to_pylist()
            gap = np.zeros(len(tokens))
            for rows, tok in lattice.tensors(tokens, table, longest):
                own = np.array([table[tokens[k]] for k in rows])
                gap[rows] = _resplit(tok, own, value, c)
            yield pa.RecordBatch.from_arrays([b.column("token_id"), b.column("token"), pa.array(gap)], names=["token_id", "token", "loss"])

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, value, _ = sent.value
        for b in batches:
            loss: dict[int, float] = {}
            texts, weight = b.column("chunk").to_pylist(), b.column("n").to_numpy()
            for rows, tok in lattice.tensors(texts, table, longest):
                whole = lattice.marginal(tok, value[:, None])[:, 0]
                for t in np.unique(tok[tok >= 0]):
                    has = (tok == t).any(axis=(1, 2))
                    part = tok[has]
                    less = lattice.marginal(np.where(part == t, -1, part), value[:, None])[:, 0]
                    loss[int(t)] = loss.get(int(t), 0.0) + float(((whole[has] - less) * weight[rows[has]]).sum())
            yield pa.RecordBatch.from_arrays([pa.array(list(loss), pa.int32()), pa.array(list(loss.values()), pa.float64())], names=["token_id", "loss"])

    long = vocab.where("not is_base")
    if mode == "resplit":
        return spread(long.select("token_id", "token")).mapInArrow(resplit, "token_id int, token string, loss double")
    part = spread(pooled.select("chunk", F.col("n").cast("double").alias("n"))).mapInArrow(exact, "token_id int, loss double")
    return long.select("token_id", "token").join(part.groupBy("token_id").agg(F.sum("loss").alias("loss")), "token_id", "left").na.fill({"loss": 0.0})


def _resplit(tok: np.ndarray, own: np.ndarray, value: np.ndarray, c: np.ndarray) -> np.ndarray:
    """For tokens `own` with these lattices: the expected count times the gap to the best other split."""
    tok = tok.copy()
    tok[:, 0, tok.shape[1] - 1] = -1
    other = _best(tok, value)
    with np.errstate(invalid="ignore"):
        return np.where(c[own] > 0, c[own] * (value[own] - other), 0.0)


def _best(tok: np.ndarray, value: np.ndarray) -> np.ndarray:
    """Log-probability of the best split of each lattice; minus infinity where there is none."""
    n, size, m = tok.shape
    best = [np.zeros(n)]
    for e in range(1, size + 1):
        now = np.full(n, -np.inf)
        for l in range(1, min(m, e) + 1):
            t = tok[:, e - l, l - 1]
            now = np.maximum(now, np.where(t >= 0, best[e - l] + value[np.maximum(t, 0)], -np.inf))
        best.append(now)
    return best[size]


#: Distinct chunks, their characters and tokens up to which a vocabulary is learned within one task.
TASK_ROWS, TASK_CHARS, TASK_TOKENS = 200_000, 2_000_000, 100_000


def pruned(chunks: list[str], n: np.ndarray, tokens: list[str], size: int, keep: float, rounds: int) -> list[str]:
    """What learn() keeps of `tokens`, by the same steps: rounds of expectation-maximisation, losses by the best other split, and the tokens of the largest losses."""
    while True:
        long = [t for t in tokens if len(t) != 1]
        base = len(tokens) - len(long)
        if len(tokens) <= size or not long:
            return tokens
        want = max(size, min(len(tokens) - 1, int(len(tokens) * keep)), base)
        ids = {t: k for k, t in enumerate(sorted(tokens))}
        logp, c = em.rounds_of(chunks, n, ids, rounds)
        value, loss = np.where(c > 0, np.maximum(logp[: len(ids)], np.log(0.5 / c.sum())), -np.inf), np.zeros(len(long))
        for rows, tok in lattice.tensors(long, ids, max(map(len, ids))):
            loss[rows] = _resplit(tok, np.array([ids[long[k]] for k in rows]), np.append(value, [-np.inf, -np.inf]), c)
        order = sorted(range(len(long)), key=lambda k: (-loss[k], long[k]))[: want - base]
        tokens = [t for t in tokens if len(t) == 1] + [long[k] for k in order]


def learn(chunks: DataFrame, size: int = 100_000, max_len: int = 16, keep: float = 0.75, em_rounds: int = 2, seed_factor: int = 4, start: DataFrame | None = None) -> DataFrame:
    """Alternates fitting and pruning from the seed, or from a vocabulary to start with, down to `size` tokens; characters always stay. If the distinct chunks and the tokens fit one task, all of it runs there."""
    pooled = stash(chunks.groupBy("chunk").agg(F.sum("n").alias("n")).select("chunk", F.col("n").cast("double").alias("n")), "pooled")
    vocab = start if start is not None else stash(seed(pooled, size * seed_factor, max_len), "vocab")
    rows, chars = pooled.agg(F.count(F.lit(1)), F.sum(F.length("chunk"))).first()
    if rows <= TASK_ROWS and (chars or 0) <= TASK_CHARS and vocab.count() <= TASK_TOKENS:
        sent = chunks.sparkSession.sparkContext.broadcast(sorted(lattice.collect_vocab(vocab)))

        def run(pdf: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"token": pruned(pdf["chunk"].tolist(), pdf["n"].to_numpy(float), sent.value, size, keep, em_rounds)})

        return stash(number(pooled.groupBy(F.lit("all").alias("k")).applyInPandas(run, "token string")), "vocab") if rows else vocab
    while True:
        n, base = vocab.agg(F.count(F.lit(1)), F.count_if("is_base")).first()
        if n <= size or n == base:
            return vocab
        want = max(size, min(n - 1, int(n * keep)), base)
        loss = prune_loss(chunks, vocab, "resplit", em_rounds)
        ranked = vocab.join(loss.select("token_id", "loss"), "token_id", "left").orderBy(F.desc("is_base"), F.desc(F.coalesce("loss", F.lit(-1.0))), "token").limit(want)
        vocab = stash(number(ranked), "vocab")


#: Characters of distinct chunks up to which merges are made within one task; beyond, characters that are merged at a time, and those from which merges are proposed.
MERGE_CHARS, MERGE_PART, MERGE_HEAD = 10_000_000, 2_000_000, 1_000_000
Pair = tuple[str, str]


def merged(chunks: list[str], n: np.ndarray, n_merges: int, forced: list[Pair] | None = None, exact: tuple[int, dict[Pair, int]] | None = None, noted: list[dict[Pair, int]] | None = None) -> list[Pair]:
    """The merges of learn_merges(), one by one. Symbols are linked both ways and every pair knows where it stood when it was made, so a merge touches its own places alone. forced: merges to begin with, whatever
    is most frequent. exact: after so many merges pairs have these counts. noted gets the counts of pairs, then what each merge adds to them."""
    forced = forced or []
    points, at = lattice.points_of(chunks)
    letters, first = np.unique(points, return_inverse=True)
    names = [chr(x) for x in letters]
    known = {x: k for k, x in enumerate(names)}
    del letters
    most = len(names) + n_merges
    size = len(points)
    sym = np.append(first.astype(np.int32), np.int32(-1))  # the last place stands for none
    del points, first
    word = np.repeat(np.arange(len(chunks), dtype=np.int32), np.diff(at))
    after, before = np.arange(1, size + 2, dtype=np.int32), np.arange(-1, size, dtype=np.int32)
    after[at[1:][np.diff(at) > 0] - 1] = size
    before[at[:-1][np.diff(at) > 0]] = size
    after[size] = before[size] = size
    n = n.astype(np.int64)
    counts: dict[int, int] = {}
    changes: list[dict[int, int]] = [{}]
    places: dict[int, list[np.ndarray]] = {}

    def add(where: np.ndarray, sign: int) -> None:
        where = where[(sym[where] >= 0) & (sym[after[where]] >= 0)]
        if not len(where):
            return
        key = sym[where].astype(np.int64) * most + sym[after[where]]
        order = np.argsort(key, kind="stable")
        key, where = key[order], where[order]
        cut = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        total = np.add.reduceat(n[word[where]], cut)
        for k, c, group in zip(key[cut].tolist(), total.tolist(), np.split(where, cut[1:]) if sign > 0 else [None] * len(cut), strict=True):
            counts[k] = counts.get(k, 0) + sign * c
            if noted is not None:
                changes[-1][k] = changes[-1].get(k, 0) + sign * c
            if sign > 0:
                places.setdefault(k, []).append(group)

    add(np.arange(size, dtype=np.int32), 1)
    merges: list[Pair] = []
    while len(merges) < n_merges:
        if exact is not None and len(merges) == exact[0]:
            counts = {known[x] * most + known[y]: c for (x, y), c in exact[1].items() if x in known and y in known}
        if len(merges) < len(forced):
            changes.append({})
            a, b = (known.get(x) for x in forced[len(merges)])
            if a is None or b is None:
                merges.append(forced[len(merges)])
                continue
        else:
            top = max(counts.values(), default=0)
            if top <= 1:
                break
            a, b = min((divmod(k, most) for k, c in counts.items() if c == top), key=lambda x: (names[x[0]], names[x[1]]))
        at_a = np.unique(np.concatenate([np.zeros(0, np.int32), *places.pop(a * most + b, [])]))
        at_a = at_a[(sym[at_a] == a) & (sym[after[at_a]] == b)]
        if a == b:  # of a run every second one, from the left
            run = np.flatnonzero(np.append(True, after[at_a[:-1]] != at_a[1:]))
            at_a = at_a[(np.arange(len(at_a)) - np.repeat(run, np.diff(np.append(run, len(at_a))))) % 2 == 0]
        at_b = after[at_a]
        add(np.unique(np.concatenate([before[at_a], at_a, at_b])), -1)
        counts = {k: c for k, c in counts.items() if c > 0 and k != a * most + b}
        merges.append((names[a], names[b]))
        z = known.setdefault(names[a] + names[b], len(names))
        if z == len(names):
            names.append(names[a] + names[b])
        beyond = after[at_b]
        sym[at_a], sym[at_b] = z, -1
        after[at_a] = beyond
        before[beyond] = at_a
        before[size] = size
        add(np.unique(np.concatenate([before[at_a], at_a])), 1)
    if noted is not None:
        noted += [{(names[k // most], names[k % most]): c for k, c in step.items() if c} for step in changes]
    return merges


def learn_merges(chunks: DataFrame, n_merges: int = 100) -> tuple[DataFrame, list[Pair]]:
    """A merge-list vocabulary: the most frequent adjacent pair is joined in all distinct chunks, ties by name, again and again. If the distinct chunks fit one task, all merges are made there (merged); else they are
    proposed from some of the chunks and checked on all (_proposed). Returns the vocabulary and the merges in order."""
    pooled = stash(chunks.groupBy("chunk").agg(F.sum("n").alias("n")), "words")
    spark = chunks.sparkSession
    chars = pooled.agg(F.sum(F.length("chunk"))).first()[0] or 0
    merges = _one_task(pooled, n_merges) if chars <= MERGE_CHARS else _proposed(pooled, chars, n_merges)
    symbols = pooled.select(F.explode(F.regexp_extract_all("chunk", F.lit("(?s)."), 0)).alias("token")).distinct()
    made = spark.createDataFrame([(a + b,) for a, b in merges], "token string") if merges else symbols.limit(0)
    return number(symbols.unionByName(made)), merges


def _one_task(words: DataFrame, n_merges: int, forced: list[Pair] | None = None, exact: tuple[int, dict[Pair, int]] | None = None) -> list[Pair]:
    sent = words.sparkSession.sparkContext.broadcast((forced, exact))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        made = merged(pdf["chunk"].tolist(), pdf["n"].to_numpy(), n_merges, *sent.value)
        return pd.DataFrame({"k": range(len(made)), "a": [a for a, _ in made], "b": [b for _, b in made]})

    got = words.groupBy(F.lit("all").alias("all")).applyInPandas(run, "k int, a string, b string").collect()
    return [(r["a"], r["b"]) for r in sorted(got, key=lambda r: r["k"])]


def _head(words: DataFrame, chars: int) -> DataFrame:
    """The frequent chunks, and of the others every so many-th with as many times its weight: about MERGE_HEAD characters, from which merges are only proposed."""
    sizes = {r[0]: r[1] for r in words.groupBy(F.floor(F.log2("n")).alias("k")).agg(F.sum(F.length("chunk"))).collect()}  # a row for each power of two
    least, held = max(sizes) + 1, 0
    for k in sorted(sizes, reverse=True):
        if held + sizes[k] > MERGE_HEAD // 2:
            break
        least, held = k, held + sizes[k]
    step = -(-(chars - held) // max(1, MERGE_HEAD // 2))
    often = F.floor(F.log2("n")) >= least
    return stash(words.where(often | (F.pmod(F.xxhash64("chunk"), F.lit(max(1, step))) == 0)).select("chunk", F.when(often, F.col("n")).otherwise(F.col("n") * step).alias("n")), "head")


def _proposed(pooled: DataFrame, chars: int, n_merges: int) -> list[Pair]:
    """The merges of chunks that don't fit one task. All that are missing are proposed from a head of the chunks; then tasks make them in parts of all chunks and say how the counts of pairs change with each. Their
    sums tell where a proposal is not the most frequent pair: merges before it stand, that pair follows, and the next proposals start from the counts there. The driver holds pairs of symbols."""
    spark = pooled.sparkSession
    words = stash(pooled.repartition(max(spark.sparkContext.defaultParallelism, -(-chars // MERGE_PART)), F.xxhash64("chunk")), "words")
    head = _head(words, chars)
    sure: list[Pair] = []  # the most frequent pairs, one after another
    exact = None
    while len(sure) < n_merges:
        proposal = _one_task(head, n_merges, sure, exact)
        sent = spark.sparkContext.broadcast(proposal)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            chunks, n, held = [], [], 0
            for batch in itertools.chain(batches, [None]):
                if batch is not None:
                    chunks += batch.column("chunk").to_pylist()
                    n.append(batch.column("n").to_numpy())
                    held += pa.compute.sum(pa.compute.utf8_length(batch.column("chunk"))).as_py() or 0
                if chunks and (batch is None or held > MERGE_PART):
                    noted: list[dict[Pair, int]] = []
                    merged(chunks, np.concatenate(n), len(sent.value), sent.value, noted=noted)
                    rows = [(k, a, b, c) for k, step in enumerate(noted) for (a, b), c in step.items()]
                    yield pa.RecordBatch.from_arrays([pa.array(x, of) for x, of in zip(zip(*rows, strict=True) if rows else [[]] * 4, (pa.int32(), pa.string(), pa.string(), pa.int64()), strict=True)], names=["step", "a", "b", "c"])
                    chunks, n, held = [], [], 0

        changes: list[list[tuple[Pair, int]]] = [[] for _ in range(len(proposal) + 1)]
        got = words.mapInArrow(lean(run), "step int, a string, b string, c long").groupBy("step", "a", "b").agg(F.sum("c").alias("c")).toArrow()
        for k, a, b, c in zip(*(got.column(x).to_pylist() for x in ("step", "a", "b", "c")), strict=True):
            changes[k].append(((a, b), c))
        counts: dict[Pair, int] = {}
        for k, step in enumerate(changes):
            for pair, c in step:
                counts[pair] = counts.get(pair, 0) + c
            counts = {pair: c for pair, c in counts.items() if c > 0}
            top = max(counts.values(), default=0)
            if k == n_merges or top <= 1:
                return proposal[:k]
            best = min(pair for pair, c in counts.items() if c == top)
            if k == len(proposal) or best != proposal[k]:
                sure, exact = [*proposal[:k], best], (k, counts)
                break
    return sure


def pair_counts(words: DataFrame) -> DataFrame:
    """(a, b, c): adjacent symbols with their weighted counts."""
    p = words.where("size(syms) > 1").select("n", F.explode(F.expr("transform(sequence(1, size(syms) - 1), i -> struct(element_at(syms, i) as a, element_at(syms, i + 1) as b))")).alias("p"))
    return p.groupBy("p.a", "p.b").agg(F.sum("n").alias("c"))
