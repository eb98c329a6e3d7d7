"""Language-model scoring with a log-frequency Bloom filter.

Counting: every task hashes the words of its training texts to 64 bits, counts single words and adjacent pairs, and sends packed arrays to the part of the hash range
that they belong to, so the shuffle carries a few large rows and no key is hot. A part adds up its counts, quantises each to a level
1 + floor(log2 count), and enters (n-gram, 1), ..., (n-gram, level) into its blocks of a blocked Bloom filter. Bits and parts are in proportion to the bytes of
training text, at every size.

Scoring: level 1, 2, ... of an n-gram is asked for until one is missing, or the largest that its part holds; the level gives back the count within a factor
of two. A word's probability mixes the pair's relative frequency with the word's smoothed one. Texts are scored in chunks of CHUNK tokens. The pairs' filter is broadcast
to the workers if it has at most MAX_BYTES, a size that is known before it is built. A larger one stays where its parts are: a chunk sends its distinct pairs to
the parts, they probe in place and send one byte for each back. Both ways give the same scores, and one shuffle is all either needs, whatever the size of the
corpus. Words always go the second way: their exact counts, which the base score needs, come back with their levels. An n-gram is sent once for each chunk, so none
is hot. Distinct words are told apart by 64-bit hashes, pairs of a part by KEPT_BITS.

Defined cases: a null text is empty and scores its end alone; a null id counts as the empty string in the split; repeated rows are scored each; if nothing is
in training all counts are 0; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..io import read_table, spread, stash
from .common import hashed_words, mixed, whole

BLOCK_BITS = 1 << 16
PROBES = 3
PAIR_BITS, WORD_BITS = 1.0, 0.25  # per byte of training text
#: Training text of a part of the hash range.
PART_BYTES = 4_000_000
#: The pairs' filter is broadcast up to this size; each worker holds a copy.
MAX_BYTES = 128 << 20
MIX = 0.4
#: Arbitrary constants that stand for the start and the end of a text.
START, END = np.uint64(0x5BF03635F0A31E05), np.uint64(0xC2B2AE3D27D4EB4F)
#: Tokens that a task counts, or scores, at a time.
FLUSH, CHUNK = 2_000_000, 600_000
#: Bits of a pair's hash that are kept behind those that name its part.
KEPT_BITS = 32
#: Bytes of text that are cut into words at a time.
PIECE = 1 << 20
#: Kinds of rows: a part's word counts, its bits for words and pairs; words and pairs that a chunk asks for; a chunk's texts.
COUNTS, WORDS, PAIRS, ASK_WORDS, ASK_PAIRS, TEXTS = range(6)


def pair_hash(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return mixed(first * np.uint64(0x9E3779B97F4A7C15) + second)


def slice_of(h: np.ndarray, n: int) -> np.ndarray:
    """Which of n equal parts of the hash range."""
    return (((h >> np.uint64(32)) * np.uint64(n)) >> np.uint64(32)).astype(np.int64)


def bit_places(h: np.ndarray, level: int) -> list[np.ndarray]:
    g = mixed(h + np.uint64(level * 0xD1342543DE82EF95 % 2**64))
    return [((g >> np.uint64(16 * i)) & np.uint64(BLOCK_BITS - 1)).astype(np.int64) for i in range(PROBES)]


def levels_of(c: np.ndarray) -> np.ndarray:
    return np.floor(np.log2(c)).astype(np.int64) + 1


def count_of(level: np.ndarray) -> np.ndarray:
    """The middle of the counts that share a level; 0 for level 0."""
    return np.where(level > 0, (np.exp2(level - 1.0) + np.exp2(level * 1.0) - 1) / 2, 0.0)


def summed(h: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(h, kind="stable")
    h, c = h[order], c[order]
    first = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]])) if len(h) else np.empty(0, np.int64)
    return h[first], np.add.reduceat(c, first) if len(h) else c


def pack(h: np.ndarray, c: np.ndarray, part_bits: int | None = None) -> bytes:
    """Hashes in order of count; counts as (count, how many). With part_bits the part is known to the reader and KEPT_BITS more are enough."""
    order = np.argsort(c, kind="stable")
    kinds, n = np.unique(c, return_counts=True)
    head = np.array([len(kinds)], np.uint64).tobytes() + kinds.astype(np.uint64).tobytes() + n.astype(np.uint64).tobytes()
    return head + (h[order].tobytes() if part_bits is None else short(h[order], part_bits))


def unpack(data: bytes, part: int = 0, part_bits: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    k = int(np.frombuffer(data, np.uint64, 1)[0])
    x = np.frombuffer(data, np.uint64, 2 * k, 8)
    rest = data[8 + 16 * k :]
    return np.frombuffer(rest, np.uint64) if part_bits is None else long(rest, part, part_bits), np.repeat(x[:k], x[k:].astype(np.int64)).astype(np.int64)


def clipped(h: np.ndarray, part_bits: int) -> np.ndarray:
    """The leading part_bits + KEPT_BITS of hashes. A part stands for a bounded stretch of text, so how often two of its pairs agree in them, about one in 5,000, does not grow with
    the corpus and is small beside the filter's own error."""
    drop = np.uint64(64 - part_bits - KEPT_BITS)
    return h >> drop << drop


def short(h: np.ndarray, part_bits: int) -> bytes:
    """What a reader who knows the part lacks of clipped hashes."""
    return (h << np.uint64(part_bits) >> np.uint64(64 - KEPT_BITS)).astype(np.uint32).tobytes()


def long(data: bytes, part: int, part_bits: int) -> np.ndarray:
    x = np.frombuffer(data, np.uint32).astype(np.uint64)
    return x << np.uint64(64 - KEPT_BITS) >> np.uint64(part_bits) | np.uint64(part << (64 - part_bits))


def planes(x: np.ndarray, width: int = 4) -> bytes:
    """Numbers below 256 ** width byte by byte, compressed."""
    return pa.compress(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes(), codec="zstd", asbytes=True)


def from_planes(data: bytes, n: int, width: int = 4) -> np.ndarray:
    out = np.zeros((n, 8), np.uint8)
    out[:, :width] = np.frombuffer(pa.decompress(data, decompressed_size=width * n, codec="zstd", asbytes=True), np.uint8).reshape(width, n).T
    return out.view("<i8").ravel()


class Filter:
    """A run of blocks of a blocked log-frequency Bloom filter."""

    def __init__(self, bits: np.ndarray, blocks: int, first: int = 0, top: int = 64) -> None:
        """bits: blocks first, first + 1, ... of `blocks`; top: the largest level that was entered."""
        self.bits, self.blocks, self.first, self.top = bits, blocks, first, top

    def levels(self, h: np.ndarray) -> np.ndarray:
        """Largest level such that it and all below are present. Sorted input touches the blocks in order."""
        out = np.zeros(len(h), np.uint8)
        live = np.arange(len(h))
        base = (slice_of(h, self.blocks) - self.first) * BLOCK_BITS
        for level in range(1, self.top + 1):
            hit = np.ones(len(live), bool)
            for p in bit_places(h[live], level):
                at = base[live] + p
                hit &= (self.bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
            live = live[hit]
            if not len(live):
                break
            out[live] = level
        return out


def fill(h: np.ndarray, c: np.ndarray, blocks: int, first_block: int, own: int) -> np.ndarray:
    """Bits of blocks first_block .. first_block + own - 1, one row per block."""
    flags = np.zeros(own * BLOCK_BITS, np.uint8)
    q, base = levels_of(c), (slice_of(h, blocks) - first_block) * BLOCK_BITS
    for level in range(1, int(q.max(initial=0)) + 1):
        on = q >= level
        h, q, base = h[on], q[on], base[on]
        for p in bit_places(h, level):
            flags[base + p] = 1
    return np.packbits(flags, bitorder="little").reshape(own, BLOCK_BITS // 8)


def _held_out(id_col: str):
    return F.crc32(F.encode(F.coalesce(F.col(id_col).cast("string"), F.lit("")), "UTF-8")) % 7 == 2


def tokens_of(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts, each with its end, and the number of tokens of each."""
    raw = [t.encode("utf-8", "replace") + b"\n" for t in texts]
    bounds = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
    h, starts = hashed_words(np.frombuffer(b"".join(raw), np.uint8))
    doc = np.searchsorted(bounds, starts, "right") - 1
    sizes = np.bincount(doc, minlength=len(raw)) + 1
    out = np.full(len(h) + len(raw), END, np.uint64)
    out[np.arange(len(h)) + doc] = h
    return out, sizes


def token_runs(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[tuple[pa.Table, np.ndarray, np.ndarray]]:
    """(rows without the text, tokens, sizes) of consecutive rows with about `most` tokens; the text is the last column."""
    held: list[tuple[pa.RecordBatch, np.ndarray, np.ndarray]] = []
    n = 0

    def flushed() -> tuple[pa.Table, np.ndarray, np.ndarray]:
        return pa.Table.from_batches([h[0] for h in held]), np.concatenate([h[1] for h in held]), np.concatenate([h[2] for h in held])

    for b in batches:
        size = np.cumsum(np.fromiter((x.as_buffer().size for x in b.column(b.num_columns - 1)), np.int64, b.num_rows)) // PIECE
        cuts = [0, *(np.flatnonzero(np.diff(size)) + 1), b.num_rows]
        for lo, hi in zip(cuts, cuts[1:], strict=False):
            if lo == hi:
                continue
            part = b.slice(lo, hi - lo)
            tokens, sizes = tokens_of(part.column(b.num_columns - 1).to_pylist())
            held.append((part.select(b.schema.names[:-1]), tokens, sizes))
            n += len(tokens)
            if n >= most:
                yield flushed()
                held, n = [], 0
    if held:
        yield flushed()


def before(tokens: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    prev = np.empty_like(tokens)
    prev[1:] = tokens[:-1]
    prev[np.concatenate([[0], np.cumsum(sizes)[:-1]])] = START
    return prev


def by_part(h: np.ndarray, parts: int) -> Iterator[tuple[int, slice]]:
    """The runs of sorted hashes that belong to each part."""
    if len(h):
        where = slice_of(h, parts)
        cut = np.concatenate([[0], np.flatnonzero(np.diff(where)) + 1, [len(h)]])
        for lo, hi in zip(cut, cut[1:], strict=False):
            yield int(where[lo]), slice(lo, hi)


@dataclass
class Model:
    """What counting leaves: a stashed table of parts (kind, part, top, data), its totals and the layout of the filters."""

    table: DataFrame
    total: int
    distinct: int
    texts: int
    parts: int
    word_own: int  # blocks of a part
    pair_own: int

    def filter_bytes(self) -> int:
        return self.parts * self.pair_own * BLOCK_BITS // 8

    def pairs(self) -> tuple[bytes, int]:
        """The pairs' filter put together, and its largest level; parts without a pair are empty blocks."""
        size = self.pair_own * BLOCK_BITS // 8
        out, top = bytearray(size * self.parts), 0
        for r in self.table.where(F.col("kind") == PAIRS).select("part", "top", "data").toLocalIterator():
            out[r["part"] * size : (r["part"] + 1) * size] = r["data"]
            top = max(top, r["top"])
        return bytes(out), top


def _row(kind: int, part: int, top: int, data: bytes) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([part], pa.int32()), pa.array([top], pa.int32()), pa.array([data], pa.binary())], names=["kind", "part", "top", "data"])


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", part_bytes: int = PART_BYTES) -> Model:
    train = docs.where(~_held_out(id_col)).select(whole(text_col).alias("_text"))
    size, texts = train.agg(F.sum(F.octet_length("_text") + 1), F.count(F.lit(1))).first()
    size = size or 1
    parts = 8
    while parts * part_bytes < size:
        parts *= 2
    word_own, pair_own = (max(1, int(size * bits / BLOCK_BITS / parts)) for bits in (WORD_BITS, PAIR_BITS))
    tasks, part_bits = max(train.sparkSession.sparkContext.defaultParallelism, parts // 4), parts.bit_length() - 1

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, tokens, sizes in token_runs(batches, FLUSH):
            for kind, h in ((COUNTS, tokens), (PAIRS, clipped(pair_hash(before(tokens, sizes), tokens), part_bits))):
                u, c = np.unique(h, return_counts=True)
                where, data = [], []
                for p, s in by_part(u, parts):
                    where.append(p)
                    data.append(pack(u[s], c[s], part_bits if kind == PAIRS else None))
                yield pa.RecordBatch.from_arrays([pa.array([kind] * len(where), pa.int32()), pa.array(where, pa.int32()), pa.array(data, pa.binary())], names=["kind", "part", "data"])

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come in order of part and kind, so one part of one kind is held at a time."""
        at, held = None, []

        def built() -> Iterator[pa.RecordBatch]:
            kind, part = at
            got = [unpack(x, part, part_bits if kind == PAIRS else None) for x in held]
            h, c = summed(np.concatenate([x[0] for x in got]), np.concatenate([x[1] for x in got]))
            top, own = int(levels_of(c).max(initial=0)), word_own if kind == COUNTS else pair_own
            bits = fill(h, c, own * parts, part * own, own).tobytes()
            if kind == COUNTS:
                yield _row(COUNTS, part, top, pack(h, c))
                yield _row(WORDS, part, top, bits)
            else:
                yield _row(PAIRS, part, top, bits)

        for b in batches:
            for kind, part, data in zip(b.column("kind").to_pylist(), b.column("part").to_pylist(), b.column("data"), strict=True):
                if at is not None and at != (kind, part):
                    yield from built()
                    held = []
                at = kind, part
                held.append(data.as_py())
        if held:
            yield from built()

    counted = spread(train).mapInArrow(count, "kind int, part int, data binary")
    ordered = counted.repartition(tasks, "part").sortWithinPartitions("part", "kind")
    table = stash(ordered.mapInArrow(build, "kind int, part int, top int, data binary"), "filters")

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            counts = [unpack(x.as_py())[1] for x in b.column("data")]
            yield pa.RecordBatch.from_arrays([pa.array([int(x.sum()) for x in counts], pa.int64()), pa.array([len(x) for x in counts], pa.int64())], names=["c", "n"])

    total, distinct = table.where(F.col("kind") == COUNTS).select("data").mapInArrow(sums, "c long, n long").agg(F.sum("c"), F.sum("n")).first()
    return Model(table, total or 0, distinct or 0, texts, parts, word_own, pair_own)


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", mix: float = MIX, max_bytes: int = MAX_BYTES, chunk: int = CHUNK) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score)."""
    spark = docs.sparkSession
    total, distinct, n_texts, parts, word_own, pair_own = model.total, model.distinct, model.texts, model.parts, model.word_own, model.pair_own
    part_bits = parts.bit_length() - 1
    near = model.filter_bytes() <= max_bytes
    sent = spark.sparkContext.broadcast(model.pairs()) if near else None
    df = spread(docs.select(F.col(id_col).alias("doc_id"), _held_out(id_col).alias("held_out"), whole(text_col).alias("_text")))
    ids = df.schema["doc_id"].dataType
    texts_schema = T.StructType([T.StructField("ids", T.ArrayType(ids)), *T._parse_datatype_string("held array<boolean>, sizes array<int>").fields])
    schema = T.StructType([*T._parse_datatype_string("chunk long, kind int, part int, top int, data binary, more binary").fields, *texts_schema.fields])
    names = schema.names

    def rows(chunk_id: int, kind: int, part: list[int], data: list[bytes], more: list[bytes | None] | None = None, rest: pa.Table | None = None, sizes: np.ndarray | None = None, kinds: list | None = None) -> pa.RecordBatch:
        n = len(part)
        if rest is None:
            lists = [pa.nulls(n, k) for k in kinds]
        else:
            one = lambda c: pa.ListArray.from_arrays(pa.array([0, rest.num_rows], pa.int32()), c.combine_chunks() if not isinstance(c.combine_chunks(), pa.ChunkedArray) else c.combine_chunks().chunk(0))
            lists = [one(rest.column(0)), one(rest.column(1)), pa.ListArray.from_arrays(pa.array([0, len(sizes)], pa.int32()), pa.array(sizes.astype(np.int32)))]
        return pa.RecordBatch.from_arrays([pa.array([chunk_id] * n, pa.int64()), pa.array([kind] * n, pa.int32()), pa.array(part, pa.int32()), pa.nulls(n, pa.int32()), pa.array(data, pa.binary()), pa.array(more or [None] * n, pa.binary()), *lists], names=names)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A chunk's texts as places in its sorted distinct words (and pairs, or the pairs' levels); and what it asks of each part."""
        at = TaskContext.get().partitionId() << 32
        pairs = Filter(np.frombuffer(sent.value[0], np.uint8), parts * pair_own, 0, sent.value[1]) if near else None
        for rest, tokens, sizes in token_runs(batches, chunk):
            u, back = np.unique(tokens, return_inverse=True)
            pu, pback = np.unique(clipped(pair_hash(before(tokens, sizes), tokens), part_bits), return_inverse=True)
            kinds = [pa.list_(rest.schema.field(0).type), pa.list_(pa.bool_()), pa.list_(pa.int32())]
            yield rows(at, TEXTS, [(at >> 32) * 31 + (at & 0xFFFF)], [planes(back)], [planes(pairs.levels(pu)[pback] if near else pback)], rest, sizes)
            for kind, h in ((ASK_WORDS, u), (ASK_PAIRS, pu)):
                if kind == ASK_WORDS or not near:
                    found = list(by_part(h, parts))
                    yield rows(at, kind, [p for p, _ in found], [h[s].tobytes() if kind == ASK_WORDS else short(h[s], part_bits) for _, s in found], kinds=kinds)
            at += 1

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come in order of part, what the part holds before what is asked of it. A part that holds nothing answers zeros; texts pass. top becomes the number of
        answers in a row."""
        part, have = None, {}
        kinds = None
        for b in batches:
            kinds = kinds or [b.schema.field(c).type for c in ("ids", "held", "sizes")]
            out: dict[str, list] = {x: [] for x in names[:6]}
            passed = []
            for k, (c, kind, p, top, data) in enumerate(zip(*(b.column(x).to_pylist() for x in names[:4]), b.column("data"), strict=True)):
                if kind == TEXTS:
                    passed.append(k)
                    continue
                if p != part:
                    part, have = p, {}
                raw = data.as_py()
                if kind == COUNTS:
                    have[kind] = unpack(raw)
                    order = np.argsort(have[kind][0])
                    have[kind] = tuple(x[order] for x in have[kind])
                elif kind in (WORDS, PAIRS):
                    own = word_own if kind == WORDS else pair_own
                    have[kind] = Filter(np.frombuffer(raw, np.uint8), parts * own, p * own, top)
                else:
                    h = np.frombuffer(raw, np.uint64) if kind == ASK_WORDS else long(raw, p, part_bits)
                    which = WORDS if kind == ASK_WORDS else PAIRS
                    level = have[which].levels(h) if which in have else np.zeros(len(h), np.uint8)
                    counts = np.zeros(len(h), np.int64)
                    if kind == ASK_WORDS and COUNTS in have:
                        known, n = have[COUNTS]
                        place = np.minimum(np.searchsorted(known, h), len(known) - 1)
                        counts = np.where(known[place] == h, n[place], 0)
                    for x, v in zip(out.values(), (c, kind, p, len(h), planes(level, 1), planes(counts, 8) if kind == ASK_WORDS else None), strict=True):
                        x.append(v)
            if passed:
                yield b.take(pa.array(passed))
            n = len(out["chunk"])
            yield pa.RecordBatch.from_arrays([*[pa.array(out[x], t) for x, t in zip(names[:6], (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], *[pa.nulls(n, t) for t in kinds]], names=names)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come in order of chunk: answers in order of kind and part, then the texts."""
        got: dict[int, list[np.ndarray]] = {}
        for b in batches:
            for k, (kind, data, more) in enumerate(zip(b.column("kind").to_pylist(), b.column("data"), b.column("more"), strict=True)):
                if kind != TEXTS:
                    n = b.column("top")[k].as_py()
                    got.setdefault(kind, []).append(from_planes(data.as_py(), n, 1))
                    if kind == ASK_WORDS:
                        got.setdefault(COUNTS, []).append(from_planes(more.as_py(), n, 8))
                    continue
                level = np.concatenate(got[ASK_WORDS])
                exact = np.concatenate(got[COUNTS])
                sizes = np.array(b.column("sizes")[k].as_py(), np.int64)
                back, c2 = (from_planes(x.as_py(), int(sizes.sum())) for x in (data, more))
                if not near:
                    c2 = np.concatenate(got[ASK_PAIRS])[c2]
                got = {}
                doc = np.repeat(np.arange(len(sizes)), sizes)
                c1, c2 = count_of(level)[back], count_of(c2)
                seen = np.empty(len(back))
                seen[1:] = c1[:-1]
                seen[np.concatenate([[0], np.cumsum(sizes)[:-1]])] = n_texts
                weight = np.where(seen > 0, mix, 0.0)
                p = (1 - weight) * (c1 + 1) / (total + distinct + 1.0) + weight * c2 / np.maximum(np.maximum(seen, c2), 1)
                base = (np.log10(exact + 1.0) - np.log10(total + distinct + 1.0))[back]
                known = np.bincount(doc, (exact > 0)[back], minlength=len(sizes)).astype(np.int64)
                add = lambda x: pa.array(np.bincount(doc, x, minlength=len(sizes)))  # noqa: B023, E731
                n = pa.array(sizes, pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [b.column("ids")[k].values, b.column("held")[k].values, n, pa.array(known), pa.array(np.full(len(sizes), total), pa.int64()), add(base), add(np.log10(p))],
                    names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
                )

    tasks = max(spark.sparkContext.defaultParallelism, parts // 4)
    held = model.table.where(F.col("kind").isin([COUNTS, WORDS] if near else [COUNTS, WORDS, PAIRS])).withColumn("chunk", F.lit(-1).cast("long"))
    at_parts = df.mapInArrow(ask, schema).unionByName(held, allowMissingColumns=True).repartition(tasks, "part").sortWithinPartitions("part", "kind")
    both = at_parts.mapInArrow(answer, schema).repartition(tasks, "chunk").sortWithinPartitions("chunk", "kind", "part")
    out = T.StructType([T.StructField("doc_id", ids), *T._parse_datatype_string("held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double").fields])
    return both.mapInArrow(finish, out)


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text"])
    return score(docs, fit(docs))
