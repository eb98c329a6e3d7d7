"""BPE encoding and decoding by speculation and verification.

The text is cut into words by the tokenizer's own pattern. For a word, greedy longest-match over the vocabulary proposes tokens. A proposal is the true
encoding exactly if every two adjacent tokens, put together, would be encoded as these two; so all adjacent pairs of all new words of a batch
are checked at once by array operations that undo merges along the seam of a pair. Words with a pair that fails are merged exactly, by a queue over ranks.
Words are remembered per worker, up to a bound; a memory that is full is emptied, which costs time only.

Defined cases: a null or empty text has no tokens; special tokens in a text are matched as the tokenizers library does; texts of any
length are encoded whole; repeated rows are encoded alike; an empty table gives an empty result; other columns pass through, except
those named like an added column, which are replaced.
"""

from __future__ import annotations

import hashlib
import heapq
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..io import read_table, spread
from .common import named, whole

MEMORY = 500_000
#: White space by Unicode, the word pattern of byte-level tokenizers, the printable stand-ins of bytes.
WHITE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
WORD = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{WHITE}\p{{L}}\p{{N}}]+|[{WHITE}]+(?![^{WHITE}])|[{WHITE}]+"
PRINTABLE = [*range(33, 127), *range(161, 173), *range(174, 256)]

_codecs: dict[str, Codec] = {}


def byte_letters() -> dict[str, int]:
    rest = [b for b in range(256) if b not in PRINTABLE]
    return {chr(b): b for b in PRINTABLE} | {chr(256 + k): b for k, b in enumerate(rest)}


class Codec:
    """Encoder and decoder for a byte-level merge tokenizer given as the JSON of the tokenizers library."""

    def __init__(self, data: bytes) -> None:
        spec = json.loads(data)
        letters = byte_letters()
        self.bytes_of = {i: bytes(letters[c] for c in s) for s, i in spec["model"]["vocab"].items()}
        self.ids = {b: i for i, b in self.bytes_of.items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special_bytes = {i: s.encode() for s, i in self.special.items()}
        names = sorted(self.special, key=len, reverse=True)
        self.cut_special = regex.compile("(" + "|".join(map(regex.escape, names)) + ")") if names else None
        size = max(self.bytes_of) + 1
        # a token is made by one merge: left part, right part, rank; single bytes have none
        self.left, self.right, self.rank = np.full(size, -1), np.full(size, -1), np.full(size, -1)
        pairs, merged = [], []
        self.merge: dict[tuple[int, int], tuple[int, int]] = {}
        for r, m in enumerate(spec["model"]["merges"]):
            a, b = m if isinstance(m, list) else m.split(" ")
            x, y = (spec["model"]["vocab"][p] for p in (a, b))
            z = spec["model"]["vocab"][a + b]
            self.merge[x, y] = (r, z)
            pairs.append((x << 32) | y)
            merged.append(r)
            if self.rank[z] < 0:
                self.left[z], self.right[z], self.rank[z] = x, y, r
        order = np.argsort(pairs)
        self.pair_keys, self.pair_ranks = np.array(pairs, dtype=np.int64)[order], np.array(merged, dtype=np.int64)[order]
        self.made = np.zeros(len(merged), dtype=np.int64)
        for (_, _), (r, z) in self.merge.items():
            self.made[r] = z
        self.byte_ids = np.array([self.ids[bytes([b])] for b in range(256)], dtype=np.int64)
        self.byte_ranks = self.rank_of(np.repeat(self.byte_ids, 256), np.tile(self.byte_ids, 256)).reshape(256, 256)
        self.words = regex.compile(WORD)
        self.plain = regex.compile(rf"[{WHITE}] | [{WHITE}]")  # a blank beside white space: words then depend on what surrounds them
        self.known: dict[str, str] = {}  # unit -> ids joined by commas
        self.raw: dict[str, bytes] = {}  # unit -> bytes that these ids stand for
        self.reach: dict[bytes, int] = {}  # first two bytes -> longest token that begins so
        for b in self.ids:
            self.reach[b[:2]] = max(self.reach.get(b[:2], 0), len(b))
        self.good: dict[int, bool] = {}
        self.stats = {"words": 0, "failed": 0}

    # --- proposal, check, exact merging
    def propose(self, word: bytes) -> list[int]:
        ids, reach, out, at, end = self.ids, self.reach, [], 0, len(word)
        if (i := ids.get(word)) is not None:
            return [i]
        while at < end:
            stop = min(end, at + reach.get(word[at : at + 2], 1))
            while (i := ids.get(word[at:stop])) is None:
                stop -= 1
            out.append(i)
            at = stop
        return out

    def rank_of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of merging a and b, or a huge number."""
        keys = (a << 32) | b
        at = np.minimum(np.searchsorted(self.pair_keys, keys), len(self.pair_keys) - 1)
        return np.where(self.pair_keys[at] == keys, self.pair_ranks[at], np.iinfo(np.int64).max)

    def compatible(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """For each pair of tokens: does their joint text encode to just these two? Merges of both are undone in falling rank. At each
        state the two tokens at the seam must not have been joined before the merge that was undone last: on the left a merge of
        equal rank goes first, on the right the seam does, since merging runs from left to right."""
        ok, live = np.ones(len(a), dtype=bool), np.arange(len(a))
        a, b = a.astype(np.int64), b.astype(np.int64)
        limit = np.full(len(a), np.iinfo(np.int64).max - 1)
        while len(live):
            clash = self.rank_of(a, b) < limit
            ok[live[clash]] = False
            ra, rb = self.rank[a], self.rank[b]
            keep = ~clash & ((ra >= 0) | (rb >= 0))
            live, a, b, ra, rb = live[keep], a[keep], b[keep], ra[keep], rb[keep]
            undo_a = ra > rb
            limit = np.where(undo_a, ra, rb + 1)
            a, b = np.where(undo_a, self.right[a], a), np.where(undo_a, b, self.left[b])
        return ok

    def exact(self, word: bytes) -> list[int]:
        """Merges by rank, then from left to right, in n log n."""
        ids = [self.ids[word[k : k + 1]] for k in range(len(word))]
        after, before = [*range(1, len(ids) + 1)], [*range(-1, len(ids) - 1)]
        heap = [(*m, k, ids[k], ids[k + 1]) for k in range(len(ids) - 1) if (m := self.merge.get((ids[k], ids[k + 1])))]
        heap = [(r, k, z, x, y) for r, z, k, x, y in heap]
        heapq.heapify(heap)
        gone = -1
        while heap:
            _, k, z, x, y = heapq.heappop(heap)
            if ids[k] != x or (n := after[k]) >= len(ids) or ids[n] != y:
                continue
            ids[k], ids[n] = z, gone
            after[k] = after[n]
            if after[k] < len(ids):
                before[after[k]] = k
                if m := self.merge.get((z, ids[after[k]])):
                    heapq.heappush(heap, (m[0], k, m[1], z, ids[after[k]]))
            if (p := before[k]) >= 0 and (m := self.merge.get((ids[p], z))):
                heapq.heappush(heap, (m[0], p, m[1], ids[p], z))
        return [i for i in ids if i != gone]

    def exact_many(self, words: list[bytes]) -> list[list[int]]:
        """exact() for many words at once: words of like length form a matrix, and each round merges the first lowest-ranked pair of every row."""
        out: list[list[int]] = [[]] * len(words)
        sizes = np.array([len(w) for w in words])
        none = np.iinfo(np.int64).max
        low = 0
        for high in (8, 12, 16, 24, 40):
            own = np.flatnonzero((sizes > low) & (sizes <= high))
            low = high
            if not len(own):
                continue
            raw = np.frombuffer(b"".join([words[k].ljust(high, b"\0") for k in own]), dtype=np.uint8).reshape(len(own), high)
            ids, n = self.byte_ids[raw], sizes[own]
            ranks = self.byte_ranks[raw[:, :-1], raw[:, 1:]]
            cols = np.arange(high)
            ranks[cols[None, 1:] >= n[:, None]] = none
            rows = np.arange(len(own))
            while len(rows):
                at = ranks.argmin(axis=1)
                best = ranks[np.arange(len(rows)), at]
                done = best == none
                if done.any():
                    for k in np.flatnonzero(done):
                        out[own[rows[k]]] = ids[k, : n[k]].tolist()
                    live = ~done
                    rows, ids, ranks, n, at, best = rows[live], ids[live], ranks[live], n[live], at[live], best[live]
                    if not len(rows):
                        break
                i = np.arange(len(rows))
                ids[i, at] = self.made[best]
                ids = np.take_along_axis(ids, np.minimum(cols[None, :] + (cols[None, :] > at[:, None]), high - 1), axis=1)
                c = cols[:-1]
                ranks = np.take_along_axis(ranks, np.minimum(c[None, :] + (c[None, :] > at[:, None]), high - 2), axis=1)
                ranks[:, -1] = none
                n = n - 1
                has = at + 1 < n
                ranks[i[has], at[has]] = self.rank_of(ids[i[has], at[has]], ids[i[has], at[has] + 1])
                ranks[i[~has], np.minimum(at[~has], high - 2)] = none
                has = at > 0
                ranks[i[has], at[has] - 1] = self.rank_of(ids[i[has], at[has] - 1], ids[i[has], at[has]])
        for k in np.flatnonzero(sizes > low):
            out[k] = self.exact(words[k])
        return out

    def learn(self, words: list[str]) -> None:
        """Put the encodings of new words into memory."""
        raw = [w.encode("utf-8", "replace") for w in words]
        said = [self.propose(w) for w in raw]
        flat = np.fromiter((i for s in said for i in s), dtype=np.int64)
        ends = np.cumsum([len(s) for s in said])
        bad: set[int] = set()
        if len(flat) > 1:
            inside = np.ones(len(flat) - 1, dtype=bool)
            inside[ends[:-1][ends[:-1] < len(flat)] - 1] = False
            seams = np.flatnonzero(inside)
            pairs, back = np.unique((flat[seams] << 32) | flat[seams + 1], return_inverse=True)
            fails = ~self.compatible(pairs >> 32, pairs & 0xFFFFFFFF)[back]
            bad = set(np.searchsorted(ends, seams[fails], side="right").tolist())
        self.stats["words"] += len(words)
        self.stats["failed"] += len(bad)
        failing = sorted(bad)
        for k, ids in zip(failing, self.exact_many([raw[k] for k in failing]), strict=True):
            said[k] = ids
        for k, w in enumerate(words):
            ids = said[k]
            self.known[w] = ",".join(map(str, ids))
            self.raw[w] = b"".join([self.bytes_of[i] for i in ids])

    # --- texts
    def split(self, text: str) -> list[str]:
        """Units of encoding, none of which influences another. Where no blank stands beside other white space, blanks end words, and what lies
        between two blanks is one unit (which may hold several words); else the words themselves."""
        if self.plain.search(text):
            return self.words.findall(text)
        head, *tail = text.split(" ")
        return ([head] if head else []) + [f" {x}" for x in tail]

    def units(self, units: list[str]) -> None:
        """Encode units that are not in memory: cut them into words, learn those, and join."""
        new = {u: self.words.findall(u) for u in units}
        words = {w for ws in new.values() for w in ws if w not in self.known}
        self.learn(list(words))
        for u, ws in new.items():
            if len(ws) != 1:
                self.known[u] = ",".join([self.known[w] for w in ws])
                self.raw[u] = b"".join([self.raw[w] for w in ws])

    def encode_batch(self, texts: list[str]) -> Iterator[tuple[str, int, bytes]]:
        """For each text: ids joined by commas, their number, and the bytes that the ids stand for."""
        cut = []
        for t in texts:
            if self.cut_special is None or not any(s in t for s in self.special):
                cut.append([(self.split(t), None)])
            else:
                cut.append([(self.split(x), None) if x not in self.special else ([], x) for x in self.cut_special.split(t) if x])
        if len(self.known) > MEMORY:
            self.known.clear()
            self.raw.clear()
        self.units(list({u for parts in cut for us, _ in parts for u in us if u not in self.known}))
        for parts in cut:
            said, raw = [], []
            for us, special in parts:
                if special is None:
                    said.extend(map(self.known.__getitem__, us))
                    raw.extend(map(self.raw.__getitem__, us))
                else:
                    said.append(str(self.special[special]))
                    raw.append(special.encode())
            joined = ",".join(said)
            yield joined, joined.count(",") + 1 if joined else 0, b"".join(raw)

    def encode(self, text: str) -> list[int]:
        said = next(self.encode_batch([text]))[0]
        return [int(x) for x in said.split(",")] if said else []

    def decode(self, ids: list[int]) -> str:
        return b"".join([self.special_bytes.get(i) or self.bytes_of[i] for i in ids]).decode("utf-8", "replace")


def codec(digest: str, data: bytes) -> Codec:
    if digest not in _codecs:
        _codecs[digest] = Codec(data)
    return _codecs[digest]


def _sent(spark: SparkSession, path: str):
    with open(path, "rb") as f:
        data = f.read()
    if len(data) > 64 << 20:
        raise ValueError("the tokenizer file is over 64 MB")
    return hashlib.sha256(data).hexdigest(), spark.sparkContext.broadcast(data)


def encode(docs: DataFrame, path: str, text_col: str = "text", ids: bool = True, digests: bool = False) -> DataFrame:
    """Adds n_tokens and, as asked, token_ids (array<int>) or ids_sha256 and decoded_sha256; the text is dropped. No shuffle."""
    digest, sent = _sent(docs.sparkSession, path)
    added = ["n_tokens", *["token_ids"] * ids, *["ids_sha256", "decoded_sha256"] * digests]
    names = [c for c in docs.columns if c.lower() not in {*added, text_col.lower()}]
    df = spread(docs.select(whole(text_col).alias("t"), F.struct(*([named(c) for c in names] or [F.lit(0).alias("none")])).alias("row")))
    kinds = {"n_tokens": T.LongType(), "token_ids": T.ArrayType(T.IntegerType()), "ids_sha256": T.StringType(), "decoded_sha256": T.StringType()}
    arrow = {"n_tokens": pa.int64(), "token_ids": pa.list_(pa.int32()), "ids_sha256": pa.string(), "decoded_sha256": pa.string()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(digest, sent.value)
        for whole_batch in batches:
            for at in range(0, whole_batch.num_rows, 256):
                b = whole_batch.slice(at, 256)
                out: dict[str, list] = {a: [] for a in added}
                for said, n, raw in c.encode_batch(b.column(0).to_pylist()):
                    out["n_tokens"].append(n)
                    if ids:
                        out["token_ids"].append(np.fromstring(said, dtype=np.int32, sep=",") if said else np.empty(0, np.int32))
                    if digests:
                        out["ids_sha256"].append(hashlib.sha256(said.encode()).hexdigest())
                        out["decoded_sha256"].append(hashlib.sha256(raw.decode("utf-8", "replace").encode()).hexdigest())
                yield pa.RecordBatch.from_arrays([b.column(1), *[pa.array(out[a], arrow[a]) for a in added]], names=["row", *added])

    schema = T.StructType([df.schema["row"], *[T.StructField(a, kinds[a]) for a in added]])
    return df.mapInArrow(run, schema).select(*[F.col("row")[c].alias(c) for c in names], *added)


def decode(encoded: DataFrame, path: str, ids_col: str = "token_ids", out_col: str = "text") -> DataFrame:
    """Replaces token ids by the text they stand for; a null array gives null."""
    digest, sent = _sent(encoded.sparkSession, path)
    rest = [c for c in encoded.columns if c.lower() not in (ids_col.lower(), out_col.lower())]
    df = encoded.select(named(ids_col).alias("i"), F.struct(*([named(c) for c in rest] or [F.lit(0).alias("none")])).alias("row"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(digest, sent.value)
        for b in batches:
            texts = pa.array([None if i is None else c.decode(i) for i in b.column(0).to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([b.column(1), texts], names=["row", "out"])

    out = df.mapInArrow(run, T.StructType([df.schema["row"], T.StructField("out", T.StringType())]))
    return out.select(*[F.col("row")[c].alias(c) for c in rest], F.col("out").alias(out_col))


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text"])
    return encode(docs, public_tokenizers.path("byte_bpe_50k.json"), ids=False, digests=True)
