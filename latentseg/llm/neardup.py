"""Near-duplicates by MinHash with tensored banding.

A text's set is its distinct five-word shingles, hashed to 64 bits. Two small collections of hash groups are computed: `left` groups of
k1 minhashes and `right` groups of k2. A table key is a pair (i, j) of one group from each side, so left * right tables of
k1 + k2 minhashes a key need only left * k1 + right * k2 minhashes. A pair of texts that meets in any table is a candidate.

Equal texts are first folded into one, known by its digest. A text that meets nobody in the left or nobody in the right groups cannot meet anybody in a
table, so it drops out before the tables are formed. In every table bucket the members are held against the bucket's first, and
verified candidates are linked. Then components are taken; where a bucket holds several, members of the others are held against one of the largest, in a few
rounds; and texts of buckets that are still mixed are paired where the rarest of their shingles meet, an exact condition for the similarity: pairs inside a
component could not change it, all others that can be similar enough are tested. So no link that joins components is lost, and a bucket of alike texts is not expanded into
all its pairs. Verification compares whole shingle sets.

Defined cases: a null, empty or all-space text has an empty set, is linked with nothing and kept; fewer than five words form one shingle; every row goes by its own
text, so rows of equal id may have different components; a null id takes part but names no component unless all ids in it are null; an empty table gives an empty result; other
columns, whatever they are called, are not read. drop_near_duplicates() leaves one row of each component: that of the smallest id, null ids last, then of the smallest text digest; of rows
that agree in id and text one stays, by the digest of its other columns. Rows with an empty set all stay.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..cluster import lean, slices
from ..io import join_frequent, join_small, join_spread, read_table, spread, stash
from .common import hashed_words, named, whole

WIDTH = 5
SEED = 20_240_601
LEFT, RIGHT, K1, K2 = 10, 10, 2, 2
#: Candidate documents whose ids may be broadcast to fetch their texts: 8 bytes each.
BROADCAST_IDS = 2_000_000
#: Rows (id, digest) that go or repeat, up to which they are broadcast: some 100 bytes each.
KEYS = 500_000
#: Rounds in which members of mixed buckets meet one of the bucket's largest component before all that is left is paired.
HEAD_ROUNDS = 1
#: Shingles of the sets that a worker remembers while it verifies pairs, 8 bytes each; texts count by their characters in eights.
REMEMBERED = 2_000_000
#: Most shingles whose frequency is broadcast: 16 bytes each, twice that as a dictionary entry.
FREQUENT = 1_000_000


def shingles(text: str, width: int = WIDTH) -> np.ndarray:
    """Distinct hashed shingles of the whole text, sorted; fewer words than `width` make one."""
    h, _ = hashed_words(np.frombuffer(text.encode("utf-8", "replace"), np.uint8))
    if not len(h):
        return h
    many = min(len(h), width)
    out = np.full(len(h) - many + 1, 0 if many == width else many, np.uint64)
    for k in range(many):
        out = out * np.uint64(0x9E3779B97F4A7C15) + h[k : len(h) - many + 1 + k]
        out ^= out >> np.uint64(29)
    return np.unique(out)


def collections(n: int, k: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    a = rng.integers(1, 2**63, size=n * k, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    b = rng.integers(0, 2**63, size=n * k, dtype=np.uint64)
    return a, b


def minhashes(sets: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """One minimum per hash function, by multiplying and mixing the high half down."""
    out = np.empty(len(a), np.uint64)
    for k in range(len(a)):
        x = sets * a[k] + b[k]
        x ^= x >> np.uint64(32)
        out[k] = (x * np.uint64(0xD6E8FEB86659FD93)).min()
    return out


def fold(mins: np.ndarray, k: int) -> list[int]:
    """Group keys: k minima each, combined into one signed 64-bit number."""
    out = np.zeros(len(mins) // k, np.uint64)
    for j in range(k):
        out = (out ^ mins[j::k]) * np.uint64(0x9FB21C651E98DF25)
        out ^= out >> np.uint64(35)
    return out.view(np.int64).tolist()


def _digest(text_col: str):
    return F.unhex(F.md5(whole(text_col)))


def signatures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", left: int = LEFT, right: int = RIGHT, k1: int = K1, k2: int = K2, seed: int = SEED) -> DataFrame:
    """(doc_id, v, n_shingles, lefts, rights) per row; v is the digest of the text, null where the set is empty."""
    rng = np.random.default_rng(seed)
    (la, lb), (ra, rb) = collections(left, k1, rng), collections(right, k2, rng)
    df = spread(docs.select(F.col(id_col).cast("long").alias("doc_id"), _digest(text_col).alias("v"), whole(text_col).alias("_text")))
    schema = "doc_id long, v binary, n_shingles long, lefts array<long>, rights array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            vs, ns, lefts, rights = [], [], [], []
            for t, v in zip(b.column("_text").to_pylist(), b.column("v").to_pylist(), strict=True):
                s = shingles(t)
                ns.append(len(s))
                vs.append(v if len(s) else None)
                lefts.append(fold(minhashes(s, la, lb), k1) if len(s) else None)
                rights.append(fold(minhashes(s, ra, rb), k2) if len(s) else None)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(vs, pa.binary()), pa.array(ns, pa.int64()), pa.array(lefts, pa.list_(pa.int64())), pa.array(rights, pa.list_(pa.int64()))], names=["doc_id", "v", "n_shingles", "lefts", "rights"])

    return df.mapInArrow(lean(run), schema)


def _meeting(texts: DataFrame, col: str) -> DataFrame:
    """Texts that share at least one group of a collection with another text."""
    rows = texts.select("v", F.posexplode(col).alias("i", "key"))
    shared = rows.groupBy("i", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("i", "key")
    return rows.join(shared, ["i", "key"], "left_semi").select("v").distinct()


def table_rows(texts: DataFrame) -> DataFrame:
    """(key, v, n) for buckets with two texts or more."""
    both = _meeting(texts, "lefts").join(_meeting(texts, "rights"), "v", "left_semi")
    alive = stash(texts.join(both, "v", "left_semi"), "alive")
    pairs = alive.select("v", "n_shingles", "rights", F.posexplode("lefts").alias("i", "l")).select("v", "n_shingles", "i", "l", F.posexplode("rights").alias("j", "r"))
    rows = pairs.select(F.xxhash64("i", "j", "l", "r").alias("key"), "v", F.col("n_shingles").alias("n"))
    shared = rows.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("key")
    return stash(rows.join(shared, "key", "left_semi"), "tables")


def _candidates(rows: DataFrame, percent: int) -> DataFrame:
    """(a, b) once, ordered, where the sizes n_a and n_b alone allow the similarity."""
    fits = 100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b")
    return rows.where(fits).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def texts_of(docs: DataFrame, wanted: DataFrame, text_col: str) -> DataFrame:
    """(v, text) of the texts that candidates name: their digests are broadcast if few, else joined by a shuffle."""
    few = wanted.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    source = docs.select(_digest(text_col).alias("v"), whole(text_col).alias("text"))
    return source.join(F.broadcast(wanted) if few else wanted, "v", "left_semi").groupBy("v").agg(F.first("text").alias("text"))


class Sets:
    """The shingles of texts, with a memory of those seen lately that is bounded by their size, not by their number."""

    def __init__(self, most: int = REMEMBERED) -> None:
        self.known: dict[str, np.ndarray] = {}
        self.most, self.held = most, 0

    def __getitem__(self, text: str) -> np.ndarray:
        if (s := self.known.get(text)) is None:
            s = shingles(text)
            size = max(len(s), len(text) // 8)
            if self.held + size > self.most:
                self.known, self.held = {}, 0
            if size <= self.most:
                self.known[text] = s
                self.held += size
        return s


def verify(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose whole sets are similar enough. Each side's text is joined in; a side with many partners is split by the join."""
    with_b = pairs.join(texts.select(F.col("v").alias("b"), F.col("text").alias("text_b")), "b")
    both = with_b.join(texts.select(F.col("v").alias("a"), F.col("text").alias("text_a")), "a").select("a", "b", "text_a", "text_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Sets()
        for batch in slices(batches):
            keep = []
            for ta, tb in zip(batch.column("text_a").to_pylist(), batch.column("text_b").to_pylist(), strict=True):
                sets, other = known[ta], known[tb]
                common = len(np.intersect1d(sets, other, assume_unique=True))
                keep.append(common > 0 and 100 * common >= percent * (len(sets) + len(other) - common))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.mapInArrow(lean(run), "a binary, b binary")


def components(edges: DataFrame) -> DataFrame:
    """(v, comp) for every vertex of edges (a, b): the smallest vertex that can be reached. Each round every vertex takes the smallest label
    among its neighbours' and then the label of that label, so chains halve; rounds end when no label changes."""
    both = stash(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = stash(both.groupBy(F.col("a").alias("v")).agg(F.least(F.min("b"), F.col("v")).alias("comp")), "labels")
    while True:
        near = both.join(labels.select(F.col("v").alias("b"), "comp"), "b").groupBy(F.col("a").alias("v")).agg(F.min("comp").alias("near"))
        step = stash(labels.join(near, "v").select("v", F.least("comp", "near").alias("comp"), F.col("comp").alias("old")), "step")
        # labels whose own label is another one; a large component is one key, so this small side goes to the rows
        centres = step.groupBy("comp").agg(F.count(F.lit(1)).alias("n")).select(F.col("comp").alias("centre"))
        moved = centres.join(step.select(F.col("v").alias("centre"), F.col("comp").alias("far")), "centre").where("far < centre")
        new = stash(join_spread(step, stash(moved, "moved"), "comp", "centre", "v", "left").select("v", F.least("comp", "far").alias("comp"), "old"), "labels")
        labels = new.select("v", "comp")
        if new.where("comp <> old").limit(1).count() == 0:
            return labels


def _rarest(own: np.ndarray, often: np.ndarray, times: np.ndarray, percent: int) -> np.ndarray:
    """The first n - ceil(percent n / 100) + 1 of a set's n shingles by frequency, then value. often, in order, with times; others count as 0."""
    freq = np.zeros(len(own), np.int64)
    if len(often):
        at = np.minimum(np.searchsorted(often, own), len(often) - 1)
        freq = np.where(often[at] == own, times[at], 0)
    return own[np.lexsort((own, freq))][: len(own) - -(-percent * len(own) // 100) + 1]


def prefix_pairs(texts: DataFrame, percent: int) -> DataFrame:
    """(a, b): every pair of texts (v, text, comp) of different components that can be similar enough, and few others. Two such sets of n and m shingles
    share one within the first n - ceil(percent n / 100) + 1 of one and the like of the other, in any common order of all shingles. The order
    is by frequency, rare ones first, so a passage that many texts share brings none of them together unless it makes up most of them. Frequent shingles, fewer than
    FREQUENT by their threshold, are broadcast with their counts."""
    split = texts.mapInArrow(lean(_explode_shingles), "v binary, comp binary, hs array<long>")
    split = stash(split, "shingles")
    counts = split.select(F.explode("hs").alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("f"))
    total = split.agg(F.coalesce(F.sum(F.size("hs")), F.lit(0))).first()[0]
    often = counts.where(F.col("f") >= max(16, total // FREQUENT + 1)).toPandas().sort_values("h")
    sent = texts.sparkSession.sparkContext.broadcast((often["h"].to_numpy(np.int64), often["f"].to_numpy(np.int64)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            found = [_rarest(own.values.to_numpy(), *sent.value, percent) for own in b.column("hs")]
            size = np.array([len(first) for first in found])
            at = pa.array(np.repeat(np.arange(len(size)), size))
            ns = np.repeat(pa.compute.list_value_length(b.column("hs")).to_numpy(), size).astype(np.int64)
            places = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            yield pa.RecordBatch.from_arrays([b.column("v").take(at), b.column("comp").take(at), pa.array(np.concatenate(found)), pa.array(ns), pa.array(places)], names=["v", "comp", "h", "n", "i"])

    rows = stash(split.mapInArrow(lean(run), "v binary, comp binary, h long, n long, i long"), "prefixes")
    shared = rows.groupBy("h").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("h")
    rows = stash(rows.join(shared, "h", "left_semi"), "prefixes")
    x, y = rows.alias("x"), rows.alias("y")
    # the first shingle that two sets share has all that they share at or behind its places
    fits = (100 + percent) * F.least(F.col("x.n") - F.col("x.i"), F.col("y.n") - F.col("y.i")) >= percent * (F.col("x.n") + F.col("y.n"))
    cross = x.join(y, (F.col("x.h") == F.col("y.h")) & (F.col("x.comp") < F.col("y.comp")) & fits)
    return cross.select(F.least("x.v", "y.v").alias("a"), F.greatest("x.v", "y.v").alias("b")).distinct()


def _explode_shingles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in slices(batches):
        hs = [shingles(t).view(np.int64) for t in b.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column("v"), b.column("comp"), pa.array(hs, pa.list_(pa.int64()))], names=["v", "comp", "hs"])


def _mixed(buckets: DataFrame, comp: DataFrame) -> DataFrame:
    """(key, v, n, comp) of the buckets that hold different components."""
    own = buckets.join(comp, "v", "left").select("key", "v", "n", F.coalesce("comp", "v").alias("comp"))
    mixed = own.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("key")
    return stash(own.join(mixed, "key", "left_semi"), "mixed")


def _linked(docs: DataFrame, id_col: str, text_col: str, percent: int, **params) -> DataFrame:
    """(doc_id, v, n_shingles, component_id, leads) for every row of docs; leads: the row's id and text are those that its component keeps."""
    sig = stash(signatures(docs, id_col, text_col, **params), "signatures")
    folded = sig.where("v is not null").groupBy("v").agg(F.min("doc_id").alias("rep"), F.max("n_shingles").alias("n_shingles"), F.first("lefts").alias("lefts"), F.first("rights").alias("rights"), F.count(F.lit(1)).alias("f"))
    texts = stash(folded, "texts")
    buckets = table_rows(texts.drop("rep", "f"))
    sources = stash(texts_of(docs, stash(buckets.select("v").distinct(), "wanted"), text_col), "sources")

    heads = buckets.groupBy("key").agg(F.min(F.struct("v", "n")).alias("head"))
    pairs = buckets.join(heads, "key").where("v <> head.v").select(F.col("head.v").alias("a"), F.col("v").alias("b"), F.col("head.n").alias("n_a"), F.col("n").alias("n_b"))
    tested = stash(_candidates(pairs, percent), "tested")
    edges = stash(verify(tested, sources, percent), "links")
    comp = components(edges)

    for r in range(HEAD_ROUNDS):
        # in a bucket that holds several components, a member of the largest is held against all members of the others
        own = _mixed(buckets, comp)
        per = own.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("c"), F.min(F.struct(F.xxhash64("v", "key", F.lit(r)).alias("h"), "v", "n")).alias("head"))
        lead = per.groupBy("key").agg(F.max(F.struct("c", "comp", "head")).alias("lead"))
        pairs = own.join(lead, "key").where("comp <> lead.comp").select(F.col("lead.head.v").alias("a"), F.col("v").alias("b"), F.col("lead.head.n").alias("n_a"), F.col("n").alias("n_b"))
        new = stash(_candidates(pairs, percent).join(tested, ["a", "b"], "left_anti"), "tested")
        found = stash(verify(new, sources, percent), "links")
        tested = tested.unionByName(new)
        if not found.limit(1).count():
            break
        edges = edges.unionByName(found)
        comp = components(edges)

    left_over = _mixed(buckets, comp).select("v", "comp").distinct()
    cross = prefix_pairs(sources.join(left_over, "v"), percent)
    found = stash(verify(stash(cross.join(tested, ["a", "b"], "left_anti"), "cross"), sources, percent), "links")
    if found.limit(1).count():
        comp = components(edges.unionByName(found))

    labelled = stash(texts.select("v", "rep", "f").join(comp, "v", "left").select("v", "rep", "f", F.coalesce("comp", "v").alias("comp")), "labelled")
    first = F.min(F.struct(F.col("rep").isNull().alias("none"), "rep", "v"))
    # components of one text need no join
    several = labelled.groupBy("comp").agg(first.alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("comp").alias("centre"), "first")
    by_text = join_spread(labelled, stash(several, "several"), "comp", "centre", "v", "left")
    by_text = by_text.select("v", "f", "rep", F.coalesce("first.rep", "rep").alias("component_id"), F.coalesce(F.col("first.v") == F.col("v"), F.lit(True)).alias("leads"))
    # a text with many copies is one key: frequent texts are broadcast
    rows = sig.select("doc_id", "n_shingles", "v")
    told = join_frequent(rows.where("v is not null"), stash(by_text, "told"), "v")
    out = told.unionByName(rows.where("v is null"), allowMissingColumns=True)
    leads = F.col("v").isNull() | (F.col("leads") & F.col("doc_id").eqNullSafe(F.col("rep")))
    return out.select("doc_id", "v", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"), leads.alias("leads"))


def link(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 75, **params) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of docs."""
    return _linked(docs, id_col, text_col, percent, **params).select("doc_id", "n_shingles", "component_id")


def kept_ids(linked: DataFrame) -> DataFrame:
    """Adds kept: the smallest id of a component stays."""
    return linked.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 75, **params) -> DataFrame:
    """One row of each component, with the columns of docs. Rows are told by id and text digest; only rows that agree in both are shuffled."""
    sig = _linked(docs, id_col, text_col, percent, **params).where("v is not null")
    rows = stash(sig.groupBy(F.col("doc_id").alias("k_id"), F.col("v").alias("k_v")).agg(F.first("leads").alias("leads"), F.count(F.lit(1)).alias("n")).where("not leads or n > 1"), "rows")
    marked = docs.select(F.struct("*").alias("row"), named(id_col).cast("long").alias("id"), _digest(text_col).alias("v"))
    same = F.col("id").eqNullSafe(F.col("k_id")) & (F.col("v") == F.col("k_v"))
    found = join_small(marked, rows, same, bound=KEYS).where("leads is null or leads")
    alone = found.where("n is null").select("row.*")
    if not rows.where("leads").limit(1).count():
        return alone
    again = found.where("n is not null").groupBy("id", "v").agg(F.min_by("row", F.md5(F.to_json("row"))).alias("row")).select("row.*")
    return alone.unionByName(again)


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kept_ids(link(read_table(spark, sf_dir, "documents", ["doc_id", "text"]))).select("doc_id", "n_shingles", "component_id", "kept")


OP10_SQL = """
with recursive w as (select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') as w from documents),
s as materialized (select distinct doc_id, array_to_string(w[i : i + 4], ' ') as g from (select doc_id, w, unnest(case when len(w) = 0 then [] when len(w) < 5 then [1] else range(1, len(w) - 3) end) as i from w)),
n as materialized (select doc_id, count(*) as n from s group by doc_id),
l as materialized (select x.doc_id as a, y.doc_id as b from s x join s y on x.g = y.g and x.doc_id < y.doc_id join n p on p.doc_id = x.doc_id join n q on q.doc_id = y.doc_id
      group by x.doc_id, y.doc_id, p.n, q.n having 100 * count(*) >= 75 * (p.n + q.n - count(*))),
e as materialized (select a, b from l union all select b, a from l),
c as (select doc_id as a, doc_id as b from documents union select c.a, e.b from c join e on c.b = e.a)
select d.doc_id, coalesce(n.n, 0) as n_shingles, m.b as component_id, d.doc_id = m.b as kept
from documents d left join n using (doc_id) join (select a, min(b) as b from c group by a) m on m.a = d.doc_id
"""
