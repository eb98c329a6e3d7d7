"""Operators against brute force on small fixtures, with nulls, empties, ties, repeats, empty tables and clashing columns."""

import base64
import hashlib
import math
import os
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from latentseg.llm import bpe, lm_bloom, media, mixing, neardup, quality, sharding, token_counts, url_graph, warc
from pyspark.sql import functions as F

P = pytest.importorskip("public_tokenizers")
ROWS = [
    (1, "The cat sat on the mat and the dog ran off to the old red barn today", "en", "a"),
    (2, "the CAT sat on the mat and the dog ran off to the old red barn today", "en", "a"),
    (3, "the cat sat on the mat and the dog ran off to the old red barn tomorrow", "en", "b"),
    (4, None, "en", "b"),
    (5, "", None, None),
    (6, " \n\t ", "de", "a"),
    (7, "a b c", "de", None),
    (8, "a b c", "de", "a"),
    (9, "x" * 3000 + " <|endoftext|> ☃ é́ \x1c tail  \n\n end", "fr", "c"),
    (9, "repeated id", "fr", "c"),
    (None, "no id at all", "fr", "c"),
    (12, "one two three\none two three\nfour five six\n" * 12, "en", "a"),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string")


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


# --- 1
def test_mixing_matches_a_plain_poisson_inversion(spark, docs):
    table = {r["m_source"]: r["rate"] for r in mixing.rates(docs).collect()}
    got = Counter((r["doc_id"], r["text"]) for r in mixing.mix(docs).collect())
    for i, t, _, s in ROWS:
        ident = str(i) if i is not None else "text:" + hashlib.md5((t or "").encode()).hexdigest()
        u = int(hashlib.md5(f"{mixing.SEED}:1:{ident}".encode()).hexdigest()[: mixing.DIGITS], 16) / mixing.SPAN
        p = cdf = math.exp(-table[s])
        n = 0
        while u >= cdf:
            n += 1
            p *= table[s] / n
            cdf += p
        assert got[(i, t)] == n


def test_mixing_positions_weights_and_clashes(spark, docs, none):
    many = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("t").alias("text"), F.when(F.col("id") % 4 == 0, "x").otherwise("y").alias("source"), F.lit(9).alias("copy"), F.lit(8).alias("slot"))
    out = mixing.mix(many, {"x": 1.0, "y": 1.0}, unit="rows")
    n = {r[0]: r[1] for r in out.groupBy("source").count().collect()}
    assert abs(n["x"] - 2000) < 250 and abs(n["y"] - 2000) < 250
    pos = sorted(r[0] for r in out.select("position").collect())
    assert pos == list(range(len(pos)))
    big = mixing.mix(many.limit(40), {"x": 1.0, "y": 1.0}, unit="rows", epochs=700.0)
    assert abs(big.count() - 28000) < 1500
    assert mixing.mix(none).count() == 0


def clashing(df, *names):
    """df with extra columns of these names that hold their own names."""
    return df.withColumns({n: F.lit(n) for n in names})


def test_mixing_keeps_columns_whatever_they_are_called(spark, docs):
    names = ["steps", "parts", "start", "rate", "m_source", "m_ident", "m_from", "m_key", "m_bucket", "_key", "bucket", "slot", "row", "salt"]
    plain = Counter((r["doc_id"], r["text"], r["copy"], r["position"]) for r in mixing.mix(docs).collect())
    out = mixing.mix(clashing(docs, *names, "position", "Copy"))
    assert out.columns == [*docs.columns, *names, "copy", "position"]
    rows = out.collect()
    assert plain == Counter((r["doc_id"], r["text"], r["copy"], r["position"]) for r in rows) and all(r[n] == n for r in rows for n in names)
    assert mixing.mix(docs, texts=False).columns == ["doc_id", "lang", "source", "copy", "position"]
    drawn = mixing.draw(clashing(docs, "n_copies", "m_steps"), mixing.rates(docs))
    assert drawn.columns == [*docs.columns, "m_steps", "n_copies"] and drawn.count() == len(ROWS)


# --- 2
def test_shards(spark, docs, none):
    out = sharding.interleave(docs, 3).collect()
    sizes = Counter(r["shard"] for r in out)
    assert max(sizes.values()) - min(sizes.values()) <= 1 and len(out) == len(ROWS)
    for k in sizes:
        assert sorted(r["slot"] for r in out if r["shard"] == k) == list(range(sizes[k]))
    want = Counter((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t, _, _ in ROWS)
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in out) == want
    assert sharding.interleave(none, 3).count() == 0


def test_shards_follow_the_brute_force_order(spark):
    rows = [(i, f"t{i}", "abc"[min(i % 5, 2)]) for i in range(300)]
    out = sharding.interleave(spark.createDataFrame(rows, "doc_id long, text string, source string"), 8).collect()
    by: dict = {}
    for i, _, s in rows:
        by.setdefault(s, []).append((hashlib.md5(f"{sharding.SEED}:{i}".encode()).hexdigest(), i))
    order = sorted((((k + 0.5) / len(v)), s, h, i) for s, v in by.items() for k, (h, i) in enumerate(sorted(v)))
    want = {i: k for k, (_, _, _, i) in enumerate(order)}
    assert all(r["position"] == want[r["doc_id"]] and r["shard"] == want[r["doc_id"]] * 8 // 300 for r in out)
    mix = Counter((r["shard"], r["source"]) for r in out)
    assert all(abs(mix[(k, s)] - len(v) / 8) <= 2 for k in range(8) for s, v in by.items())


# --- 3
def test_warc_round_trip(spark, tmp_path):
    pages = [(1, "http://a/", "<p>x</p>"), (2, "http://b/\r\nX: y", "<p>x</p>"), (3, None, None), (4, "u", ""), (5, "v", "é" * 70000), (None, "w", "solo"), (None, "w", "<p>x</p>")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("digest", F.lit("clash"))
    index = warc.archive(df, f"file://{tmp_path}")
    back = {(r["page_id"], r["payload_digest"]): r for r in warc.read_members(index, f"file://{tmp_path}/normalised").collect()}
    for i, _, h in pages:
        p = (h or "").encode()
        r = back[(i, base64.b32encode(hashlib.sha1(p).digest()).decode())]
        assert r["payload_bytes"] == len(p)
        same = [j for j, _, g in pages if (g or "") == (h or "") and j is not None]
        first = min(same) if same else None
        assert r["record_type"] == ("response" if i == first or not same else "revisit")
        assert r["refers_to"] == (None if r["record_type"] == "response" else first)
        assert r["payload"] is None or bytes(r["payload"]) == p
    assert warc.archive(df.limit(0), f"file://{tmp_path}/e").count() == 0


def test_normaliser_can_run_again_after_removing(spark, tmp_path):
    df = spark.createDataFrame([(i, "u", f"page {i}") for i in range(9)], "page_id long, url string, html string").coalesce(1)
    names = warc.write_monolithic(warc.grouped(df), f"file://{tmp_path}/m").collect()
    archives = spark.createDataFrame(names, "archive string")
    first = warc.normalise(archives, f"file://{tmp_path}/m", f"file://{tmp_path}/n", remove=True).collect()
    again = warc.normalise(archives, f"file://{tmp_path}/m", f"file://{tmp_path}/n", remove=True).collect()
    assert first == again and sum(r["records"] for r in first) == 9


def test_every_member_stands_alone(spark, tmp_path):
    df = spark.createDataFrame([(i, "u", f"page {i}" * i) for i in range(30)], "page_id long, url string, html string").coalesce(1)
    index = warc.archive(df, f"file://{tmp_path}").collect()
    for r in index:
        with open(f"{tmp_path}/normalised/{r['archive']}", "rb") as f:
            f.seek(r["offset"])
            assert zlib.decompress(f.read(r["length"]), 31).startswith(b"WARC/1.1\r\n")


# --- 4
def test_media_is_lossless_and_both_decoders_agree():
    rng = random.Random(0)
    for n in (64, 128, 4096, 4160, 20032):
        p = bytes(rng.randrange(256) for _ in range(n))
        a = media.encode_avi(p)
        back, frames = media.payload_of(a)
        assert back == p
        jpeg = bytes(media.parse_avi(a)["frames"][0])
        scan = jpeg[jpeg.index(b"\xff\xda") + 10 : -2]
        slow = media._decode_bits(scan, (8, 8 * len(frames[0])), [(1, 1, 1)], {1: 0}, {0: {(8, 0): 8}, 16: {(8, 0): 8}}, 1)
        assert (slow == frames[0]).all()


def test_media_query_and_clips(spark, docs, none):
    out = media.inspect(media.store(docs)).collect()
    assert len(out) == len(ROWS)
    want = Counter()
    for i, t, _, _ in ROWS:
        raw = (t or "").encode()
        p = raw.ljust(max(64, -(-len(raw) // 64) * 64), b"\0")
        want[(i, len(raw), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))] += 1
    assert want == Counter((r["doc_id"], r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in out)
    assert media.inspect(media.store(none)).count() == 0
    flat, loud = bytes([10]) * 4096, bytes([200]) * 4096
    avi = media.encode_avi(flat * 5 + loud * 5)
    c = media.clips(spark.createDataFrame([(1, bytearray(avi)), (2, None)], "id int, avi binary"), "id", "avi").collect()
    assert [(r["n_frames"], r["start_s"]) for r in c] == [(5, 0.0), (5, 0.2)]


def grey_frame(level: int, quantiser: int = 16, tables: bool = True) -> bytes:
    """A flat 64 x 8 frame coded with the standard tables: DC differences and an end of block."""
    dc, ac = ({v: k for k, v in media._standard_tables()[t].items()} for t in (0, 16))
    bits, step = "", round((level - 128) * 8 / quantiser)
    for d in [step] + [0] * 7:
        n = abs(d).bit_length()
        for size, code in (dc[n], (n, d if d >= 0 else d + (1 << n) - 1), ac[0]):
            bits += f"{code:0{size}b}" if size else ""
    bits += "1" * (-len(bits) % 8)
    scan = bytes(int(bits[k : k + 8], 2) for k in range(0, len(bits), 8)).replace(b"\xff", b"\xff\0")
    seg = media._segment
    return b"\xff\xd8" + seg(0xDB, bytes([0] + [quantiser] * 64)) + seg(0xC0, b"\x08\0\x08\0\x40\x01\x01\x11\0") + seg(0xDA, b"\1\1\0\0\x3f\0") + scan + b"\xff\xd9"


def test_cuts_between_ordinary_frames():
    for a, b in ((0, 255), (20, 60), (150, 200)):
        assert media.shots([media.pixels(grey_frame(x)) for x in [a] * 5 + [b] * 5]) == [(0, 5), (5, 10)]
        assert abs(int(media.pixels(grey_frame(a))[3, 9]) - a) <= 1
    for a, b in ((10, 60), (65, 122)):  # the stored form of a payload
        p = media.encode_avi(bytes([a]) * 4096 * 3 + bytes([b]) * 4096 * 3)
        assert media.shots([media.pixels(f) for f in media.parse_avi(p)["frames"]]) == [(0, 3), (3, 6)]


def test_inverse_dct_against_its_definition():
    rng = np.random.default_rng(1)
    block = rng.integers(-30, 30, 64)
    zz, r, c = {}, 0, 0
    for k in range(64):
        zz[r, c] = block[k]
        up = (r + c) % 2 == 0
        if up:
            r, c = (r + 1, c) if c == 7 else (max(r - 1, 0), c + 1)
        else:
            r, c = (r, c + 1) if r == 7 else (r + 1, max(c - 1, 0))
    s = lambda u: math.sqrt(0.5) if u == 0 else 1.0
    want = [sum(s(u) * s(v) / 4 * zz[v, u] * math.cos((2 * x + 1) * u * math.pi / 16) * math.cos((2 * y + 1) * v * math.pi / 16) for u in range(8) for v in range(8)) for y in range(8) for x in range(8)]
    assert np.allclose(block @ media._inverse_dct(), want, atol=1e-3)


def test_all_riff_segments_give_frames():
    one, two = media.encode_avi(bytes([10]) * 8192), media.encode_avi(bytes([60]) * 4096)
    assert len(media.parse_avi(one + two[:8] + b"AVIX" + two[12:])["frames"]) == 3


def test_bit_reader_time_is_linear():
    import time

    took = []
    for blocks in (250, 2000):
        jpeg = media.encode_frame(np.random.default_rng(blocks).integers(0, 255, 64 * blocks, dtype=np.uint8))
        scan = jpeg[jpeg.index(b"\xff\xda") + 10 : -2]
        t = time.process_time()
        out = media._decode_bits(scan, (8, 8 * blocks), [(1, 1, 1)], {1: 0}, {0: {(8, 0): 8}, 16: {(8, 0): 8}}, 1)
        took.append(time.process_time() - t)
        assert (out == media.decode_frame(jpeg)).all()
    assert took[1] < 8 * 4 * max(took[0], 0.05)


def test_media_stored_form_and_feature(spark):
    text = "A" * 4096 * 4 + "z" * 4096 * 3
    (r,) = media.inspect(media.store(spark.createDataFrame([(1, text)], "doc_id long, text string"))).collect()
    avi = media.encode_avi(text.encode())
    assert (r["media_bytes"], r["media_sha256"], r["feature"]) == (len(avi), hashlib.sha256(avi).hexdigest(), "frames=7;clips=0-160;160-280")
    assert [(c["clip"], c["start_s"], c["end_s"], c["n_frames"]) for c in r["clips"]] == [(0, 0.0, 0.16, 4), (1, 0.16, 0.28, 3)]


# --- 5
def test_token_lengths_equal_the_library(spark, docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    plain = [(i, x, a, b) for i, x, a, b in ROWS if "<|endoftext|>" not in (x or "")] + [(50, "é☃ " * 20000, "zz", "zz")]
    df = clashing(spark.createDataFrame(plain, "doc_id long, text string, lang string, source string"), "_text", "t", "row")
    got = token_counts.token_lengths(df, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, ["lang", "source", "_text", "t", "row"])
    assert got.columns == ["lang", "source", "_text", "t", "row", "n_tokens"]
    want = Counter((a, b, len(t.encode(x or "", add_special_tokens=False).ids)) for _, x, a, b in plain)
    assert want == Counter((r["lang"], r["source"], r["n_tokens"]) for r in got.collect())
    sums = token_counts.suffix_sums(token_counts.histogram(got, ["lang", "source"]), ["lang", "source"]).collect()
    by = {}
    for (a, b, n), k in want.items():
        by.setdefault((a, b), []).extend([n] * k)
    assert sum(r["docs"] for r in sums) == len(plain)
    for r in sums:
        own = by[r["lang"], r["source"]]
        assert r["docs"] == own.count(r["n_tokens"]) and r["longer_tokens"] == sum(x for x in own if x > r["n_tokens"]) and r["total_docs"] == len(own)


def test_token_counts(spark, docs, none):
    lengths = token_counts.token_lengths(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, ["lang"])
    all_ = [r["n_tokens"] for r in lengths.collect()]
    s = token_counts.suffix_sums(token_counts.histogram(lengths, []), [])
    for r in s.collect():
        n = r["n_tokens"]
        assert r["longer_docs"] == sum(x > n for x in all_) and r["longer_tokens"] == sum(x for x in all_ if x > n)
        assert r["truncated_tokens"] == sum(min(x, n) for x in all_) and r["total_tokens"] == sum(all_)
    for r in token_counts.at_limits(s, [], [0, 5, 16, 10**6]).collect():
        assert r["kept_tokens"] == sum(min(x, r["context"]) for x in all_) and r["cut_docs"] == sum(x > r["context"] for x in all_)
    q = token_counts.quantiles(s, [], [50]).first()
    assert q["p50"] == sorted(all_)[(len(all_) + 1) // 2 - 1]
    assert token_counts.suffix_sums(token_counts.histogram(token_counts.token_lengths(none, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, ["lang"]), ["lang"]), ["lang"]).count() == 0


# --- 6
def tok(t):
    return (t or "").encode().lower().split() + [None]


def test_lm_scores_match_brute_force_by_either_way(spark, docs, none):
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2
    train = [tok(t) for i, t, _, _ in ROWS if not held(i)]
    c = Counter(w for t in train for w in t)
    pairs = Counter(x for t in train for x in zip(["start", *t], t, strict=False))
    n, v = sum(c.values()), len(c)
    near = lambda k: float(lm_bloom.count_of(lm_bloom.levels_of(np.array([k])))[0]) if k else 0.0

    def of(t):
        total = 0.0
        for a, b in zip(["start", *t], t, strict=False):
            seen, c2 = float(len(train)) if a == "start" else near(c[a]), near(pairs[a, b])
            w = lm_bloom.MIX if seen else 0.0
            total += math.log10((1 - w) * (near(c[b]) + 1) / (n + v + 1) + w * c2 / max(seen, c2, 1))
        return total

    want = Counter((i, held(i), len(tok(t)), sum(c[w] > 0 for w in tok(t)), n, round(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in tok(t)), 6), round(of(tok(t)), 6)) for i, t, _, _ in ROWS)
    for part_bytes, max_bytes, chunk in ((lm_bloom.PART_BYTES, lm_bloom.MAX_BYTES, lm_bloom.CHUNK), (400, lm_bloom.MAX_BYTES, 7), (400, 0, 7), (lm_bloom.PART_BYTES, 0, lm_bloom.CHUNK)):
        m = lm_bloom.fit(docs.withColumn("chunk", F.lit(1)), part_bytes=part_bytes)
        assert (m.total, m.distinct) == (n, v) and (m.parts > 8) == (part_bytes == 400)
        out = lm_bloom.score(docs.withColumn("kind", F.lit("x")), m, max_bytes=max_bytes, chunk=chunk).collect()
        assert want == Counter((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6), round(r["score"], 6)) for r in out)
    assert lm_bloom.score(none, lm_bloom.fit(none)).count() == 0
    alone = lm_bloom.score(docs, lm_bloom.fit(none)).collect()
    assert len(alone) == len(ROWS) and all(r["n_known"] == 0 and r["train_tokens"] == 0 and r["base_score"] == 0 for r in alone)


def test_words_are_told_apart_and_windows_do_not_matter(monkeypatch):
    from latentseg.llm import common

    rng = random.Random(3)
    text = "".join(rng.choice("aAbB é☃\x00\x1c \t\n\x0b\x0c\r") for _ in range(5000)) + " " + "q" * 3000 + " end"
    raw = np.frombuffer(text.encode(), np.uint8)
    words = text.encode().lower().split()
    whole, starts = common.hashed_words(raw)
    assert len(whole) == len(words) and len(set(zip(words, whole.tolist(), strict=True))) == len(set(words)) == len(set(whole.tolist()))
    monkeypatch.setattr(common, "WINDOW", 37)
    again, places = common.hashed_words(raw)
    assert (again == whole).all() and (places == starts).all()
    assert len(common.hashed_words(np.frombuffer(b" \n", np.uint8))[0]) == 0


def test_filter_never_forgets_and_seldom_invents():
    rng = np.random.default_rng(1)
    h = rng.integers(0, 2**64 - 1, 5000, dtype=np.uint64)
    c = rng.integers(1, 40, 5000)
    f = lm_bloom.Filter(lm_bloom.fill(h, c, 4, 0, 4).ravel(), 4, 0, int(lm_bloom.levels_of(c).max()))
    assert (f.levels(np.sort(h)) >= lm_bloom.levels_of(c[np.argsort(h)])).all()
    other = rng.integers(0, 2**64 - 1, 5000, dtype=np.uint64)
    assert (f.levels(other) > 0).mean() < 0.1
    full = lm_bloom.Filter(np.full(4 * lm_bloom.BLOCK_BITS // 8, 255, np.uint8), 4, 0, 9)
    assert (full.levels(other) == 9).all()  # a saturated filter ends at the largest level that was entered
    assert all(lm_bloom.count_of(lm_bloom.levels_of(np.array([k])))[0] <= 2 * k and lm_bloom.count_of(lm_bloom.levels_of(np.array([k])))[0] >= k / 2 for k in range(1, 100))


# --- 7
def test_url_rules_and_graph(spark):
    link = lambda *u: "".join(f"<a href='{x}'>x</a>" for x in u)
    pages = [(1, "http://A.Example.org/es/1", ""), (2, "https://example.org/en/12?q", ""), (3, "https://example.org/en/2#x", link("http://good.net/1")), (4, None, None), (5, "no scheme", None), (6, "http://x.com/de/1", None), (7, "http://good.net", ""), (8, "http://bad.net/", link("http://x.com/de/1")), (9, "http://notexample.org/es/", ""), (9, "http://notexample.org/es/", "")]
    out = {r["page_id"]: r for r in url_graph.judge(spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("host", F.lit("clash"))).collect()}
    assert [(out[i]["rule"], out[i]["verdict"]) for i in (1, 2, 3, 6, 9)] == [("example.org/es/", "block"), ("example.org/en/1", "block"), ("org/", "allow"), ("com/de/", "block"), ("org/", "allow")]
    assert (out[1]["host"], out[1]["path"]) == ("a.example.org", "/es/1") and (out[4]["host"], out[4]["path"]) == ("", "")
    assert out[7]["verdict"] == "allow" and out[7]["trust"] > 0 and out[8]["verdict"] == "block" and out[8]["distrust"] > 0
    assert url_graph.judge(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def dense_rank(edges, seeds, d=url_graph.DAMPING):
    """Solved at once: what hosts without links hold returns to the seeds."""
    hosts = sorted({h for e in edges for h in e[:2]} | set(seeds))
    at = {h: i for i, h in enumerate(hosts)}
    p = np.zeros((len(hosts), len(hosts)))
    for a, b, n in edges:
        p[at[a], at[b]] += n
    out = p.sum(axis=1)
    s = np.array([seeds.get(h, 0.0) for h in hosts])
    p = np.where(out[:, None] > 0, p / np.maximum(out, 1)[:, None], s[None, :])
    r = np.linalg.solve(np.eye(len(hosts)) - d * p.T, (1 - d) * s)
    return dict(zip(hosts, r, strict=True))


@pytest.mark.parametrize("degree", [url_graph.DEGREE, 3])
def test_ranks_equal_a_dense_solution(spark, monkeypatch, degree):
    monkeypatch.setattr(url_graph, "DEGREE", degree)
    rng = random.Random(5)
    host = [f"h{i}" for i in range(30)]
    edges = {(a, b): rng.randint(1, 5) for a in host[:20] for b in rng.sample(host, 4) if a != b}
    edges |= {("hub", b): 1 for b in host} | {(f"c{i}", f"c{i + 1}"): 1 for i in range(4)}
    rows = [("x", a, b, n) for (a, b), n in edges.items()] + [("y", b, a, n) for (a, b), n in edges.items()]
    seeds = {"x": {"c0": 0.5, "h3": 0.25, "hub": 0.25}, "y": {"h25": 1.0}}
    sd = spark.createDataFrame([(k, h, v) for k, s in seeds.items() for h, v in s.items()], "kind string, host string, seed double")
    got = {(r["kind"], r["host"]): r["rank"] for r in url_graph.ranks(spark.createDataFrame(rows, "kind string, src string, dst string, n long"), sd).collect()}
    for k in seeds:
        want = dense_rank([(a, b, n) for kk, a, b, n in rows if kk == k], seeds[k])
        assert abs(sum(v for (kk, _), v in got.items() if kk == k) - 1) < 1e-9
        assert all(abs(got.get((k, h), 0.0) - v) < 1e-4 for h, v in want.items())


def test_many_rules_equal_few(spark, monkeypatch):
    pages = [(1, "http://A.Example.org/es/1", ""), (2, "https://example.org/en/12?q", ""), (4, None, None), (6, "http://x.com/de/1", None), (7, "http://good.net", ""), (9, "http://notexample.org/es/", ""), (10, "http://com/fr/", ""), (11, "http://a..b/", "")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    few = {r["page_id"]: (r["rule"], r["verdict"]) for r in url_graph.judge(df).collect()}
    monkeypatch.setattr(url_graph, "FEW_RULES", 0)
    assert few == {r["page_id"]: (r["rule"], r["verdict"]) for r in url_graph.judge(df).collect()}


# --- 8
def test_bpe_equals_the_library(spark, docs, none):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    rng = random.Random(3)
    extra = ["".join(rng.choice("abceth  \n\t 'sdlre12.,!éüß日\x1c\x85") for _ in range(rng.randint(0, 60))) for _ in range(300)]
    texts = [r[1] or "" for r in ROWS] + extra
    with open(P.path("byte_bpe_50k.json"), "rb") as f:
        c = bpe.Codec(f.read())
    for text, (said, n, raw), e in zip(texts, c.encode_batch(texts), t.encode_batch(texts, add_special_tokens=False), strict=True):
        assert said == ",".join(map(str, e.ids)) and n == len(e.ids) and raw.decode("utf-8", "replace") == t.decode(e.ids, skip_special_tokens=False), text
    clash = clashing(docs, "n_tokens", "_text", "t", "row", "i", "out", "_ids")
    enc = bpe.encode(clash, P.path("byte_bpe_50k.json"))
    assert enc.columns == ["doc_id", "lang", "source", "_text", "t", "row", "i", "out", "_ids", "n_tokens", "token_ids"]
    assert all(r["_text"] == "_text" and r["row"] == "row" for r in enc.collect())
    back = bpe.decode(enc, P.path("byte_bpe_50k.json"))
    assert Counter(r["text"] for r in back.collect()) == Counter(r[1] or "" for r in ROWS)
    assert bpe.encode(none, P.path("byte_bpe_50k.json")).count() == 0


def test_compatibility_check_equals_exact_merging():
    with open(P.path("byte_bpe_50k.json"), "rb") as f:
        c = bpe.Codec(f.read())
    rng = np.random.default_rng(5)
    a, b = rng.integers(0, 3000, 3000), rng.integers(0, 3000, 3000)
    ok = c.compatible(a, b)
    for x, y, k in zip(a, b, ok, strict=True):
        assert k == (c.exact(c.bytes_of[int(x)] + c.bytes_of[int(y)]) == [x, y])
    words = [bytes(rng.choice(np.frombuffer(b"ethaoinsrdl ", np.uint8), rng.integers(1, 45))) for _ in range(400)]
    assert c.exact_many(words) == [c.exact(w) for w in words]


# --- 9
def brute_quality(t):
    t = t or ""
    w = [x for x in __import__("re").split(r"[\x20\x09-\x0d]+", t) if x]
    seen = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    cover = {i + k for i in range(len(w) - 2) if seen[tuple(w[i : i + 3])] > 1 for k in range(3)}
    lines = [x for x in t.split("\n") if any(ch not in " \t\n\x0b\x0c\r" for ch in x)]
    return len(w), sum(map(len, w)), sum(t.count(ch) for ch in "#*$%&|<>"), len(lines) - len(set(lines)), len(cover)


def test_quality_measures(spark, docs, none):
    got = Counter((r["doc_id"], *(r[c] for c in quality.BASE)) for r in quality.measure(docs).collect())
    assert got == Counter((i, *brute_quality(t)) for i, t, _, _ in ROWS)
    assert quality.filter_quality(none).count() == 0


def test_quality_keeps_clean_and_drops_junk(spark):
    rng = random.Random(2)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 8)))
    good = [(i, " ".join(word() for _ in range(120)), "en", "s") for i in range(80)]
    bad = [(100 + i, " ".join(word() + "###$$" for _ in range(120)), "en", "s") for i in range(8)]
    df = spark.createDataFrame(good + bad + [(200, "too short", None, None)], "doc_id long, text string, lang string, source string").withColumn("n_words", F.lit("clash")).withColumn("t_lang", F.lit(1))
    out = quality.filter_quality(df)
    assert out.columns == df.columns and {r["doc_id"] for r in out.collect()} == set(range(80))


def test_quality_keeps_columns_whatever_they_are_called(spark, docs):
    names = ["_w", "_t", "_h", "_l", "_d", "_m", "_shout", "_n_lines", "row", "t", "w", "m", "h", "d", "shout", "doc", "j_lang", "t_source", "hi_r_shout", "rows"]
    got = quality.measure(clashing(docs, *names, "N_words")).collect()
    assert Counter((r["doc_id"], *(r[c] for c in quality.BASE)) for r in got) == Counter((i, *brute_quality(t)) for i, t, _, _ in ROWS)
    assert all(r[n] == n for r in got for n in names)
    df = clashing(docs.withColumn("text", F.concat(F.coalesce("text", F.lit("")), F.lit(" "), F.array_join(F.transform(F.sequence(F.lit(1), F.lit(80)), lambda i: F.concat(F.lit("w"), i)), " "))), *names, "kept", "base_failed")
    out = quality.filter_quality(df)
    assert out.columns == df.columns and out.count() > 0 and all(r["kept"] == "kept" for r in out.collect())


def test_sketches_merge(spark, docs):
    m = quality.measure(docs.withColumn("text", F.repeat(F.concat("text", F.lit(" w1 w2 w3 ")), 1))).withColumn("base_failed", F.lit(False)).cache()
    both = quality.merge(quality.sketch(m.where("doc_id < 6"), ["lang"]).unionByName(quality.sketch(m.where("doc_id >= 6 or doc_id is null"), ["lang"])), ["lang"])
    assert both.exceptAll(quality.sketch(m, ["lang"])).count() == 0


def test_fences_follow_each_group(spark):
    """An outlier of a ratio goes in the group where it is rare and stays where the same value is usual."""
    usual = {"r_symbols": 40, "r_shout": 100, "r_dup_lines": 300, "r_repeats": 300, "r_word_len": 590}
    calm = {"r_symbols": 0, "r_shout": 15, "r_dup_lines": 0, "r_repeats": 5, "r_word_len": 500}
    rows = []
    for k in range(400):
        for lang, mid in (("calm", calm), ("wild", usual)):
            rows.append((len(rows), lang, lang, False, *[x + k % 5 if x else 0 for x in mid.values()]))
    planted = {}
    for at, r in enumerate(usual):
        for lang, mid in (("calm", calm), ("wild", usual)):
            planted[len(rows)] = (r, lang)
            rows.append((len(rows), lang, lang, False, *[usual[r] if k == at else x + 2 * (x > 0) for k, x in enumerate(mid.values())]))
    m = spark.createDataFrame(rows, "doc_id long, lang string, source string, base_failed boolean, " + ", ".join(f"{r} long" for r in usual))
    kept = {r["doc_id"] for r in quality.judge(m, quality.thresholds(m)).where("kept").collect()}
    assert {planted[i] for i in planted if i in kept} == {(r, "wild") for r in usual}
    assert kept >= set(range(800))


def test_fences_change_gradually_with_the_size_of_a_group(spark):
    """More rows of a group move its fence from that of its language to its own, without a step."""
    def fence(n):
        level = F.col("id") % 10 + F.when(F.col("source") == "own", 110).otherwise(10)
        rows = spark.range(20_000).withColumn("source", F.lit("big")).unionByName(spark.range(n).withColumn("source", F.lit("own")))
        zero = {r: F.lit(0).cast("long") for r in quality.RATIOS}
        m = rows.withColumns({**zero, "lang": F.lit("en"), "base_failed": F.lit(False), "r_word_len": F.lit(500).cast("long"), "r_shout": level})
        return {r["t_source"]: r["hi_r_shout"] for r in quality.thresholds(m).collect()}["own"]

    found = [fence(n) for n in (1, 25, 49, 51, 200, 3000)]
    assert found == sorted(found) and found[0] < 60 and found[-1] > 120 and found[3] - found[2] < 12


def test_pipeline_quality_uses_own_fences(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 8)))
    loud = lambda n: " ".join(word().upper() if k < n else word() for k in range(100))
    rows = [(i, loud(i % 2), "xx", "calm") for i in range(300)] + [(1000 + i, loud(11 + i % 2), "yy", "wild") for i in range(300)] + [(500, loud(11), "xx", "calm")]
    out = {r[0] for r in quality.filter_quality(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).select("doc_id").collect()}
    assert 500 not in out and len(out & set(range(1000, 1300))) >= 290 and len(out & set(range(300))) >= 290


# --- 10
def brute_groups(rows):
    def shingles(t):
        w = (t or "").encode().lower().split()
        return {tuple(w)} if 0 < len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if w else set()

    sets = [shingles(t) for _, t in rows]
    comp = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                x, y = comp[i], comp[j]
                comp = [x if c == y else c for c in comp]
    best = {}
    for (i, _), c in zip(rows, comp, strict=True):
        best[c] = min(best.get(c, i), i)
    return {i: (len(s), best[c]) for (i, _), s, c in zip(rows, sets, comp, strict=True)}


def test_near_duplicates_equal_brute_force(spark, none):
    rng = random.Random(4)
    base = [[f"w{rng.randrange(400)}" for _ in range(120)] for _ in range(12)]
    rows = []
    for k, words in enumerate(base):
        for v in range(12):
            w = list(words)
            for _ in range(v // 2):
                w[rng.randrange(len(w))] = f"n{rng.randrange(10**6)}"
            rows.append((1000 - len(rows), " ".join(w) if v else " ".join(w).upper()))
    rows += [(2000, None), (2001, ""), (2002, "one two"), (2003, "ONE two"), (2004, " ")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("v", F.lit("clash"))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in neardup.link(df).collect()}
    assert got == brute_groups(rows)
    kept = {r["doc_id"] for r in neardup.drop_near_duplicates(df).collect()}
    assert kept == {i for i, (_, c) in got.items() if i == c}
    assert neardup.link(none).count() == 0


def test_near_duplicates_odd_rows(spark, docs):
    out = neardup.link(docs).collect()
    assert len(out) == len(ROWS)
    by = {r["doc_id"]: r["component_id"] for r in out if r["doc_id"] not in (9, None)}
    assert by[1] == by[2] == by[3] == 1 and by[7] == by[8] == 7 and by[4] == 4 and by[5] == 5


def test_one_row_of_a_component_stays(spark):
    """Repeated ids, repeated rows and null ids."""
    base = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty"
    alone, other = "some text that no other row has at all in this table", "yet another text which is only here and twice in the table"
    rows = [(1, base), (2, alone), (2, base + " more"), (3, other), (3, other), (None, base), (4, None), (4, None), (None, ""), (None, "null id and a text of its own with words"), (None, "null id and a text of its own with words")]
    df = clashing(spark.createDataFrame(rows, "doc_id long, text string"), "_gone", "v", "k_id", "row", "leads", "id")
    out = neardup.drop_near_duplicates(df)
    assert out.columns == df.columns
    assert Counter((r["doc_id"], r["text"]) for r in out.collect()) == Counter([(1, base), (2, alone), (3, other), (4, None), (4, None), (None, ""), (None, "null id and a text of its own with words")])
    kept = {(r["doc_id"], r["component_id"]) for r in neardup.kept_ids(neardup.link(df)).where("kept").collect()}
    assert {(1, 1), (2, 2), (3, 3)} <= kept


def test_components_join_by_salt_beyond_the_bound(spark, monkeypatch):
    from latentseg import io

    monkeypatch.setattr(neardup, "join_spread", lambda *a, **k: io.join_spread(*a, **k, bound=0))
    edges = [(bytes([0, i]), bytes([0, i + 1])) for i in range(40)] + [(bytes([1, 0]), bytes([1, i])) for i in range(1, 60)]
    got = {bytes(r["v"]): bytes(r["comp"]) for r in neardup.components(spark.createDataFrame([tuple(map(bytearray, e)) for e in edges], "a binary, b binary")).collect()}
    assert got == {v: bytes([v[0], 0]) for e in edges for v in e}


# --- pipeline
def test_pipeline_equals_brute_force(spark, tmp_path):
    """run() on a small table, each stage redone in plain Python from its definition."""
    import corpus_pipeline
    from tokenizers import Tokenizer

    rng = random.Random(8)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 8)))
    rows = []
    for i in range(120):
        text = " ".join(word() for _ in range(60 + i % 30))
        rows.append((i, text, "en" if i % 3 else "de", "ab"[i % 2]))
    rows += [(200 + i, rows[i][1].upper() if i % 2 else rows[i][1] + " tail", *rows[i][2:]) for i in range(10)]
    rows += [(300, "too short", "en", "a"), (301, None, None, None), (302, "same three words " * 40, "en", "a"), (303, " ".join(word() + "##$$%" for _ in range(90)), "en", "a")]
    df = spark.createDataFrame([(*r, len(r[1] or "")) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")
    df.write.parquet(f"{tmp_path}/documents.parquet")
    # quality
    m = {}
    for i, t, lang, source in rows:
        n, chars, symbols, dup, rep = brute_quality(t)
        lines = [x for x in (t or "").split("\n") if x.strip()]
        if n >= 50 and 100 * rep <= 50 * n:
            shout = sum(c.isascii() and c.isupper() or c == "!" for c in t)
            m[i] = (lang, source, {"r_symbols": 1000 * symbols // chars, "r_shout": 1000 * shout // chars, "r_dup_lines": 1000 * dup // len(lines), "r_repeats": 1000 * rep // n, "r_word_len": 100 * chars // n})
    low = lambda v, p: sorted(v)[-(-p * len(v) // 100) - 1]
    ok = set(m)
    for ratio, (a, b, below) in quality.RATIOS.items():
        pull = lambda v, up: {q: (len(v) * low(v, q) + quality.PRIOR * up[q]) // (len(v) + quality.PRIOR) for q in (a, b)}  # noqa: B023, E731
        top = {q: low([x[2][ratio] for x in m.values()], q) for q in (a, b)}
        for i, (lang, source, values) in m.items():
            of_lang = pull([x[2][ratio] for x in m.values() if x[0] == lang], top)
            q = pull([x[2][ratio] for x in m.values() if x[:2] == (lang, source)], of_lang)
            spread = quality.REACH * (q[b] - q[a] if q[b] > q[a] else quality.NO_SPREAD)
            if values[ratio] > q[b] + spread or below and values[ratio] < q[a] - spread:
                ok.discard(i)
    left = [r for r in rows if r[0] in ok]
    # near-duplicates
    groups = brute_groups([(r[0], r[1]) for r in left])
    left = [r for r in left if groups[r[0]][1] == r[0]]
    # mixing
    size = Counter()
    for _, t, _, s in left:
        size[s] += len(t.encode()) + 1
    raw = {s: round(v**mixing.TEMPERATURE, 3) for s, v in size.items()}
    copies = []
    for i, _, _, s in left:
        rate = raw[s] / sum(raw.values()) * sum(size.values()) / size[s]
        u = int(hashlib.md5(f"{mixing.SEED}:1:{i}".encode()).hexdigest()[: mixing.DIGITS], 16) / mixing.SPAN
        p = cdf = math.exp(-rate)
        n = 0
        while u >= cdf:
            n += 1
            p *= rate / n
            cdf += p
        copies += [(hashlib.md5(f"{mixing.SEED}:order:{k}:{i}".encode()).hexdigest(), i, k) for k in range(1, n + 1)]
    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    text = {r[0]: r[1] for r in left}
    want = []
    for at, (_, i, k) in enumerate(sorted(copies)):
        ids = t.encode(text[i], add_special_tokens=False).ids
        want.append((i, k, at, tuple(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    got = [(r["doc_id"], r["copy"], r["position"], tuple(r["token_ids"]), r["ids_sha256"], r["decoded_sha256"]) for r in corpus_pipeline.run(spark, str(tmp_path)).orderBy("position").collect()]
    assert got == want and {300, 301, 302}.isdisjoint(i for i, *_ in got) and 0 < len(left) < len(rows) - 13


def test_pipeline_stages(spark, sf):
    import corpus_pipeline
    from latentseg.io import read_table, stash

    docs = read_table(spark, sf, "documents")
    cols = docs.columns
    assert [k for k, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "mix", "encode"]
    kept = []
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = stash(stage(spark, docs, sf), "stage")
        kept.append(docs.count())
        assert docs.columns[: len(cols)] == cols or k == 3
    assert kept[0] >= kept[1] > 0 and kept[2] == kept[3]
    assert os.path.isfile(corpus_pipeline.__file__)


# --- the queries themselves
def test_queries_have_their_contract_columns(spark, sf):
    from latentseg.llm import queries

    want = {
        "op1_mix_sources": "doc_id bigint, source string, text string, copy bigint, position bigint",
        "op2_stratified_shards": "doc_id bigint, size bigint, text_crc32 bigint, law string, shard int, slot bigint, grown_shard int",
        "op3_warc": "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint",
        "op4_media_avi": "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string",
        "op5_token_counts": "lang string, source string, n_tokens bigint, docs bigint, tokens bigint",
        "op6_lm_scores": "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double",
        "op7_url_graph": "page_id bigint, host string, path string, rule string, verdict string",
        "op8_bpe": "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string",
        "op9_quality": "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean",
        "op10_near_duplicates": "doc_id bigint, n_shingles bigint, component_id bigint, kept boolean",
    }
    made = queries.queries()
    assert set(made) == set(want)
    for name, columns in want.items():
        df = made[name](spark, sf)
        kinds = dict(df.dtypes)
        assert [f"{c} {kinds.get(c)}" for c in [x.split()[0] for x in columns.split(", ")]] == columns.split(", "), name
    law = made["op2_stratified_shards"](spark, sf).select("law", "grown_shard").distinct().collect()
    assert [(r["law"], r["grown_shard"]) for r in law] == [("rows", None)]


def test_remembered_sets_are_bounded_by_their_size():
    """Long texts took 160 kB each of a memory that was bounded by the number of texts."""
    texts = [" ".join(f"w{k}.{i}" for i in range(400)) for k in range(40)]
    sets = neardup.Sets(most=2_000)
    for t in [*texts, *texts[::-1]]:
        assert (sets[t] == neardup.shingles(t)).all()
        assert sum(map(len, sets.known.values())) <= sets.held <= 2_000
    assert sets[texts[0]] is sets[texts[0]]


def test_kernels_hand_their_memory_back():
    from latentseg import cluster

    freed = []
    old, cluster.release = cluster.release, lambda: freed.append(1)
    try:
        batch = neardup.pa.RecordBatch.from_pydict({"x": list(range(1_200))})
        assert [b.num_rows for b in cluster.lean(cluster.slices)(iter([batch]))] == [500, 500, 200]
        assert freed == [1]
    finally:
        cluster.release = old
    cluster.release()


def test_rarest_shingles_are_those_of_a_plain_sort():
    rng = np.random.default_rng(3)
    own = np.unique(rng.integers(-(2**62), 2**62, 300))
    freq = dict(zip(own[::3].tolist(), rng.integers(16, 20, 100).tolist(), strict=True)) | {7: 99}
    often = np.array(sorted(freq), np.int64)
    for percent in (75, 100, 1):
        want = sorted(own.tolist(), key=lambda h: (freq.get(h, 0), h))[: len(own) - -(-percent * len(own) // 100) + 1]
        assert neardup._rarest(own, often, np.array([freq[h] for h in often.tolist()]), percent).tolist() == want
        assert len(neardup._rarest(own[:1], often[:0], often[:0], percent)) == 1
