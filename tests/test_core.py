"""Hand-checked toy, invariants of EM and scoring, guards, engines, plans."""

import math

import numpy as np
import pytest
from latentseg import decide, em, guard, lattice, metrics, planner, score, text, vocab, workloads
from latentseg.io import read_table, stash
from latentseg.model import SegmentModel
from pyspark.sql import functions as F

TOY = {"a": -2.0, "b": -2.0, "ab": -2.5, "ba": -3.0, "aba": -4.5}
IDS = {t: i for i, t in enumerate(TOY)}


def toy_logp():
    return np.array([*TOY.values(), em.UNKNOWN, -np.inf])


def test_toy_best_and_marginal():
    ((_, tok),) = lattice.tensors(["abab"], IDS, 3)
    fx = np.append(np.round(toy_logp()[:-1] * em.SCALE), lattice.NEVER).astype(np.int64)[:, None]
    assert lattice.best_fx(tok, fx)[0, 0] == -5_000_000
    assert abs(lattice.marginal(tok, toy_logp()[:, None])[0, 0] + 4.382378) < 1e-6
    tokens, s = lattice.segment_one("abab", IDS, 3, fx[:, 0])
    assert tokens == ["ab", "ab"] and s == -5_000_000


def test_expected_counts_cover_every_character_and_match_enumeration():
    ((_, tok),) = lattice.tensors(["abab"], IDS, 3)
    c, ll = lattice.expected_counts(tok, np.array([2.0]), toy_logp())
    assert abs(sum(c[i] * len(t) for t, i in IDS.items()) - 8) < 1e-9
    paths = []

    def walk(at, said):
        if at == 4:
            paths.append(said)
        for t in TOY:
            if "abab".startswith(t, at):
                walk(at + len(t), [*said, t])

    walk(0, [])
    assert len(paths) == 6
    w = [math.exp(sum(TOY[t] for t in p)) for p in paths]
    for t, i in IDS.items():
        assert abs(c[i] - 2 * sum(x * p.count(t) for x, p in zip(w, paths)) / sum(w)) < 1e-9
    assert abs(ll - 2 * math.log(sum(w))) < 1e-9


def test_hard_counts_are_whole_numbers():
    ((_, tok),) = lattice.tensors(["abab", "baab"], IDS, 3)
    c, _ = lattice.expected_counts(tok, np.array([3.0, 1.0]), toy_logp(), hard=True)
    assert np.allclose(c, np.round(c)) and abs(sum(c[i] * len(t) for t, i in IDS.items()) - 16) < 1e-9


def test_paths_and_segmentations(spark):
    chunks = spark.createDataFrame([("abab",), ("b",)], "chunk string")
    v = vocab.number(spark.createDataFrame([(t,) for t in TOY], "token string"))
    lat = lattice.build(chunks, v)
    assert {r[0]: r[1] for r in lat.select("chunk", lattice.count_paths(F.col("edges"))).collect()} == {"abab": 6, "b": 1}
    assert lattice.enumerate_segmentations(chunks, v).where("chunk = 'abab'").count() == 6


@pytest.fixture(scope="module")
def fitted(spark, sf):
    tr, te = workloads.train_test(spark, sf, 60, 40, 20)
    v = workloads.small_vocab(tr, 200, 3)
    return tr, te, v, SegmentModel.fit(tr, v, rounds=4)


def test_em_invariants(fitted):
    _, _, _, m = fitted
    by: dict = {}
    for r in m.trace.orderBy("round").collect():
        by.setdefault(r["label"], []).append(r["loglik"])
    for values in by.values():
        assert all(b >= a - 1e-6 for a, b in zip(values, values[1:]))
    sums = m.theta.groupBy("label").agg(F.sum(F.col("c")).alias("c")).join(m.stats, "label").collect()
    assert all(abs(r["c"] - r["n_tokens"]) < 1e-6 * r["c"] for r in sums)
    assert m.theta.where("logp > 0").count() == 0


def test_engines_agree_whatever_the_partitions(fitted):
    _, te, _, m = fitted
    want = {r[0]: (r[1], round(r[2], 6)) for r in m.transform(te, engine="map").select("row_id", "label", "score").collect()}
    for engine in ("dictionary", "native"):
        assert want == {r[0]: (r[1], round(r[2], 6)) for r in m.transform(te.repartition(3), engine=engine).select("row_id", "label", "score").collect()}
    assert want == {r[0]: (r[1], round(r[2], 6)) for r in m.transform(te, block=1).select("row_id", "label", "score").collect()}


def test_best_at_most_marginal_and_posterior_sums(fitted):
    _, te, _, m = fitted
    a = m.transform(te).select("row_id", F.col("score").alias("a"), F.aggregate(F.map_values("posterior"), F.lit(0.0), lambda x, y: x + y).alias("p"))
    b = m.transform(te, how="marginal").select("row_id", F.col("topk").alias("t"))
    j = a.join(b, "row_id").select("a", "p", F.get("t", F.lit(0))["score"].alias("b")).collect()
    assert all(r["b"] >= r["a"] - 1e-3 and abs(r["p"] - 1) < 1e-9 for r in j)


def test_segment_round_trip(fitted):
    _, te, _, m = fitted
    s = score.segment(te.limit(20), m).select("text", F.array_join("tokens", "").alias("t")).collect()
    assert all(r["text"] == r["t"] for r in s) and len(s) == 80


def test_subset_add_and_save(fitted, spark, tmp_path):
    tr, te, v, m = fitted
    part = m.subset(["de", "en"])
    full = m.transform(te).select("row_id", F.filter("topk", lambda x: x["label"].isin("de", "en"))[0]["label"].alias("x"))
    assert part.transform(te).join(full, "row_id").where("label <> x").count() == 0
    grown = SegmentModel.fit(tr.where("label <> 'es'"), v, rounds=4).add_label(tr.where("label = 'es'"), rounds=4)
    assert grown.theta.select("label", "token_id", "logp_fx").exceptAll(m.theta.select("label", "token_id", "logp_fx")).count() == 0
    m.save(f"file://{tmp_path}/m")
    again = SegmentModel.load(spark, f"file://{tmp_path}/m")
    assert again.transform(te).select("row_id", "label").exceptAll(m.transform(te).select("row_id", "label")).count() == 0


def test_edge_cases(fitted, spark):
    _, _, _, m = fitted
    rows = [(0, None), (1, ""), (2, "x"), (3, "   "), (4, "日本語テスト"), (5, "🙂é"), (6, "ab " * 4000)]
    got = {r[0]: r[1] for r in m.transform(spark.createDataFrame(rows, "i int, text string")).select("i", "label").collect()}
    assert got[0] is None and got[1] is None and all(got[i] is not None for i in range(2, 7))
    with pytest.raises(ValueError):
        m.subset(["none"]).transform(spark.createDataFrame(rows, "i int, text string"))


def test_guard(fitted):
    tr, te, _, m = fitted
    g = guard.Guard(c=-9.0, min_samples=100).fit(tr, m, high=[])
    p = g.predict(te).collect()
    inside = {r[0] for r in g.limits.select("label").collect()}
    for r in p:
        if r["guarded"] != r["label"]:
            assert r["label"] in inside and r["guarded"] not in inside and r["looked"]
    capped = {r["label"]: r["floor"] for r in g.model.stats.collect()}
    assert all(x <= -9.0 for x in capped.values())


def test_threshold_percentile_interpolates(spark):
    m = spark.createDataFrame([("a", float(x)) for x in (1, 2, 4, 8)], "label string, margin double")
    st = spark.createDataFrame([("a", 0), ("b", 5)], "label string, n_samples long")
    small = guard.small_group(st, 10)
    t = {r["label"]: r["delta"] for r in guard.thresholds(m, st, small, small.limit(0), q_max=50.0, min_samples=10).collect()}
    assert abs(t["a"] - 3.0) < 1e-9 and t["b"] == 0.0


def test_metrics_identities(spark):
    p = spark.createDataFrame([("a", "a"), ("a", "b"), ("b", "b"), ("c", "a")], "gold string, label string")
    t = {r["label"]: r for r in metrics.evaluate(p).collect()}
    assert sum(r["tp"] + r["fn"] for r in t.values()) == 4 and sum(r["fp"] for r in t.values()) == sum(r["fn"] for r in t.values())
    assert t["a"]["f1"] == 0.5 and t["c"]["f1"] == 0.0 and t["a"]["fpr"] == 0.5


def toy_chunks(spark):
    rows = [("x", "abab", 50), ("x", "aba", 30), ("x", "bb", 2), ("x", "abcabc", 20), ("x", "cc", 9), ("x", "bca", 1)]
    return spark.createDataFrame(rows, "label string, chunk string, n long")


def test_prune_loss_follows_its_definition(spark):
    """exact: with and without the token; resplit: its count times the gap to its best other split. Both put the same tokens first and last."""
    ch = toy_chunks(spark)
    v = vocab.number(spark.createDataFrame([(t,) for t in ("a", "b", "c", "ab", "aba", "bb", "abc", "ca")], "token string"))
    exact = {r["token"]: r["loss"] for r in vocab.prune_loss(ch, v, "exact").collect()}
    near = {r["token"]: r["loss"] for r in vocab.prune_loss(ch, v, "resplit").collect()}
    fitted = em.fit(ch.groupBy("chunk").agg(F.sum("n").alias("n")).select(F.lit("all").alias("label"), "chunk", "n"), v, rounds=2)
    ids = lattice.collect_vocab(v)
    logp = {r["token_id"]: (r["logp"], r["c"]) for r in fitted.theta.where("c > 0").collect()}

    def splits(text, without):
        if not text:
            yield []
        for t in ids:
            if text.startswith(t) and t != without:
                for rest in splits(text[len(t) :], without):
                    yield [t, *rest]

    value = lambda path: sum(logp[ids[t]][0] for t in path) if all(ids[t] in logp for t in path) else -math.inf
    for t in near:
        other = max(value(p) for p in splits(t, t))
        c = logp.get(ids[t], (0, 0))[1]
        assert abs(near[t] - (c * (logp[ids[t]][0] - other) if c else 0)) < 1e-6
        whole = lambda without: sum(n * math.log(sum(math.exp(value(p)) for p in splits(w, without))) for _, w, n in [(r["label"], r["chunk"], r["n"]) for r in ch.collect()])
        assert abs(exact[t] - (whole(None) - whole(t))) < 1e-6
    order = lambda d: sorted(d, key=lambda t: (-d[t], t))
    assert order(exact)[0] == order(near)[0] and order(exact)[-1] in order(near)[-2:] and all(x > -1e-9 for x in exact.values())


def test_learned_vocabulary_shrinks_to_its_size(spark):
    v = vocab.learn(toy_chunks(spark), 6, 3)
    tokens = {r["token"] for r in v.collect()}
    assert len(tokens) == 6 and {"a", "b", "c"} <= tokens
    assert vocab.learn(toy_chunks(spark), 4, 3, start=v).count() == 4


def sequential_merges(words, n):
    words = {w: (list(w), c) for w, c in words.items()}
    out = []
    for _ in range(n):
        count = {}
        for syms, c in words.values():
            for p in zip(syms, syms[1:]):
                count[p] = count.get(p, 0) + c
        if not count or max(count.values()) <= 1:
            break
        best = min(count, key=lambda p: (-count[p], p))
        out.append(best)
        for w, (syms, c) in words.items():
            done = []
            for x in syms:
                if done and (done[-1], x) == best and done[-1] is not None:
                    done[-1:] = [best[0] + best[1], None]
                else:
                    done.append(x)
            words[w] = ([x for x in done if x is not None], c)
    return out


def test_merges_equal_sequential_merging(spark, sf):
    chunks = text.chunk_counts(workloads.base(spark, sf).where("doc_id < 60")).groupBy("chunk").agg(F.sum("n").alias("n")).withColumn("label", F.lit("x"))
    v, merges = vocab.learn_merges(chunks, 60)
    assert merges == sequential_merges({r["chunk"]: r["n"] for r in chunks.collect()}, 60)
    assert {a + b for a, b in merges} <= {r["token"] for r in v.collect()}


def test_vocabularies_from_files(spark, tmp_path):
    import base64
    import json

    base = spark.createDataFrame([("a",), ("z",)], "token string")
    (tmp_path / "v.tsv").write_text("the\t-1.5\nof\t-2\n")
    (tmp_path / "v.json").write_text('{"token": "the"}\n{"token": null}\n')
    letters = {b: c for c, b in vocab.byte_letters().items()}
    coded = lambda t: "".join(letters[x] for x in t.encode())
    (tmp_path / "t.json").write_text(json.dumps({"model": {"vocab": {coded(" the"): 0, coded("é"): 1, letters[0xC3]: 2}}}))
    (tmp_path / "u.json").write_text(json.dumps({"model": {"vocab": [["\u2581the", -1.0], ["日", -2.0]]}}))
    (tmp_path / "r.txt").write_bytes(b"\n".join(base64.b64encode(t) + b" 0" for t in (b" of", b"\xc3", "é".encode())))
    tokens = lambda *a, **k: {r["token"] for r in vocab.load(spark, *a, **k).collect()}
    at = f"file://{tmp_path}"
    assert tokens(f"{at}/v.tsv", "tsv", base) == {"the", "of", "a", "z"} and tokens(f"{at}/v.json", "json") == {"the"}
    assert tokens(f"{at}/t.json", "tokenizer") == {" the", "é"} and tokens(f"{at}/t.json", "tokenizer", unit="byte") == {" the", "Ã©", "Ã"}
    assert tokens(f"{at}/u.json", "tokenizer") == {" the", "日"} and tokens(f"{at}/r.txt", "ranks") == {" of", "é"}
    c = vocab.coverage(spark.createDataFrame([("x", "azb", 2)], "label string, chunk string, n long"), vocab.number(base)).first()
    assert (c["characters"], c["covered"]) == (6, 4)
    assert vocab.byte_alphabet(spark).count() == 256


def test_rounds_in_one_task_equal_rounds_over_the_cluster(spark, sf):
    tr, _ = workloads.train_test(spark, sf, 40, 10, 20)
    ch, v = stash(text.chunk_counts(tr), "c"), workloads.small_vocab(tr, 150, 3)
    for init in ("uniform", "base", "freq"):
        a, b = em.fit(ch, v, rounds=5, init=init), em.fit(ch, v, rounds=5, init=init, rows_per_task=200)
        x = {(r["label"], r["token_id"]): (r["logp"], r["c"]) for r in a.theta.collect()}
        y = {(r["label"], r["token_id"]): (r["logp"], r["c"]) for r in b.theta.collect()}
        assert x.keys() == y.keys() and all(abs(x[k][0] - y[k][0]) < 1e-6 and abs(x[k][1] - y[k][1]) < 1e-6 * (1 + x[k][1]) for k in x)
        t = [{(r["label"], r["round"]): r["loglik"] for r in f.trace.collect()} for f in (a, b)]
        assert t[0].keys() == t[1].keys() and all(abs(t[0][k] - t[1][k]) < 1e-6 * abs(t[0][k]) for k in t[0])
    hard = em.fit(ch, v, rounds=3, kind="hard")
    assert hard.theta.count() == a.theta.count()


def test_only_tokens_that_never_occur_are_unseen(spark, sf):
    """After 20 rounds most counts have gone; the cap still touches those tokens alone that no lattice of the label has."""
    tr, _ = workloads.train_test(spark, sf, 40, 10, 20)
    v = workloads.small_vocab(tr, 200, 3)
    m = SegmentModel.fit(tr, v, rounds=20)
    ids = lattice.collect_vocab(v)
    occurs = {}
    for r in text.chunk_counts(tr).collect():
        occurs.setdefault(r["label"], set()).update(t for _, _, t in lattice.edges_of(r["chunk"], ids, 3) if t >= 0)
    theta = {}
    for r in m.theta.collect():
        theta.setdefault(r["label"], set()).add(r["token_id"])
    assert theta == occurs
    assert m.theta.where("c = 0").count() > 0
    capped = m.cap_unseen(-30.0)
    assert capped.theta.exceptAll(m.theta).count() == 0
    _, a = __import__("latentseg.model", fromlist=["x"]).block_matrix(m, m.labels(), "best")
    _, b = __import__("latentseg.model", fromlist=["x"]).block_matrix(capped, m.labels(), "best")
    changed = {(m.labels()[k], i) for i, k in zip(*np.nonzero(a != b)) if i < len(ids)}
    assert changed == {(x, i) for x in m.labels() for i in range(len(ids)) if i not in occurs[x]}
    u = {r["label"]: r["unseen"] for r in m.unseen().collect()}
    assert u == {x: len(ids) - len(occurs[x]) for x in occurs}


def test_whole_strings_have_no_cuts(spark, sf):
    """kind none: tokens may cross any place, and the score is that of one dynamic program over the whole string."""
    tr, te = workloads.train_test(spark, sf, 20, 10, 0)
    v = workloads.small_vocab(tr, 150, 3)
    m = SegmentModel.fit(tr, v, rounds=2, kind="none")
    labels = m.labels()
    ids, matrix = __import__("latentseg.model", fromlist=["x"]).block_matrix(m, labels, "best")
    out = m.transform(te, topk=4).collect()
    assert max(len(r["text"]) for r in out) > 200
    for r in out:
        got = {x["label"]: round(x["score"] * em.SCALE) for x in r["topk"]}
        assert got == {x: lattice.segment_one(r["text"], ids, 3, matrix[:, k])[1] for k, x in enumerate(labels)}
    assert SegmentModel.fit(tr, v, rounds=1, kind="space").transform(te).where("label is null").count() == 0


def test_bytes_and_prefix_space_through_the_model(spark, sf):
    tr, te = workloads.train_test(spark, sf, 40, 20, 20)
    ch = text.chunk_counts(tr, prefix_space=True, unit="byte")
    assert ch.agg(F.max(F.ascii(F.array_max(F.split("chunk", ""))))).first()[0] <= 255
    merges, _ = vocab.learn_merges(ch, 40)
    v = stash(vocab.number(vocab.byte_alphabet(spark).unionByName(merges.select("token"))), "v")
    m = SegmentModel.fit(tr, v, rounds=2, prefix_space=True, unit="byte")
    p = m.transform(te.unionByName(te.limit(1).withColumn("text", F.lit("日本 🙂"))))
    assert metrics.macro(metrics.evaluate(p)).first()["accuracy"] > 0.7 and p.where("score < -1e5").count() == 0
    s = score.segment(te.limit(10), m, labels=["de"]).select("text", text.detokenize(F.col("tokens"), "byte").alias("t")).collect()
    assert all(r["t"] == r["text"] or r["t"] == " " + r["text"] for r in s)


def test_posterior_and_prior_over_all_labels(fitted):
    _, te, _, m = fitted
    full = {r["row_id"]: r for r in m.transform(te, topk=4).collect()}
    for r in m.transform(te, topk=1).collect():
        assert list(r["posterior"]) == [r["label"]] and abs(r["posterior"][r["label"]] - full[r["row_id"]]["posterior"][r["label"]]) < 1e-12
    prior = {"de": 0.9, "en": 1e-9, "es": 0.05, "fr": 0.05}
    for engine in ("map", "dictionary", "native"):
        for r in m.transform(te, topk=1, prior=prior, engine=engine).collect():
            s = {x["label"]: x["score"] + math.log(prior[x["label"]]) for x in full[r["row_id"]]["topk"]}
            best = max(s, key=s.get)
            z = sum(math.exp(v - s[best]) for v in s.values())
            assert r["label"] == best and abs(r["score"] - s[best]) < 1e-6 and abs(r["posterior"][best] - 1 / z) < 1e-9


def test_passes_blocks_and_column_names(fitted, monkeypatch):
    _, te, _, m = fitted
    want = {r["row_id"]: (r["label"], r["posterior"]) for r in m.transform(te, topk=3).collect()}
    monkeypatch.setattr(planner, "PASS_BYTES", 1)
    clash = te.withColumns({c: F.lit(c) for c in ("row", "chunks", "at", "so_far", "total", "before", "n")})
    out = m.transform(clash, topk=3, block=1)
    assert out.columns == [*clash.columns, "topk", "label", "score", "margin", "posterior"]
    for r in out.collect():
        label, p = want[r["row_id"]]
        assert r["label"] == label and r["chunks"] == "chunks" and all(abs(r["posterior"][k] - p[k]) < 1e-9 for k in p)
    for engine in ("dictionary", "native"):
        assert {r["row_id"]: r["label"] for r in m.transform(clash, engine=engine).collect()} == {k: v[0] for k, v in want.items()}


def test_joins_of_uneven_keys(spark):
    from latentseg import io

    big = spark.range(5000).select(F.when(F.col("id") % 3 == 0, 0).otherwise(F.col("id") % 400).alias("k"), "id")
    small = big.groupBy("k").agg(F.count(F.lit(1)).alias("f")).withColumn("v", F.col("k") * 2)
    want = sorted((r["k"], r["id"], r["k"] * 2) for r in big.collect())
    for bound in (1000, 5):
        assert sorted((r["k"], r["id"], r["v"]) for r in io.join_frequent(big, stash(small, "s"), "k", bound=bound).collect()) == want
        s = stash(small.select(F.col("k").alias("sk"), "v"), "s")
        assert sorted((r["k"], r["id"], r["v"]) for r in io.join_spread(big, s, "k", "sk", "id", bound=bound, salts=4).collect()) == want


def test_bucketed_table_joins_without_a_shuffle(spark):
    from latentseg import io

    io.write_bucketed(spark.range(100).withColumnRenamed("id", "k"), "latentseg_bucketed", "k", 4)
    t = spark.table("latentseg_bucketed")
    f = planner.plan_text(t.groupBy("k").count())
    assert t.count() == 100 and "Exchange" not in f.split("\n\n")[0]
    spark.sql("drop table latentseg_bucketed")


def test_scorers_from_elsewhere(spark):
    from latentseg.hook import Scorer

    def load():
        return lambda texts: np.array([[-float(len(t)), -5.0, -50.0] for t in texts])

    df = spark.createDataFrame([(1, "ab"), (2, "abcdefgh"), (3, None), (4, "")], "i int, text string")
    out = {r["i"]: r for r in Scorer(["z", "b", "c"], load).transform(df, topk=2).collect()}
    assert out[1]["label"] == "z" and out[2]["label"] == "b" and out[3]["label"] is None and out[4]["label"] is None
    assert abs(out[1]["margin"] - 3.0) < 1e-9 and abs(out[2]["posterior"]["b"] - 1 / (1 + math.exp(-3) + math.exp(-45))) < 1e-9


def test_percentiles_are_exact(spark):
    rng = np.random.default_rng(3)
    values = {"a": rng.exponential(9, 1000), "b": np.full(50, 2.5), "c": rng.exponential(1, 3), "d": np.array([1.0])}
    rows = spark.createDataFrame([(k, float(x)) for k, v in values.items() for x in v], "label string, margin double")
    q = spark.createDataFrame([("a", 5.0), ("b", 3.0), ("c", 40.0), ("d", 1.0), ("none", 2.0)], "label string, q double")
    got = {r["label"]: r["delta"] for r in guard.percentiles(rows, q).collect()}
    assert got.keys() == values.keys() and all(abs(got[k] - np.percentile(values[k], dict(a=5, b=3, c=40, d=1)[k])) < 1e-9 for k in values)


def test_pretokeniser_is_lossless(spark, sf):
    d = read_table(spark, sf, "documents", ["text"])
    assert d.where(F.array_join(text.pretokenize(F.col("text")), "") != F.col("text")).count() == 0


def test_plans(spark, sf, fitted):
    _, _, _, m = fitted
    f = planner.facts(m.transform(read_table(spark, sf, "documents", ["doc_id", "text"]).where("doc_id < 5").repartition(8), engine="map"))
    assert f["exchanges"] <= 1 and not f["cartesian"] and any("doc_id" in x for x in f["pushed"])
    assert all("lang" not in x for x in f["read"])


def test_hierarchical_and_prior(fitted, spark):
    _, te, _, m = fitted
    parents = spark.createDataFrame([("de", "g"), ("en", "g"), ("es", "r"), ("fr", "r")], "label string, family string")
    h = decide.hierarchical(stash(te, "t"), m, parents)
    assert h.count() == te.count() and metrics.macro(metrics.evaluate(h)).first()["accuracy"] > 0.6
    one = m.transform(te, prior={"de": 1.0})
    assert one.where("label <> 'de'").count() == 0


def test_expected_counts_of_improbable_chunks_go_through_logs():
    ids = {c: k for k, c in enumerate(["a", "b", "ab", "ba", "aba"])}
    chunks = ["abab", "abxa", "x" * 4, "ab" * 700, "abx" * 400, "a"]
    for rows, tok in lattice.tensors(chunks, ids, 3):
        logp, w = em.init_theta(len(ids)), np.arange(1.0, len(rows) + 1)
        c, ll = lattice.expected_counts(tok, w, logp)
        want, ll2 = lattice._by_logs(tok, w, logp, False)
        assert np.allclose(c, want, rtol=1e-9) and abs(ll - ll2) < 1e-9 * abs(ll2) and c[-1] == 0


def test_packed_lattices_fit_as_salted_chunks_and_single_tasks_do(spark, sf, monkeypatch):
    tr, _ = workloads.train_test(spark, sf, 60, 40, 20)
    chunks, v = stash(text.chunk_counts(tr), "chunks"), workloads.small_vocab(tr, 200, 3)

    def fitted(**kw):
        f = em.fit(chunks, v, rounds=4, **kw)
        return {(r["label"], r["token_id"]): (r["logp_fx"], round(r["c"], 6)) for r in f.theta.collect()}, {(r["label"], r["round"]): (round(r["loglik"], 4), round(r["tv"], 9)) for r in f.trace.collect()}

    def close(a, b):
        assert a.keys() == b.keys() and all(abs(x - y) <= 2e-6 * max(1, abs(x)) for k in a for x, y in zip(a[k], b[k], strict=True))

    for how in ({}, {"init": "freq"}, {"kind": "hard"}):
        alone, packed = fitted(**how), fitted(rows_per_task=50, **how)
        with monkeypatch.context() as m:
            m.setattr(em, "DENSE_CELLS", 0)
            salted = fitted(rows_per_task=50, **how)
        for x in (packed, salted):
            close(alone[0], x[0])
            close(alone[1], x[1])


def test_a_trie_of_lattices_counts_as_tensors_do():
    rng = np.random.default_rng(5)
    tokens = ["a", "b", "ab", "ba", "aba", "bb", "aab", "c" * 3, "abababab"]
    ids = {c: k for k, c in enumerate(tokens)}
    chunks = sorted({"".join(rng.choice(list("abc"), rng.integers(1, 12))) for _ in range(200)} | {"a" * 64, "x" * 15, "xyz" * 20, "\x00", "a\x00", "é", "😀a"}, key=lambda x: x[::-1])
    trie = lattice.Trie.of(chunks, lattice.Suffixes(ids))
    assert trie.level[-1] < sum(map(len, chunks))
    trie = lattice.Trie.from_bytes(trie.to_bytes())
    w, logp = np.arange(1.0, len(chunks) + 1), em.init_theta(len(ids))
    logp[:5] += rng.normal(size=5)
    want, ll2 = np.zeros(len(logp)), 0.0
    for rows, tok in lattice.tensors(chunks, ids, 8):
        c, ll = lattice._by_logs(tok, w[rows], logp, False)
        want, ll2 = want + c, ll2 + ll
    c, ll = trie.expected_counts(w, logp)
    assert np.allclose(c, want, rtol=1e-9) and abs(ll - ll2) < 1e-9 * abs(ll2) and c[-1] == 0
    again = {chunks[k]: t for rows, tok in trie.tensors(np.arange(len(chunks))) for k, t in zip(rows, tok, strict=True)}
    for rows, tok in lattice.tensors(chunks, ids, 64):
        assert all((again[chunks[k]] == t).all() for k, t in zip(rows, tok, strict=True))


def test_vocabularies_and_merges_within_a_task_are_those_of_rounds(spark, sf, monkeypatch):
    chunks = stash(text.chunk_counts(workloads.base(spark, sf).where("doc_id < 40")), "c")
    tokens = lambda v: sorted((r["token_id"], r["token"]) for r in v.collect())
    with monkeypatch.context() as m:  # neither a job for each pruning step nor one for each round of merges
        m.delattr(vocab, "prune_loss")
        m.delattr(vocab, "pair_counts")
        start = vocab.learn(chunks, 400, 4)
        learned = tokens(start), tokens(vocab.learn(chunks, 250, 4, start=start))
        v, merges = vocab.learn_merges(chunks, 40)
    monkeypatch.setattr(vocab, "TASK_ROWS", 0)
    monkeypatch.setattr(vocab, "MERGE_CHARS", 0)
    again = vocab.learn(chunks, 400, 4)
    assert learned == (tokens(again), tokens(vocab.learn(chunks, 250, 4, start=again)))
    w, rounds = vocab.learn_merges(chunks, 40)
    assert merges == rounds and tokens(v) == tokens(w) and len(merges) == 40


def test_merges_of_parts_are_proposed_and_checked(spark, sf, monkeypatch):
    """From a poor head the proposals are often wrong; the merges are still those of one task, in some passes over all chunks and none for each merge."""
    chunks = stash(text.chunk_counts(workloads.base(spark, sf).where("doc_id < 40")), "c")
    odd = spark.createDataFrame([("x", "aaaa", 9), ("x", "aaa", 5), ("x", "zq", 1), ("x", "漢字漢字漢", 4)], "label string, chunk string, n long")
    want = [vocab.learn_merges(df, n)[1] for df, n in ((chunks, 60), (odd, 50))]
    one, passes = vocab._one_task, []
    monkeypatch.setattr(vocab, "_one_task", lambda *a: passes.append(1) or one(*a))
    for name, bound in (("MERGE_CHARS", 0), ("MERGE_PART", 3000), ("MERGE_HEAD", 2000)):
        monkeypatch.setattr(vocab, name, bound)
    assert [vocab.learn_merges(df, n)[1] for df, n in ((chunks, 60), (odd, 50))] == want
    assert 2 < len(passes) < 40 and len(want[0]) == 60 and want[1][0] == ("a", "a")
