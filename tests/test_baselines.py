import numpy as np
from latentseg import metrics, workloads
from latentseg.baselines import avg_embedding, linear, ngram_lm
from latentseg.baselines.avg_embedding import AvgEmbedding
from latentseg.baselines.fixed_seg_nb import FixedSegNB
from latentseg.baselines.ngram_lm import NgramLM
from latentseg.bigram import TokenBigram
from pyspark.sql import functions as F


def test_character_grams_are_grams(spark):
    got = spark.createDataFrame([("abC",), ("",)], "t string").select(linear.char_grams(F.col("t"), 1, 3).alias("g")).collect()
    assert got[0]["g"] == [" ", "a", "b", "c", " ", " a", "ab", "bc", "c ", " ab", "abc", "bc "]
    assert got[1]["g"] == [" ", " ", "  ", "  "]


def test_all_beat_chance(spark, sf):
    tr, te = workloads.train_test(spark, sf, 60, 40, 20)
    v = workloads.small_vocab(tr, 200, 3)
    acc = lambda p: metrics.macro(metrics.evaluate(p)).first()["accuracy"]
    assert acc(NgramLM.fit(tr).transform(te, "row_id")) > 0.8
    assert acc(FixedSegNB.fit(tr, v, rounds=2).transform(te, "row_id")) > 0.8
    assert acc(AvgEmbedding.fit(tr).transform(te)) > 0.8
    assert acc(linear.tfidf_linear(tr, iters=8).transform(te)) > 0.8
    assert acc(linear.svm_family(tr, iters=8).transform(te)) > 0.8
    assert acc(linear.shallow_ffn(tr, iters=30).transform(te)) > 0.5
    assert acc(TokenBigram.fit(tr, workloads.fit(tr, v, 2)).transform(te, "row_id")) > 0.8


def test_embedding_gradient_is_that_of_the_loss():
    rng = np.random.default_rng(0)
    texts, gold = ["abc", "xyz b"], np.array([0, 1])
    f, size = avg_embedding.features(texts, 1, 2, 32)
    x, y = rng.normal(size=(32, 4)), rng.normal(size=(2, 4))

    def loss(x, y):
        s = avg_embedding.means(x, f, size) @ y.T
        return float((np.log(np.exp(s).sum(axis=1)) - s[np.arange(2), gold]).sum())

    a, b = x.copy(), y.copy()
    avg_embedding.train(texts, gold, a, b, 1, 2, [1e-6])
    for old, new, k in ((x, a, 0), (y, b, 1)):
        for _ in range(6):
            at = tuple(rng.integers(n) for n in old.shape)
            up, down = old.copy(), old.copy()
            up[at] += 1e-5
            down[at] -= 1e-5
            slope = (loss(up, y) - loss(down, y)) / 2e-5 if k == 0 else (loss(x, up) - loss(x, down)) / 2e-5
            assert abs((old[at] - new[at]) / 1e-6 - slope) < 1e-4
    assert size.tolist() == [5 + 4, 7 + 6]


def test_runs_at_once_equal_one_by_one(spark, sf):
    tr, te = workloads.train_test(spark, sf, 20, 10, 20)
    both = tr.withColumn("j", F.lit(1)).unionByName(tr.withColumn("j", F.lit(2)))
    out = avg_embedding.fit_runs(both.select("j", "label", "text"), te, ["j"], epochs=20)
    got = {r["j"]: (r["a"], r["n"]) for r in out.groupBy("j").agg(metrics.right().alias("a"), F.count(F.lit(1)).alias("n")).collect()}
    assert got[1] == got[2] and got[1][1] == te.count() and got[1][0] > 0.5


def test_frequencies_are_those_of_hashed_grams(spark):
    """One long text among odd ones: grams cost time in proportion to a text's length, and keep the places that HashingTF gives them."""
    from pyspark.ml.feature import HashingTF

    texts = ["", "a", "Aß😀 ñ", "x\u0000y", "The cat, the hat", "e" * 60_000]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "id int, t string")
    want = HashingTF(inputCol="g", outputCol="v", numFeatures=4096).transform(df.where("id < 5").withColumn("g", linear.char_grams(F.col("t"), 1, 3)))
    got = {r["id"]: r["_tf"] for r in linear.term_frequencies(df, "t", 1, 3, 4096).collect()}
    assert all(got[r["id"]] == r["v"] for r in want.collect())
    assert sum(got[5].values) == 60_002 + 60_001 + 60_000 and len(got[5].values) == 8


def test_batches_of_counts_survive_packing():
    texts = ["ab", "", "e" * 300, "e" * 70_000] * 5
    made = avg_embedding.batches_of(texts, 1, 2, 64)
    assert [len(size) for _, _, size in made] == [16, 4]
    for rows, n, size in made:
        (rows2, n2, size2), gold = avg_embedding.unpack(avg_embedding.pa.py_buffer(avg_embedding.pack((rows, n, size), np.arange(len(size)))))
        assert (rows2 == rows).all() and n2.dtype == n.dtype and (n2 == n).all() and (size2 == size).all() and (n2.sum(axis=1) == size).all() and len(gold) == len(size)


def test_partitions_are_trained_side_by_side(spark, sf, monkeypatch):
    """An iterator over a frame runs a partition at a time, so no training may hang on one."""
    kind, plans = type(spark.range(1)), []
    old = kind.toLocalIterator
    monkeypatch.setattr(kind, "toLocalIterator", lambda self, *a, **kw: plans.append(self._jdf.queryExecution().toString()) or old(self, *a, **kw))
    tr, te = workloads.train_test(spark, sf)
    m = AvgEmbedding.fit(tr, epochs=10)
    assert plans and not any("MapInArrow" in x for x in plans)
    assert metrics.macro(metrics.evaluate(m.transform(te))).first()["accuracy"] > 0.8


def test_counted_grams_are_those_listed_one_by_one(spark, monkeypatch):
    """Odd texts, repeated keys, a null key and texts over several windows; for grams of any length."""
    rows = [("a", "The cat, the hat"), ("a", "the"), ("b", ""), ("b", None), (None, "Aß😀 ñ\u0000İΣ"), ("c", "e" * 5_000), ("c", "\U0010ffff " * 40), ("a", "the cat")]
    df = spark.createDataFrame(rows, "k string, t string").coalesce(1)
    for n in (1, 2, 3, 7):
        want = ngram_lm.grams(df, ["k"], "t", n).groupBy("k", "ctx", "ch").agg(F.count(F.lit(1)).alias("m"))
        got = ngram_lm.gram_counts(df, "k", "t", n).groupBy("k", "ctx", "ch").agg(F.sum("m").alias("m"))
        assert got.exceptAll(want).count() == 0 and got.count() == want.count()
    text = "".join(chr(0x4E00 + k * k % 20_000) for k in range(20_000))  # more than 63 bits for 7 of these
    owner, ctx, ch, m = ngram_lm.counted(np.array([0]), [text], 7)
    assert m.sum() == 20_000 and len(m) == len({(" " * 6 + text)[k : k + 7] for k in range(20_000)}) == len(set(zip(ctx, ch, strict=True)))


def test_grams_are_counted_before_they_are_listed(spark, sf):
    """A row for each place of a text is what made the fit slow: all that leaves the kernel is a row for each different gram of a window."""
    tr, te = workloads.train_test(spark, sf)
    listed = tr.agg(F.sum(F.length("text"))).first()[0]
    made = ngram_lm.gram_counts(tr, "label", "text", 3)
    assert made.agg(F.sum("m")).first()[0] == listed and made.count() < listed / 5
    m = ngram_lm.NgramLM.fit(tr)
    assert m.counts.agg(F.sum("c")).first()[0] == listed
    assert metrics.macro(metrics.evaluate(m.transform(te, "row_id"))).first()["accuracy"] > 0.95


def test_epochs_are_fitted_from_one_count(spark, sf, monkeypatch):
    """Several numbers of epochs give what each gives by itself, and n-grams are counted once."""
    tr, _ = workloads.train_test(spark, sf, 20, 10, 20)
    alone = [AvgEmbedding.fit(tr, epochs=e) for e in (1, 12)]
    kind, kept = type(tr), []
    old = kind.persist
    monkeypatch.setattr(kind, "persist", lambda self, *a: kept.append(1) or old(self, *a))
    both = AvgEmbedding.fit_each(tr, (1, 12))
    assert kept == [1] and all((a.inputs == b.inputs).all() and (a.outputs == b.outputs).all() for a, b in zip(alone, both, strict=True))


def test_ngram_model_scores_texts_in_one_scan(spark, monkeypatch):
    """The same labels as by joins; characters that no training text has, ties, nulls and texts over a window among them."""
    tr = spark.createDataFrame([("a", "abcabcäxy"), ("b", "bcdx yz\n𝄞"), ("c", "zzz zz"), ("d", "zzz zz"), ("c", None), ("a", "é\x00")], "label string, text string")
    texts = ["abc", "ABC xyz", "zzzz", "zz 漢字", "漢", "", None, "bcd\n𝄞𝄞", "ab" * 50, "é\x00 z"]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "row_id long, text string").repartition(3)
    m = ngram_lm.NgramLM.fit(tr)
    by = {}
    for how, held, numbers, window in (("scan", 8_000_000, 1 << 22, 1 << 20), ("sorted", 8_000_000, 1, 7), ("joins", 0, 1, 1 << 20)):
        for name, v in (("HELD", held), ("NUMBERS", numbers), ("WINDOW", window)):
            monkeypatch.setattr(ngram_lm, name, v)
        own = ngram_lm.NgramLM(m.counts, m.contexts, m.labels, m.n, m.alphabet)
        out = own.transform(df, "row_id")
        assert ("Join" in out._jdf.queryExecution().optimizedPlan().toString()) == (how == "joins")
        by[how] = sorted(map(tuple, out.select("row_id", "text", "label").collect()))
    assert by["scan"] == by["joins"] == by["sorted"]
    monkeypatch.undo()
    v = m.values()
    s = {(r["row_id"], r["label"]): r["score"] for r in m.scores(df, "row_id").collect()}
    assert s == {(k, x): t for k, row in enumerate(v.scores([(t or "").lower() for t in texts]).tolist()) for x, t in zip(v.labels, row, strict=True) if texts[k]}


def test_fixed_split_counts_and_scores_as_by_joins(spark, monkeypatch):
    """Splits, token counts and labels of the kernels are those of segment() and of joins, with characters that the vocabulary lacks."""
    from latentseg import lattice
    from latentseg.baselines import fixed_seg_nb
    from latentseg.score import SplitKernel

    rng = np.random.default_rng(5)
    ids = {t: i for i, t in enumerate(["a", "b", "ab", "ba", "aba", "bb", "c"])}
    fx = rng.integers(-4, 0, (len(ids) + 2, 3)).astype(np.int32)  # ties are common
    values = rng.integers(-99, 0, (len(ids) + 2, 4))
    chunks, split = ["".join(rng.choice(list("abcd"), n)) for n in rng.integers(1, 9, 60)], np.array([2, 0, 1, 0])
    got = SplitKernel(ids, fx, values, split).scores(chunks)
    for c, row in zip(chunks, got, strict=True):
        want = [lattice.segment_one(c, ids, 3, fx[:, k])[0] for k in range(3)]
        assert row.tolist() == [sum(int(values[ids.get(t, -2), j]) for t in want[split[j]]) for j in range(4)]
    v = spark.createDataFrame([(0, "a", 1, True), (1, "ab", 2, False), (2, "b", 1, True), (3, "ba", 2, False)], "token_id int, token string, token_len int, is_base boolean")
    tr = spark.createDataFrame([("x", "abab ba é"), ("y", "bba ab bb"), ("z", "éé ab"), ("w", "éé ab")], "label string, text string")
    te = spark.createDataFrame(list(enumerate(["ab", "bb ba", "é", "漢 ab", "", None, "ba" * 40])), "row_id long, text string")
    m = FixedSegNB.fit(tr, v, rounds=3)
    want = FixedSegNB._tokens(tr.withColumnRenamed("label", "gold"), m.pooled, ["gold"])
    assert sorted(map(tuple, m.table.select("label", "token", "c").collect())) == sorted(map(tuple, want.collect()))
    by = []
    for held in (fixed_seg_nb.HELD, 0):
        monkeypatch.setattr(fixed_seg_nb, "HELD", held)
        out = m.transform(te, "row_id")
        assert ("Join" in out._jdf.queryExecution().optimizedPlan().toString()) == (held == 0)
        by.append(sorted(map(tuple, out.select("row_id", "text", "label").collect())))
    assert by[0] == by[1]
