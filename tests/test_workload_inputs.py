"""What the experiments hand to the model: whole texts and all rows."""

import pytest
import numpy as np
from latentseg import text, workloads
from latentseg.io import read_table
from pyspark.sql import functions as F


@pytest.fixture
def seen(monkeypatch):
    """Frames that are fitted and scored, without fitting or scoring."""
    found = {"fit": [], "score": []}

    class Stub:
        vocab = None

        def transform(self, df, **kw):
            found["score"].append(df)
            return df

    def fit(tr, *a, **kw):
        found["fit"].append(tr)
        return Stub()

    monkeypatch.setattr(workloads, "fit", fit)
    monkeypatch.setattr(workloads, "_main", lambda s, d: Stub())
    monkeypatch.setattr(workloads, "small_vocab", lambda *a: None)
    monkeypatch.setattr(workloads, "said", lambda *a: [])
    monkeypatch.setattr(workloads, "long", lambda *a: [])
    monkeypatch.setattr(workloads.metrics, "evaluate", lambda p: p)
    return found


def test_other_classes_see_whole_documents(spark, sf, seen):
    workloads.RUNS["w20_other_classes"](spark, sf)
    parts = [a.select("doc_id", "text").unionByName(b.select("doc_id", "text")) for a, b in zip(seen["fit"], seen["score"], strict=True)]
    docs, labels = (read_table(spark, sf, t) for t in ("documents", "labels"))
    for part, want in zip(parts, (docs.join(labels, "doc_id"), docs.join(labels, "doc_id"), docs), strict=True):
        want = want.select("doc_id", "text")
        assert part.count() == want.count() and part.exceptAll(want).count() == 0


def test_label_noise_takes_whole_pages_and_a_fixed_sample(spark, sf, seen):
    workloads.RUNS["w24_label_noise"](spark, sf)
    (noisy,), clean = seen["fit"], workloads.train_test(spark, sf)[0]
    added = noisy.exceptAll(clean.select("row_id", "label", "text"))
    pages = read_table(spark, sf, "pages").select(text.page_lang(F.col("html")).alias("label"), F.col("html").alias("text")).where("label in ('es', 'de')")
    assert pages.exceptAll(added.select("label", "text")).count() == 0
    fixed = text.sample_j(clean.where("label = 'en'"), 50, 3)
    assert fixed.select("row_id").exceptAll(added.select("row_id")).count() == 0


def test_training_takes_all_lines(spark, sf):
    tr, te = workloads.train_test(spark, sf)
    ln = workloads.base(spark, sf)
    assert tr.count() == ln.where("bucket >= 2").count() and te.count() == ln.where("bucket = 0").count()
    assert (workloads.ROUNDS, workloads.EPOCHS) == (20, 100)


def test_sample_efficiency_runs_the_whole_grid(spark, sf, monkeypatch):
    """All systems on the same subsets; by default nine sizes and five seeds."""
    import inspect

    f = workloads.RUNS["w05_sample_efficiency"]
    defaults = {k: v.default for k, v in inspect.signature(f).parameters.items() if v.default is not inspect.Parameter.empty}
    assert defaults == {"sizes": (5, 10, 25, 50, 100, 200, 300, 400, 500), "seeds": (1, 2, 3, 4, 5)}
    monkeypatch.setattr(workloads, "learned_vocab", lambda s, d: workloads.small_vocab(workloads.train_test(s, d)[0], 200, 3))
    monkeypatch.setattr(workloads, "ROUNDS", 3)
    monkeypatch.setattr(workloads, "EPOCHS", 10)
    out = {(a, b, c): v for a, b, c, v in f(spark, sf, sizes=(5, 40), seeds=(1, 2))}
    assert {k[0] for k in out} == {"latent", "fixed_split", "ngram", "avg_embedding"} and len(out) == 4 * 2 * 2
    assert all(0.2 < v <= 1 for k, v in out.items() if k[2] == "mean")
    assert out["latent", "J=40", "mean"] > out["latent", "J=5", "mean"]
    # a run of the grid is what a fit on its subset alone gives
    _, te = workloads.train_test(spark, sf)
    pool, v = workloads.base(spark, sf).where("bucket >= 2"), workloads.learned_vocab(spark, sf)
    alone = [workloads.said(workloads.fit(text.sample_j(pool, 5, seed), v, 3).transform(te), "x")[2][3] for seed in (1, 2)]
    assert abs(sum(alone) / 2 - out["latent", "J=5", "mean"]) < 1e-5


def test_systems_are_fitted_side_by_side_and_once(spark, sf, monkeypatch):
    """The embeddings and the other systems wait for each other; what they share is made once."""
    import threading

    both, made = threading.Barrier(2, timeout=60), []

    def fitted(name, tr, v=None):
        made.append(name)
        if name in ("avg_embedding", "ngram"):
            both.wait()
        return lambda te: te

    workloads.train_test(spark, sf)
    monkeypatch.setattr(workloads, "train", fitted)
    monkeypatch.setattr(workloads, "once", lambda s, d, name, make: workloads_once(s, d, f"side-{name}", make) if "system" in name else workloads_once(s, d, name, make))
    workloads.ready(spark, sf, ("ngram", "avg_embedding"))
    assert sorted(made) == ["avg_embedding", "ngram"]
    seen = []
    workloads.side_by_side(*[lambda: workloads_once(spark, sf, "side-one", lambda: seen.append(1) or 1)] * 4)
    assert seen == [1]


def test_three_labels_fit_each_system_once(spark, sf, seen, monkeypatch):
    names = []
    monkeypatch.setattr(workloads, "train", lambda name, tr, v=None: names.append(name) or (lambda te: te))
    stub = type("Stub", (), {"vocab": None, "transform": lambda self, df: df, "subset": lambda self, labels: self})()
    monkeypatch.setattr(workloads, "_main", lambda s, d: stub)
    workloads.RUNS["w02_label_subset"](spark, sf)
    assert sorted(names) == ["avg_embedding", "ffn", "latent", "ngram"]


workloads_once = workloads.once


def test_runs_are_scored_in_one_scan_as_by_joins(spark, monkeypatch):
    """Sample efficiency: the best label of each run from a scan is that from rows of labels, with texts that have none and a label that a run lacks."""
    from latentseg import planner
    from latentseg.baselines import avg_embedding, fixed_seg_nb, ngram_lm

    src = [("x", "abab ba é"), ("x", "ab ab"), ("y", "bba ab bb"), ("z", "éé ab"), ("w", "éé ab")]
    rows = spark.createDataFrame([(j, seed, x, t, f"{x}|{j}|{seed}") for j in (1, 2) for seed in (1, 2) for k, (x, t) in enumerate(src) if k % (seed + 1) or j == 2], "j int, seed int, label string, text string, own string")
    te = spark.createDataFrame([(k, "x", t) for k, t in enumerate(["ab", "bb ba", "é", "漢 ab", "", None, "ba" * 40])], "row_id long, gold string, text string")
    v = spark.createDataFrame([(0, "a", 1, True), (1, "ab", 2, False), (2, "b", 1, True), (3, "ba", 2, False)], "token_id int, token string, token_len int, is_base boolean")
    own = rows.select(F.col("own").alias("label"), "text")
    m, n = workloads.fit(own, v, 3), ngram_lm.NgramLM.fit(own)
    pooled = workloads.fit(rows.select(F.concat_ws("|", F.lit("*"), F.col("j").cast("string"), F.col("seed").cast("string")).alias("label"), "text"), v, 3)
    by = []
    for bound in (8_000_000, 0):
        for module, name in ((planner, "PASS_BYTES"), (fixed_seg_nb, "HELD"), (ngram_lm, "HELD")):
            monkeypatch.setattr(module, name, bound)
        n._known.clear()
        found = [workloads._picked_latent(m, te, 4), workloads._picked_ngram(n, te), workloads._fixed_runs(rows, te, pooled, v)]
        by.append([sorted(tuple(map(str, r)) for r in df.select("j", "seed", "gold", "label").collect()) for df in found])
    assert by[0] == by[1] and [len(x) for x in by[0]] == [20, 20, 20]
    x, y = avg_embedding.start(64, 3, 4, 1)
    y += np.arange(12).reshape(3, 4) % 5
    texts = np.array(["ab", None, "", "ba é"] * 300, dtype=object)
    assert avg_embedding.Held(texts, texts, 1, 3, 64).predict(x, y, ["a", "b", "c"]) == avg_embedding.AvgEmbedding(x, y, ["a", "b", "c"], 1, 3).predict(texts.tolist())
    made = avg_embedding.fit_runs(rows, te.where("text is not null"), ["j", "seed"], 2)
    assert made.groupBy("j", "seed").count().count() == 4 and "RepartitionByExpression" in made._jdf.queryExecution().optimizedPlan().toString()


def test_systems_are_tested_while_others_are_fitted(spark, sf, monkeypatch):
    """The embeddings are not ready before the others have been tested; results are in the order of the systems."""
    import threading

    tested = {x: threading.Event() for x in ("ngram", "fixed_split", "latent")}

    def fitted(spark, sf, name):
        assert name != "avg_embedding" or all(e.wait(60) for e in tested.values())
        return lambda te: te

    monkeypatch.setattr(workloads, "system", fitted)
    names = ("avg_embedding", "ngram", "fixed_split", "latent")
    assert workloads.ready(spark, sf, names, lambda name: [tested[name].set() if name in tested else None, name]) == [[None, x] for x in names]


def test_corrupted_texts_of_all_rates_meet_a_system_once(spark, sf, monkeypatch):
    """Each rate has the texts that a corruption by itself gives, rows keep keys of their own, and a system scores them in one scan."""
    lines = [(1, 0, "Ab c  é漢 🙂."), (1, 1, ""), (2, 0, None), (None, 3, "\tq\n r"), (10**12, 7, "x" * 1200)]
    src = spark.createDataFrame(lines, "doc_id long, line_no int, text string")
    rates = (0, 50, 500, 1000)
    got = text.corrupt_each(src, rates)
    for r in rates:
        assert sorted(map(str, got.where(F.col("per_mille") == r).select(*src.columns).collect())) == sorted(map(str, text.corrupt(src, r).collect()))
    scored = []

    def fitted(spark, sf, name):
        return lambda te: scored.append((name, te)) or te.withColumn("label", F.lit("en"))

    monkeypatch.setattr(workloads, "system", fitted)
    out = workloads.RUNS["w08_corruption"](spark, sf)
    assert sorted(x for x, _ in scored) == sorted(workloads.MAIN) and len(out) == 16
    te = scored[0][1]
    src = workloads.base(spark, sf).where("bucket = 0")
    assert te.select("row_id").distinct().count() == te.count() == 4 * src.count()
    one = text.corrupt(src, 250).select("doc_id", "line_no", "text")
    assert te.where("per_mille = 250").select("doc_id", "line_no", "text").exceptAll(one).count() == 0
    share = src.where("label = 'en'").count() / src.count()
    assert all(abs(v - share) < 1e-6 for *_, v in out) and [r[1] for r in out[:5]] == ["rate=0.05"] * 4 + ["rate=0.1"]


def test_borrowed_vocabularies_are_made_when_asked_for(spark, sf, monkeypatch):
    """Neither merges nor characters are learned for a vocabulary that needs none, and each is learned once."""
    made = []
    monkeypatch.setattr(workloads.vocab, "learn_merges", lambda ch, n: made.append(n) or (workloads.vocab.substrings(ch, 1).select("token"), []))
    monkeypatch.setattr(workloads, "once", lambda s, d, name, make: workloads_once(s, d, f"asked-{name}" if "borrowed" in name else name, make))
    found = workloads.borrowed(spark, sf)
    assert list(found)[-6:] == ["merges_en", "merges_all", "far_words", "characters", "bytes", "trigrams"] and made == []
    assert found["bytes"]()[0].count() == 256 and made == []
    assert found["merges_en"]()[0].count() == workloads.borrowed(spark, sf)["merges_en"]()[0].count() > 20 and made == [300]


def test_in_domain_works_in_two_chains(spark, sf, monkeypatch):
    """Curated lines and borrowed vocabularies do not wait for all systems, three vocabularies alone are asked for, and rows keep their order."""
    import threading

    asked, both = [], threading.Barrier(2, timeout=60)
    stub = type("Stub", (), {"transform": lambda self, te: te})()
    monkeypatch.setattr(workloads, "system", lambda s, d, name: lambda te: te)
    monkeypatch.setattr(workloads, "said", lambda pred, name, setting="": [(name, setting, "x", 0.0)])
    monkeypatch.setattr(workloads, "borrowing", lambda s, d, name, *a: asked.append(name) or (len(asked) == 1 and both.wait(), ([(*a, "", "x", 0.0)], None))[1])
    monkeypatch.setattr(workloads.AvgEmbedding, "fit", lambda *a, **kw: both.wait() is not None and stub)
    names = [r[0] for r in workloads.RUNS["w01_in_domain"](spark, sf)]
    assert asked == list(workloads.borrowed(spark, sf))[:3] and both.broken is False
    assert names == [*workloads.MAIN, "fixed_split", "ngram_interp", "ngram_backoff", "tfidf", "svm", "ffn", "majority", "avg_embedding_curated", *[f"latent, {x}" for x in asked]]


def test_ranges_of_grams_are_fitted_side_by_side(spark, sf, monkeypatch):
    """All ranges are under way at once, each with all numbers of epochs; rows are in the order of epochs, then of ranges."""
    import threading

    all_, te = threading.Barrier(3, timeout=60), spark.range(1)

    class Fitted:
        def __init__(self, *what):
            self.what = what

        def transform(self, df):
            return self.what

    monkeypatch.setattr(workloads, "dialect_data", lambda s, d: (te, te))
    monkeypatch.setattr(workloads.AvgEmbedding, "fit_each", lambda tr, epochs, low, high: all_.wait() is not None and [Fitted(e, low, high) for e in epochs])
    monkeypatch.setattr(workloads, "said", lambda pred, name, setting: [(name, setting, k, pred) for k in ("macro_f1", "accuracy")])
    out = workloads.RUNS["w15_epochs"](spark, sf)
    assert [x[3] for x in out] == [(e, lo, hi) for e in (1, 5, 25, 100) for lo, hi in ((1, 2), (1, 3), (2, 4))]
    assert out[4] == ("avg_embedding", "epochs=5,n=1-3", "macro_f1", (5, 1, 3))
