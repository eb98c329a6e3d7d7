"""The experiments, on the given tables. Each returns rows (workload, system, setting, metric, value).

Systems learn from all training lines, as many rounds and epochs as published (20 and 100), and are tested on all test lines, unless the size of one of them is what an experiment varies.
Fitted systems are shared by the experiments of one application."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import decide, guard, lattice, metrics, relops, score, text, vocab
from .baselines import linear, naive
from .baselines.avg_embedding import AvgEmbedding, fit_runs
from .baselines.fixed_seg_nb import FixedSegNB, fixed_point, kernel_of, token_counts
from .baselines.ngram_lm import NgramLM, map_scores
from .io import fresh_path, read_table, side_by_side, stash, write_labeled
from .model import SegmentModel
from .queries import all_lines, once

Rows = list[tuple[str, str, str, float]]
RUNS: dict[str, Callable] = {}
ROUNDS, EPOCHS = 20, 100
#: Size of the learned vocabulary and its longest token; the given tables are small.
SIZE, LONGEST = 1500, 6
#: A tokenizer file to borrow a vocabulary from; the package that names one is optional.
TOKENIZER = "byte_bpe_50k"


def workload(name: str):
    def add(f):
        RUNS[name] = f
        return f

    return add


def run(name: str, spark: SparkSession, sf_dir: str, **params) -> DataFrame:
    rows = [(name, *map(str, r[:3]), float(r[3]) if r[3] is not None else None) for r in RUNS[name](spark, sf_dir, **params)]
    return spark.createDataFrame(rows, "workload string, system string, setting string, metric string, value double")


# --- data


def base(spark: SparkSession, sf_dir: str) -> DataFrame:
    return once(spark, sf_dir, "w-lines", lambda: stash(all_lines(spark, sf_dir).withColumn("row_id", F.col("doc_id") * 100000 + F.col("line_no")), "lines"))


def train_test(spark: SparkSession, sf_dir: str, j: int | None = None, test: int | None = None, length: int = 20) -> tuple[DataFrame, DataFrame]:
    """Training lines, and `length`-character snippets of test lines (whole lines for 0); j and test bound them for each label. Equal texts never straddle."""

    def make() -> tuple[DataFrame, DataFrame]:
        ln = base(spark, sf_dir)
        bounded = lambda df, n: df if n is None else text.sample_j(df, n, 1)
        tr = stash(bounded(ln.where("bucket >= 2"), j), "train")
        te = bounded(ln.where("bucket = 0"), test)
        te = te if not length else text.snippets(te, length).withColumn("text", F.trim("snippet")).where("text <> ''")
        return tr, stash(te.select("row_id", "doc_id", F.col("label").alias("gold"), "text", "n_chars"), "test")

    return once(spark, sf_dir, f"w-{j}-{test}-{length}", make)


def small_vocab(train: DataFrame, size: int = 1000, max_len: int = 5) -> DataFrame:
    return stash(vocab.base_topk(text.chunk_counts(train), size, 2, max_len), "vocab")


def fit(rows: DataFrame, v: DataFrame | None = None, rounds: int = ROUNDS, **kw) -> SegmentModel:
    return SegmentModel.fit(rows, v if v is not None else small_vocab(rows), rounds=rounds, **kw)


def counted(spark: SparkSession, sf_dir: str, unit: str = "codepoint", prefix_space: bool = False) -> DataFrame:
    """The chunks of all training lines, cut and counted once for all models that cut so."""
    tr, _ = train_test(spark, sf_dir)
    return once(spark, sf_dir, f"w-chunks-{unit}-{prefix_space}", lambda: stash(text.chunk_counts(tr, prefix_space=prefix_space, unit=unit), "chunks"))


def said(pred: DataFrame, system: str, setting: str = "") -> Rows:
    m = metrics.macro(metrics.evaluate(pred.select("gold", "label"))).first()
    return [(system, setting, k, m[k]) for k in ("macro_f1", "macro_fpr", "accuracy", "rows")]


def long(df: DataFrame, system: str, key: str, values: list[str]) -> Rows:
    return [(system, r[key], v, r[v]) for r in df.collect() for v in values]  # a row a label, band or setting


def learned_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base system's own vocabulary: learned by pruning on a thousand lines a label."""

    def make() -> DataFrame:
        tr, _ = train_test(spark, sf_dir)
        return vocab.learn(stash(text.chunk_counts(vocab.sample_per_label(tr, 1000)), "chunks"), SIZE, LONGEST)

    return once(spark, sf_dir, "w-learned", make)


def _main(spark: SparkSession, sf_dir: str) -> SegmentModel:
    tr, _ = train_test(spark, sf_dir)
    return once(spark, sf_dir, "w-model", lambda: fit(tr, learned_vocab(spark, sf_dir), chunks=counted(spark, sf_dir)))


Predict = Callable[[DataFrame], DataFrame]


def train(name: str, tr: DataFrame, v: DataFrame | None = None, chunks: DataFrame | None = None) -> Predict:
    """A fitted system: rows with row_id and text to rows with label. chunks: the rows cut and counted already."""
    if name == "latent":
        return fit(tr, v).transform
    if name == "fixed_split":
        m = FixedSegNB.fit(tr, v, rounds=ROUNDS, chunks=chunks)
    elif name.startswith("ngram"):
        m = NgramLM.fit(tr, smooth=name.partition("_")[2] or "add_k")
    elif name == "avg_embedding":
        m = AvgEmbedding.fit(tr, epochs=EPOCHS)
    elif name == "tfidf":
        m = linear.tfidf_linear(tr)
    elif name == "svm":
        m = linear.svm_family(tr)
    elif name == "ffn":
        m = linear.shallow_ffn(tr)
    else:
        return lambda te: naive.majority(tr, te)
    return lambda te: m.transform(te, "row_id")


def system(spark: SparkSession, sf_dir: str, name: str) -> Predict:
    """A system fitted on all training lines, once."""
    tr, _ = train_test(spark, sf_dir)
    if name == "latent":
        return _main(spark, sf_dir).transform
    if name == "latent_guarded":
        g = once(spark, sf_dir, "w-guard", lambda: guard.Guard(min_samples=1000, c=-12.0).fit(text.snippets(tr, 20).withColumn("text", F.col("snippet")), _main(spark, sf_dir)))
        return lambda te: g.predict(te).withColumn("label", F.col("guarded"))
    return once(spark, sf_dir, f"w-system-{name}", lambda: train(name, tr, learned_vocab(spark, sf_dir), counted(spark, sf_dir)) if name == "fixed_split" else train(name, tr))


def ready(spark: SparkSession, sf_dir: str, names: tuple[str, ...], then: Callable[[str], Rows] = lambda name: [], light: tuple[Callable[[], Rows], ...] = (), heavy: tuple[Callable[[], Rows], ...] = ()) -> list[Rows]:
    """Fits the systems side by side, in two chains: embeddings keep cores busy for longest, others wait for many small steps. Those of pyspark.ml keep their rows in memory as the embeddings do,
    so they follow these. A system is tested by `then` as soon as it is fitted. light and heavy are further steps of the two chains; what they give follows that of the systems."""
    train_test(spark, sf_dir)
    last = ("avg_embedding", "tfidf", "svm", "ffn")
    steps: list[tuple] = [(x in last, x, lambda x=x: system(spark, sf_dir, x) and then(x)) for x in names]
    steps += [(chain, (chain, k), f) for chain, more in ((False, light), (True, heavy)) for k, f in enumerate(more)]
    chains = [own for own in ([x for x in steps if not x[0]], [x for x in steps if x[0]]) if own]
    got = dict(x for part in side_by_side(*[lambda own=own: [(key, f()) for _, key, f in own] for own in chains]) for x in part)
    return [got[key] for _, key, _ in steps]


def compare(spark: SparkSession, sf_dir: str, te: DataFrame, names: tuple[str, ...], setting: str = "") -> Rows:
    return [r for rows in ready(spark, sf_dir, names, lambda name: said(system(spark, sf_dir, name)(te), name, setting)) for r in rows]


MAIN = ("latent", "latent_guarded", "avg_embedding", "ngram")


# --- experiments


@workload("w01_in_domain")
def _(s, d):
    """All systems on the same split, fitted in two chains; borrowed vocabularies and the curated lines are parts of these."""
    tr, te = train_test(s, d)

    def curated() -> Rows:
        own = tr.join(read_table(s, d, "labels").where("quality = 0").select("doc_id"), "doc_id", "left_anti").dropDuplicates(["text"])
        return said(AvgEmbedding.fit(own, epochs=EPOCHS).transform(te), "avg_embedding_curated")

    names = (*MAIN, "fixed_split", "ngram_interp", "ngram_backoff", "tfidf", "svm", "ffn", "majority")
    few = tuple(lambda x=x: borrowing(s, d, x, f"latent, {x}")[0] for x in list(borrowed(s, d))[:3])
    *out, last = ready(s, d, names, lambda name: said(system(s, d, name)(te), name), few, (curated,))
    return [r for rows in (*out[: len(names)], last, *out[len(names) :]) for r in rows]


@workload("w02_label_subset")
def _(s, d):
    """Three labels: systems refitted on them, the full model restricted to them, and the full model on the same rows."""
    tr, te = train_test(s, d)
    three = ["de", "en", "fr"]
    part, few = te.where(F.col("gold").isin(three)), tr.where(F.col("label").isin(three))
    m, *fitted = side_by_side(lambda: _main(s, d), *[lambda n=n: train(n, few) for n in ("avg_embedding", "ffn", "ngram")])
    found = {"latent": train("latent", few, m.vocab), **dict(zip(("avg_embedding", "ffn", "ngram"), fitted, strict=True))}
    out = said(m.subset(three).transform(part), "latent", "restricted") + said(m.transform(part), "latent", "unrestricted")
    for name, f in found.items():
        out += said(f(part), name, "refitted")
    # a detector that covers some labels only, on rows of all
    return out + said(found["ffn"](te), "ffn", "covers three, all rows")


def pages_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = read_table(spark, sf_dir, "pages", ["page_id", "html"])
    return p.select(F.col("page_id").alias("row_id"), text.page_lang(F.col("html")).alias("gold"), F.regexp_extract("html", "<title>(.*?)</title>", 1).alias("title"), text.html_to_text(F.col("html")).alias("text"))


@workload("w03_web_text")
def _(s, d):
    """Page text, with other sources than the training lines."""
    return compare(s, d, stash(pages_text(s, d), "pages"), (*MAIN, "fixed_split", "tfidf"), "pages")


def dialect_data(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """14 varieties. As in the published set three of them have few test rows: 16, 16 and 4."""

    def make() -> tuple[DataFrame, DataFrame]:
        dl = stash(text.dialects(base(spark, sf_dir)), "dialects")
        te = dl.where("bucket = 0")
        for label, n in (("de-1", 16), ("de-2", 16), ("de-3", 4)):
            te = te.where(F.col("label") != label).unionByName(text.sample_j(te.where(F.col("label") == label), n, 2))
        return stash(dl.where("bucket >= 2"), "train"), stash(te.select("row_id", F.col("label").alias("gold"), "text", "n_chars"), "test")

    return once(spark, sf_dir, "w-dialects", make)


def dialect_model(spark: SparkSession, sf_dir: str) -> SegmentModel:
    return once(spark, sf_dir, "w-dialect-model", lambda: fit(dialect_data(spark, sf_dir)[0], learned_vocab(spark, sf_dir)))


def dialect_guard(spark: SparkSession, sf_dir: str) -> guard.Guard:
    m = dialect_model(spark, sf_dir)
    return once(spark, sf_dir, "w-dialect-guard", lambda: guard.Guard(min_samples=400, c=-12.0).fit(dialect_data(spark, sf_dir)[0], m))


def family_of(label) -> F.Column:
    return F.split(label, "-")[0]


@workload("w04_dialects")
def _(s, d):
    tr, te = dialect_data(s, d)
    m, _, embedding, ngram = side_by_side(lambda: dialect_model(s, d), lambda: dialect_guard(s, d), lambda: train("avg_embedding", tr), lambda: train("ngram", tr))
    parents = s.createDataFrame([(x, x.split("-")[0]) for x in m.labels()], "label string, family string")
    out = []
    found = {"latent": m.transform, "latent_guarded": lambda df: dialect_guard(s, d).predict(df).withColumn("label", F.col("guarded")), "avg_embedding": embedding, "ngram": ngram}
    for name, f in found.items():
        t = stash(metrics.evaluate(f(te)), "measures")
        out += long(metrics.family_means(t, parents).na.fill({"family": "all", "label": "mean"}).withColumn("at", F.concat_ws("/", "family", "label")), name, "at", ["f1"])
    for fam in sorted({x.split("-")[0] for x in m.labels()}):  # inside one family, as its organisers score
        own = te.where(family_of(F.col("gold")) == fam)
        out += said(train("svm", tr.where(F.col("family") == fam))(own), "svm", fam) + said(m.subset([x for x in m.labels() if x.startswith(fam)]).transform(own), "latent", fam)
    return out


@workload("w05_sample_efficiency")
def _(s, d, sizes=(5, 10, 25, 50, 100, 200, 300, 400, 500), seeds=(1, 2, 3, 4, 5)):
    """Every size, seed and system on the same subsets. A run's labels are labels of their own (label, size, seed), so all runs of a system are fitted in one job and scored in one; the best label of each run is
    its prediction. Sizes above what a label has take all its lines."""
    _, te = train_test(s, d)
    te = stash(te.select("row_id", "gold", "text"), "test")
    pool = base(s, d).where("bucket >= 2")
    v = learned_vocab(s, d)
    runs = s.createDataFrame([(j, seed) for j in sizes for seed in seeds], "j int, seed int")
    order = F.md5(F.concat_ws(":", F.col("seed").cast("string"), F.col("doc_id").cast("string"), F.col("line_no").cast("string")))
    ranked = pool.join(F.broadcast(s.createDataFrame([(x,) for x in seeds], "seed int"))).withColumn("rank", F.row_number().over(Window.partitionBy("label", "seed").orderBy(order, "doc_id", "line_no")))  # a handful of seeds
    rows = ranked.where(F.col("rank") <= max(sizes)).join(F.broadcast(runs), "seed").where("rank <= j")
    rows = stash(rows.select("j", "seed", "label", "doc_id", "text", F.concat_ws("|", "label", F.col("j").cast("string"), F.col("seed").cast("string")).alias("own")), "runs")

    own = rows.select(F.col("own").alias("label"), "text")
    m, ngram = fit(own, v), NgramLM.fit(own)
    found = {"latent": _picked_latent(m, te, len(sizes) * len(seeds)), "ngram": _picked_ngram(ngram, te)}
    # one split for all labels of a run: the pooled distribution of the run
    pooled = fit(rows.select(F.concat_ws("|", F.lit("*"), F.col("j").cast("string"), F.col("seed").cast("string")).alias("label"), "text"), v)
    found["fixed_split"] = _fixed_runs(rows, te, pooled, v)
    found["avg_embedding"] = fit_runs(rows, te, ["j", "seed"], EPOCHS)
    out = []
    for name, pred in found.items():
        table = pred.groupBy("j", "seed").agg(metrics.right().alias("accuracy"))
        out += [(name, f"J={r['j']}", k, r[k]) for r in metrics.mean_sd(table, ["j"], "accuracy").orderBy("j").collect() for k in ("mean", "sd")]
    return out


def _pick(scores: DataFrame, te: DataFrame) -> DataFrame:
    """(j, seed, gold, label): the best label of each run, ties to the smaller one, from (row_id, own, score)."""
    parts = F.split("own", r"\|")
    one = scores.select("row_id", parts[0].alias("label"), parts[1].cast("int").alias("j"), parts[2].cast("int").alias("seed"), "score")
    best = one.groupBy("row_id", "j", "seed").agg(F.min_by("label", F.struct((-F.col("score")).alias("s"), "label")).alias("label"))
    return best.join(te.select("row_id", "gold"), "row_id").select("j", "seed", "gold", "label")


PICKED = T.StructType([T.StructField("j", T.IntegerType()), T.StructField("seed", T.IntegerType()), T.StructField("gold", T.StringType()), T.StructField("label", T.StringType())])


def _picker(owns: list[str]) -> Callable[[pa.Array, np.ndarray, np.ndarray], list]:
    """What _pick gives, within a scan: from the gold labels of some rows, the scores of their own labels (label|j|seed, in the columns of owns) and which rows have scores."""
    parts = [x.rsplit("|", 2) for x in owns]
    runs, labels = sorted({(int(j), int(seed)) for _, j, seed in parts}), sorted({x for x, _, _ in parts})
    col = np.full((len(runs), len(labels)), -1)
    for k, (x, j, seed) in enumerate(parts):
        col[runs.index((int(j), int(seed))), labels.index(x)] = k

    def said(gold: pa.Array, total: np.ndarray, has: np.ndarray) -> list:
        s = np.where(col >= 0, total[has][:, col], lattice.NEVER)
        best = s.argmax(axis=2).ravel().astype(np.int32)
        each = lambda k: pa.array(np.tile(np.array([r[k] for r in runs], np.int32), int(has.sum())))
        return [each(0), each(1), gold.take(pa.array(np.repeat(np.flatnonzero(has), len(runs)))), pa.DictionaryArray.from_arrays(best, pa.array(labels, pa.string())).dictionary_decode()]

    return said


def _picked_latent(m: SegmentModel, te: DataFrame, runs: int) -> DataFrame:
    """The labels of all runs meet a text in one scan; more of them than a pass has go through the lists of a row's best labels."""
    pick = _picker(m.labels())
    got = score.best_of_runs(te.select("gold", "text"), m, "text", PICKED, lambda row, total, has: pick(row.field("gold"), total, has))
    if got is not None:
        return got
    top = m.transform(te, topk=10 * runs).select("row_id", F.explode("topk").alias("x"))
    return _pick(top.select("row_id", F.col("x.label").alias("own"), "x.score"), te)


def _picked_ngram(m: NgramLM, te: DataFrame) -> DataFrame:
    if (values := m.values()) is None:
        return _pick(m.scores(te, "row_id").withColumnRenamed("label", "own"), te)
    pick = _picker(values.labels)
    return map_scores(te.select("gold", "text"), "text", values, PICKED, lambda b, total, has: pick(b.column("gold"), total, has))


def _fixed_runs(rows: DataFrame, te: DataFrame, pooled: SegmentModel, v: DataFrame, k: float = 0.5) -> DataFrame:
    """(j, seed, gold, label) of naive Bayes over the split that each run's pooled distribution gives."""
    split = lambda c: F.concat(F.lit("*"), F.regexp_extract(c, r"(\|\d+\|-?\d+)$", 1))
    chunks = stash(text.chunk_counts(rows.select(F.col("own").alias("label"), "text")).withColumn("split", split("label")), "chunks")
    table = stash(token_counts(chunks, pooled).groupBy("label", "token").agg(F.sum("c").alias("c")), "tokens")
    totals = stash(table.groupBy("label").agg(F.sum("c").alias("t")), "totals")
    size = v.count()
    if (made := kernel_of(pooled, table, totals, size, k, {r["label"]: r["split"] for r in totals.select("label", split("label").alias("split")).collect()})) is not None:
        sent, pick = te.sparkSession.sparkContext.broadcast(made[1]), _picker(made[0])
        cut = F.filter(pooled.chunks("text"), lambda c: c != "")
        return score.scan(te.select("gold", "text"), cut, lambda: [score.SplitKernel(*sent.value)], len(made[0]), PICKED, lambda row, total, has: pick(row.field("gold"), total, has))
    # more values than are sent: tokens meet them by joins
    b = stash(te.select("row_id", F.explode(pooled.chunks("text")).alias("chunk")).where("chunk <> ''").groupBy("row_id", "chunk").agg(F.count(F.lit(1)).alias("m")), "test")
    cuts = score.segment(b.select("chunk").distinct(), score.whole_chunks(pooled), "chunk")
    cuts = stash(cuts.select("chunk", F.col("label").alias("split"), "tokens"), "cuts")
    seen = b.join(cuts, "chunk").select("row_id", "split", F.explode("tokens").alias("token"), "m").groupBy("row_id", "split", "token").agg(F.sum("m").alias("m"))
    owns = totals.withColumn("split", split("label"))
    cells = seen.join(F.broadcast(owns), "split").join(table, ["label", "token"], "left")  # a row for each label of a run
    value = fixed_point(F.coalesce("c", F.lit(0)), F.col("t"), k, size)
    return _pick(cells.groupBy("row_id", F.col("label").alias("own")).agg(F.sum(F.col("m") * value).alias("score")), te)


@workload("w06_out_of_domain")
def _(s, d):
    p = stash(pages_text(s, d), "pages")
    out = compare(s, d, stash(p.select("row_id", "gold", F.col("title").alias("text")).where("text <> ''"), "titles"), MAIN, "titles") + compare(s, d, p, MAIN, "pages")
    c = _main(s, d).transform(read_table(s, d, "conversations", ["conv_id", "turn", "text"])).groupBy("conv_id", "label").agg(F.count(F.lit(1)).alias("n"))
    c = c.groupBy("conv_id").agg(F.sum("n").alias("n"), F.max("n").alias("top")).where("n > 1")
    return [*out, ("latent", "conversations", "agreement", c.agg(F.avg(F.col("top") / F.col("n"))).first()[0])]


@workload("w07_length")
def _(s, d):
    _, te = train_test(s, d, length=0)
    return [r for rows in ready(s, d, MAIN, lambda name: long(metrics.accuracy_by_length(system(s, d, name)(te)), name, "band", ["accuracy", "rows"])) for r in rows]


@workload("w08_corruption")
def _(s, d, rates=(50, 100, 250, 500)):
    """The texts of all rates meet a system in one scan, as soon as it is fitted."""
    src = base(s, d).where("bucket = 0").select("row_id", "doc_id", "line_no", F.col("label").alias("gold"), "text")

    def noisy() -> DataFrame:
        return stash(text.corrupt_each(src, rates).withColumn("row_id", F.concat_ws(":", F.col("row_id").cast("string"), F.col("per_mille").cast("string"))), "noisy")

    def tested(name: str) -> dict[int, float]:
        pred = system(s, d, name)(once(s, d, f"w-noisy-{rates}", noisy))
        return {r["per_mille"]: r["accuracy"] for r in metrics.accuracy_by(pred, "per_mille").collect()}  # a row a rate

    found = dict(zip(MAIN, ready(s, d, MAIN, tested), strict=True))
    return [(name, f"rate={r / 1000}", "accuracy", found[name].get(r)) for r in rates for name in MAIN]


def tokenizer_path(suffix: str) -> str | None:
    """The optional package that ships public tokenizer files says where one lies."""
    try:
        import public_tokenizers
    except ImportError:
        return None
    return public_tokenizers.path(f"{TOKENIZER}.{suffix}")


def borrowed(spark: SparkSession, sf_dir: str) -> dict[str, Callable[[], tuple[DataFrame, dict]]]:
    """Vocabularies from elsewhere, and how text is cut for them; characters (or bytes) that one lacks are added. Each is made when it is first asked for."""
    ch = lambda: counted(spark, sf_dir)
    chars = lambda: once(spark, sf_dir, "w-characters", lambda: stash(vocab.substrings(ch(), 1).select("token"), "characters"))
    with_chars = lambda v: (stash(vocab.number(v.select("token").unionByName(chars())), "vocab"), {})
    bytewise = {"unit": "byte", "prefix_space": True}
    every = vocab.byte_alphabet(spark)

    def far_words() -> DataFrame:
        far = None
        for table, col in (("part", "p_name"), ("nation", "n_name"), ("customer", "c_mktsegment")):
            w = read_table(spark, sf_dir, table, [col]).select(F.explode(F.regexp_extract_all(F.lower(col), F.lit(r"\p{L}+"), 0)).alias("token")).distinct()
            far = w if far is None else far.unionByName(w)
        return far

    jobs: dict[str, Callable[[], tuple[DataFrame, dict]]] = {}
    if path := tokenizer_path("json"):
        jobs["tokenizer file"] = lambda: (stash(vocab.load(spark, f"file://{path}", "tokenizer", every, "byte"), "vocab"), bytewise)
    if ranks := tokenizer_path("tiktoken"):
        jobs["ranked list"] = lambda: (stash(vocab.load(spark, f"file://{ranks}", "ranks", chars()), "vocab"), {})
    jobs |= {"merges_en": lambda: with_chars(vocab.learn_merges(ch().where("label = 'en'"), 300)[0]), "merges_all": lambda: with_chars(vocab.learn_merges(ch(), 300)[0])}
    jobs |= {"far_words": lambda: with_chars(far_words()), "characters": lambda: with_chars(chars()), "bytes": lambda: (stash(vocab.number(every), "vocab"), bytewise)}
    jobs["trigrams"] = lambda: with_chars(vocab.substrings(ch(), 3, 3).orderBy(F.desc("c"), "token").limit(SIZE).select("token"))
    return {name: lambda name=name, make=make: once(spark, sf_dir, f"w-borrowed-{name}", make) for name, make in jobs.items()}


def borrowing(spark: SparkSession, sf_dir: str, name: str, system: str, setting: str = "") -> tuple[Rows, DataFrame]:
    """Measures of a model with a borrowed vocabulary that learned from all training lines, and that vocabulary."""
    tr, te = train_test(spark, sf_dir)
    v, how = borrowed(spark, sf_dir)[name]()
    return said(fit(tr, v, chunks=counted(spark, sf_dir, **how), **how).transform(te), system, setting), v


@workload("w09_borrowed_vocabulary")
def _(s, d):
    """All models learn from all lines, some of them side by side; a model is fitted as soon as its vocabulary is there. Those that are learned take longest and are begun first."""
    _, te = train_test(s, d)
    counted(s, d)

    def one(name: str) -> Rows:
        if name == "own":
            return said(_main(s, d).transform(te), "latent", name)
        rows, v = borrowing(s, d, name, "latent", name)
        return rows + [("latent", name, "tokens", v.count())]

    names = ["own", *borrowed(s, d)]
    order = sorted(names, key=lambda x: x not in ("own", "merges_en", "merges_all"))
    found = dict(zip(order, side_by_side(*[lambda x=x: one(x) for x in order]), strict=True))
    return [r for x in names for r in found[x]]


@workload("w10_vocabulary_size")
def _(s, d, sizes=(256, 512, 1024, 2048, 4096, 8192, 16384)):
    """Each smaller vocabulary is pruned from the next larger, while the model of that one is tested. Nothing runs beside a fit, as its seconds are a result; lines are cut once, before."""
    tr, te = train_test(s, d)
    ch = stash(text.chunk_counts(vocab.sample_per_label(tr, 1000)), "chunks")
    order = sorted(sizes, reverse=True)
    all_, v = side_by_side(lambda: counted(s, d), lambda: vocab.learn(ch, order[0], LONGEST))

    def tested(m: SegmentModel, n: int, seconds: float) -> Rows:
        out = [("latent", f"V={n}", "fit_seconds", seconds), ("latent", f"V={n}", "tokens", m.vocab.count()), ("latent", f"V={n}", "stored", m.size().first()["stored"])]
        return out + [x for x in said(m.transform(te), "latent", f"V={n}") if x[2] in ("macro_f1", "accuracy")]

    out: Rows = []
    for n, smaller in zip(order, [*order[1:], None], strict=True):
        t = time.perf_counter()
        m = fit(tr, v, chunks=all_)
        took = time.perf_counter() - t
        rows, v = side_by_side(lambda m=m, n=n, took=took: tested(m, n, took), lambda v=v, smaller=smaller: smaller and vocab.learn(ch, smaller, LONGEST, start=v))
        out += rows
    return out


def skewed(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame, SegmentModel]:
    """Training lines: all of en, 200 of fr, 50 of de, 10 of es, 40 of a variety of each but en. Validation and test snippets."""

    def make():
        dl = stash(text.dialects(base(spark, sf_dir)).withColumn("label", F.when(F.col("label").endswith("-1") & ~F.col("label").startswith("en"), F.col("label")).otherwise(F.col("family"))), "varieties")
        pool, tr = dl.where("bucket >= 2"), dl.where("bucket >= 2 and label = 'en'")
        for label, n in (("fr", 200), ("de", 50), ("es", 10), ("fr-1", 40), ("de-1", 40), ("es-1", 40)):
            tr = tr.unionByName(text.sample_j(pool.where(F.col("label") == label), n, 1))
        tr = stash(tr, "skewed")
        cut = lambda b: stash(text.snippets(dl.where(f"bucket = {b}"), 20).select("row_id", "doc_id", F.col("label").alias("gold"), F.col("snippet").alias("text"), "n_chars"), "cut")
        return tr, cut(1), cut(0), fit(tr, learned_vocab(spark, sf_dir))

    return once(spark, sf_dir, "w-skewed", make)


SCRIPTS = [(x, "latin") for x in ("en", "fr", "de", "es", "fr-1", "de-1", "es-1")]


@workload("w11_guarded")
def _(s, d, min_samples=100, c=-12.0):
    """Base, each correction alone, both; a group of larger labels of high entropy; constants chosen on validation rows, reported on rows that had no part in the choice."""
    tr, va, te, m = skewed(s, d)
    high = [r[0] for r in guard.high_entropy_group(m.stats, s.createDataFrame(SCRIPTS, "label string, script string"), k=0.5, min_samples=min_samples).collect()]
    out = [("guarded", "", "high_entropy_labels", len(high))]
    snips = stash(text.snippets(tr, 20).withColumn("text", F.col("snippet")), "train")
    make = lambda **kw: guard.Guard(**({"c": c, "min_samples": min_samples} | kw)).fit(snips, m, high=high)
    for name, cap, re in (("base", False, False), ("cap", True, False), ("reexamined", False, True), ("guarded", True, True)):
        p = stash(make(cap=cap, reexam=re).predict(te), "pred")
        out += said(p.withColumn("label", F.col("guarded")), name)
        t = metrics.evaluate(p.select("gold", F.col("guarded").alias("label")))
        out += long(metrics.f1_by_size(t, m.stats, [40, min_samples, 1000]), name, "from_size", ["mean_f1"])
        r = metrics.reexam_counts(p).first()
        out += [(name, "", "looked", r["looked"]), (name, "", "changed", r["changed"])]
    shared = make(shared=True).predict(te)
    out += said(shared.withColumn("label", F.col("guarded")), "guarded", "one threshold for all labels")
    g = make()
    scored = stash(g.model.transform(va), "valid")
    by_q = {q: make(q_max=q).limits for q in (2.0, 5.0, 10.0)}
    grid = stash(guard.tune(scored, by_q, [5.0, 10.0, 20.0]), "grid")
    out += [("tuned", f"q={r['q_max']},A={r['abs_limit']}", "validation_macro_f1", r["macro_f1"]) for r in grid.collect()]
    q, a = guard.choose(grid)
    held = metrics.heldout(te, va.select("row_id"), "row_id")
    for name, limits in (("base", None), ("tuned", by_q[q])):
        p = m.transform(held) if limits is None else guard.reexamine(g.model.transform(held), limits, abs_limit=a).withColumn("label", F.col("guarded"))
        out += said(p, name, "held out")
    return out


@workload("w12_balanced")
def _(s, d):
    """As many test rows of every label as the rarest has."""
    tr, _, te, m = skewed(s, d)
    n = te.groupBy("gold").agg(F.count(F.lit(1)).alias("n")).agg(F.min("n")).first()[0]
    ranked = te.withColumn("r", F.row_number().over(Window.partitionBy("gold").orderBy(F.md5(F.col("row_id").cast("string")))))
    even = stash(ranked.where(F.col("r") <= n).drop("r"), "even")
    p = guard.Guard(c=-12.0, min_samples=100).fit(text.snippets(tr, 20).withColumn("text", F.col("snippet")), m, high=[]).predict(even)
    return said(m.transform(even), "base") + said(p.withColumn("label", F.col("guarded")), "guarded")


@workload("w13_macrolanguage")
def _(s, d):
    """Varieties are merged into their language after the decision, out of domain."""
    tr, p = dialect_data(s, d)[0], stash(pages_text(s, d), "pages")
    m, _, embedding = side_by_side(lambda: dialect_model(s, d), lambda: dialect_guard(s, d), lambda: train("avg_embedding", tr))
    parents = s.createDataFrame([(x, x.split("-")[0]) for x in m.labels()], "label string, macro string")
    found = {"latent": m.transform(p), "latent_guarded": dialect_guard(s, d).predict(p).withColumn("label", F.col("guarded")), "avg_embedding": embedding(p)}
    return [(name, "pages", "macro_accuracy", metrics.macro_accuracy(x, parents).first()[0]) for name, x in found.items()]


@workload("w14_best_vs_marginal")
def _(s, d):
    _, te = train_test(s, d)
    m, out, kept = _main(s, d), [], {}
    for how in ("best", "marginal"):
        kept[how] = stash(m.transform(te, how=how), how)
        t = time.perf_counter()
        m.transform(te, how=how).write.format("noop").mode("overwrite").save()
        out += said(kept[how], how) + [(how, "", "seconds", time.perf_counter() - t)]
    c = metrics.compare_scores(kept["best"], kept["marginal"], "row_id").first()
    return [*out, ("both", "", "same_label", c["same_label"]), ("both", "", "mean_gap", c["mean_gap"])]


@workload("w15_epochs")
def _(s, d, epochs=(1, 5, 25, 100), ranges=((1, 2), (1, 3), (2, 4))):
    """The ranges of n-grams are fitted side by side, and tested while others are fitted."""
    tr, te = dialect_data(s, d)

    def one(lo: int, hi: int) -> list[Rows]:
        fitted = AvgEmbedding.fit_each(tr, epochs, low=lo, high=hi)
        return [[x for x in said(m.transform(te), "avg_embedding", f"epochs={e},n={lo}-{hi}") if x[2] == "macro_f1"] for m, e in zip(fitted, epochs, strict=True)]

    found = side_by_side(*[lambda lo=lo, hi=hi: one(lo, hi) for lo, hi in ranges])
    return [x for k in range(len(epochs)) for own in found for x in own[k]]


def ciphers(df: DataFrame, k: int, label_col: str = "label") -> DataFrame:
    """k copies of each language under letter permutations; every third is written in Greek letters."""
    out = None
    for i in range(k):
        alpha = text.GREEK if i % 3 == 2 else text.LETTERS
        part = df.withColumn("text", text.cipher(F.col("text"), i, alpha)).withColumn(label_col, F.concat(F.col(label_col), F.lit(f"-{i}")))
        out = part if out is None else out.unionByName(part)
    return out


def cipher_data(spark: SparkSession, sf_dir: str, n_labels: int, j: int = 30, test: int = 20) -> tuple[DataFrame, DataFrame]:
    """n_labels labels: copies of the languages under letter permutations, with j training and `test` test lines each."""
    ln, k = base(spark, sf_dir), -(-n_labels // 4)
    own = lambda c: F.col(c).isin([f"{x}-{i}" for i in range(k) for x in ("en", "fr", "de", "es")][:n_labels])
    tr = stash(ciphers(text.sample_j(ln.where("bucket >= 2"), j, 1), k).where(own("label")), "ciphers")
    te = ciphers(text.sample_j(ln.where("bucket = 0"), test, 1).select("row_id", F.col("label").alias("gold"), "text"), k, "gold")
    return tr, stash(te.where(own("gold")), "test")


def latency(f: Predict, te: DataFrame, n: int) -> float:
    """Milliseconds a row, after a first run that starts workers."""
    f(te).write.format("noop").mode("overwrite").save()
    t = time.perf_counter()
    f(te).write.format("noop").mode("overwrite").save()
    return (time.perf_counter() - t) * 1000 / n


@workload("w16_label_set_size")
def _(s, d, labels=(4, 40, 100)):
    out = []
    for n in labels:
        tr, te = cipher_data(s, d, n)
        at, rows = f"L={n}", te.count()
        v = small_vocab(tr, 1000, 4)
        for name in ("latent", "avg_embedding", "ngram"):
            t = time.perf_counter()
            f = train(name, tr, v)
            out.append((name, at, "fit_seconds", time.perf_counter() - t))
            out += [(name, at, "ms_per_row", latency(f, te, rows)), *said(f(te), name, at)]
        m = fit(tr, v)
        edges = lattice.cost(lattice.build(text.chunk_counts(te, "gold").groupBy("chunk").agg(F.sum("n").alias("n")), v), n).first()
        out += [("latent", at, "relaxations", edges["relaxations"]), ("latent", at, "stored", m.size().first()["stored"])]
        if n > 4:
            parents = s.createDataFrame([(x, "greek" if int(x.split("-")[1]) % 3 == 2 else "latin") for x in m.labels()], "label string, family string")
            out += said(decide.hierarchical(te, m, parents), "hierarchical", at)
    return out


@workload("w17_add_label")
def _(s, d):
    tr, te = train_test(s, d)
    v = _main(s, d).vocab
    m = fit(tr.where("label <> 'es'"), v)
    t = time.perf_counter()
    grown = m.add_label(tr.where("label = 'es'"), rounds=ROUNDS)
    took = time.perf_counter() - t
    cols = ["label", "token_id", "logp_fx"]
    old = m.theta.select(*cols).exceptAll(grown.theta.select(*cols)).count()
    return [("latent", "es", "seconds", took), ("latent", "es", "old_rows_changed", old), *said(grown.transform(te), "latent", "grown")]


@workload("w18_error_analysis")
def _(s, d):
    _, _, te, m = skewed(s, d)
    f = metrics.fp_concentration(m.transform(te), guard.small_group(m.stats, 100)).first()
    c = guard.cap_counts(m.stats, -12.0).first()
    return [("base", "", k, f[k]) for k in ("false_positives", "into_groups", "share_ppm", "gold_ppm")] + [("base", "", "floor_slope", metrics.floor_slope(m.stats).first()[0]), ("cap", "", "changed", c[0]), ("cap", "", "unchanged", c[1])]


@workload("w19_curation")
def _(s, d):
    """Labels every line, lays the sure ones out by label, counts them by source and label, and finds documents whose lines change language."""
    p = stash(_main(s, d).transform(base(s, d).withColumnRenamed("label", "gold")), "labelled")
    sure = p.where("margin > 5")
    mixed = relops.change_points(sure, "label").select("doc_id").distinct().count()
    write_labeled(sure.select("doc_id", "line_no", "source", "text", "label"), at := fresh_path(s, "sure"))
    c = s.read.parquet(at).rollup("label", "source").agg(F.count(F.lit(1)).alias("lines"))
    totals = [("latent", f"{r['label'] or 'all'}/{r['source'] or 'all'}", "sure_lines", r["lines"]) for r in c.collect()]  # a row for each label and source
    return [*totals, ("latent", "", "code_mixed_documents", mixed), *said(p, "latent", "all lines")]


@workload("w20_other_classes")
def _(s, d):
    """Quality, toxicity and source as classes of whole documents."""
    docs = read_table(s, d, "documents", ["doc_id", "text", "source"])
    lab = docs.join(read_table(s, d, "labels"), "doc_id")
    out = []
    for name, df in (("quality", lab.withColumn("label", F.col("quality").cast("string"))), ("toxic", lab.withColumn("label", F.col("toxic").cast("string"))), ("source", docs.withColumn("label", F.col("source")))):
        df = stash(df.select("doc_id", "label", "text", text.bucket(F.col("text")).alias("bucket")), name)
        m = fit(df.where("bucket >= 1"), small_vocab(df.where("bucket >= 1"), 1000, 4))
        te = stash(df.where("bucket = 0").withColumnRenamed("label", "gold").withColumn("row_id", F.col("doc_id")), "test")
        out += said(m.transform(te), "latent", name) + said(train("majority", df.where("bucket >= 1"))(te), "majority", name)
    return out


@workload("w21_contamination")
def _(s, d):
    tr, _ = train_test(s, d)
    out = []
    for name, test in (("benchmark", read_table(s, d, "benchmark", ["text"])), ("test", base(s, d).where("bucket = 0").select("text"))):
        r = metrics.contamination(base(s, d).where("bucket >= 2"), test).first()
        out += [("shingles", name, "rows", r["rows"]), ("shingles", name, "contaminated", r["contaminated"])]
    return out


@workload("w22_prior")
def _(s, d):
    """Six characters of a line: so little text that the prior matters."""
    _, te = train_test(s, d, length=6)
    counts = {r[0]: r[1] for r in base(s, d).where("bucket >= 2").groupBy("label").count().collect()}
    total = sum(counts.values())
    m = _main(s, d)
    return said(m.transform(te), "latent", "uniform") + said(m.transform(te, prior={k: n / total for k, n in counts.items()}), "latent", "corpus prior")


@workload("w23_orthography")
def _(s, d):
    _, te = train_test(s, d)
    m = _main(s, d)
    return said(m.transform(te), "latent", "as is") + said(m.transform(te.withColumn("text", text.no_marks(F.col("text")))), "latent", "no marks") + said(m.transform(te.withColumn("text", text.cipher(F.col("text"), 2, text.GREEK))), "latent", "greek letters")


@workload("w24_label_noise")
def _(s, d):
    """Markup of all pages and English lines under the labels of rarer languages."""
    tr, te = train_test(s, d)
    raw = read_table(s, d, "pages", ["page_id", "html"]).select(F.col("page_id").alias("row_id"), text.page_lang(F.col("html")).alias("label"), F.col("html").alias("text")).where("label in ('es', 'de')")
    en = text.sample_j(tr.where("label = 'en'"), 50, 3).select("row_id", F.lit("es").alias("label"), "text")
    noisy = tr.select("row_id", "label", "text").unionByName(raw).unionByName(en)
    out = long(metrics.evaluate(_main(s, d).transform(te)), "clean", "label", ["precision", "recall", "f1"])
    return out + long(metrics.evaluate(fit(stash(noisy, "train"), _main(s, d).vocab).transform(te)), "noisy", "label", ["precision", "recall", "f1"])


@workload("vocab_learned")
def _(s, d):
    """The learned vocabulary against the same number of most frequent substrings."""
    tr, te = train_test(s, d)
    v = learned_vocab(s, d)
    return [("learned", "", "tokens", v.count()), *said(_main(s, d).transform(te), "latent", "learned"), *said(fit(tr, small_vocab(tr, SIZE, LONGEST)).transform(te), "latent", "most frequent")]


def _baseline(name: str):
    def run_(s, d):
        _, te = train_test(s, d)
        return said(system(s, d, name)(te), name)

    return run_


for _name, _system in (("avg_embedding", "avg_embedding"), ("tfidf_linear", "tfidf"), ("svm_family", "svm"), ("shallow_ffn", "ffn")):
    RUNS[_name] = _baseline(_system)


@workload("prune_loss_exact_toy")
def _(s, d):
    """What the log-likelihood falls by without each token of a small vocabulary: exactly, and by the best other split."""
    ch = once(s, d, "toy-chunks", lambda: stash(text.chunk_counts(base(s, d).where("bucket >= 2")).where("n >= 20"), "chunks"))
    v = once(s, d, "toy-vocab", lambda: stash(vocab.base_topk(ch, 60, 2, 3), "vocab"))
    out = []
    for mode in ("exact", "resplit"):
        out += [(mode, r["token"], "loss", round(r["loss"], 3)) for r in vocab.prune_loss(ch, v, mode).collect()]
    return out


@workload("token_bigram")
def _(s, d):
    from .bigram import TokenBigram

    tr, te = train_test(s, d)
    return said(TokenBigram.fit(tr, _main(s, d)).transform(te, "row_id"), "token_bigram")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f"workload_{n}" if n.startswith("w") else n: (lambda s, d, n=n: run(n, s, d)) for n in RUNS}


SEGMENT = score.segment
