"""Measures over predictions (gold, label). One pass with partial sums, then rows in the number of labels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .text import band


def evaluate(pred: DataFrame, gold_col: str = "gold", label_col: str = "label", over: str = "gold") -> DataFrame:
    """(label, tp, fp, fn, tn, precision, recall, f1, fpr). Labels of the gold standard, or with over='model' also those only predicted. 0/0 is 0."""
    pairs = pred.groupBy(F.col(gold_col).alias("gold"), F.col(label_col).alias("label")).agg(F.count(F.lit(1)).alias("n"))
    gold = pairs.groupBy(F.col("gold").alias("l")).agg(F.sum("n").alias("support"), F.sum(F.when(F.col("gold") == F.col("label"), F.col("n")).otherwise(0)).alias("tp"))
    said = pairs.where("label is not null").groupBy(F.col("label").alias("m")).agg(F.sum("n").alias("said"))
    total = pairs.agg(F.sum("n").alias("total"))
    j = gold.join(said, F.col("l") == F.col("m"), "left" if over == "gold" else "full").join(F.broadcast(total))  # total is one row
    z = lambda c: F.coalesce(c, F.lit(0))
    j = j.select(F.coalesce("l", "m").alias("label"), z("tp").alias("tp"), (z("said") - z("tp")).alias("fp"), (z("support") - z("tp")).alias("fn"), "total")
    j = j.withColumn("tn", F.col("total") - F.col("tp") - F.col("fp") - F.col("fn")).drop("total")
    div = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    tp, fp, fn, tn = map(F.col, ("tp", "fp", "fn", "tn"))
    j = j.withColumns({"precision": div(tp, tp + fp), "recall": div(tp, tp + fn), "f1": div(2 * tp, 2 * tp + fp + fn), "fpr": div(fp, fp + tn)})
    return j


def macro(table: DataFrame) -> DataFrame:
    n = F.sum(F.col("tp") + F.col("fn"))
    return table.agg(F.round(F.avg("f1"), 6).alias("macro_f1"), F.round(F.avg("fpr"), 6).alias("macro_fpr"), F.round(F.sum("tp") / n, 6).alias("accuracy"), n.alias("rows"))


def right(gold_col: str = "gold", label_col: str = "label") -> Column:
    return F.avg(F.coalesce((F.col(gold_col) == F.col(label_col)), F.lit(False)).cast("int"))


def accuracy_by(pred: DataFrame, by: str) -> DataFrame:
    return pred.groupBy(by).agg(F.round(right(), 6).alias("accuracy"), F.count(F.lit(1)).alias("rows"))


def accuracy_by_length(pred: DataFrame, n_col: str = "n_chars") -> DataFrame:
    return accuracy_by(pred.withColumn("band", band(F.col(n_col))), "band")


def mean_sd(table: DataFrame, by: list[str], value: str) -> DataFrame:
    return table.groupBy(*by).agg(F.round(F.avg(value), 6).alias("mean"), F.round(F.stddev_samp(value), 6).alias("sd"), F.count(F.lit(1)).alias("repeats"))


def f1_by_size(table: DataFrame, stats: DataFrame, bounds: list[int]) -> DataFrame:
    """Mean F1 of labels by bands of training size; bounds are lower ends after 0."""
    lows = [0, *bounds]
    b = F.lit(None).cast("long")
    for lo in lows:
        b = F.when(F.col("n_samples") >= lo, F.lit(lo).cast("long")).otherwise(b)
    return table.join(F.broadcast(stats.select("label", "n_samples")), "label").withColumn("from_size", b).groupBy("from_size").agg(F.round(F.avg("f1"), 6).alias("mean_f1"), F.count(F.lit(1)).alias("labels"))


def confusion(pred: DataFrame) -> DataFrame:
    return pred.groupBy("gold", "label").agg(F.count(F.lit(1)).alias("n"))


def top_confusions(pred: DataFrame, k: int = 20, large: list[str] | None = None) -> DataFrame:
    c = confusion(pred).where("gold <> label")
    if large is not None:
        c = c.where(F.col("gold").isin(large) & F.col("label").isin(large))
    return c.orderBy(F.desc("n"), "gold", "label").limit(k)


def family_means(table: DataFrame, parents: DataFrame) -> DataFrame:
    """(family, label, f1): rows of labels, means of families, and the mean of all."""
    j = table.join(F.broadcast(parents.select("label", "family")), "label")
    return j.rollup("family", "label").agg(F.round(F.avg("f1"), 6).alias("f1"), F.count(F.lit(1)).alias("labels"))


def macro_accuracy(pred: DataFrame, parents: DataFrame) -> DataFrame:
    """Accuracy after gold and label are both taken to their macrolanguage; unknown ones stand for themselves."""
    a = parents.select(F.col("label").alias("a"), F.col("macro").alias("ma"))
    b = parents.select(F.col("label").alias("b"), F.col("macro").alias("mb"))
    j = pred.join(F.broadcast(a), F.col("gold") == F.col("a"), "left").join(F.broadcast(b), F.col("label") == F.col("b"), "left")
    return j.agg(F.round(F.avg((F.coalesce("ma", "gold") == F.coalesce("mb", "label")).cast("int")), 6).alias("macro_accuracy"), F.count(F.lit(1)).alias("rows"))


def fp_concentration(pred: DataFrame, groups: DataFrame) -> DataFrame:
    """False positives, how many land in the groups, their share, and the groups' share of gold, in millionths."""
    g = groups.select("label", F.lit(1).alias("in_group"))
    j = pred.join(F.broadcast(g), "label", "left").join(F.broadcast(g.select(F.col("label").alias("gold"), F.col("in_group").alias("gold_in"))), "gold", "left")
    fp = F.count_if(F.col("gold") != F.col("label"))
    into = F.count_if((F.col("gold") != F.col("label")) & (F.col("in_group") == 1))
    gold = F.count_if(F.col("gold_in") == 1)
    return j.agg(fp.alias("false_positives"), into.alias("into_groups"), F.floor(into * 1_000_000 / F.greatest(fp, F.lit(1))).alias("share_ppm"), F.floor(gold * 1_000_000 / F.count(F.lit(1))).alias("gold_ppm"))


def floor_slope(stats: DataFrame) -> DataFrame:
    return stats.agg(F.round(F.regr_slope("floor", F.log10("n_tokens")), 6).alias("slope"), F.count(F.lit(1)).alias("labels"))


def reexam_counts(pred: DataFrame) -> DataFrame:
    return pred.agg(F.count_if("looked").alias("looked"), F.count_if(F.col("guarded") != F.col("label")).alias("changed"), F.count(F.lit(1)).alias("rows"))


def compare_scores(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Two prediction sets over the same rows: agreement, and the mean gap of scores."""
    j = a.select(key, F.col("label").alias("la"), F.col("score").alias("sa")).join(b.select(key, F.col("label").alias("lb"), F.col("score").alias("sb")), key)
    return j.agg(F.round(F.avg((F.col("la") == F.col("lb")).cast("int")), 6).alias("same_label"), F.round(F.avg(F.col("sb") - F.col("sa")), 6).alias("mean_gap"), F.count(F.lit(1)).alias("rows"))


def heldout(pool: DataFrame, used: DataFrame, key: str) -> DataFrame:
    return pool.join(used.select(key).distinct(), key, "left_anti")


def contamination(train: DataFrame, test: DataFrame, n: int = 5, text_col: str = "text") -> DataFrame:
    """Test rows, and how many share an n-word shingle with training text."""

    def shingles(df: DataFrame) -> DataFrame:
        w = df.withColumn("w", F.filter(F.split(F.lower(text_col), r"\s+"), lambda x: x != ""))
        return w.where(f"size(w) >= {n}").withColumn("g", F.explode(F.expr(f"transform(sequence(1, size(w) - {n - 1}), i -> array_join(slice(w, i, {n}), ' '))")))

    t = test.withColumn("_id", F.monotonically_increasing_id())
    hit = shingles(t).select("_id", "g").join(shingles(train).select("g").distinct(), "g", "left_semi").select("_id").distinct()
    return t.join(hit.withColumn("hit", F.lit(1)), "_id", "left").agg(F.count(F.lit(1)).alias("rows"), F.count_if(F.col("hit") == 1).alias("contaminated"))


def multilabel_f1(pred: DataFrame, gold_array: str = "golds", label_col: str = "label") -> DataFrame:
    """(label, f1) where a row may carry several gold labels: a prediction is right for a label if the row carries it."""
    said = pred.select(F.col(label_col).alias("label"), F.array_contains(gold_array, F.col(label_col)).alias("ok")).groupBy("label").agg(F.count_if("ok").alias("tp"), F.count_if(~F.col("ok")).alias("fp"))
    gold = pred.select(F.explode(gold_array).alias("label"), F.col(label_col).alias("said")).groupBy("label").agg(F.count_if(F.col("said") != F.col("label")).alias("fn"))
    j = gold.join(said, "label", "left").na.fill(0)
    return j.select("label", F.round(2 * F.col("tp") / F.greatest(2 * F.col("tp") + F.col("fp") + F.col("fn"), F.lit(1)), 6).alias("f1"))
