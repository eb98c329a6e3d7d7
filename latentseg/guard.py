"""Guards for labels with little training data: a shared cap on unseen tokens, and a second look at close predictions into under-fitted labels.

After the cap scores are no longer normalised, so posteriors over them are approximate. Guards can hurt out of domain; they are opt-in."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import decide
from .io import stash
from .model import SegmentModel


def cap_unseen(model: SegmentModel, c: float = -17.0) -> SegmentModel:
    return model.cap_unseen(c)


def small_group(stats: DataFrame, min_samples: int = 18_000) -> DataFrame:
    return stats.where(F.col("n_samples") < min_samples).select("label")


def high_entropy_group(stats: DataFrame, parents: DataFrame | None = None, k: float = 3.0, min_samples: int = 18_000, labels: list[str] | None = None) -> DataFrame:
    """Larger labels whose entropy lies over the median of their script by more than k median absolute deviations; or the labels given. The one part
    that compares labels with each other."""
    if labels is not None:
        return stats.where(F.col("label").isin(labels)).select("label")
    s = stats.select("label", "n_samples", "entropy")
    s = s.join(F.broadcast(parents.select("label", "script")), "label", "left") if parents is not None else s.withColumn("script", F.lit("all"))
    mid = s.groupBy("script").agg(F.expr("percentile(entropy, 0.5)").alias("mid"))
    s = s.join(mid, s["script"].eqNullSafe(mid["script"])).drop(mid["script"])
    mad = s.groupBy("script").agg(F.expr("percentile(abs(entropy - mid), 0.5)").alias("mad"))
    s = s.join(mad, s["script"].eqNullSafe(mad["script"])).drop(mad["script"])
    return s.where((F.col("n_samples") >= min_samples) & (F.col("entropy") - F.col("mid") > k * F.col("mad")) & (F.col("mad") > 0)).select("label")


def quantile_rank(n_samples: Column, in_small: Column, q_max: float, min_samples: int) -> Column:
    """Percentile for a label's threshold: falls with its size in the small group, constant in the other."""
    return F.when(in_small, q_max * (1 - n_samples / min_samples)).otherwise(F.lit(q_max))


def thresholds(margins: DataFrame, stats: DataFrame, small: DataFrame, high: DataFrame, q_max: float = 5.0, min_samples: int = 18_000, shared: bool = False) -> DataFrame:
    """(label, grp, q, delta) from training margins (label, margin) on which the label is top. A label without any gets 0, so it is never looked at again.
    shared: one threshold at q_max over the margins of both groups."""
    grp = small.select("label", F.lit("small").alias("grp")).unionByName(high.select("label", F.lit("high").alias("grp")))
    g = stats.select("label", "n_samples").join(grp, "label").withColumn("q", quantile_rank(F.col("n_samples"), F.col("grp") == "small", q_max, min_samples))
    if shared:
        one = margins.join(grp, "label", "left_semi").agg(F.expr(f"percentile(margin, {q_max / 100})").alias("delta"))
        return g.join(F.broadcast(one)).select("label", "grp", "q", F.coalesce("delta", F.lit(0.0)).alias("delta"))  # one row
    delta = percentiles(margins, g.select("label", "q"))
    return g.join(delta, "label", "left").select("label", "grp", "q", F.coalesce("delta", F.lit(0.0)).alias("delta"))


def percentiles(margins: DataFrame, q: DataFrame) -> DataFrame:
    """(label, delta): for each label the exact q-th percentile of its margins, interpolated. Margins are counted in steps that grow with them, about a thousand to a doubling; only those that share a step with the
    wanted ranks are put in order, so no task sees all rows of a label."""
    m = margins.join(F.broadcast(q), "label").select("label", "q", "margin", F.floor(F.log2(1 + F.greatest("margin", F.lit(0.0))) * 1024).cast("long").alias("step"))
    each = Window.partitionBy("label")
    steps = m.groupBy("label", "q", "step").agg(F.count(F.lit(1)).alias("n"))
    steps = steps.withColumn("upto", F.sum("n").over(each.orderBy("step"))).withColumn("pos", F.col("q") / 100 * (F.sum("n").over(each) - 1))
    held = (F.col("upto") > F.floor("pos")) & (F.col("upto") - F.col("n") <= F.ceil("pos"))
    near = stash(steps.where(held).select("label", "step", "pos", (F.col("upto") - F.col("n")).alias("before")), "steps")
    d = m.join(F.broadcast(near), ["label", "step"]).groupBy("label", "step", "margin", "pos", "before").agg(F.count(F.lit(1)).alias("n"))  # two steps a label at most
    d = d.withColumn("upto", F.col("before") + F.sum("n").over(Window.partitionBy("label", "step").orderBy("margin")))
    at = lambda p: F.min(F.when(F.col("upto") > p, F.col("margin")))
    ends = d.groupBy("label").agg(F.first("pos").alias("pos"), at(F.floor("pos")).alias("lo"), at(F.ceil("pos")).alias("hi"))
    return ends.select("label", (F.col("lo") + (F.col("pos") - F.floor("pos")) * (F.col("hi") - F.col("lo"))).alias("delta"))


def reexamine(df: DataFrame, limits: DataFrame, k: int = 5, abs_limit: float = 10.0) -> DataFrame:
    """Adds looked and guarded to rows with topk, label and margin: a prediction into a group with a margin under its threshold goes to the first of the k best labels that is in
    neither group and within abs_limit of the winner; if there is none it stays. A map over rows; limits has a row a label."""
    flat = limits.agg(F.map_from_entries(F.collect_list(F.struct("label", "delta"))).alias("_delta"))
    j = df.join(F.broadcast(flat))  # one row with an entry a label
    delta = F.col("_delta")[F.col("label")]
    looked = F.coalesce(F.col("margin") < delta, F.lit(False))
    top = F.get("topk", F.lit(0))["score"]
    outside = F.filter(F.slice("topk", 1, k), lambda x: F.col("_delta")[x["label"]].isNull() & (top - x["score"] <= abs_limit))
    return j.withColumn("looked", looked).withColumn("guarded", F.when(looked & (F.size(outside) > 0), F.get(outside, F.lit(0))["label"]).otherwise(F.col("label"))).drop("_delta")


@dataclass
class Guard:
    c: float = -17.0
    min_samples: int = 18_000
    q_max: float = 5.0
    k: int = 5
    abs_limit: float = 10.0
    shared: bool = False
    cap: bool = True
    reexam: bool = True
    limits: DataFrame | None = None
    model: SegmentModel | None = None

    def fit(self, train: DataFrame, model: SegmentModel, label_col: str = "label", text_col: str = "text", parents: DataFrame | None = None, high: list[str] | None = None) -> Guard:
        """Thresholds from the capped model's margins on the training rows of the grouped labels alone."""
        capped = model.cap_unseen(self.c) if self.cap else model
        small = small_group(model.stats, self.min_samples)
        tall = high_entropy_group(model.stats, parents, min_samples=self.min_samples, labels=high)
        own = train.select(F.col(label_col).alias("gold"), F.col(text_col).alias("text")).join(F.broadcast(small.unionByName(tall)), F.col("gold") == F.col("label"), "left_semi")
        scored = capped.transform(own).where("label = gold").select("label", "margin")
        limits = stash(thresholds(scored, model.stats, small, tall, self.q_max, self.min_samples, self.shared), "limits")
        return replace(self, limits=limits, model=capped)

    def add_label(self, train: DataFrame, model: SegmentModel, label: str, **cols: str) -> Guard:
        """The threshold of a new label alone; those of the others stay."""
        fresh = self.fit(train.where(F.col(cols.get("label_col", "label")) == label), model, high=[], **cols)
        own = fresh.limits.where(F.col("label") == label)
        return replace(fresh, limits=self.limits.where(F.col("label") != label).unionByName(own))

    def predict(self, df: DataFrame, text_col: str = "text") -> DataFrame:
        """transform() of the capped model, then looked and guarded."""
        scored = self.model.transform(df, text_col, topk=self.k)
        if not self.reexam:
            return scored.withColumns({"looked": F.lit(False), "guarded": F.col("label")})
        return reexamine(scored, self.limits, self.k, self.abs_limit)


def choose(grid: DataFrame) -> tuple[float, float]:
    """(q_max, abs_limit) of the best macro F1 of a grid that tune() gives; ties to the smaller constants."""
    r = grid.orderBy(F.desc("macro_f1"), "q_max", "abs_limit").first()
    return r["q_max"], r["abs_limit"]


def tune(valid: DataFrame, limits_by_q: dict[float, DataFrame], abs_limits: list[float], gold_col: str = "gold") -> DataFrame:
    """(q_max, abs_limit, macro_f1) per grid point over stored topk lists: nothing is scored again."""
    from . import metrics

    rows = None
    for q, limits in limits_by_q.items():
        for a in abs_limits:
            pred = reexamine(valid, limits, abs_limit=a).select(F.col(gold_col).alias("gold"), F.col("guarded").alias("label"))
            m = metrics.macro(metrics.evaluate(pred, "gold")).select(F.lit(q).alias("q_max"), F.lit(a).alias("abs_limit"), "macro_f1")
            rows = m if rows is None else rows.unionByName(m)
    return rows


def cap_counts(stats: DataFrame, c: float = -17.0) -> DataFrame:
    return stats.agg(F.count_if(F.col("floor") > c).alias("changed"), F.count_if(F.col("floor") <= c).alias("unchanged"))
