"""Quality rules with adaptive thresholds.

Per document the rules look at five integer ratios. For each (lang, source) a mergeable sketch of every ratio is
kept: counts per log-linear bucket, exact below 512 and within 1/256 above. Sketches of parts add up, so the sketch of a language or of
everything is a sum of rows and new data only add counts. A quantile of a group is its sketch's, drawn towards that of its language as PRIOR further rows would
draw it, and a language's towards that of all rows; so there is no size at which the rule changes, and a group of few rows goes by its language. The fence of a ratio
lies REACH spreads beyond the upper of two quantiles, a spread being their distance. Documents are joined with the fences of their group and filtered.

Defined cases: a null text counts as empty and fails the base rules; null lang or source form groups of their own; repeated rows are
judged alike; an empty table gives an empty result; other columns pass through, whatever they are called, except those named (in any case) like
an added column, which are replaced by measure() and judge() and kept by filter_quality().
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..io import join_small, read_table, stash
from .common import SPACES, UPPER, beside, whole, words_of

BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
#: Ratio -> (lower and upper quantile in per cent, whether the low side has a fence too). Ratios are per mille but word_len (per cent of a character). Symbols and word
#: length go by the body of their values, as junk may be a tenth of a group; most documents repeat nothing, so for repetition, as for capitals, the tail sets the scale.
RATIOS = {"r_symbols": (25, 75, False), "r_shout": (50, 95, False), "r_dup_lines": (50, 99, False), "r_repeats": (50, 99, False), "r_word_len": (25, 75, True)}
QUANTILES = sorted({q for a, b, _ in RATIOS.values() for q in (a, b)})
REACH = 3
#: Rows that a parent's quantiles weigh in those of a group.
PRIOR = 100
#: Stands in for a spread of zero only.
NO_SPREAD = 5


def measure(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds BASE, base_failed and the ratios. Whole texts, built-in functions only; no shuffle."""
    added = {*BASE, *RATIOS, "base_failed"}
    text = F.col("t")
    df = docs.select(beside(docs, added), whole(text_col).alias("t"))
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.length(F.translate(x, SPACES, "")) > 0)
    df = df.select("row", "t", words_of(text).alias("w"), lines.alias("l"))
    w, n = F.col("w"), F.size("w")
    windows = F.when(n >= 3, F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))).otherwise(F.array().cast("array<bigint>"))
    gone = lambda chars: (F.length("t") - F.length(F.translate(text, chars, ""))).cast("long")
    df = df.select(
        "row",
        n.cast("long").alias("n_words"),
        F.length(F.translate(text, SPACES, "")).cast("long").alias("word_chars"),
        gone("#*$%&|<>").alias("n_symbols"),
        gone(UPPER + "!").alias("shout"),
        F.size("l").cast("long").alias("n_lines"),
        (F.size("l") - F.size(F.array_distinct("l"))).cast("long").alias("n_dup_lines"),
        windows.alias("h"),
    )
    df = df.withColumn("d", F.size("h") - F.size(F.array_distinct("h")))
    df = df.withColumn("n_repeat_words", F.when(F.col("d") > 0, _covered(F.col("h"))).otherwise(F.lit(0)).cast("long"))
    share = lambda a, b, unit: F.expr(f"({unit} * {a}) div greatest({b}, 1L)")
    found = df.select(
        "row",
        *BASE,
        ((F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))).alias("base_failed"),
        share("n_symbols", "word_chars", 1000).alias("r_symbols"),
        share("shout", "word_chars", 1000).alias("r_shout"),
        share("n_dup_lines", "n_lines", 1000).alias("r_dup_lines"),
        share("n_repeat_words", "n_words", 1000).alias("r_repeats"),
        share("word_chars", "n_words", 100).alias("r_word_len"),
    )
    # a generated row: filters on measures stay above it, else the optimiser would repeat their expressions inside each other
    made = F.explode(F.array(F.struct(*[c for c in found.columns if c != "row"]))).alias("m")
    return found.select("row", made).select("row.*", "m.*")


def _covered(hashes: Column) -> Column:
    """Words that lie in some window which occurs twice or more: sort windows, keep places with an equal neighbour, unite their words."""
    ordered = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def twice(o: Column) -> Column:
        same = lambda x, j: F.coalesce(F.get(o, j)["h"] == x["h"], F.lit(False))
        places = F.filter(o, lambda x, j: same(x, j - 1) | same(x, j + 1))
        return F.size(F.array_distinct(F.flatten(F.transform(places, lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2)))))

    # a one-element array binds the sorted windows once
    return F.get(F.transform(F.array(ordered), twice), F.lit(0))


def bucket(x: Column) -> Column:
    """Log-linear bucket: the nine leading bits of a number."""
    cut = F.greatest(F.lit(0), F.length(F.bin(x)) - 9)
    power = F.expr("1L") * F.pow(F.lit(2.0), cut).cast("long")
    return F.floor(x / power).cast("long") * power


def sketch(measured: DataFrame, groups: list[str]) -> DataFrame:
    """(groups, ratio, bucket, n) of the rows that pass the base rules. Merge two sketches by adding n."""
    rows = measured.where(~F.col("base_failed")).select(*groups, F.explode(F.array(*[F.struct(F.lit(r).alias("ratio"), bucket(F.col(r)).alias("bucket")) for r in RATIOS])).alias("x"))
    return rows.groupBy(*groups, "x.ratio", "x.bucket").agg(F.count(F.lit(1)).alias("n"))


def merge(sketches: DataFrame, groups: list[str]) -> DataFrame:
    return sketches.groupBy(*groups, "ratio", "bucket").agg(F.sum("n").alias("n"))


def quantiles(sketches: DataFrame, groups: list[str]) -> DataFrame:
    """(groups, ratio, rows, p<q> for each of QUANTILES) of each sketch; a window sees one sketch, at most some thousand buckets."""
    each = Window.partitionBy(*groups, "ratio")
    cum = sketches.withColumn("upto", F.sum("n").over(each.orderBy("bucket"))).withColumn("rows", F.sum("n").over(each))
    at = lambda percent: F.min(F.when(100 * F.col("upto") >= percent * F.col("rows"), F.col("bucket")))
    return cum.groupBy(*groups, "ratio").agg(F.max("rows").alias("rows"), *[at(q).alias(f"p{q}") for q in QUANTILES])


def drawn(own: DataFrame, parent: DataFrame, on: list[str]) -> DataFrame:
    """The quantiles of groups, with those of their parents as PRIOR further rows. Whole numbers, so every engine agrees."""
    up = parent.select(F.col("ratio").alias("up_ratio"), *[F.col(c).alias(f"up_{c}") for c in on], *[F.col(f"p{q}").alias(f"up{q}") for q in QUANTILES])
    same = F.col("ratio") == F.col("up_ratio")
    for c in on:
        same = same & F.col(c).eqNullSafe(F.col(f"up_{c}"))
    both = own.join(F.broadcast(up) if not on else up, same)  # without keys it is a row a ratio
    return both.select(*[c for c in own.columns if c not in {f"p{q}" for q in QUANTILES}], *[F.expr(f"(rows * p{q} + {PRIOR} * up{q}) div (rows + {PRIOR})").alias(f"p{q}") for q in QUANTILES])


def thresholds(measured: DataFrame, lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """(t_lang, t_source, hi_<ratio>, lo_<ratio>): one row per (lang, source) that has rows passing the base rules."""
    groups = ["t_lang", "t_source"]
    fine = stash(sketch(measured.select(F.col(lang_col).alias("t_lang"), F.col(source_col).alias("t_source"), "base_failed", *RATIOS), groups), "sketch")
    by_lang = drawn(quantiles(merge(fine, ["t_lang"]), ["t_lang"]), quantiles(merge(fine, []), []), [])
    q = drawn(quantiles(fine, groups), by_lang, ["t_lang"])
    wide = []
    for ratio, (low, high, below) in RATIOS.items():
        a, b = F.col(f"p{low}"), F.col(f"p{high}")
        spread = REACH * F.when(b > a, b - a).otherwise(F.lit(NO_SPREAD))
        mine = F.col("ratio") == ratio
        wide.append(F.max(F.when(mine, b + spread)).alias(f"hi_{ratio}"))
        if below:
            wide.append(F.max(F.when(mine, a - spread)).alias(f"lo_{ratio}"))
    return q.groupBy(*groups).agg(*wide)


def judge(measured: DataFrame, bounds: DataFrame, lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """Adds kept: the base rules hold and no ratio lies beyond its group's fences."""
    packed = measured.select(beside(measured, {"kept"}), F.col(lang_col).alias("j_lang"), F.col(source_col).alias("j_source"), "base_failed", *RATIOS)
    on = F.col("j_lang").eqNullSafe(F.col("t_lang")) & F.col("j_source").eqNullSafe(F.col("t_source"))
    fine = F.lit(True)
    for ratio, (_, _, below) in RATIOS.items():
        fine = fine & (F.col(ratio) <= F.col(f"hi_{ratio}"))
        if below:
            fine = fine & (F.col(ratio) >= F.col(f"lo_{ratio}"))
    return join_small(packed, bounds, on).select("row.*", (~F.col("base_failed") & F.coalesce(fine, F.lit(True))).alias("kept"))


def filter_quality(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """The rows of docs that are kept, with the columns of docs. Texts are measured once: rows that pass the base rules are written with their measures."""
    one = docs.select(F.struct("*").alias("doc"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"), F.col(source_col).alias("source"))
    passed = stash(measure(one).where("not base_failed").drop("text"), "measured")
    return judge(passed, stash(thresholds(passed), "fences")).where("kept").select("doc.*")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source"])
    measured = stash(measure(docs).drop("text"), "measured")
    return judge(measured, stash(thresholds(measured), "fences")).select("doc_id", *BASE, "base_failed", "kept")


_CUM = """select {keys} ratio, max(total) as rows, {quantiles}
    from (select *, sum(n) over (partition by {keys} ratio order by bucket) as upto, sum(n) over (partition by {keys} ratio) as total
          from (select {keys} ratio, bucket, count(*) as n from b group by all)) group by all"""
_CUM = _CUM.replace("{quantiles}", ", ".join(f"min(case when 100 * upto >= {q} * total then bucket end) as p{q}" for q in QUANTILES))
_PULL = ", ".join(f"((x.rows * x.p{q} + {PRIOR} * y.p{q}) // (x.rows + {PRIOR}))::bigint as p{q}" for q in QUANTILES)
_AT = lambda k: "case ratio " + " ".join(f"when '{r}' then p{v[k]}" for r, v in RATIOS.items()) + " end"
OP9_SQL = f"""
with t as (select doc_id, lang, source, coalesce(text, '') as text from documents),
w as (select *, list_filter(regexp_split_to_array(text, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') as w,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) as l from t),
g as (select doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as g from (select doc_id, w, unnest(range(1, len(w) - 1)) as i from w)),
r as (select doc_id, count(distinct p) as n_repeat_words from (
        select doc_id, unnest([i, i + 1, i + 2]) as p from (select *, count(*) over (partition by doc_id, g) as c from g) where c > 1) group by doc_id),
m as (select w.doc_id, lang, source, len(w)::bigint as n_words, length(regexp_replace(text, '[\\x20\\x09-\\x0D]', '', 'g'))::bigint as word_chars,
        (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols,
        (length(text) - length(regexp_replace(text, '[A-Z!]', '', 'g')))::bigint as shout, len(l)::bigint as n_lines,
        (len(l) - len(list_distinct(l)))::bigint as n_dup_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words from w left join r using (doc_id)),
q as (select *, (n_words < 50 or 100 * n_repeat_words > 50 * n_words) as base_failed, 1000 * n_symbols // greatest(word_chars, 1) as r_symbols,
        1000 * shout // greatest(word_chars, 1) as r_shout, 1000 * n_dup_lines // greatest(n_lines, 1) as r_dup_lines,
        1000 * n_repeat_words // greatest(n_words, 1) as r_repeats, 100 * word_chars // greatest(n_words, 1) as r_word_len from m),
u as (unpivot (select doc_id, lang, source, r_symbols, r_shout, r_dup_lines, r_repeats, r_word_len from q where not base_failed)
      on r_symbols, r_shout, r_dup_lines, r_repeats, r_word_len into name ratio value x),
b as (select *, (x // (1 << greatest(0, length(bin(x)) - 9))) * (1 << greatest(0, length(bin(x)) - 9)) as bucket from u),
g1 as ({_CUM.format(keys="lang, source,")}), g2 as ({_CUM.format(keys="lang,")}), g3 as ({_CUM.format(keys="")}),
f2 as (select x.lang, x.ratio, {_PULL} from g2 x join g3 y using (ratio)),
f1 as (select x.lang, x.source, x.ratio, {_PULL} from g1 x join f2 y on x.ratio = y.ratio and x.lang is not distinct from y.lang),
f as (select lang, source, ratio, {_AT(0)} as a, {_AT(1)} as z from f1),
s as (select *, {REACH} * (case when z > a then z - a else {NO_SPREAD} end) as spread from f),
bad as (select distinct u.doc_id from u join s on u.ratio = s.ratio and u.lang is not distinct from s.lang and u.source is not distinct from s.source
        where x > z + spread or (u.ratio = 'r_word_len' and x < a - spread))
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       (not base_failed and doc_id not in (select doc_id from bad)) as kept from q
"""
