"""Relational operators around the classifier, as queries with SQL: composition of corpora, joins in time, windows, set operations, JSON."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .io import read_table
from .queries import Q, all_lines, ngram_pred, query, sql, _NG  # noqa: F401
from .text import band

_LB = "case when n_chars <= 150 then 'short' when n_chars <= 500 then 'mid' else 'long' end"


def composition(lines: DataFrame) -> DataFrame:
    size = F.when(F.col("n_chars") <= 150, "short").when(F.col("n_chars") <= 500, "mid").otherwise("long")
    return lines.withColumn("size", size)


@query("composition_cube", sql(f"select label, size, count(*) as n, sum(n_chars)::bigint as chars from (select label, n_chars, {_LB} as size from lines) group by cube (label, size)", "lines"))
def _(s, d):
    return composition(all_lines(s, d)).cube("label", "size").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@query("composition_grouping_sets", sql(f"select label, source, size, count(*) as n from (select label, source, {_LB} as size from lines) group by grouping sets ((label, source), (label, size), ())", "lines"))
def _(s, d):
    composition(all_lines(s, d)).createOrReplaceTempView("composed_lines")
    return s.sql("select label, source, size, count(*) as n from composed_lines group by grouping sets ((label, source), (label, size), ())")


@query("composition_rollup", sql("select source, label, count(*) as n from lines group by rollup (source, label)", "lines"))
def _(s, d):
    return all_lines(s, d).rollup("source", "label").agg(F.count(F.lit(1)).alias("n"))


@query("top_sources_per_label", sql("select * from (select label, source, n, row_number() over (partition by label order by n desc, source) as r from (select label, source, count(*) as n from lines group by all)) where r <= 3", "lines"))
def _(s, d):
    c = all_lines(s, d).groupBy("label", "source").agg(F.count(F.lit(1)).alias("n"))
    return c.withColumn("r", F.row_number().over(Window.partitionBy("label").orderBy(F.desc("n"), "source"))).where("r <= 3")


def change_points(lines: DataFrame, label_col: str) -> DataFrame:
    """Lines whose label differs from that of the line before in the same document: code-mixed documents show there."""
    w = Window.partitionBy("doc_id").orderBy("line_no")
    return lines.withColumn("before", F.lag(label_col).over(w)).where(F.col("before") != F.col(label_col))


def smoothed(lines: DataFrame, label_col: str, k: int = 2) -> DataFrame:
    """Majority of the labels from k lines before to k after; ties to the smaller label."""
    w = Window.partitionBy("doc_id").orderBy("line_no").rowsBetween(-k, k)
    near = lines.withColumn("near", F.collect_list(label_col).over(w))
    counted = F.transform(F.array_distinct("near"), lambda x: F.struct((-F.size(F.filter("near", lambda y: y == x))).alias("n"), x.alias("label")))
    return near.withColumn("smooth", F.array_min(counted)["label"]).drop("near")


_LEN = "case when n_chars % 3 = 0 then 'a' when n_chars % 3 = 1 then 'b' else 'c' end"


def _coded(s, d):
    return all_lines(s, d).withColumn("code", F.when(F.col("n_chars") % 3 == 0, "a").when(F.col("n_chars") % 3 == 1, "b").otherwise("c")).select("doc_id", "line_no", "code")


@query("label_change_points", sql(f"select doc_id, line_no, code, before from (select doc_id, line_no, code, lag(code) over (partition by doc_id order by line_no) as before from (select doc_id, line_no, {_LEN} as code from lines)) where before <> code", "lines"))
def _(s, d):
    return change_points(_coded(s, d), "code")


@query("smoothed_line_labels", sql(f"""with c as (select doc_id, line_no, {_LEN} as code from lines), n as (select a.doc_id, a.line_no, b.code, count(*) as n from (select *, row_number() over (partition by doc_id order by line_no) as i from c) a
 join (select *, row_number() over (partition by doc_id order by line_no) as i from c) b on a.doc_id = b.doc_id and b.i between a.i - 2 and a.i + 2 group by all)
 select c.doc_id, c.line_no, c.code, m.smooth from c join (select doc_id, line_no, min_by(code, struct_pack(n := -n, code := code)) as smooth from n group by all) m using (doc_id, line_no)""".replace("with c as", ", c as", 1).replace("select c.doc_id", "select c.doc_id", 1), "lines").replace("  , c as", ", c as"))
def _(s, d):
    return smoothed(_coded(s, d), "code")


@query("cumulative_share", sql("select label, source, n, sum(n) over (partition by label order by n desc, source rows unbounded preceding)::bigint as upto, round(percent_rank() over (partition by label order by n), 6) as pr, ntile(4) over (partition by label order by n desc, source)::int as quarter, dense_rank() over (partition by label order by n)::int as dr from (select label, source, count(*) as n from lines group by all)", "lines"))
def _(s, d):
    c = all_lines(s, d).groupBy("label", "source").agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("label")
    return c.select("label", "source", "n", F.sum("n").over(w.orderBy(F.desc("n"), "source").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"), F.round(F.percent_rank().over(w.orderBy("n")), 6).alias("pr"), F.ntile(4).over(w.orderBy(F.desc("n"), "source")).alias("quarter"), F.dense_rank().over(w.orderBy("n")).alias("dr"))


_EV = "(select *, event_id % (select count(*) from documents) as doc_id from events)"


def events_with_labels(events: DataFrame, docs: DataFrame, n_docs: int, hint: str | None = None) -> DataFrame:
    """Events refer to documents; each takes its document's label. The document side is narrow (id, label)."""
    return events.withColumn("doc_id", F.col("event_id") % n_docs).join(docs.select("doc_id", F.col("lang").alias("label")).hint(hint) if hint else docs.select("doc_id", F.col("lang").alias("label")), "doc_id")


def _events(s, d):
    docs = read_table(s, d, "documents", ["doc_id", "lang"])
    return events_with_labels(read_table(s, d, "events"), docs, docs.count())


@query("events_tumbling", f"select time_bucket(interval 1 hour, ts) as hour, lang as label, count(*) as n from {_EV} join documents using (doc_id) group by all")
def _(s, d):
    return _events(s, d).groupBy(F.window("ts", "1 hour").alias("w"), "label").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("hour"), "label", "n")


@query("events_sliding", f"select date_trunc('hour', ts) - to_hours(k) as start_ts, lang as label, count(*) as n from {_EV} join documents using (doc_id), (select unnest(range(0, 6)) as k) group by all")
def _(s, d):
    return _events(s, d).groupBy(F.window("ts", "6 hours", "1 hour").alias("w"), "label").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start_ts"), "label", "n")


@query("events_sessions", "select user_id, min(ts) as start_ts, count(*) as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as k from (select *, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minute then 0 else 1 end as fresh from events)) group by user_id, k")
def _(s, d):
    e = read_table(s, d, "events", ["user_id", "ts"])
    return e.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start_ts"), "n")


@query("events_asof_document", "select event_id, coalesce(last_value(case when event_type = 'purchase' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding), -1) as last_purchase from events")
def _(s, d):
    """As-of join inside one table: a running last value needs one sort by user, no range join."""
    e = read_table(s, d, "events", ["event_id", "user_id", "ts", "event_type"])
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.select("event_id", F.coalesce(F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True).over(w), F.lit(-1).cast("long")).alias("last_purchase"))


@query("events_interval_join", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and b.event_id <> a.event_id and b.ts >= a.ts and b.ts <= a.ts + interval 5 minute")
def _(s, d):
    a = read_table(s, d, "events", ["event_id", "user_id", "ts"]).alias("a")
    b = a.alias("b")
    on = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.event_id") != F.col("b.event_id")) & (F.col("b.ts") >= F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("interval 5 minutes"))
    return a.join(b, on).select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))


@query("dedup_documents", "select lang, count(*) as docs, count(distinct md5(text)) as texts, min(doc_id) as first_id from documents group by lang")
def _(s, d):
    df = read_table(s, d, "documents", ["doc_id", "lang", "text"]).withColumn("h", F.md5("text"))
    return df.groupBy("lang", "h").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("i")).groupBy("lang").agg(F.sum("n").alias("docs"), F.count(F.lit(1)).alias("texts"), F.min("i").alias("first_id"))


@query("label_set_ops", "select 'intersect' as op, lang as label from (select lang from documents intersect select regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) from pages) union all select 'except', lang from (select lang from documents except select 'en') union all select 'union', lang from (select lang from documents union select 'xx')")
def _(s, d):
    a = read_table(s, d, "documents", ["lang"]).distinct()
    b = read_table(s, d, "pages", ["html"]).select(F.regexp_extract("html", r'<html lang="([a-z]+)"', 1).alias("lang")).distinct()
    tag = lambda df, op: df.select(F.lit(op).alias("op"), F.col("lang").alias("label"))
    x = s.createDataFrame([("xx",)], "lang string")
    return tag(a.intersect(b), "intersect").unionByName(tag(a.exceptAll(s.createDataFrame([("en",)], "lang string")), "except")).unionByName(tag(a.union(x).distinct(), "union"))


@query("semi_anti_labels", "select 'labelled' as kind, lang, count(*) as n from documents where doc_id in (select doc_id from labels) group by lang union all select 'open', lang, count(*) from documents where doc_id not in (select doc_id from labels) group by lang")
def _(s, d):
    docs, lab = read_table(s, d, "documents", ["doc_id", "lang"]), read_table(s, d, "labels", ["doc_id"])
    count = lambda how, kind: docs.join(lab, "doc_id", how).groupBy("lang").agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "lang", "n")
    return count("left_semi", "labelled").unionByName(count("left_anti", "open"))


@query("orders_month_trend", "select strftime(o_orderdate, '%Y-%m') as month, count(*) as orders, round(sum(o_totalprice), 2) as total, count(distinct o_custkey) as customers from orders group by 1")
def _(s, d):
    o = read_table(s, d, "orders", ["o_orderdate", "o_totalprice", "o_custkey"])
    return o.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"), F.count_distinct("o_custkey").alias("customers"))


@query("far_domain_words", r"select w as token, count(*) as n from (select unnest(regexp_extract_all(lower(p_name), '\p{L}+')) as w from part) group by w")
def _(s, d):
    return read_table(s, d, "part", ["p_name"]).select(F.explode(F.regexp_extract_all(F.lower("p_name"), F.lit(r"\p{L}+"), 0)).alias("token")).groupBy("token").agg(F.count(F.lit(1)).alias("n"))


@query("label_stats_quality", "select lang, quality, toxic, count(*) as n, round(avg(n_chars), 4) as mean, round(stddev_samp(n_chars), 4) as sd, round(median(n_chars), 4) as mid from documents join labels using (doc_id) group by all")
def _(s, d):
    j = read_table(s, d, "documents", ["doc_id", "lang", "n_chars"]).join(read_table(s, d, "labels"), "doc_id")
    return j.groupBy("lang", "quality", "toxic").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("n_chars"), 4).alias("mean"), F.round(F.stddev_samp("n_chars"), 4).alias("sd"), F.round(F.median("n_chars"), 4).alias("mid"))


@query("json_props_agg", "select event_type, count(*) as n, count(json_extract_string(props, '$.' || (json_keys(props)[1]))) as with_first from events group by event_type")
def _(s, d):
    e = read_table(s, d, "events", ["event_type", "props"])
    keys = F.json_object_keys("props")
    return e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.count(F.element_at(F.from_json("props", "map<string,string>"), F.get(keys, F.lit(0)))).alias("with_first"))


@query("conversation_agreement", sql(r"select conv_id, count(*) as turns, count(distinct role) as roles, sum(length(text))::bigint as chars, min_by(role, turn) as opened from conversations group by conv_id", "lines"))
def _(s, d):
    c = read_table(s, d, "conversations")
    return c.groupBy("conv_id").agg(F.count(F.lit(1)).alias("turns"), F.count_distinct("role").alias("roles"), F.sum(F.length("text")).alias("chars"), F.min_by("role", "turn").alias("opened"))


@query("sketch_distinct", sql("select label, count(distinct text) as texts, true as near from lines group by label", "lines"))
def _(s, d):
    """Distinct lines exactly, and whether the merged sketches of the buckets come within a twentieth of that."""
    parts = all_lines(s, d).groupBy("label", "bucket").agg(F.hll_sketch_agg("text", 14).alias("h"), F.collect_set(F.md5("text")).alias("own"))
    x = parts.groupBy("label").agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("a"), F.sum(F.size("own")).alias("texts"))  # equal texts share a bucket
    return x.select("label", "texts", (F.abs(F.col("a") - F.col("texts")) <= 0.05 * F.col("texts")).alias("near"))


@query("sketch_top_sources", "select lang as label, source, count(*) as n from documents group by all")
def _(s, d):
    """Heavy hitters by a sketch that holds more items than there are sources, so its counts are exact."""
    t = read_table(s, d, "documents", ["lang", "source"]).groupBy(F.col("lang").alias("label")).agg(F.expr("approx_top_k(source, 100, 2000)").alias("t"))
    return t.select("label", F.explode("t").alias("x")).select("label", F.col("x.item").alias("source"), F.col("x.count").alias("n"))


@query("sketch_percentiles", sql("select label, quantile_disc(n_chars, 0.5) as p50, quantile_disc(n_chars, 0.95) as p95 from lines group by label", "lines"))
def _(s, d):
    """Percentiles of line length by a sketch whose accuracy exceeds the rows of these tables; at any size its error in rank is under a millionth."""
    at = lambda p: F.percentile_approx("n_chars", p, 1_000_000)
    return all_lines(s, d).groupBy("label").agg(at(0.5).alias("p50"), at(0.95).alias("p95"))


@query("events_shuffle_hash", f"select lang as label, event_type, count(*) as n from {_EV} join documents using (doc_id) group by all")
def _(s, d):
    """Events meet the labels of documents by a shuffled hash join: no sort of either side."""
    docs = read_table(s, d, "documents", ["doc_id", "lang"])
    e = read_table(s, d, "events", ["event_id", "event_type"])
    return events_with_labels(e, docs, docs.count(), "shuffle_hash").groupBy("label", "event_type").agg(F.count(F.lit(1)).alias("n"))


BAND = band
