"""Queries of the core with equivalent SQL. The model is fitted and applied by SegmentModel and Guard to whole texts; a vocabulary of characters and 200 substrings of two
or three letters lets SQL run the same dynamic programs as folds over the places of a chunk, with the last three values as their state."""

from __future__ import annotations

import threading
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decide, em, guard, lattice, metrics, score, text, vocab
from .baselines import naive
from .baselines.fixed_seg_nb import FixedSegNB
from .baselines.ngram_lm import NgramLM, runner_up
from .io import fingerprint, read_table, stash
from .model import SegmentModel

_memo: dict[tuple, object] = {}
_locks: dict[tuple, threading.RLock] = {}
_guard = threading.Lock()
MIN_SAMPLES, CAP, LIMIT = 1000, -9.0, 10.0
#: Size of the vocabulary beyond characters, length of its longest token, rounds of EM.
TOP, LONGEST, ROUNDS = 200, 3, 2


def once(spark: SparkSession, sf_dir: str, name: str, make: Callable):
    """Share what several queries start from, within one application and for as long as the tables stay as they are."""
    key = (spark.sparkContext.applicationId, sf_dir, fingerprint(spark, f"{sf_dir}/documents.parquet"), name)
    with _guard:
        own = _locks.setdefault(key, threading.RLock())
    with own:  # systems are fitted side by side; what they share is made once
        if key not in _memo:
            _memo[key] = make()
        return _memo[key]


def forget() -> None:
    _memo.clear()


# --- what the queries start from


def all_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text.lines(read_table(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source"]))


def train_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return all_lines(spark, sf_dir).where("bucket >= 2")


def chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(label, chunk, n) of the training lines."""
    return once(spark, sf_dir, "chunks", lambda: stash(text.chunk_counts(train_lines(spark, sf_dir)), "chunks"))


def small_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    return once(spark, sf_dir, "vocab", lambda: stash(vocab.base_topk(chunks(spark, sf_dir), TOP, 2, LONGEST), "vocab"))


def rounds(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Two EM rounds from the uniform start, step by step."""

    def make() -> dict[str, DataFrame]:
        ids = lattice.collect_vocab(small_vocab(spark, sf_dir))
        placed = em.prepare(chunks(spark, sf_dir))
        p1 = stash(em.e_step(placed, ids), "r1")
        t1 = stash(em.m_step(em.sum_counts(p1)), "t1")
        p2 = stash(em.e_step(placed, ids, t1), "r2")
        t2 = stash(em.m_step(em.sum_counts(p2)), "t2")
        return {"p1": p1, "t1": t1, "p2": p2, "t2": t2}

    return once(spark, sf_dir, "rounds", make)


def small_model(spark: SparkSession, sf_dir: str) -> SegmentModel:
    return once(spark, sf_dir, "model", lambda: SegmentModel.fit(train_lines(spark, sf_dir), small_vocab(spark, sf_dir), rounds=ROUNDS))


def snippet_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, gold, bucket, n_chars, snippet)"""
    s = text.snippets(all_lines(spark, sf_dir))
    return s.select((F.col("doc_id") * 100000 + F.col("line_no")).alias("row_id"), F.col("label").alias("gold"), "bucket", "n_chars", "snippet")


def snippet_top(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Test snippets as the model labels them."""
    rows = snippet_rows(spark, sf_dir).where("bucket = 0")
    return once(spark, sf_dir, "snippet-top", lambda: stash(small_model(spark, sf_dir).transform(rows, "snippet"), "top"))


def document_top(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole documents as the model labels them."""
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text", "lang"]).withColumnRenamed("lang", "gold")
    return once(spark, sf_dir, "document-top", lambda: stash(small_model(spark, sf_dir).transform(docs).drop("text"), "top"))


def fitted_guard(spark: SparkSession, sf_dir: str, shared: bool = False) -> guard.Guard:
    """Thresholds from training snippets."""
    train = snippet_rows(spark, sf_dir).where("bucket >= 2").select(F.col("gold").alias("label"), F.col("snippet").alias("text"))
    g = guard.Guard(c=CAP, min_samples=MIN_SAMPLES, abs_limit=LIMIT, shared=shared)
    return once(spark, sf_dir, f"guard{shared}", lambda: g.fit(train, small_model(spark, sf_dir), high=[]))


def guarded(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = snippet_rows(spark, sf_dir).where("bucket = 0")
    return once(spark, sf_dir, "guarded", lambda: stash(fitted_guard(spark, sf_dir).predict(rows, "snippet"), "guarded"))


def guarded_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text", "lang"]).withColumnRenamed("lang", "gold")
    return once(spark, sf_dir, "guarded-documents", lambda: stash(fitted_guard(spark, sf_dir).predict(docs).drop("text"), "guarded"))


def fixed_split(spark: SparkSession, sf_dir: str) -> FixedSegNB:
    return once(spark, sf_dir, "fixed", lambda: FixedSegNB.fit(train_lines(spark, sf_dir), small_vocab(spark, sf_dir), rounds=ROUNDS))


def ngram(spark: SparkSession, sf_dir: str, smooth: str = "add_k") -> NgramLM:
    return once(spark, sf_dir, f"ngram-{smooth}", lambda: NgramLM.fit(train_lines(spark, sf_dir), smooth=smooth))


def ngram_pred(spark: SparkSession, sf_dir: str, smooth: str = "add_k") -> DataFrame:
    """(row_id, gold, n_chars, label) on test snippets."""
    rows = snippet_rows(spark, sf_dir).where("bucket = 0").select("row_id", "gold", "n_chars", F.col("snippet").alias("text"))
    return once(spark, sf_dir, f"pred-{smooth}", lambda: stash(ngram(spark, sf_dir, smooth).transform(rows, "row_id").select("row_id", "gold", "n_chars", "label"), "pred"))


PARENTS = [("de", "germanic", "latin", "de"), ("en", "germanic", "latin", "en"), ("es", "romance", "latin", "ib"), ("fr", "romance", "latin", "fr")]


def parents(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(PARENTS, "label string, family string, script string, macro string")


# --- SQL pieces, in the order in which they build on each other

_H8 = "('0x' || substr(md5({0}), 1, 8))::bigint"
_CH = r"' ?\p{L}+| ?[^\s\p{L}]+|\s+'"


def _sum(*terms: str) -> str:
    """Log of the sum of exponentials; a null term is none."""
    top = f"greatest({', '.join(terms)})"
    return f"{top} + ln({' + '.join(f'coalesce(exp({t} - {top}), 0)' for t in terms)})"


def _fold(values: str, join: str, unit: str = "double", extra: str = "", keep: str = "") -> str:
    """A fold over the places of a chunk. values: list of structs with v1, v2, v3, what the token of one, two or three characters that ends (or begins) there adds; the state is x0, x1, x2,
    the results of the last three places. join gives the next from the three candidates; `keep` further fields."""
    nothing = f"'v1': null::{unit}, 'v2': null::{unit}, 'v3': null::{unit}"
    terms = ("(a.x0 + x.v1)", "(a.x1 + x.v2)", "(a.x2 + x.v3)")
    first = f"{{{nothing}, 'x0': 0::{unit}, 'x1': null::{unit}, 'x2': null::{unit}{extra}}}"
    now = join.format(*terms)
    return f"list_reduce({values}, lambda a, x: {{'v1': x.v1, 'v2': x.v2, 'v3': x.v3, 'x0': {now}, 'x1': a.x0, 'x2': a.x1{keep.format(*terms, now=now)}}}, {first})"


def _places(table: str, by: str, value: str, unit: str = "double", extra: str = "", first: str = "null::{unit}") -> str:
    """The list that _fold takes, by groups; `value` says what t1, t2, t3 add as v1, v2, v3."""
    return f"list({{'v1': {value.format(1)}, 'v2': {value.format(2)}, 'v3': {value.format(3)}, 'x0': null::{unit}, 'x1': null::{unit}, 'x2': null::{unit}{extra}}} order by {by})"


_LOGSUM = _sum("{0}", "{1}", "{2}")
_HIST = ", 'h': []::double[]"


def _em_sql(p: str, source: str) -> str:
    """Two rounds over `source` (label, chunk, n), then statistics and distributions, under names that begin with p. A fold forwards and one backwards keep the values at all places."""

    def step(k: int, groups: str, table: str, value: str) -> str:
        on = " and ".join(f"{{0}}.{g} = {{1}}.{g}" for g in groups.split(", "))
        fwd = _fold(_places(table, "e", value, extra=_HIST), _LOGSUM, extra=", 'h': [0.0::double]", keep=", 'h': list_append(a.h, {now})")
        bwd = _fold(_places(table, "s desc", value, extra=_HIST), _LOGSUM, extra=", 'h': [0.0::double]", keep=", 'h': list_append(a.h, {now})")
        return f"""{p}f{k} as materialized (select {groups}, {fwd}.h as h from {p}e{k} group by {groups}),
        {p}b{k} as materialized (select {groups}, {bwd}.h as h from {p}s{k} group by {groups})"""

    unit = "case when t{0} is not null then -ln((select count(*) from vocab)) end"
    return f"""{p}e1 as materialized (select chunk, e, t1, t2, t3 from ends), {p}s1 as materialized (select chunk, s, t1, t2, t3 from starts),
        {step(1, "chunk", f"{p}e1", unit)},
        {p}z1 as materialized (select chunk, h[len(h)] as z from {p}f1),
        {p}x1 as materialized (select x.chunk, token_id, sum(exp(f.h[x.s + 1] - ln((select count(*) from vocab)) + b.h[len(b.h) - x.e] - f.h[len(f.h)])) as c from edges x join {p}f1 f using (chunk) join {p}b1 b using (chunk) group by all),
        {p}c1 as materialized (select label, token_id, sum(n * c) as c from {source} join {p}x1 using (chunk) group by all),
        {p}t1 as materialized (select label, token_id, c, ln(c / sum(c) over (partition by label)) as logp from {p}c1),
        {p}e2 as materialized (select w.label, w.chunk, x.e, a.logp as t1, b.logp as t2, c.logp as t3 from {source} w join ends x using (chunk) left join {p}t1 a on a.label = w.label and a.token_id = x.t1 left join {p}t1 b on b.label = w.label and b.token_id = x.t2 left join {p}t1 c on c.label = w.label and c.token_id = x.t3),
        {p}s2 as materialized (select w.label, w.chunk, x.s, a.logp as t1, b.logp as t2, c.logp as t3 from {source} w join starts x using (chunk) left join {p}t1 a on a.label = w.label and a.token_id = x.t1 left join {p}t1 b on b.label = w.label and b.token_id = x.t2 left join {p}t1 c on c.label = w.label and c.token_id = x.t3),
        {step(2, "label, chunk", f"{p}e2", "t{0}").replace(f"from {p}e2 group by label, chunk), ", f"from {p}e2 group by label, chunk), ")},
        {p}c2 as materialized (select w.label, x.token_id, sum(w.n * exp(f.h[x.s + 1] + t.logp + b.h[len(b.h) - x.e] - f.h[len(f.h)])) as c from {source} w join edges x using (chunk) join {p}t1 t on t.label = w.label and t.token_id = x.token_id
          join {p}f2 f on f.label = w.label and f.chunk = w.chunk join {p}b2 b on b.label = w.label and b.chunk = w.chunk group by all),
        {p}t2 as materialized (select label, token_id, c, ln(c / sum(c) over (partition by label)) as logp from {p}c2 where c > {em.TINY}),
        {p}stats as materialized (select label, sum(c) as n_tokens, ln(0.5 / sum(c)) as floor, sum(-exp(logp) * logp) as entropy from {p}t2 group by all),
        {p}seen as materialized (select distinct label, token_id from {source} join edges using (chunk)),
        {p}theta as materialized (select label, token_id, greatest(coalesce(logp, floor), floor) as logp, round(greatest(coalesce(logp, floor), floor) * 1000000)::bigint as fx, coalesce(c, 0) as c from {p}seen left join {p}t2 using (label, token_id) join {p}stats using (label))"""


def _score_sql(p: str, floor: str = "floor") -> str:
    """wscore(label, chunk, score_fx, logp) of the distinct chunks of src(row_id, chunk), under all labels: the best split in fixed point, the sum over splits; said: the tokens of the best split, a longer last token
    first among equals. A character that is no token is worth UNKNOWN."""
    unknown = int(em.UNKNOWN * em.SCALE)
    fx = "x{0}"
    best = _fold(_places("", "e", fx, "bigint", extra=", 'p0': []::int[], 'p1': []::int[], 'p2': []::int[], 'k1': y1, 'k2': y2, 'k3': y3"), "greatest({0}, {1}, {2})", "bigint",
                 extra=", 'p0': []::int[], 'p1': []::int[], 'p2': []::int[], 'k1': null::int, 'k2': null::int, 'k3': null::int",
                 keep=", 'p0': case when {2} >= greatest({0}, {1}, {2}) then list_append(a.p2, x.k3) when {1} >= greatest({0}, {1}, {2}) then list_append(a.p1, x.k2) else list_append(a.p0, x.k1) end, 'p1': a.p0, 'p2': a.p1, 'k1': x.k1, 'k2': x.k2, 'k3': x.k3")
    logs = _fold(_places("", "e", "l{0}"), _LOGSUM)
    value = lambda k: f"x.t{k} as y{k}, c{k}.fx as x{k}, c{k}.logp as l{k}" if k > 1 else f"coalesce(x.t1, -2) as y1, case when x.t1 is null then {unknown} else c1.fx end as x1, case when x.t1 is null then {em.UNKNOWN} else c1.logp end as l1"
    joins = " ".join(f"left join {p}cell c{k} on c{k}.label = s.label and c{k}.token_id = x.t{k}" for k in (1, 2, 3))
    return f"""{p}cell as materialized (select s.label, v.token_id, coalesce(fx, round({floor} * 1000000)::bigint) as fx, coalesce(logp, {floor}) as logp from {p}stats s cross join vocab v left join {p}theta t on t.label = s.label and t.token_id = v.token_id),
        {p}sc as materialized (select chunk, e, a.token_id as t1, b.token_id as t2, c.token_id as t3 from (select chunk, e, substr(chunk, e, 1) as s1, case when e > 1 then substr(chunk, e - 1, 2) end as s2, case when e > 2 then substr(chunk, e - 2, 3) end as s3
          from (select chunk, unnest(range(1, length(chunk) + 1)) as e from (select distinct chunk from src))) left join vocab a on a.token = s1 left join vocab b on b.token = s2 left join vocab c on c.token = s3),
        {p}sv as materialized (select s.label, x.chunk, x.e, {value(1)}, {value(2)}, {value(3)} from {p}sc x cross join {p}stats s {joins}),
        {p}wscore as materialized (select label, chunk, b.x0 as score_fx, b.p0 as path, logp from (select label, chunk, {best} as b, {logs}.x0 as logp from {p}sv group by all))"""


SQL = {
    "lines": f"""lines as materialized (select doc_id, line_no, label, source, trim(raw) as text, length(trim(raw))::bigint as n_chars, ({_H8.format("trim(raw)")} % 5)::int as bucket
        from (select doc_id, lang as label, source, unnest(string_split(text, chr(10))) as raw, unnest(range(len(string_split(text, chr(10)))))::int as line_no from documents) where trim(raw) <> '')""",
    "chunks": f"""chunks as materialized (select label, c as chunk, count(*) as n from (select label, unnest(regexp_extract_all(text, {_CH})) as c from lines where bucket >= 2) where c <> '' group by all)""",
    "vocab": f"""u as materialized (select chunk, sum(n)::bigint as n from chunks group by chunk),
        spans as materialized (select chunk, n, s, l, substr(chunk, s, l) as token from (select chunk, n, unnest(range(1, length(chunk) + 1)) as s from u), (select unnest([1, 2, 3]) as l) where s + l - 1 <= length(chunk)),
        subs as (select token, sum(n)::bigint as c from spans group by token),
        vocab as materialized (select (row_number() over (order by token) - 1)::int as token_id, token, length(token)::int as token_len, length(token) = 1 as is_base
          from ((select token from subs where length(token) = 1) union (select token from (select token, c from subs where length(token) > 1 order by c desc, token limit {TOP}))))""",
    "edges": """edges as materialized (select chunk, s - 1 as s, s - 1 + l as e, l, token_id from spans join vocab using (token)),
        ends as materialized (select chunk, e, max(token_id) filter (where l = 1) as t1, max(token_id) filter (where l = 2) as t2, max(token_id) filter (where l = 3) as t3 from edges group by all),
        starts as materialized (select chunk, s, max(token_id) filter (where l = 1) as t1, max(token_id) filter (where l = 2) as t2, max(token_id) filter (where l = 3) as t3 from edges group by all)""",
    "paths": """walk as (select chunk, e, [token_id] as toks from edges where s = 0 and length(chunk) <= 4 union all select w.chunk, x.e, list_append(w.toks, x.token_id) from walk w join edges x on w.chunk = x.chunk and w.e = x.s),
        paths as materialized (select chunk, toks from walk where e = length(chunk))""",
    "em": _em_sql("", "chunks"),
    "samples": "samples as materialized (select label, count(*) as n_samples from lines where bucket >= 2 group by label)",
    "score": _score_sql(""),
    "capped": _score_sql("", f"least(floor, {CAP})"),
    "snips": rf"""snips as materialized (select doc_id * 100000 + line_no as row_id, label as gold, bucket, n_chars,
        substr(text, ({_H8.format("doc_id || ':' || line_no")} % greatest(1, n_chars - 19))::int + 1, 20) as snippet from lines)""",
    "src_train": "src as materialized (select 0 as row_id, chunk, 1 as m from u)",
    "src_snips": f"src as materialized (select row_id, chunk, count(*) as m from (select row_id, unnest(regexp_extract_all(snippet, {_CH})) as chunk from snips) group by all)",
    "src_docs": f"src as materialized (select doc_id as row_id, chunk, count(*) as m from (select doc_id, unnest(regexp_extract_all(text, {_CH})) as chunk from documents) group by all)",
    "src_both": f"src as materialized (select row_id, chunk, count(*) as m from (select row_id, unnest(regexp_extract_all(snippet, {_CH})) as chunk from snips union all select -1 - doc_id, unnest(regexp_extract_all(text, {_CH})) from documents) group by all)",
    "rows": """scores as materialized (select row_id, label, sum(m * score_fx)::bigint / 1000000.0::double as score, sum(m * score_fx)::bigint as fx from src join wscore using (chunk) group by all),
        ranked as materialized (select *, row_number() over (partition by row_id order by fx desc, label) as r, exp(score - max(score) over w) / sum(exp(score - m)) over w as p from (select *, max(score) over (partition by row_id) as m from scores) window w as (partition by row_id)),
        top as materialized (select a.row_id, a.label, a.score - b.score as margin, a.fx - b.fx as margin_fx, a.score from ranked a left join ranked b on a.row_id = b.row_id and b.r = 2 where a.r = 1)""",
    "limits": f"""sized as (select label, n_samples, 5 * (1 - n_samples::double / {MIN_SAMPLES}) as q from samples where n_samples < {MIN_SAMPLES}),
        mg as (select top.label, list_sort(list(margin)) as m from top join snips using (row_id) where bucket >= 2 and label = gold group by all),
        rank_at as (select label, q, m, q / 100 * (len(m) - 1) as pos from sized left join mg using (label)),
        lim as materialized (select label, q, coalesce(m[floor(pos)::int + 1] + (pos - floor(pos)) * (m[ceil(pos)::int + 1] - m[floor(pos)::int + 1]), 0) as delta from rank_at)""",
    "guarded": f"""look as (select t.row_id, t.label, t.score, coalesce(t.margin < lim.delta, false) as looked from top t left join lim using (label)),
        alt as (select l.row_id, min_by(k.label, k.r) as label from look l join ranked k on k.row_id = l.row_id and k.r <= 5 where k.label not in (select label from lim) and l.score - k.score <= {LIMIT} group by l.row_id),
        gd as materialized (select l.row_id, l.label, l.looked, case when l.looked then coalesce(alt.label, l.label) else l.label end as guarded from look l left join alt using (row_id))""",
    "grams": """tg as (select label, '  ' || lower(text) as p from lines where bucket >= 2),
        g3 as (select label, substr(p, i, 2) as ctx, substr(p, i + 2, 1) as ch from (select label, p, unnest(range(1, length(p) - 1)) as i from tg)),
        cnt as materialized (select label, ctx, ch, count(*) as c from g3 group by all), ctxs as materialized (select label, ctx, sum(c)::bigint as t from cnt group by all),
        alpha as (select count(distinct ch) as a from cnt), uni as (select label, ch, sum(c)::bigint as uc from cnt group by all), tot as (select label, sum(c)::bigint as ut from cnt group by all)""",
    "pred": """sg as (select row_id, '  ' || lower(snippet) as p from snips where bucket = 0),
        sg3 as (select row_id, substr(p, i, 2) as ctx, substr(p, i + 2, 1) as ch, count(*) as m from (select row_id, p, unnest(range(1, length(p) - 1)) as i from sg) group by all),
        val as (select label, ctx, ch, round(ln({p}) * 1000000)::bigint as v from (select distinct ctx, ch from sg3) cross join tot left join cnt using (label, ctx, ch) left join ctxs using (label, ctx) left join uni using (label, ch) cross join alpha),
        ns as materialized (select row_id, label, sum(m * v)::bigint as score from sg3 join val using (ctx, ch) group by all),
        pred as materialized (select row_id, gold, n_chars, label from snips join (select row_id, min_by(label, struct_pack(s := -score, label := label)) as label from ns group by row_id) using (row_id))""",
    "measures": """conf as (select gold, label, count(*) as n from pred group by all), al as (select distinct gold as label from conf),
        per as materialized (select al.label, coalesce((select n from conf where gold = al.label and conf.label = al.label), 0)::bigint as tp,
          coalesce((select sum(n) from conf where conf.label = al.label and gold <> al.label), 0)::bigint as fp, coalesce((select sum(n) from conf where gold = al.label and conf.label <> al.label), 0)::bigint as fn, (select sum(n) from conf) as total from al),
        per2 as materialized (select label, tp, fp, fn, (total - tp - fp - fn)::bigint as tn, case when tp + fp > 0 then tp / (tp + fp) else 0.0 end as precision, case when tp + fn > 0 then tp / (tp + fn) else 0.0 end as recall,
          case when 2 * tp + fp + fn > 0 then 2 * tp / (2 * tp + fp + fn) else 0.0 end as f1, case when fp + total - tp - fp - fn > 0 then fp / (total - tp - fn) else 0.0 end as fpr from per)""",
}
_P = {
    "add_k": "(coalesce(c, 0) + 0.5::double) / (coalesce(t, 0) + 0.5::double * a)",
    "interp": "case when t > 0 then 0.6::double * coalesce(c, 0) / t + (1 - 0.6::double) * ((coalesce(uc, 0) + 0.5::double) / (ut + 0.5::double * a)) else (coalesce(uc, 0) + 0.5::double) / (ut + 0.5::double * a) end",
    "backoff": "case when c > 0 then c::double / t else 0.4::double * ((coalesce(uc, 0) + 0.5::double) / (ut + 0.5::double * a)) end",
}


def sql(last: str, *names: str, p: str = "add_k") -> str:
    parts = ", ".join(SQL[n].replace("{p}", _P[p]) for n in names)
    return f"with recursive {parts} {last}"


_VOC = ("lines", "chunks", "vocab")
_LAT = (*_VOC, "edges")
_EM = (*_LAT, "em")
_TRAIN = (*_EM, "src_train", "score")
_SNIP = (*_EM, "snips", "src_snips", "score", "rows")
_DOCS = (*_EM, "src_docs", "score", "rows")
_CAPPED = (*_EM, "samples", "snips", "src_snips", "capped", "rows")
_LIMITS = (*_CAPPED, "limits")
_NG = ("lines", "snips", "grams", "pred")
_MS = (*_NG, "measures")

Q: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        Q[name] = (f, oracle)
        return f

    return add


# --- text
@query("lines", sql("select * from lines", "lines"))
def _(s, d):
    return all_lines(s, d)


@query("snippets", sql("select * exclude (gold), gold from snips where bucket = 0", "lines", "snips"))
def _(s, d):
    return snippet_rows(s, d).where("bucket = 0")


@query("chunks_regex", r"select doc_id, len(c)::int as n_chunks, list_sum(list_transform(c, lambda x: length(x)))::bigint as n_chars, c[1] as first_chunk from (select doc_id, regexp_extract_all(text, ' ?\p{L}+| ?[^\s\p{L}]+|\s+') as c from documents)")
def _(s, d):
    c = read_table(s, d, "documents", ["doc_id", "text"]).select("doc_id", text.pretokenize(F.col("text")).alias("c"))
    return c.select("doc_id", F.size("c").alias("n_chunks"), F.aggregate("c", F.lit(0).cast("long"), lambda a, x: a + F.length(x)).alias("n_chars"), F.get("c", F.lit(0)).alias("first_chunk"))


@query("chunk_frequencies", f"select lang as label, c as chunk, count(*) as n from (select lang, unnest(regexp_extract_all(text, {_CH})) as c from documents) where c <> '' group by all")
def _(s, d):
    return text.chunk_counts(read_table(s, d, "documents", ["lang", "text"]), "lang")


@query("bytes_with_prefix_space", f"select lang as label, count(*) as chunks, sum(strlen(c))::bigint as units, max(strlen(c))::int as longest from (select lang, unnest(regexp_extract_all(case when text = '' or starts_with(text, ' ') then text else ' ' || text end, {_CH})) as c from documents) where c <> '' group by lang")
def _(s, d):
    c = text.pretokenize(F.col("text"), "regex", True, "byte")
    df = read_table(s, d, "documents", ["lang", "text"]).select(F.col("lang").alias("label"), F.explode(c).alias("c"))
    return df.groupBy("label").agg(F.count(F.lit(1)).alias("chunks"), F.sum(F.length("c")).alias("units"), F.max(F.length("c")).alias("longest"))


@query("codepoint_stats", "select lang, count(*) as docs, sum(length(text))::bigint as chars, max(length(text))::bigint as longest, count(distinct text) as texts from documents group by lang")
def _(s, d):
    return read_table(s, d, "documents", ["lang", "text"]).groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.length("text")).alias("chars"), F.max(F.length("text")).cast("long").alias("longest"), F.count_distinct("text").alias("texts"))


@query("byte_stats", "select lang, sum(strlen(text))::bigint as bytes, sum(strlen(text) - length(text))::bigint as extra from documents group by lang")
def _(s, d):
    return read_table(s, d, "documents", ["lang", "text"]).groupBy("lang").agg(F.sum(F.octet_length("text")).alias("bytes"), F.sum(F.octet_length("text") - F.length("text")).alias("extra"))


_HTML = r"""trim(regexp_replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '<!--.*?-->', ' ', 'gs'), '<script.*?</script>', ' ', 'gs'), '<style.*?</style>', ' ', 'gs'), '<[^>]*>', ' ', 'g'),
    '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&amp;', '&'), '\s+', ' ', 'g'))"""


@query("page_text_lang", f"select page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) as gold, length({_HTML})::int as n_chars, md5({_HTML}) as digest from pages")
def _(s, d):
    t = text.html_to_text(F.col("html"))
    return read_table(s, d, "pages", ["page_id", "html"]).select("page_id", text.page_lang(F.col("html")).alias("gold"), F.length(t).alias("n_chars"), F.md5(t).alias("digest"))


@query("split_buckets", sql("select label, bucket, count(*) as n, count(distinct text) as texts from lines group by all", "lines"))
def _(s, d):
    return all_lines(s, d).groupBy("label", "bucket").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("text").alias("texts"))


@query("sample_j_per_label", sql("select doc_id, line_no, label, md5(text) as digest from (select *, row_number() over (partition by label order by md5('1:' || doc_id || ':' || line_no), doc_id, line_no) as rn from lines where bucket >= 2) where rn <= 50", "lines"))
def _(s, d):
    return text.sample_j(all_lines(s, d).where("bucket >= 2"), 50, 1).select("doc_id", "line_no", "label", F.md5("text").alias("digest"))


@query("corrupt_lines", sql(f"""select doc_id, line_no, string_agg(case when trim(ch) <> '' and h % 1000 < 100 then substr('{text.LETTERS}', (h // 1000 % 26)::int + 1, 1) else ch end, '' order by i) as text
 from (select doc_id, line_no, i, ch, {_H8.format("'1:' || doc_id || ':' || line_no || ':' || i")} as h from (select doc_id, line_no, unnest(string_split(text, '')) as ch, unnest(range(length(text))) as i from lines where bucket = 0)) group by all""", "lines"))
def _(s, d):
    return text.corrupt(all_lines(s, d).where("bucket = 0"), 100).select("doc_id", "line_no", "text")


@query("cipher_documents", f"select doc_id, lang || '-2' as label, md5(translate(lower(text), '{text.LETTERS}', '{text.permutation(2)}')) as digest from documents")
def _(s, d):
    return read_table(s, d, "documents", ["doc_id", "lang", "text"]).select("doc_id", F.concat("lang", F.lit("-2")).alias("label"), F.md5(text.cipher(F.col("text"), 2)).alias("digest"))


def _dialect_sql() -> str:
    cases = []
    for lang, vs in text.VARIETIES.items():
        for v, rules in enumerate(vs):
            if rules:
                out = "w"
                for a, b in rules:
                    out = f"replace({out}, '{a}', '{b}')"
                cases.append(f"when label = '{lang}' and v = {v} then array_to_string(list_transform(string_split(text, ' '), lambda w: case when {_H8.format(f"'{v}:' || w")} % 100 < {text.SHARE} then {out} else w end), ' ')")
    n = " ".join(f"when '{k}' then {len(v)}" for k, v in text.VARIETIES.items())
    return f"select doc_id, line_no, label as family, label || '-' || v as label, md5(case {' '.join(cases)} else text end) as digest from (select *, ({_H8.format("'variety:' || text")} % case label {n} else 1 end)::int as v from lines)"


@query("dialect_documents", sql(_dialect_sql(), "lines"))
def _(s, d):
    return text.dialects(all_lines(s, d)).select("doc_id", "line_no", "family", "label", F.md5("text").alias("digest"))


_BAND = "case " + " ".join(f"when n_chars between {lo} and {hi} then '{n}'" for lo, hi, n in text.BANDS) + " end"


@query("length_bands", sql(f"select label, {_BAND} as band, count(*) as n from lines group by all", "lines"))
def _(s, d):
    bands = s.createDataFrame(text.BANDS, "lo long, hi long, band string")
    ln = all_lines(s, d).select("label", "n_chars")
    return ln.join(F.broadcast(bands), (F.col("n_chars") >= F.col("lo")) & (F.col("n_chars") <= F.col("hi"))).groupBy("label", "band").agg(F.count(F.lit(1)).alias("n"))


# --- vocabulary and lattice
@query("seed_substrings", sql("select token, c from subs where c >= 5", *_VOC))
def _(s, d):
    return vocab.substrings(chunks(s, d), LONGEST).where("c >= 5")


@query("vocab_base_topk", sql("select * from vocab", *_VOC))
def _(s, d):
    return small_vocab(s, d)


@query("vocab_seed", sql("select token from (select token, c from subs where length(token) > 1 and c >= 2 order by c * length(token) desc, token limit 300) union select token from subs where length(token) = 1", *_VOC))
def _(s, d):
    return vocab.seed(chunks(s, d), 300, LONGEST).select("token")


@query("merge_first_pairs", sql("select substr(chunk, i, 1) as a, substr(chunk, i + 1, 1) as b, sum(n)::bigint as c from (select chunk, n, unnest(range(1, length(chunk))) as i from chunks) group by all", "lines", "chunks"))
def _(s, d):
    return vocab.pair_counts(chunks(s, d).withColumn("syms", F.split("chunk", "")))


@query("lattice_edges", sql("select chunk, s::int as s, e::int as e, token_id from edges", *_LAT))
def _(s, d):
    lat = lattice.build(chunks(s, d).select("chunk").distinct(), small_vocab(s, d))
    return lat.select("chunk", F.explode("edges").alias("x")).select("chunk", "x.s", "x.e", F.col("x.t").alias("token_id"))


_WAYS = _fold(_places("", "e", "case when t{0} is not null then 0 end", "bigint"), "0", "bigint").replace("'x0': 0,", "'x0': case when x.v1 = 0 then coalesce(a.x0, 0) else 0 end + case when x.v2 = 0 then coalesce(a.x1, 0) else 0 end + case when x.v3 = 0 then coalesce(a.x2, 0) else 0 end,").replace("'x0': 0::bigint", "'x0': 1::bigint")


@query("path_counts", sql(f"select chunk, {_WAYS}.x0 as n_paths from ends group by chunk", *_LAT))
def _(s, d):
    lat = lattice.build(chunks(s, d).select("chunk").distinct(), small_vocab(s, d))
    return lat.select("chunk", lattice.count_paths(F.col("edges")).alias("n_paths"))


@query("segmentations", sql("select chunk, array_to_string((select list(token order by i) from (select unnest(toks) as tid, unnest(range(len(toks))) as i) join vocab on tid = token_id), '|') as said from paths", *_LAT, "paths"))
def _(s, d):
    """All splits, listed: of chunks of at most four characters, since their number doubles with each."""
    return lattice.enumerate_segmentations(chunks(s, d).where("length(chunk) <= 4").select("chunk").distinct(), small_vocab(s, d), 4).select("chunk", F.array_join("tokens", "|").alias("said"))


@query("lattice_cost", sql("select count(*) as chunks, sum(n * length(chunk))::bigint as characters, sum(n * k)::bigint as edges, (4 * sum(n * k))::bigint as relaxations, (sum(n * k) * 1000 // sum(n * length(chunk)))::bigint as branching_milli from u join (select chunk, count(*) as k from edges group by chunk) using (chunk)", *_LAT))
def _(s, d):
    return lattice.cost(lattice.build(chunks(s, d).groupBy("chunk").agg(F.sum("n").alias("n")), small_vocab(s, d)), 4)


# --- EM
def _named(s, d, df):
    return df.join(F.broadcast(small_vocab(s, d).select("token_id", "token")), "token_id")


@query("em_round1_expected", sql("select label, token, round(c, 4) as c from c1 join vocab using (token_id)", *_EM))
def _(s, d):
    return _named(s, d, rounds(s, d)["t1"]).select("label", "token", F.round("c", 4).alias("c"))


@query("em_round2_theta", sql("select label, token, round(logp, 6) as logp from t2 join vocab using (token_id) where c > 1e-9", *_EM))
def _(s, d):
    return _named(s, d, rounds(s, d)["t2"].where("c > 1e-9")).select("label", "token", F.round("logp", 6).alias("logp"))


@query("corpus_loglik_r1", sql("select label, round(sum(n * z), 3) as loglik from chunks join z1 using (chunk) group by label", *_EM))
def _(s, d):
    return em.corpus_loglik(rounds(s, d)["p1"]).select("label", F.round("loglik", 3).alias("loglik"))


@query("corpus_loglik_r2", sql("select w.label, round(sum(n * h[len(h)]), 3) as loglik from chunks w join f2 using (label, chunk) group by w.label", *_EM))
def _(s, d):
    return em.corpus_loglik(rounds(s, d)["p2"]).select("label", F.round("loglik", 3).alias("loglik"))


@query("tv_r1_r2", sql("select label, round(sum(abs(coalesce(exp(t1.logp), 0) - coalesce(exp(t2.logp), 0))) / 2, 8) as tv from t1 full join t2 using (label, token_id) group by label", *_EM))
def _(s, d):
    r = rounds(s, d)
    return em.total_variation(r["t1"], r["t2"]).select("label", F.round("tv", 8).alias("tv"))


@query("model_theta", sql("select label, token, fx as logp_fx from theta join vocab using (token_id)", *_EM))
def _(s, d):
    """As SegmentModel.fit leaves it."""
    return _named(s, d, small_model(s, d).theta).select("label", "token", "logp_fx")


@query("unseen_tokens", sql("select label, (select count(*) from vocab) - count(*) as unseen, count(*) as seen from seen group by label", *_EM))
def _(s, d):
    """Tokens that never occur in a label's corpus: no lattice of it has them, whatever count the rounds leave to those that occur."""
    return small_model(s, d).unseen()


@query("floors", sql("select label, n_samples, round(n_tokens, 3) as n_tokens, round(floor, 6) as floor from stats join samples using (label)", *_EM, "samples"))
def _(s, d):
    return small_model(s, d).stats.select("label", "n_samples", F.round("n_tokens", 3).alias("n_tokens"), F.round("floor", 6).alias("floor"))


@query("entropy_by_label", sql("select label, round(entropy, 6) as entropy from stats", *_EM))
def _(s, d):
    return small_model(s, d).stats.select("label", F.round("entropy", 6).alias("entropy"))


@query("floor_slope", sql("select round(regr_slope(floor, log10(n_tokens)), 6) as slope, count(*) as labels from stats", *_EM))
def _(s, d):
    return metrics.floor_slope(small_model(s, d).stats)


@query("model_size", sql("select (select count(*) from stats) as labels, (select count(*) from vocab) as tokens, (select count(*) from stats) * (select count(*) from vocab) as dense, count(*) as stored from theta", *_EM))
def _(s, d):
    return small_model(s, d).size()


@query("init_by_frequency", sql("select label, token, round(ln(c / sum(c) over (partition by label)), 6) as logp from (select label, token, sum(w.n)::double as c from chunks w join (select chunk, token from spans join vocab using (token)) x using (chunk) group by all)", *_VOC))
def _(s, d):
    v = small_vocab(s, d)
    t = em.start_theta(chunks(s, d), v, lattice.collect_vocab(v), "freq")
    return _named(s, d, t).select("label", "token", F.round("logp", 6).alias("logp"))


# --- scoring
@query("best_score_chunks", sql("select chunk, label, score_fx from wscore", *_TRAIN))
def _(s, d):
    return score.best_chunks(chunks(s, d), small_model(s, d)).select("chunk", "label", "score_fx")


@query("marginal_chunks", sql("select chunk, label, round(logp, 6) as logp from wscore", *_TRAIN))
def _(s, d):
    return score.marginal_chunks(chunks(s, d), small_model(s, d)).select("chunk", "label", F.round("logp", 6).alias("logp"))


@query("segmentation_chunks", sql("select chunk, label, score_fx, array_to_string((select list(coalesce(token, '?') order by i) from (select unnest(path) as tid, unnest(range(len(path))) as i) left join vocab on tid = token_id), '|') as said from wscore where chunk in (select chunk from u where n >= 5)".replace("left join", "join"), *_TRAIN))
def _(s, d):
    """How chunks that occur five times or more split under each label."""
    often = chunks(s, d).groupBy("chunk").agg(F.sum("n").alias("n")).where("n >= 5").select("chunk")
    return score.segment(often, score.whole_chunks(small_model(s, d)), "chunk").select("chunk", "label", "score_fx", F.array_join("tokens", "|").alias("said"))


@query("best_vs_marginal", sql("select label, round(avg(logp - score_fx / 1000000.0), 6) as mean_gap, count(*) as chunks, count_if(logp < score_fx / 1000000.0 - 0.0001) as below from wscore group by label", *_TRAIN))
def _(s, d):
    m = small_model(s, d)
    j = score.best_chunks(chunks(s, d), m).join(score.marginal_chunks(chunks(s, d), m), ["chunk", "label"]).withColumn("best", F.col("score_fx") / 1e6)
    return j.groupBy("label").agg(F.round(F.avg(F.col("logp") - F.col("best")), 6).alias("mean_gap"), F.count(F.lit(1)).alias("chunks"), F.count_if(F.col("logp") < F.col("best") - 0.0001).alias("below"))


@query("predict_documents", sql("select row_id as doc_id, label, fx as score_fx from ranked where r = 1", *_DOCS))
def _(s, d):
    """Whole documents, by the classifier as it is used."""
    return document_top(s, d).where("label is not null").select("doc_id", "label", F.round(F.col("score") * 1e6).cast("long").alias("score_fx"))


@query("margin_documents", sql("select row_id as doc_id, margin_fx::bigint as margin from top", *_DOCS))
def _(s, d):
    return document_top(s, d).where("label is not null").select("doc_id", F.round(F.col("margin") * 1e6).cast("long").alias("margin"))


@query("topk_documents", sql("select row_id as doc_id, string_agg(label, ',' order by r) as labels from ranked where r <= 3 group by row_id", *_DOCS))
def _(s, d):
    return document_top(s, d).where("label is not null").select("doc_id", F.array_join(F.transform(F.slice("topk", 1, 3), lambda x: x["label"]), ",").alias("labels"))


@query("posterior_documents", sql("select row_id as doc_id, label, round(p, 6) as p from ranked", *_DOCS))
def _(s, d):
    return document_top(s, d).select("doc_id", F.explode("posterior").alias("label", "p")).withColumn("p", F.round("p", 6))


@query("predict_snippets", sql("select row_id, gold, label from top join snips using (row_id) where bucket = 0", *_SNIP))
def _(s, d):
    return snippet_top(s, d).select("row_id", "gold", "label")


@query("margin_snippets", sql("select row_id, margin_fx::bigint as margin from top join snips using (row_id) where bucket = 0", *_SNIP))
def _(s, d):
    return snippet_top(s, d).select("row_id", F.round(F.col("margin") * 1e6).cast("long").alias("margin"))


@query("posterior_snippets", sql("select row_id, label, round(p, 6) as p from ranked join snips using (row_id) where bucket = 0", *_SNIP))
def _(s, d):
    return snippet_top(s, d).select("row_id", F.explode("posterior").alias("label", "p")).withColumn("p", F.round("p", 6))


#: A prior that changes decisions on short snippets.
PRIOR = {"de": 0.05, "en": 0.6, "es": 0.3, "fr": 0.05}
_PRIOR = "case label " + " ".join(f"when '{k}' then ln({v}::double)" for k, v in PRIOR.items()) + " end"


@query("prior_snippets", sql(f"select row_id, max_by(label, v) as label, round(1 / sum(exp(v - m)), 6) as p from (select *, max(v) over (partition by row_id) as m from (select row_id, label, score + {_PRIOR} as v from scores) join snips using (row_id) where bucket = 0) group by row_id", *_SNIP))
def _(s, d):
    """The label of the largest posterior under a prior, over all labels though one is listed."""
    rows = snippet_rows(s, d).where("bucket = 0")
    t = small_model(s, d).transform(rows, "snippet", topk=1, prior=PRIOR)
    return t.select("row_id", "label", F.round(F.col("posterior")[F.col("label")], 6).alias("p"))


@query("label_subset_predict", sql("select row_id, min_by(label, r) as label from ranked join snips using (row_id) where bucket = 0 and label in ('de', 'en', 'fr') group by row_id", *_SNIP))
def _(s, d):
    part = small_model(s, d).subset(["en", "fr", "de"])
    return part.transform(snippet_rows(s, d).where("bucket = 0"), "snippet").select("row_id", "label")


@query("marginal_predict", sql("select row_id, arg_max(label, v) as label from (select row_id, label, round(sum(m * logp), 6) as v from src join wscore using (chunk) group by all) join snips using (row_id) where bucket = 0 group by row_id", *_SNIP))
def _(s, d):
    return small_model(s, d).transform(snippet_rows(s, d).where("bucket = 0"), "snippet", how="marginal").select("row_id", "label")


# --- guards
@query("cap_counts", sql(f"select count_if(floor > {CAP}) as changed, count_if(floor <= {CAP}) as unchanged from stats", *_EM))
def _(s, d):
    return guard.cap_counts(small_model(s, d).stats, CAP)


@query("high_entropy_group", sql("""select label from (select *, median(abs(entropy - mid)) over () as mad from (select *, median(entropy) over () as mid from stats join samples using (label)))
    where n_samples >= 100 and entropy - mid > 0.5 * mad and mad > 0""", *_EM, "samples"))
def _(s, d):
    return guard.high_entropy_group(small_model(s, d).stats, parents(s), 0.5, 100)


@query("predict_capped", sql("select row_id, gold, label from top join snips using (row_id) where bucket = 0", *_CAPPED))
def _(s, d):
    rows = snippet_rows(s, d).where("bucket = 0")
    return guard.cap_unseen(small_model(s, d), CAP).transform(rows, "snippet").select("row_id", "gold", "label")


@query("thresholds", sql("select label, round(q, 6) as q, round(delta, 5) as delta from lim", *_LIMITS))
def _(s, d):
    return fitted_guard(s, d).limits.select("label", F.round("q", 6).alias("q"), F.round("delta", 5).alias("delta"))


@query("thresholds_shared", sql("select label, round(coalesce((select quantile_cont(margin, 0.05) from top join snips using (row_id) where bucket >= 2 and label = gold and label in (select label from sized)), 0), 5) as delta from sized", *_LIMITS))
def _(s, d):
    return fitted_guard(s, d, True).limits.select("label", F.round("delta", 5).alias("delta"))


@query("reexamined", sql("select count_if(looked) as looked, count_if(guarded <> label) as changed, count(*) as rows from gd join snips using (row_id) where bucket = 0", *_LIMITS, "guarded"))
def _(s, d):
    return metrics.reexam_counts(guarded(s, d))


@query("predict_guarded", sql("select row_id, gold, label, guarded from gd join snips using (row_id) where bucket = 0", *_LIMITS, "guarded"))
def _(s, d):
    return guarded(s, d).select("row_id", "gold", "label", "guarded")


@query("predict_guarded_documents", sql("select -1 - row_id as doc_id, label, looked, guarded from gd where row_id < 0", *_EM, "samples", "snips", "src_both", "capped", "rows", "limits", "guarded"))
def _(s, d):
    """Whole documents, by the guarded classifier as it is used."""
    return guarded_documents(s, d).where("label is not null").select("doc_id", "label", "looked", "guarded")


@query("fp_concentration", sql(f"select count_if(gold <> label) as false_positives, count_if(gold <> label and label in (select label from sized)) as into_groups, (count_if(gold <> label and label in (select label from sized)) * 1000000 // greatest(count_if(gold <> label), 1))::bigint as share_ppm, (count_if(gold in (select label from sized)) * 1000000 // count(*))::bigint as gold_ppm from top join snips using (row_id) cross join (select 1) where bucket = 0".replace("(select label from sized)", f"(select label from samples where n_samples < {MIN_SAMPLES})"), *_SNIP, "samples"))
def _(s, d):
    stats = small_model(s, d).stats
    return metrics.fp_concentration(snippet_top(s, d).select("gold", "label"), guard.small_group(stats, MIN_SAMPLES))


# --- baselines
for _smooth in ("add_k", "interp", "backoff"):
    query(f"ngram_lm_{_smooth.replace('_', '')}", sql("select row_id, gold, n_chars, label from pred", *_NG, p=_smooth))(lambda s, d, _smooth=_smooth: ngram_pred(s, d, _smooth))


@query("ngram_margins", sql("select row_id, label, (score - nxt)::bigint as margin from (select *, lead(score) over w as nxt, row_number() over w as r from ns window w as (partition by row_id order by score desc, label)) where r = 1", *_NG))
def _(s, d):
    rows = snippet_rows(s, d).where("bucket = 0").select("row_id", F.col("snippet").alias("text"))
    return runner_up(ngram(s, d).scores(rows, "row_id"), "row_id")


_POOLED = (*_EM, "pooled", "snips", "src_lines", "fixed")
SQL["pooled"] = "one as materialized (select '*' as label, chunk, n from u), " + _em_sql("z_", "one")
SQL["src_lines"] = f"""said as materialized (select doc_id * 100000 + line_no as row_id, label as gold, bucket, text from lines), src as materialized (select row_id, chunk, count(*) as m from (select row_id, unnest(regexp_extract_all(text, {_CH})) as chunk from said where bucket >= 2
        union all select -1 - row_id, unnest(regexp_extract_all(snippet, {_CH})) from snips where bucket = 0) group by all)"""
SQL["fixed"] = _score_sql("z_") + f""", ftok as materialized (select row_id, token_id, sum(m)::bigint as m from (select row_id, unnest(path) as token_id, m from src join z_wscore using (chunk)) group by all),
        fcnt as materialized (select gold as label, token_id, sum(m)::bigint as c from ftok join said using (row_id) where row_id >= 0 group by all), ftot as (select label, sum(c)::bigint as t from fcnt group by label),
        fval as materialized (select label, token_id, round(ln((coalesce(c, 0) + 0.5::double) / (t + 0.5::double * (select count(*) from vocab))) * 1000000)::bigint as v from (select distinct token_id from ftok where row_id < 0) cross join ftot left join fcnt using (label, token_id)),
        fsc as materialized (select -1 - row_id as row_id, label, sum(m * v)::bigint as score from ftok join fval using (token_id) where row_id < 0 group by all)"""


@query("fixed_seg_nb", sql("select row_id, gold, p.label from snips join (select row_id, min_by(label, struct_pack(s := -score, label := label)) as label from fsc group by row_id) p using (row_id)", *_POOLED))
def _(s, d):
    rows = snippet_rows(s, d).where("bucket = 0").select("row_id", "gold", F.col("snippet").alias("text"))
    return fixed_split(s, d).transform(rows, "row_id").select("row_id", "gold", "label")


@query("majority", sql("select row_id, gold, (select label from lines where bucket >= 2 group by label order by count(*) desc, label limit 1) as label from snips where bucket = 0", "lines", "snips"))
def _(s, d):
    return naive.majority(all_lines(s, d).where("bucket >= 2"), snippet_rows(s, d).where("bucket = 0").select("row_id", "gold"))


@query("uniform_random", sql(f"select row_id, gold, ['de', 'en', 'es', 'fr'][({_H8.format('snippet')} % 4)::int + 1] as label from snips where bucket = 0", "lines", "snips"))
def _(s, d):
    return naive.uniform(["de", "en", "es", "fr"], snippet_rows(s, d).where("bucket = 0"), "snippet").select("row_id", "gold", "label")


@query("tfidf_features", sql("select g, df, round(ln((n + 1.0) / (df + 1.0)), 6) as idf from (select g, count(distinct row_id) as df from (select row_id, unnest(list_transform(range(1, length(snippet) - 1), lambda i: substr(lower(snippet), i, 3))) as g from snips where bucket = 0 and length(snippet) >= 3) group by g) cross join (select count(*) as n from snips where bucket = 0) where df >= 3", "lines", "snips"))
def _(s, d):
    r = stash(snippet_rows(s, d).where("bucket = 0"), "rows")
    g = r.where("length(snippet) >= 3").select("row_id", F.explode(F.expr("array_distinct(transform(sequence(1, length(snippet) - 2), i -> substring(lower(snippet), i, 3)))")).alias("g"))
    df = g.groupBy("g").agg(F.count(F.lit(1)).alias("df")).where("df >= 3")
    return df.withColumn("idf", F.round(F.log((F.lit(r.count()) + 1.0) / (F.col("df") + 1.0)), 6))


# --- measures
_ROUND = ", ".join(f"round({c}, 6) as {c}" for c in ("precision", "recall", "f1", "fpr"))


@query("per_label_metrics", sql(f"select label, tp, fp, fn, tn, {_ROUND} from per2", *_MS))
def _(s, d):
    t = metrics.evaluate(ngram_pred(s, d))
    return t.withColumns({c: F.round(c, 6) for c in ("precision", "recall", "f1", "fpr")})


@query("macro_metrics", sql("select round(avg(f1), 6) as macro_f1, round(avg(fpr), 6) as macro_fpr, round(sum(tp) / sum(tp + fn), 6) as accuracy, sum(tp + fn)::bigint as rows from per2", *_MS))
def _(s, d):
    return metrics.macro(metrics.evaluate(ngram_pred(s, d)))


@query("accuracy_by_length", sql(f"select {_BAND} as band, round(avg((gold = label)::int), 6) as accuracy, count(*) as rows from pred group by 1", *_NG))
def _(s, d):
    return metrics.accuracy_by_length(ngram_pred(s, d))


@query("f1_by_size_band", sql(f"select case when n_samples >= {MIN_SAMPLES} then {MIN_SAMPLES} when n_samples >= 500 then 500 else 0 end::bigint as from_size, round(avg(f1), 6) as mean_f1, count(*) as labels from per2 join (select label, count(*) as n_samples from lines where bucket >= 2 group by label) using (label) group by 1", *_MS))
def _(s, d):
    stats = all_lines(s, d).where("bucket >= 2").groupBy("label").agg(F.count(F.lit(1)).alias("n_samples"))
    return metrics.f1_by_size(metrics.evaluate(ngram_pred(s, d)), stats, [500, MIN_SAMPLES])


@query("confusion_matrix", sql("select gold, label, count(*) as n from pred group by all", *_NG))
def _(s, d):
    return metrics.confusion(ngram_pred(s, d))


@query("confusion_pivot", sql("select gold, count_if(label = 'de') as de, count_if(label = 'en') as en, count_if(label = 'es') as es, count_if(label = 'fr') as fr from pred group by gold", *_NG))
def _(s, d):
    return ngram_pred(s, d).groupBy("gold").pivot("label", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


@query("top_confusions", sql("select gold, label, count(*) as n from pred where gold <> label group by all order by n desc, gold, label limit 5", *_NG))
def _(s, d):
    return metrics.top_confusions(ngram_pred(s, d), 5)


_RATES = (100, 500)
_NOISE = f"""noise as materialized (select rate, row_id, gold, string_agg(case when trim(ch) <> '' and h % 1000 < rate then substr('{text.LETTERS}', (h // 1000 % 26)::int + 1, 1) else ch end, '' order by i) as snippet
    from (select rate, row_id, gold, i, ch, {_H8.format("'1:' || doc_id || ':' || line_no || ':' || i")} as h from (select rate, row_id, row_id // 100000 as doc_id, row_id % 100000 as line_no, gold, unnest(string_split(snippet, '')) as ch, unnest(range(length(snippet))) as i
      from snips cross join (select unnest([{", ".join(map(str, _RATES))}]) as rate) where bucket = 0)) group by all)"""
SQL["noise"] = _NOISE
SQL["pred_noise"] = SQL["pred"].replace("select row_id, '  ' || lower(snippet) as p from snips where bucket = 0", "select row_id * 1000 + rate as row_id, '  ' || lower(snippet) as p from noise").replace("pred as materialized (select row_id, gold, n_chars, label from snips join", "pred as materialized (select rate, gold, label from (select row_id * 1000 + rate as row_id, rate, gold from noise) join")


@query("accuracy_by_corruption", sql("select rate, round(avg((gold = label)::int), 6) as accuracy, count(*) as rows from pred group by rate", "lines", "snips", "noise", "grams", "pred_noise"))
def _(s, d):
    src = snippet_rows(s, d).where("bucket = 0").select("row_id", F.expr("row_id div 100000").alias("doc_id"), (F.col("row_id") % 100000).alias("line_no"), "gold", F.col("snippet").alias("text"))
    noisy = None
    for r in _RATES:
        one = text.corrupt(src, r).select((F.col("row_id") * 1000 + r).alias("row_id"), F.lit(r).alias("rate"), "gold", "text")
        noisy = one if noisy is None else noisy.unionByName(one)
    return metrics.accuracy_by(ngram(s, d).transform(stash(noisy, "noisy"), "row_id"), "rate")


_FAM = "(values " + ", ".join(f"('{a}', '{b}', '{m}')" for a, b, _, m in PARENTS) + ") p(label, family, macro)"


@query("family_rollup", sql(f"select family, label, round(avg(f1), 6) as f1, count(*) as labels from per2 join {_FAM} using (label) group by rollup (family, label)", *_MS))
def _(s, d):
    return metrics.family_means(metrics.evaluate(ngram_pred(s, d)), parents(s))


@query("macro_accuracy", sql(f"select round(avg((a.macro = b.macro)::int), 6) as macro_accuracy, count(*) as rows from pred join {_FAM.replace(' p(', ' a(')} on a.label = pred.gold join {_FAM.replace(' p(', ' b(')} on b.label = pred.label", *_NG))
def _(s, d):
    return metrics.macro_accuracy(ngram_pred(s, d), parents(s))


@query("multilabel_f1", sql("select label, round(2 * tp / greatest(2 * tp + fp + fn, 1), 6) as f1 from (select g.label, coalesce(tp, 0) as tp, coalesce(fp, 0) as fp, fn from (select l as label, count_if(label <> l) as fn from (select label, unnest([gold, 'en']) as l from pred where gold <> 'en') group by l) g left join (select label, count_if(label in (gold, 'en')) as tp, count_if(label not in (gold, 'en')) as fp from pred where gold <> 'en' group by label) s using (label))", *_NG))
def _(s, d):
    return metrics.multilabel_f1(ngram_pred(s, d).where("gold <> 'en'").withColumn("golds", F.array("gold", F.lit("en"))))


_SH = "select {0}, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' '))) as g from (select {0}, list_filter(regexp_split_to_array(lower(text), '\\s+'), lambda x: x <> '') as w from {1}) where len(w) >= 5"


@query("contamination", f"with t as ({_SH.format('item_id', 'benchmark')}), s as (select distinct g from ({_SH.format('doc_id', 'documents')})) select (select count(*) from benchmark) as rows, (select count(distinct item_id) from t where g in (select g from s)) as contaminated")
def _(s, d):
    return metrics.contamination(read_table(s, d, "documents", ["text"]), read_table(s, d, "benchmark", ["item_id", "text"]))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v[0] for k, v in Q.items()}


def _counts(s: str) -> str:
    """count_if(x) as a filtered count, which is a bigint in DuckDB."""
    while (at := s.find("count_if(")) >= 0:
        depth, end = 1, at + 9
        while depth:
            depth += {"(": 1, ")": -1}.get(s[end], 0)
            end += 1
        s = f"{s[:at]}count(*) filter (where {s[at + 9 : end - 1]}){s[end:]}"
    return s


def oracle_sql() -> dict[str, str]:
    return {k: _counts(v[1]) for k, v in Q.items() if v[1]}
