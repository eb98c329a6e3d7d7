"""URL filters: explicit rules first, then trust and distrust carried over the link graph of hosts.

Links of all pages make weighted edges between hosts. Trust flows along links from hosts with allowed pages (personalised PageRank), distrust
flows against links from hosts with blocked pages (a host that links to blocked ones is suspect). What flows into a host without further links returns to the
seeds, so both ranks add up to 1 and can be compared. A host is blocked if its distrust exceeds its trust by a factor; a tie, up to TOLERANCE, is allowed.

Both ranks are carried together: each round is one join and one sum, a few rounds make a job whose result is written to the shared folder, and rounds end when what
is still on its way is under TOLERANCE of the whole. Edges, seeds and ranks stay in Spark. With x = seed + damping * flow(x) the mass that reaches hosts without links
is simply lost, and dividing by the sum at the end is the same as returning it in every round.

Defined cases: a null url, or one without "://", has empty host and path, fits no rule and is allowed; null or empty html has no links; repeated rows are judged alike and
their links count each; of two rules of one length that fit, the greater by name wins; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..io import join_small, read_table, spread, stash
from .common import ascii_lower

#: (verdict, rule): production parameters.
RULES = [("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/")]
DAMPING, FACTOR, TOLERANCE = 0.85, 1.0, 1e-5
#: Rounds of a job, and the most there can be: damping ** 120 is below TOLERANCE.
STEP, MOST_ROUNDS = 6, 120
#: Up to so many rules are folded into one expression; a longer list is joined as a table.
FEW_RULES = 200
#: Edges of a host up to which they meet its rank in one task.
DEGREE = 100_000


def after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def host_of(url: Column) -> Column:
    return ascii_lower(F.coalesce(F.regexp_extract(after_scheme(url), r"^([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(after_scheme(url), r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_for(host: Column, path: Column, rules: list[tuple[str, str]]) -> Column:
    """struct(rule, verdict) of the longest rule that fits, or null."""
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        name, _, rest = rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith("/" + rest)
        found = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(found)
    return found


def rule_table(spark: SparkSession, rules: list[tuple[str, str]]) -> DataFrame:
    """(name, prefix, rule, verdict)"""
    return spark.createDataFrame([(r.partition("/")[0], "/" + r.partition("/")[2], r, v) for v, r in rules], "name string, prefix string, rule string, verdict string")


def with_rules(pages: DataFrame, table: DataFrame) -> DataFrame:
    """Adds fit to rows with host and path, for any number of rules: each distinct host meets the rules of its own and its parents' names, and rows meet their
    host's list, which is as long as rules for one host are many."""
    hosts = pages.select("host").where("host <> ''").distinct()
    parents = F.transform(F.sequence(F.lit(0), F.size("p") - 1), lambda i: F.array_join(F.slice(F.col("p"), i + 1, F.size("p")), "."))
    each = hosts.withColumn("p", F.split("host", "\\.")).select("host", F.explode(parents).alias("name"))
    lists = each.join(table, "name").groupBy(F.col("host").alias("r_host")).agg(F.array_sort(F.collect_list(F.struct(F.length("rule").alias("n"), "rule", "prefix", "verdict"))).alias("r_list"))
    out = join_small(pages, stash(lists, "rules"), F.col("host") == F.col("r_host"))
    best = F.element_at(F.filter("r_list", lambda r: F.col("path").startswith(r["prefix"])), -1)
    fit = F.when(F.size(F.filter("r_list", lambda r: F.col("path").startswith(r["prefix"]))) > 0, F.struct(best["rule"].alias("rule"), best["verdict"].alias("verdict")))
    return out.withColumn("fit", fit).drop("r_host", "r_list")


def host_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(src, dst, n) between different hosts; summed before it is shuffled, so a hub costs a row for each task."""
    links = spread(pages.select(url_col, html_col)).select(host_of(F.col(url_col)).alias("src"), F.explode(F.regexp_extract_all(html_col, F.lit(r"""(?i)href\s*=\s*["']?(https?://[^"'\s>]+)"""), 1)).alias("link"))
    return links.select("src", host_of(F.col("link")).alias("dst")).where("src <> dst and src <> '' and dst <> ''").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def ranks(edges: DataFrame, seeds: DataFrame, damping: float = DAMPING, tolerance: float = TOLERANCE) -> DataFrame:
    """(kind, host, rank): personalised PageRank along src -> dst of each kind. edges is (kind, src, dst, n), seeds is (kind, host, seed) with seeds that add up to 1. Only
    hosts that rank has reached are carried. The edges of a hub are dealt to several tasks."""
    out = stash(edges.groupBy(F.col("kind").alias("o_kind"), F.col("src").alias("o_src")).agg(F.sum("n").alias("total"), (F.floor(F.count(F.lit(1)) / DEGREE) + 1).cast("int").alias("salts")), "degrees")
    with_out = edges.join(out, (F.col("kind") == F.col("o_kind")) & (F.col("src") == F.col("o_src")))
    share = stash(with_out.select(F.col("kind").alias("e_kind"), "src", "dst", (F.col("n") / F.col("total")).alias("p"), F.pmod(F.xxhash64("dst"), F.col("salts")).cast("int").alias("e_salt")), "shares")
    hubs = stash(out.where("salts > 1").select("o_kind", "o_src", "salts"), "hubs")
    any_hub = hubs.limit(1).count() > 0
    seeds = stash(seeds.select("kind", "host", "seed"), "seeds")
    x, before = seeds.withColumnRenamed("seed", "x"), {}
    for _ in range(0, MOST_ROUNDS, STEP):
        for _ in range(STEP):
            if any_hub:
                at = join_small(x, hubs, (F.col("kind") == F.col("o_kind")) & (F.col("host") == F.col("o_src")))
                x = at.select("kind", "host", "x", F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)).alias("salt"))
            else:
                x = x.withColumn("salt", F.lit(0))
            flow = share.join(x, (F.col("e_kind") == F.col("kind")) & (F.col("src") == F.col("host")) & (F.col("e_salt") == F.col("salt")))
            both = flow.select("kind", F.col("dst").alias("host"), (F.col("x") * F.col("p") * damping).alias("x")).unionByName(seeds.withColumnRenamed("seed", "x"))
            x = both.groupBy("kind", "host").agg(F.sum("x").alias("x"))
        x = stash(x, "ranks")
        total = {r["kind"]: r["t"] for r in x.groupBy("kind").agg(F.sum("x").alias("t")).collect()}  # a row a kind
        if all(t - before.get(k, 0.0) <= tolerance * t for k, t in total.items()):
            break
        before = total
    sums = x.groupBy(F.col("kind").alias("t_kind")).agg(F.sum("x").alias("t"))
    return x.join(F.broadcast(sums), F.col("kind") == F.col("t_kind")).select("kind", "host", (F.col("x") / F.col("t")).alias("rank"))  # a row a kind


def judge(pages: DataFrame, rules: list[tuple[str, str]] = RULES, damping: float = DAMPING, tolerance: float = TOLERANCE, factor: float = FACTOR, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, host, path, rule, verdict, trust, distrust) per page."""
    ruled = pages.select(F.col(id_col).alias("page_id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    if len(rules) <= FEW_RULES:
        ruled = ruled.withColumn("fit", rule_for(F.col("host"), F.col("path"), rules))
    else:
        ruled = with_rules(ruled, rule_table(pages.sparkSession, rules))
    links = stash(host_edges(pages, url_col, html_col), "links")
    edges = links.select(F.lit("allow").alias("kind"), "src", "dst", "n").unionByName(links.select(F.lit("block").alias("kind"), F.col("dst").alias("src"), F.col("src").alias("dst"), "n"))
    own = ruled.where(F.col("fit").isNotNull() & (F.col("host") != "")).groupBy(F.col("fit.verdict").alias("kind"), "host").agg(F.count(F.lit(1)).alias("n"))
    totals = own.groupBy(F.col("kind").alias("t_kind")).agg(F.sum("n").alias("total"))
    seeds = own.join(F.broadcast(totals), F.col("kind") == F.col("t_kind")).select("kind", "host", (F.col("n") / F.col("total")).alias("seed"))  # a row a kind
    rank = ranks(edges, seeds, damping, tolerance)
    of = lambda kind: F.coalesce(F.sum(F.when(F.col("kind") == kind, F.col("rank"))), F.lit(0.0))
    hosts = stash(rank.groupBy(F.col("host").alias("r_host")).agg(of("allow").alias("trust"), of("block").alias("distrust")), "hosts")
    out = join_small(ruled, hosts, F.col("host") == F.col("r_host")).withColumns({c: F.coalesce(c, F.lit(0.0)) for c in ("trust", "distrust")})
    suspect = F.col("distrust") > factor * (1 + tolerance) * F.col("trust")
    verdict = F.coalesce("fit.verdict", F.when(suspect, "block").otherwise("allow"))
    return out.select("page_id", "host", "path", F.col("fit.rule").alias("rule"), verdict.alias("verdict"), "trust", "distrust")


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(read_table(spark, sf_dir, "pages", ["page_id", "url", "html"])).drop("trust", "distrust")


def _rank_sql(name: str, src: str, dst: str, verdict: str) -> str:
    """As many rounds as there can be, each a step of a recursion over all hosts."""
    return f"""{name}_seed as materialized (select host, count(*)::double / sum(count(*)) over () as seed from ruled where verdict = '{verdict}' and host <> '' group by host),
{name}_p as materialized (select {src} as src, {dst} as dst, n::double / sum(n) over (partition by {src}) as p from edges),
{name}_x as (select 0 as k, host, seed as x from {name}_seed union all
  select k + 1, host, sum(x) from (select k, dst as host, x * p * {DAMPING} as x from {name}_x join {name}_p on src = host union all
    select k, s.host, s.seed from {name}_seed s cross join (select max(k) as k from {name}_x)) where k < {MOST_ROUNDS} group by k, host),
{name}_r as materialized (select host, x / sum(x) over () as rank from {name}_x where k = {MOST_ROUNDS})"""


def _fit_sql(what: int) -> str:
    cases = []
    for verdict, rule in sorted(RULES, key=lambda r: (-len(r[1]), r[1])):
        name, _, rest = rule.partition("/")
        cases.append(f"when (host = '{name}' or ends_with(host, '.{name}')) and starts_with(path, '/{rest}') then '{(verdict, rule)[what]}'")
    return "case " + " ".join(cases) + " end"


_HOST = "translate(coalesce(regexp_extract(case when instr({0}, '://') > 0 then substr({0}, instr({0}, '://') + 3) else '' end, '^([^/?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
OP7_SQL = f"""
with recursive h as (select page_id, html, {_HOST.format("url")} as host, coalesce(regexp_extract(case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end, '^[^/?#]*([^?#]*)', 1), '') as path from pages),
ruled as materialized (select page_id, host, path, {_fit_sql(1)} as rule, {_fit_sql(0)} as verdict from h),
links as (select host as src, unnest(regexp_extract_all(html, '(?i)href\\s*=\\s*["'']?(https?://[^"''\\s>]+)', 1)) as link from h),
edges as materialized (select src, {_HOST.format("link")} as dst, count(*) as n from links group by all having src <> dst and src <> '' and dst <> ''),
{_rank_sql("t", "src", "dst", "allow")},
{_rank_sql("d", "dst", "src", "block")}
select page_id, host, path, rule, coalesce(verdict, case when coalesce(d.rank, 0) > {FACTOR} * (1 + {TOLERANCE}) * coalesce(t.rank, 0) then 'block' else 'allow' end) as verdict
from ruled left join t_r t using (host) left join d_r d using (host)
"""
