"""URL filters: rules, then link-graph propagation for hosts that no rule decides.

A rule names a host and a path and fits that host and its subdomains where the URL's path starts with the rule's; the
longest rule wins. Pages that no rule fits get the verdict of their host in the graph of links between hosts:

- trust is a personalised PageRank that starts from hosts with allowed pages and follows links;
- distrust starts from hosts with blocked pages and follows links backwards: whoever links there is suspect.

A host is blocked if its distrust exceeds its trust by more than ``margin`` times the share it would have if all hosts had
the same. Links of a host to itself carry nothing; mass that finds no link returns to the seeds.

The rank is a sum over all numbers of steps away from the seeds, scaled to one: each round moves the last term one step on and
adds it, and the rounds go on until the terms still to come weigh less than the tolerance. A term weighs at most ``damping`` times
the one before, so the number of rounds has a bound, beyond which an error is raised.

Everything is aggregated to pairs of hosts before it is joined, both propagations run in the same joins, and each round's
ranks are written to the shared folder. Nothing is collected but two sums per round.

Of rules that fit, the longest (host and path together) wins; of equally long ones that with the longer host, then ``block``.
They are part of the expression if few and joined as a table if many, with the same result. Rules with a null part fit nothing.

Defined cases: a URL that is null or has no ``://`` has an empty host and path, takes no part in the graph and is
allowed; null html has no links; repeated rows count each; without seeds or links nothing is propagated; an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .store import materialise

#: Fixed values: (verdict, host, path).
RULES = [
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
]
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
LINK = r"""<[aA]\s[^>]*?[hH][rR][eE][fF]\s*=\s*["']([^"']*)["']"""
SCHEME = "^[A-Za-z][A-Za-z0-9+.-]*:"
DAMPING = 0.85
#: Share of a rank's mass that may be missing when propagation ends.
TOLERANCE = 1e-9
MARGIN = 1.0
#: More rules than this are joined as a table instead of being part of the expression.
INLINE_RULES = 200


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, "://([^/?#]*)", 1), F.lit("")), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, "://[^/?#]*([^?#]*)", 1), F.lit(""))


def fits(host: Column, path: Column, rule_host: Column, rule_path: Column) -> Column:
    return ((host == rule_host) | host.endswith(F.concat(F.lit("."), rule_host))) & path.startswith(rule_path)


def apply_rules(pages: DataFrame, rules: list[tuple[str, str, str]] | DataFrame) -> DataFrame:
    """Adds rule and rule_verdict (null where none fits) to rows with host and path. Rules are (verdict, host, path)."""
    if isinstance(rules, list) and len(rules) <= INLINE_RULES:
        rule = verdict = F.lit(None).cast("string")
        for v, h, p in sorted((r for r in rules if None not in r), key=lambda r: (len(r[1]) + len(r[2]), len(r[1]), r[0])):
            hit = fits(F.col("host"), F.col("path"), F.lit(h), F.lit(p))
            rule, verdict = F.when(hit, F.lit(h + p)).otherwise(rule), F.when(hit, F.lit(v)).otherwise(verdict)
        return pages.withColumn("rule", rule).withColumn("rule_verdict", verdict)
    table = pages.sparkSession.createDataFrame(rules, "verdict string, rule_host string, rule_path string") if isinstance(rules, list) else rules
    # each distinct (host, path) meets the rules of its own suffixes only
    labels = F.split("host", "\\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    each = pages.select("host", "path").distinct().withColumn("rule_host", F.explode(suffixes)).join(table, "rule_host").where(F.col("path").startswith(F.col("rule_path")))
    full = F.concat("rule_host", "rule_path")
    order = F.struct(F.length(full).alias("n"), F.length("rule_host").alias("n_host"), F.col("verdict"), full.alias("rule"))
    best = each.where("verdict is not null").groupBy(F.col("host").alias("_h"), F.col("path").alias("_p")).agg(F.max(order).alias("_best"))
    best = best.select("_h", "_p", F.col("_best.rule").alias("rule"), F.col("_best.verdict").alias("rule_verdict"))
    return pages.join(best, (F.col("host") == F.col("_h")) & (F.col("path") == F.col("_p")), "left").drop("_h", "_p")


def host_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(src, dst, n): links between different hosts."""
    link = F.col("link")
    target = (
        F.when(link.rlike(SCHEME + "//"), F.regexp_extract(link, "://([^/?#]*)", 1))
        .when(link.startswith("//"), F.regexp_extract(link, "^//([^/?#]*)", 1))
        .when(link.rlike(SCHEME), F.lit(None))
        .otherwise(F.lit(""))  # relative: the page's own host
    )
    links = pages.select(host_of(F.col(url_col)).alias("src"), F.explode(F.regexp_extract_all(html_col, F.lit(LINK), F.lit(1))).alias("link"))
    found = links.select("src", F.translate(target, _UPPER, _LOWER).alias("dst"))
    return found.where("src <> '' and dst <> '' and src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def propagate(edges: DataFrame, seeds: DataFrame, damping: float = DAMPING, tolerance: float = TOLERANCE) -> DataFrame:
    """(kind, host, rank) for kinds trust and distrust. Edges are (src, dst, n), seeds (kind, host, mass) of sum 1 per kind."""
    if not 0 <= damping < 1:
        raise ValueError("damping must be at least 0 and less than 1")
    both = edges.select(F.lit("trust").alias("kind"), F.col("src").alias("host"), F.col("dst").alias("to"), "n").unionByName(
        edges.select(F.lit("distrust").alias("kind"), F.col("dst").alias("host"), F.col("src").alias("to"), "n")
    )
    outgoing = materialise(both.groupBy("kind", "host").agg(F.sum("n").alias("all")), "hosts-out")
    shares = materialise(both.join(outgoing, ["kind", "host"]).select("kind", "host", "to", (F.col("n") / F.col("all")).alias("share")), "host-shares")
    state = seeds.select("kind", "host", F.col("mass").alias("term"), F.col("mass").alias("total"))
    to_come = damping / (1 - damping) if damping else 0.0  # weight of all later terms beside the last one, at most
    most = 2 + math.ceil(math.log(tolerance / to_come) / math.log(damping)) if to_come > tolerance else 1
    for _ in range(most):
        term = damping * F.sum(F.col("term") * F.col("share"))
        moved = state.where("term > 0").join(shares, ["kind", "host"]).groupBy("kind", F.col("to").alias("host")).agg(term.alias("term"))
        parts = moved.select("kind", "host", "term", F.col("term").alias("total")).unionByName(state.select("kind", "host", F.lit(0.0).alias("term"), "total"))
        state = materialise(parts.groupBy("kind", "host").agg(F.sum("term").alias("term"), F.sum("total").alias("total")), "host-ranks")
        sums = {r.kind: r for r in state.groupBy("kind").agg(F.sum("term").alias("term"), F.sum("total").alias("total")).collect()}  # two rows at most
        if all(r.term * to_come <= tolerance for r in sums.values()):
            whole = {kind: sums[kind].total if kind in sums else 1.0 for kind in ("trust", "distrust")}
            return state.select("kind", "host", (F.col("total") / F.when(F.col("kind") == "trust", whole["trust"]).otherwise(whole["distrust"])).alias("rank"))
    raise RuntimeError(f"propagation did not settle in {most} rounds")


def filter_urls(
    pages: DataFrame, rules: list[tuple[str, str, str]] | DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html",
    damping: float = DAMPING, tolerance: float = TOLERANCE, margin: float = MARGIN,
) -> DataFrame:
    """(id, host, path, rule, verdict, trust, distrust): the last two are the host's shares, null without a host."""
    rows = pages.select(F.col(id_col).alias(id_col), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    judged = materialise(apply_rules(rows, rules), "url-rules")
    hosts = materialise(
        judged.where("host <> ''").groupBy("host").agg(F.count_if(F.col("rule_verdict") == "allow").alias("allowed"), F.count_if(F.col("rule_verdict") == "block").alias("blocked")), "url-hosts"
    )
    edges = materialise(host_edges(pages, url_col, html_col), "host-edges")
    allowed, blocked = hosts.agg(F.sum("allowed"), F.sum("blocked")).first()
    seeds = hosts.where("allowed > 0").select(F.lit("trust").alias("kind"), "host", (F.col("allowed") / F.lit(float(allowed or 1))).alias("mass")).unionByName(
        hosts.where("blocked > 0").select(F.lit("distrust").alias("kind"), "host", (F.col("blocked") / F.lit(float(blocked or 1))).alias("mass"))
    )
    ranks = propagate(edges, materialise(seeds, "url-seeds"), damping, tolerance)
    known = hosts.select("host").unionByName(edges.select(F.col("src").alias("host"))).unionByName(edges.select(F.col("dst").alias("host"))).distinct()
    n_hosts = max(known.count(), 1)
    rank = lambda kind: F.coalesce(F.sum(F.when(F.col("kind") == kind, F.col("rank"))), F.lit(0.0)).alias(kind)
    scores = materialise(ranks.groupBy(F.col("host").alias("_host")).agg(rank("trust"), rank("distrust")), "host-scores")
    out = judged.join(scores, F.col("host") == F.col("_host"), "left").drop("_host")
    here = F.col("host") != ""
    trust, distrust = (F.when(here, F.coalesce(F.col(c), F.lit(0.0))) for c in ("trust", "distrust"))
    out = out.withColumn("trust", trust).withColumn("distrust", distrust)
    by_graph = F.when(F.col("distrust") - F.col("trust") > margin / n_hosts, "block").otherwise("allow")
    return out.select(id_col, "host", "path", "rule", F.coalesce("rule_verdict", by_graph).alias("verdict"), "trust", "distrust")


def op3_url_filters(spark, sf_dir: str) -> DataFrame:
    out = filter_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"), RULES)
    return out.select("page_id", "host", "path", "rule", "verdict")


def _op3_sql() -> str:
    host = lambda x: f"translate(coalesce(regexp_extract({x}, '://([^/?#]*)', 1), ''), '{_UPPER}', '{_LOWER}')"
    cases = sorted(RULES, key=lambda r: (len(r[1] + r[2]), len(r[1]), r[0]), reverse=True)
    fit = lambda r: f"(host = '{r[1]}' or ends_with(host, '.{r[1]}')) and starts_with(path, '{r[2]}')"
    rule = " ".join(f"when {fit(r)} then '{r[1]}{r[2]}'" for r in cases)
    verdict = " ".join(f"when {fit(r)} then '{r[0]}'" for r in cases)
    link = LINK.replace("'", "''")
    ctes = [
        f"u as materialized (select page_id, {host('url')} as host, coalesce(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '') as path, html from pages)",
        f"j as materialized (select page_id, host, path, case {rule} end as rule, case {verdict} end as rv from u)",
        "h as materialized (select host, count(*) filter (rv = 'allow') as a, count(*) filter (rv = 'block') as b from j where host <> '' group by host)",
        f"l as (select host as src, unnest(regexp_extract_all(html, '{link}', 1)) as link from u)",
        f"e as materialized (select src, dst, count(*) as n from (select src, case when regexp_matches(link, '{SCHEME}//') then {host('link')} when starts_with(link, '//') then translate(regexp_extract(link, '^//([^/?#]*)', 1), '{_UPPER}', '{_LOWER}') when regexp_matches(link, '{SCHEME}') then null else '' end as dst from l) where src <> '' and dst <> '' and src <> dst group by src, dst)",
        "both_ways as (select 'trust' as kind, src as host, dst as to_host, n from e union all select 'distrust', dst, src, n from e)",
        "s as materialized (select kind, host, to_host, n / sum(n) over (partition by kind, host) as share from both_ways)",
        "r0 as materialized (select 'trust' as kind, host, a / (select sum(a) from h) as r from h where a > 0 union all select 'distrust', host, b / (select sum(b) from h) from h where b > 0)",
        f"t as (select kind, host, r::DOUBLE as r, 0 as k from r0 union all select kind, to_host, {DAMPING}::DOUBLE * sum(r * share), k + 1 from t join s using (kind, host) where k < 200 group by kind, to_host, k)",
        "x as (select kind, host, sum(r) as r from t group by kind, host)",
        "y as (select kind, host, r / sum(r) over (partition by kind) as r from x)",
    ]
    return f"""with recursive {', '.join(ctes)},
sc as (select host, coalesce(sum(r) filter (kind = 'trust'), 0) as t, coalesce(sum(r) filter (kind = 'distrust'), 0) as d from y group by host),
nh as (select greatest(count(*), 1) as n from (select host from h union select src from e union select dst from e))
select page_id, j.host, path, rule, coalesce(rv, case when j.host <> '' and coalesce(d, 0) - coalesce(t, 0) > {MARGIN}::DOUBLE / nh.n then 'block' else 'allow' end) as verdict
from j left join sc on sc.host = j.host cross join nh"""


OP3_SQL = _op3_sql()
