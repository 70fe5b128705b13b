"""URL filter with redirect equivalence, in DataFrame operations only.

A rule names a host and the beginning of a path and fits the host with all its subdomains; the longest
rule that fits a url decides.  Urls that redirect to each other, or name the same canonical address, are
aliases: connected components over those edges.  A url without a rule is blocked if its component holds a
blocked url and none that a rule allows explicitly; else it is allowed.

Edges come from all canonical links and refresh directions of a page that stand neither in a comment nor in
a script, and from `redirects(source, target)` if given.  A target without a scheme is meant relative to its
page's base, which is its url unless a base tag says otherwise; character references in it are decoded.  Urls
are compared without scheme, fragment, letter case of the host, and a slash at the path's end.

Rules are an expression of the plan while they are few; more of them, or a table of rules, are joined by host.

Defined cases: a null url, or one without "://", has an empty host and path, fits no rule and is an alias
of nothing; a null page has no edges; repeated rows give a row each; an empty table gives an empty
result; further columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import components, materialize

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: More rules than this are joined as a table; the results are the same.
MAX_INLINE = 200


@dataclass(frozen=True)
class Rule:
    """text: host, then the path's beginning, as in "example.net/en/"."""

    text: str
    verdict: str

    @property
    def host(self) -> str:
        return self.text.partition("/")[0]

    @property
    def path(self) -> str:
        return "/" + self.text.partition("/")[2]


# The rules of the query.
RULES = (Rule("net/", "block"), Rule("example.net/en/", "allow"), Rule("example.com/de/", "block"), Rule("org/fr/", "allow"))


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def matched_rule(host: Column, path: Column, rules: tuple[Rule, ...] = RULES) -> tuple[Column, Column]:
    """(text, verdict) of the longest rule that fits, nulls if none does; of equally long ones, allow first."""
    text = verdict = None
    for rule in sorted(rules, key=lambda r: (-len(r.text), r.verdict, r.text)):
        fits = ((host == rule.host) | host.endswith("." + rule.host)) & path.startswith(rule.path)
        text = F.when(fits, rule.text) if text is None else text.when(fits, rule.text)
        verdict = F.when(fits, rule.verdict) if verdict is None else verdict.when(fits, rule.verdict)
    null = F.lit(None).cast("string")
    return (null, null) if text is None else (text, verdict)


def with_rules(rows: DataFrame, rules: tuple[Rule, ...] | DataFrame) -> DataFrame:
    """rows(host, path, ...) with rule and own, the text and the verdict of the rule that fits; rules: or a table (text, verdict)."""
    if not isinstance(rules, DataFrame):
        if len(rules) <= MAX_INLINE:
            text, verdict = matched_rule(F.col("host"), F.col("path"), rules)
            return rows.withColumn("rule", text).withColumn("own", verdict)
        rules = rows.sparkSession.createDataFrame([(r.text, r.verdict) for r in rules], "text string, verdict string")
    cut = F.split("text", "/", 2)
    table = rules.select(cut[0].alias("at_host"), F.concat(F.lit("/"), F.coalesce(F.get(cut, F.lit(1)), F.lit(""))).alias("at_path"), "text", "verdict")
    names = rows.select("host", "path").distinct()
    labels = F.split("host", r"\.")
    above = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda k: F.array_join(F.slice(labels, k, F.size(labels)), "."))
    met = names.select("host", "path", F.explode(above).alias("at_host")).join(table, "at_host").where(F.col("path").startswith(F.col("at_path")))
    best = met.groupBy("host", "path").agg(F.min(F.struct(-F.length("text"), "verdict", "text")).alias("best"))
    best = best.select("host", "path", F.col("best.text").alias("rule"), F.col("best.verdict").alias("own"))
    return rows.join(best, ["host", "path"], "left")


def query_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^?#]*(\?[^#]*)", 1), F.lit(""))


def address(url: Column) -> Column:
    """What two spellings of a url share; null without "://"."""
    return F.when(url.contains("://"), F.concat(host_of(url), F.regexp_replace(path_of(url), r"/\z", ""), query_of(url)))


# Character references that addresses have, the ampersand's last.
REFERENCES = (("&quot;", '"'), ("&#34;", '"'), ("&apos;", "'"), ("&#39;", "'"), ("&lt;", "<"), ("&gt;", ">"), ("&#47;", "/"), ("&#x2F;", "/"), ("&#38;", "&"), ("&#x26;", "&"), ("&amp;", "&"))
# What holds no tags, the tags, and their addresses, in quotes of either kind or in none.
UNSEEN = r"(?is)<!--.*?-->|<script\b.*?</script\s*>"
CANONICAL = r"""(?is)<link\b[^>]*[\s"']rel\s*=\s*(?:"[^">]*\bcanonical\b[^">]*"|'[^'>]*\bcanonical\b[^'>]*'|canonical\b)[^>]*>"""
REFRESH = r"""(?is)<meta\b[^>]*[\s"']http-equiv\s*=\s*["']?\s*refresh\b[^>]*>"""
BASE = r"""(?is)<base\b[^>]*[\s"']href\s*=[^>]*>"""
HREF = r"""(?is)[\s"']href\s*=\s*(?:"\s*([^">]*?)\s*"|'\s*([^'>]*?)\s*'|([^\s"'>]+))"""
MOVED = r"""(?is)\burl\s*=\s*(?:"\s*([^">]*?)\s*"|'\s*([^'>]*?)\s*'|([^\s"'>]+))"""


def _value(tag: Column, pattern: str) -> Column:
    """The address in a tag, decoded; empty without one."""
    out = F.concat(*(F.regexp_extract(tag, pattern, k) for k in (1, 2, 3)))
    for name, char in REFERENCES:
        out = F.replace(out, F.lit(name), F.lit(char))
    return out


def resolved(source: Column, target: Column) -> Column:
    """The url that target means on the page source; a target with a scheme of its own stays as it is."""
    site = F.regexp_extract(source, r"(?s)^(.*?://[^/?#]*)", 1)
    path, query = path_of(source), query_of(source)
    own, rest = F.regexp_extract(target, r"(?s)^([^?#]*)", 1), F.regexp_extract(target, r"(?s)^[^?#]*(.*)", 1)
    # beside the page: its path up to the last slash, then the target's without steps "." and ".."
    steps = F.split(F.concat(F.regexp_extract(path, r"(?s)^/(.*/)?", 1), own), "/", -1)
    steps = F.when(F.element_at(steps, -1).isin(".", ".."), F.concat(steps, F.array(F.lit("")))).otherwise(steps)
    walked = F.aggregate(
        steps,
        F.array().cast("array<string>"),
        lambda done, s: F.when(s == ".", done).when(s == "..", F.slice(done, F.lit(1), F.greatest(F.size(done) - 1, F.lit(0)))).otherwise(F.concat(done, F.array(s))),
    )
    beside = F.concat(site, F.lit("/"), F.array_join(walked, "/"), rest)
    return (
        F.when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:"), target)
        .when(target.startswith("//"), F.concat(F.lit("http:"), target))
        .when(target.startswith("/"), F.concat(site, target))
        .when(target.startswith("?"), F.concat(site, path, target))
        .when(target.startswith("#"), F.concat(site, path, query, target))
        .otherwise(beside)
    )


def page_links(pages: DataFrame) -> DataFrame:
    """(source, target) urls from canonical links and refresh directions."""
    small = F.lower("html")
    marked = pages.where(small.contains("canonical") | small.contains("refresh"))
    shown = marked.select(F.col("url").alias("source"), F.regexp_replace("html", UNSEEN, "").alias("html"))
    tags = F.concat(
        F.transform(F.regexp_extract_all("html", F.lit(CANONICAL), F.lit(0)), lambda tag: _value(tag, HREF)),
        F.transform(F.regexp_extract_all("html", F.lit(REFRESH), F.lit(0)), lambda tag: _value(tag, MOVED)),
    )
    base = _value(F.regexp_extract("html", BASE, 0), HREF)
    found = shown.select("source", base.alias("base"), F.explode(F.array_distinct(tags)).alias("target")).where("target != ''")
    beside = F.when(F.col("base") == "", F.col("source")).otherwise(resolved(F.col("source"), F.col("base")))
    return found.select("source", beside.alias("base"), "target").select("source", resolved(F.col("base"), F.col("target")).alias("target"))


def judge_urls(pages: DataFrame, rules: tuple[Rule, ...] | DataFrame = RULES, redirects: DataFrame | None = None) -> DataFrame:
    """For each row of pages(page_id, url, html): page_id, url, host, path, rule, alias (its component), verdict."""
    links = page_links(pages)
    if redirects is not None:
        links = links.unionByName(redirects.select("source", "target"))
    links = materialize(links.where("source is not null and target is not null"), "links")
    named = links.select(address(F.col("source")).alias("a"), address(F.col("target")).alias("b"))
    alias = components(named.where("a is not null and b is not null"))
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    rows = pages.select("page_id", "url").withColumn("host", host).withColumn("path", path)
    rows = with_rules(rows, rules).withColumn("node", address(F.col("url")))
    # an alias's own rule counts whether the page is in the table or not
    ends = links.select(F.col("source").alias("url")).unionByName(links.select(F.col("target").alias("url"))).distinct()
    ends = with_rules(ends.withColumn("host", host).withColumn("path", path), rules).withColumn("node", address(F.col("url")))
    known = ends.select("node", "own").unionByName(rows.select("node", "own")).where("node is not null and own is not null")
    known = known.groupBy("node").agg(F.bool_or(F.col("own") == "block").alias("block"), F.bool_or(F.col("own") == "allow").alias("allow"))
    sides = alias.join(known, "node").groupBy("component").agg(F.bool_or("block").alias("block"), F.bool_or("allow").alias("allow"))
    # one row per url that is linked at all: its component, and whether that is blocked
    judged = materialize(
        alias.join(sides, "component", "left").select(
            F.col("node").alias("alias_node"), F.col("component").alias("alias"), F.coalesce(F.col("block") & ~F.col("allow"), F.lit(False)).alias("blocked")
        ),
        "aliases",
    )
    return rows.join(judged, rows["node"] == judged["alias_node"], "left").select(
        "page_id", "url", "host", "path", "rule", "alias",
        F.coalesce("own", F.when(F.col("blocked"), "block"), F.lit("allow")).alias("verdict"),
    )


def op5_url_filter(spark, sf_dir) -> DataFrame:
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet")).drop("url")


def _sql_text(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def oracle_sql(rules: tuple[Rule, ...] = RULES) -> str:
    """judge_urls in DuckDB's SQL."""
    site = "regexp_extract({u}, '(?s)^(.*?://[^/?#]*)', 1)"
    host = f"translate(coalesce(regexp_extract({{u}}, '(?s)^.*?://([^/?#]*)', 1), ''), '{UPPER}', '{LOWER}')"
    path = "coalesce(regexp_extract({u}, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '')"
    query = r"coalesce(regexp_extract({u}, '(?s)^.*?://[^?#]*(\?[^#]*)', 1), '')"
    node = rf"CASE WHEN contains({{u}}, '://') THEN {host} || regexp_replace({path}, '/\z', '') || {query} END"
    best = sorted(rules, key=lambda r: (-len(r.text), r.verdict, r.text))
    fits = lambda r: f"(h = {_sql_text(r.host)} OR ends_with(h, {_sql_text('.' + r.host)})) AND starts_with(p, {_sql_text(r.path)})"
    ruled = "CASE " + " ".join(f"WHEN {fits(r)} THEN {_sql_text(r.text)}" for r in best) + " END"
    side = lambda verdict: ", ".join(_sql_text(r.text) for r in rules if r.verdict == verdict)

    def value(tag: str, pattern: str) -> str:
        out = " || ".join(f"regexp_extract({tag}, {_sql_text(pattern)}, {k})" for k in (1, 2, 3))
        for name, char in REFERENCES:
            out = f"replace({out}, {_sql_text(name)}, {_sql_text(char)})"
        return out

    def meant(u: str, t: str) -> str:
        own, rest = f"regexp_extract({t}, '(?s)^([^?#]*)', 1)", f"regexp_extract({t}, '(?s)^[^?#]*(.*)', 1)"
        steps = f"string_split(regexp_extract({path.format(u=u)}, '(?s)^/(.*/)?', 1) || {own}, '/')"
        steps = f"CASE WHEN {steps}[-1] IN ('.', '..') THEN list_append({steps}, '') ELSE {steps} END"
        walked = f"""list_reduce(list_concat([CAST([] AS VARCHAR[])], list_transform({steps}, lambda s: [s])),
          lambda done, s: CASE WHEN s[1] = '.' THEN done WHEN s[1] = '..' THEN done[1:len(done) - 1] ELSE list_concat(done, s) END)"""
        return rf"""CASE WHEN regexp_matches({t}, '^[A-Za-z][A-Za-z0-9+.-]*:') THEN {t} WHEN starts_with({t}, '//') THEN 'http:' || {t}
      WHEN starts_with({t}, '/') THEN {site.format(u=u)} || {t} WHEN starts_with({t}, '?') THEN {site.format(u=u)} || {path.format(u=u)} || {t}
      WHEN starts_with({t}, '#') THEN {site.format(u=u)} || {path.format(u=u)} || {query.format(u=u)} || {t}
      ELSE {site.format(u=u)} || '/' || coalesce(array_to_string({walked}, '/'), '') || {rest} END"""

    return f"""
WITH RECURSIVE parts AS (SELECT page_id, url, coalesce(html, '') AS html, {host.format(u="url")} AS h, {path.format(u="url")} AS p FROM pages),
ruled AS (SELECT *, {ruled} AS rule, {node.format(u="url")} AS node FROM parts),
shown AS (SELECT url, regexp_replace(html, {_sql_text(UNSEEN)}, '', 'g') AS html FROM parts WHERE url IS NOT NULL AND (html ILIKE '%canonical%' OR html ILIKE '%refresh%')),
tags AS (
  SELECT url, base, unnest(list_distinct(list_concat(list_transform(canon, lambda c: {value("c", HREF)}), list_transform(fresh, lambda c: {value("c", MOVED)})))) AS target
  FROM (SELECT url, {value(f"regexp_extract(html, {_sql_text(BASE)}, 0)", HREF)} AS base,
               regexp_extract_all(html, {_sql_text(CANONICAL)}) AS canon, regexp_extract_all(html, {_sql_text(REFRESH)}) AS fresh FROM shown)),
beside AS (SELECT url, CASE WHEN base = '' THEN url ELSE {meant("url", "base")} END AS base, target FROM tags WHERE target <> ''),
links AS (SELECT url AS source, {meant("base", "target")} AS target FROM beside),
ends AS (SELECT url, {host.format(u="url")} AS h, {path.format(u="url")} AS p FROM (SELECT source AS url FROM links UNION SELECT target FROM links)),
known AS (SELECT node, rule FROM ruled WHERE rule IS NOT NULL UNION SELECT {node.format(u="url")}, {ruled} FROM ends),
sides AS (
  SELECT node, bool_or(rule IN ({side("block")})) AS block, bool_or(rule IN ({side("allow")})) AS allow
  FROM known WHERE node IS NOT NULL AND rule IS NOT NULL GROUP BY node),
edges AS (SELECT {node.format(u="source")} AS a, {node.format(u="target")} AS b FROM links),
both_ways AS (SELECT a, b FROM edges WHERE a <> b UNION SELECT b, a FROM edges WHERE a <> b),
reach(a, b) AS (SELECT a, b FROM both_ways UNION SELECT r.a, e.b FROM reach r JOIN both_ways e ON r.b = e.a),
near AS (SELECT a, b FROM reach UNION SELECT a, a FROM both_ways),
alias AS (SELECT near.a AS node, min(near.b) AS alias, bool_or(block) AND NOT bool_or(allow) AS blocked FROM near LEFT JOIN sides ON near.b = sides.node GROUP BY near.a)
SELECT page_id, h AS host, p AS path, rule, alias.alias AS alias,
       CASE WHEN rule IN ({side("block")}) THEN 'block' WHEN rule IS NOT NULL THEN 'allow' WHEN alias.blocked THEN 'block' ELSE 'allow' END AS verdict
FROM ruled LEFT JOIN alias ON ruled.node = alias.node
"""


OP5_SQL = oracle_sql()
