"""URL filters: host and path rules, and block decisions that spread over redirects, canonical links and equivalent spellings.

Pages and the addresses they redirect to or name as canonical are nodes; connected components of these links are groups
of aliases. An address with a rule keeps the rule's verdict. Any other takes block if its group holds a blocked address
and no address that a rule allows; an explicit allow goes first. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .shared import join_by_size, stored

# The rules of the contract.
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))
CANONICAL = r"""(?is)<link\b(?=[^>]*\brel\s*=\s*["']?canonical\b)[^>]*\bhref\s*=\s*["']?([^"'\s>]+)"""
REFRESH = r"""(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*["']?refresh\b)[^>]*\bcontent\s*=\s*["']?\s*[0-9.]*\s*;\s*url\s*=\s*["']?([^"'\s>]+)"""
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_for(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits, else null; rules are a short literal list, checked longest first."""
    if len(rules) > 2000:
        raise ValueError("give a longer list of rules as a table, to match_rules()")
    out = F.lit(None).cast("string")
    for _, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        rule_host, slash, rest = rule.partition("/")
        fits = ((host == rule_host) | host.endswith("." + rule_host)) & path.startswith(slash + rest)
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


def match_rules(pages: DataFrame, rules: DataFrame) -> DataFrame:
    """For long lists: pages (page_id, host, path) and rules (verdict, rule) -> page_id, rule, verdict; an equi-join on each suffix of the host."""
    labels = F.split("host", r"\.")
    suffixes = pages.withColumn("suffix", F.explode(F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.concat_ws(".", F.slice(labels, i, F.size(labels))))))
    named = rules.select("verdict", "rule", F.substring_index("rule", "/", 1).alias("suffix"), F.expr("substring(rule, instr(rule, '/'))").alias("start"))
    hit = suffixes.join(named, "suffix").where(F.col("path").startswith(F.col("start")))
    return hit.groupBy("page_id").agg(F.max_by(F.struct("rule", "verdict"), F.struct(F.length("rule"), "rule")).alias("r")).select("page_id", "r.*")


def normal_form(url: Column) -> Column:
    """One spelling for equivalent addresses: no scheme, fragment, default port, `www.` or tracking parameters, and no last slash."""
    host = F.regexp_replace(F.regexp_replace(host_of(url), r"^www\.", ""), r":(80|443)$", "")
    query = F.regexp_extract(url, r"(?s)^[^?#]*\?([^#]*)", 1)
    kept = F.array_sort(F.filter(F.split(query, "&"), lambda p: (p != "") & ~p.rlike(r"^(utm_[a-z]+|ref|fbclid|gclid)(=|$)")))
    path = F.regexp_replace(path_of(url), r"/+$", "")
    return F.when(host != "", F.concat(host, path, F.when(F.size(kept) > 0, F.concat(F.lit("?"), F.concat_ws("&", kept))).otherwise("")))


def resolved(base: Column, link: Column) -> Column:
    """A link as an absolute address, seen from a page."""
    scheme = F.regexp_extract(base, r"(?s)^(.*?)://", 1)
    root = F.concat(scheme, F.lit("://"), host_of(base))
    folder = F.regexp_replace(path_of(base), r"[^/]*$", "")
    return (
        F.when(F.coalesce(link, F.lit("")) == "", None)
        .when(link.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*://"), link)
        .when(link.startswith("//"), F.concat(scheme, F.lit(":"), link))
        .when(link.startswith("/"), F.concat(root, link))
        .otherwise(F.concat(root, F.when(folder == "", F.lit("/")).otherwise(folder), link))
    )


def link_edges(pages: DataFrame) -> DataFrame:
    """(a, b): a page's address and what it redirects to, names as canonical, or is another spelling of."""
    html = F.coalesce(F.col("html"), F.lit(""))
    guard = html.rlike("(?i)canonical|http-equiv")
    targets = F.when(guard, F.array(F.regexp_extract(html, CANONICAL, 1), F.regexp_extract(html, REFRESH, 1))).otherwise(F.array().cast("array<string>"))
    links = pages.select("url", F.explode(targets).alias("link")).select(F.col("url").alias("a"), resolved(F.col("url"), F.col("link")).alias("b"))
    spelt = pages.select(F.col("url").alias("a"), F.concat(F.lit("="), normal_form(F.col("url"))).alias("b"))
    return links.where("a is not null and b is not null").unionByName(spelt.where("a is not null and b is not null"))


def judge(pages: DataFrame, rules=RULES, redirects: DataFrame | None = None) -> DataFrame:
    """(page_id, host, path, rule, verdict, alias_blocked) of every page; alias_blocked tells whether its group of aliases is blocked.

    redirects: further (from_url, to_url) rows. A null url, or one without ://, has an empty host and path, no alias and
    the verdict allow. Repeated rows are judged alike; an empty table gives none; other columns are ignored."""
    base = pages.select("page_id", "url", "html")
    rule = lambda url: rule_for(host_of(url), path_of(url), rules)
    verdict_of = F.create_map(*(F.lit(x) for v, r in rules for x in (r, v))) if rules else F.create_map().cast("map<string,string>")
    edges = link_edges(base)
    if redirects is not None:
        edges = edges.unionByName(redirects.select(F.col("from_url").alias("a"), F.col("to_url").alias("b")))
    shared = edges.groupBy("b").agg(F.min("a").alias("least"), F.max("a").alias("most")).where((F.col("least") != F.col("most")) | ~F.col("b").startswith("="))
    useful = edges.join(shared.select("b"), "b", "left_semi")  # a spelling of one page only links nothing
    groups = connected_components(useful)
    named = groups.where(~F.col("node").startswith("=")).withColumn("v", verdict_of[rule(F.col("node"))])
    flags = named.groupBy("component").agg(F.count(F.lit(1)).alias("nodes"), F.max(F.coalesce(F.col("v") == "block", F.lit(False))).alias("blocked"), F.max(F.coalesce(F.col("v") == "allow", F.lit(False))).alias("allowed"))
    decided = stored(flags.where("blocked and not allowed").select("component", "nodes"), "blocked")
    spread = join_by_size(named.select("node", "component"), decided, "component", "nodes", max(1, named.count())).select(F.col("node").alias("url"))
    pages_of = base.where("url is not null").groupBy("url").agg(F.count(F.lit(1)).alias("rows"))
    spread = stored(spread.join(pages_of, "url").withColumn("spread", F.lit(True)), "aliases")
    judged = base.select("page_id", "url", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), rule(F.col("url")).alias("rule"))
    if not spread.limit(1).count():
        joined = judged.withColumn("spread", F.lit(False))
    else:  # rows that an alias blocks meet it by size; the others are told by a semi join's opposite, which needs no row of theirs twice
        hit = join_by_size(judged, spread, "url", "rows", max(1, base.count())).drop("rows")
        rest = without_keys(judged, spread.select("url", "rows"), "url").withColumn("spread", F.lit(False))
        joined = hit.unionByName(rest)
    return joined.select(
        "page_id", "host", "path", "rule",
        F.when(F.col("rule").isNotNull(), verdict_of[F.col("rule")]).when(F.col("spread"), "block").otherwise("allow").alias("verdict"),
        F.col("spread").alias("alias_blocked"),
    )


def without_keys(left: DataFrame, right: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Rows whose key is null or not in `right`. The key that many rows share is spread over salts, and the short list repeated for each."""
    salted = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    listed = right.select(F.col(key)).withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))).withColumn("_salt", F.col("_salt").cast("long"))
    nameless = left.where(F.col(key).isNull())
    return salted.where(F.col(key).isNotNull()).join(listed, [key, "_salt"], "left_anti").drop("_salt").unionByName(nameless)
