"""URL verdicts that hold for every alias of a URL.

Rules of hosts and paths judge URLs directly. Aliases are URLs joined by redirects and canonical links that pages declare,
resolved against the page's own URL, and by plain rewriting (scheme, `www.`, default port, fragment, tracking parameters, a closing slash). Their connected
components carry decisions: a URL that no rule fits is allowed where an alias is explicitly allowed, else blocked where an
alias is blocked, else allowed.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from floorcount.llm.components import components
from floorcount.llm.scratch import Scratch, free_name, must_be_free

#: (verdict, host, path)
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Query parameters that say where a visitor came from.
TRACKING = r"^(utm_[a-z]+|gclid|fbclid)="
AFTER = r"(?s)^.*?://([^/?#]*)([^?#]*)"


def host(url: Column) -> Column:
    """After the first ://, up to /, ? or #; A-Z lower-cased; empty for null or where there is no ://."""
    return F.coalesce(F.when(F.contains(url, F.lit("://")), F.translate(F.regexp_extract(url, AFTER, 1), UPPER, LOWER)), F.lit(""))


def path(url: Column) -> Column:
    """What follows the host, up to ? or #."""
    return F.coalesce(F.when(F.contains(url, F.lit("://")), F.regexp_extract(url, AFTER, 2)), F.lit(""))


def rule_of(host_: Column, path_: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule as text, verdict) of the longest rule that fits the host, or a domain above it, and the path's start.

    Of rules of one length, allow comes first.
    """
    fits = lambda h, p: ((host_ == h) | host_.endswith(f".{h}")) & path_.startswith(p)
    ordered = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[0], r[1]))
    pick = lambda of: reduce(lambda rest, r: F.when(fits(r[1], r[2]), of(r)).otherwise(rest), reversed(ordered), F.lit(None).cast("string"))
    return pick(lambda r: F.lit(r[1] + r[2])), pick(lambda r: F.lit(r[0]))


def rewritten(url: Column) -> Column:
    """One form for URLs that differ only by scheme, www., default port, fragment, tracking parameters or a closing slash."""
    h = F.regexp_replace(F.regexp_replace(host(url), r"^www\.", ""), r":(80|443)$", "")
    query = F.regexp_extract(url, r"(?s)^.*?://[^?#]*\?([^#]*)", 1)
    kept = F.array_join(F.filter(F.split(query, "&", -1), lambda x: ~F.regexp_like(x, F.lit(TRACKING))), "&")
    rest = F.when(kept != "", F.concat(F.lit("?"), kept)).otherwise("")
    return F.when(F.contains(url, F.lit("://")), F.concat(F.lit("//"), h, F.regexp_replace(path(url), r"/$", ""), rest))


def declared(html: Column) -> Column:
    """Targets of canonical links and of refresh redirects, as an array."""
    tags = F.regexp_extract_all(html, F.lit(r"(?is)<(?:link|meta)\b[^>]*>"), F.lit(0))
    canonical = F.transform(F.filter(tags, lambda t: F.regexp_like(t, F.lit(r"(?is)\brel\s*=\s*[\"']?canonical\b"))), lambda t: F.regexp_extract(t, r"(?is)\bhref\s*=\s*[\"']?([^\"'\s>]+)", 1))
    refresh = F.transform(F.filter(tags, lambda t: F.regexp_like(t, F.lit(r"(?is)\bhttp-equiv\s*=\s*[\"']?refresh\b"))), lambda t: F.regexp_extract(t, r"(?is)\bcontent\s*=\s*[\"'][^\"']*?url\s*=\s*([^\"'\s>;]+)", 1))
    return F.filter(F.concat(canonical, refresh), lambda t: t != "")


#: Character references that stand in URLs, the one of & last.
REFERENCES = ((r"(?i)&(quot|#34|#x22);", '"'), (r"(?i)&(apos|#39|#x27);", "'"), (r"(?i)&(lt|#60|#x3c);", "<"), (r"(?i)&(gt|#62|#x3e);", ">"), (r"(?i)&(amp|#38|#x26);", "&"))


def resolved(target: Column, base: Column) -> Column:
    """A target as a page with the URL base means it: character references decoded; relative ones completed from base.

    Null for targets within the page, for those of schemes without ://, and for relative ones of a base without ://.
    """
    t = reduce(lambda x, r: F.regexp_replace(x, r[0], r[1]), REFERENCES, target)
    scheme = F.regexp_extract(base, r"(?s)^(.*?):", 1)
    top = F.regexp_extract(base, r"(?s)^(.*?://[^/?#]*)", 1)
    folder = F.regexp_extract(path(base), r"(?s)^(.*/)", 1)
    step = lambda seen, x: F.when(x == "..", F.slice(seen, 1, F.greatest(F.size(seen) - 1, F.lit(0)))).when(x == ".", seen).otherwise(F.concat(seen, F.array(x)))
    bare, rest = F.regexp_extract(t, r"(?s)^([^?#]*)", 1), F.regexp_extract(t, r"(?s)^[^?#]*(.*)$", 1)
    whole = F.regexp_replace(F.when(bare.startswith("/"), bare).otherwise(F.concat(F.when(folder == "", F.lit("/")).otherwise(folder), bare)), "^/", "")
    steps = F.aggregate(F.split(whole, "/", -1), F.array().cast("array<string>"), step)
    closing = F.when(F.regexp_like(bare, F.lit(r"(^|/)[.]{1,2}$")) & (F.size(steps) > 0), F.lit("/")).otherwise("")
    joined = F.concat(top, F.lit("/"), F.array_join(steps, "/"), closing, rest)
    completed = F.when(t.startswith("//"), F.concat(scheme, F.lit(":"), t)).when(t.startswith("?"), F.concat(top, path(base), t)).otherwise(joined)
    inside = (t == "") | t.startswith("#") | F.regexp_like(t, F.lit(r"^[A-Za-z][A-Za-z0-9+.-]*:"))
    return F.when(F.contains(bare, F.lit("://")), t).when(~inside & F.contains(base, F.lit("://")), completed)


def edges(pages: DataFrame, redirects: DataFrame | None = None, url: str = "url", html: str = "html") -> DataFrame:
    """Rows (a, b) of aliases: a URL and its rewritten form, and those of what it declares; redirects: rows (source, target)."""
    u = F.col(f"`{url}`")
    said = pages.filter(u.isNotNull()).select(u.alias("u"), F.explode(F.concat(F.array(u), F.coalesce(F.transform(declared(F.col(f"`{html}`")), lambda t: resolved(t, u)), F.array().cast("array<string>")))).alias("v"))
    out = said.select(F.col("u").alias("a"), rewritten(F.col("v")).alias("b")).unionAll(said.filter("u <> v").select(F.col("v").alias("a"), rewritten(F.col("v"))))
    if redirects is not None:
        pair = redirects.select(F.col("source").cast("string").alias("a"), F.col("target").cast("string").alias("b")).dropna()
        out = out.unionAll(pair).unionAll(pair.select("a", rewritten(F.col("a")))).unionAll(pair.select(F.col("b").alias("a"), rewritten(F.col("b"))))
    return out.dropna().filter("a <> b").distinct()


def judge_urls(pages: DataFrame, redirects: DataFrame | None = None, rules=RULES, url: str = "url", html: str = "html", scratch: Scratch | None = None) -> DataFrame:
    """pages without html, with host, path, rule and verdict.

    A rule's verdict on the URL itself comes first; then an allow, then a block of an alias; then allow. Null URLs and URLs
    without :// have an empty host and path, no rule and no alias, and are allowed. Repeated rows are judged alike; an empty
    table gives an empty one. Columns of the result's names must not be there.
    """
    must_be_free(pages, "host", "path", "rule", "verdict")
    scratch = scratch or Scratch(pages.sparkSession, "urls")
    u = F.col(f"`{url}`")
    rule, own = rule_of(F.col("host"), F.col("path"), rules)
    rest = [c for c in pages.columns if c != html]
    mine, node, passed = (free_name(pages, n) for n in ("_own", "_node", "_passed"))
    judged = pages.select(*[F.col(f"`{c}`") for c in rest], host(u).alias("host"), path(u).alias("path")).withColumns({"rule": rule, mine: own})
    pairs = edges(pages, redirects, url, html)
    groups = scratch.keep(components(pairs, "a", "b", scratch), "aliases")
    known = pairs.select(F.col("a").alias("n")).unionAll(pairs.select("b")).distinct()
    decided = known.withColumns({"h": host(F.col("n")), "p": path(F.col("n"))}).withColumn("v", rule_of(F.col("h"), F.col("p"), rules)[1]).filter("v is not null").select("n", "v")
    verdicts = decided.join(groups, F.col("n") == F.col("node")).groupBy(F.col("component").alias("c")).agg(F.min("v").alias("passed"))  # allow sorts before block
    reach = groups.join(verdicts, F.col("component") == F.col("c")).select(F.col("node").alias(node), F.col("passed").alias(passed))
    out = judged.join(reach, u == F.col(node), "left")
    return out.select(*[F.col(f"`{c}`") for c in rest], "host", "path", "rule", F.coalesce(mine, passed, F.lit("allow")).alias("verdict"))
