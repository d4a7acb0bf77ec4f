"""URL filter: host and path rules, and block decisions that spread over redirect and canonical-link equivalences.

A rule fits its host and all subdomains where the url's path starts with the rule's; the longest rule wins. A url without
a rule takes the decision of its equivalents: urls joined by redirects or canonical links (connected components), and,
if wanted, urls that differ only in scheme, a leading www. or m., query, fragment, a closing slash or .html. In such a
group an explicit allow goes before any block. Only DataFrame operations are used.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import connected_components
from .storage import checkpointed

#: More rules than this are joined by a shuffle instead of a broadcast.
BROADCAST_RULES = 50_000
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_PARTS = r"(?s)^.*?://([^/?#]*)([^?#]*)"


def host(url: Column) -> Column:
    """What follows the first :// up to / ? # or the end, A-Z lower-cased; empty for null or without ://."""
    return F.coalesce(F.translate(F.regexp_extract(url, _PARTS, 1), _UPPER, _LOWER), F.lit(""))


def path(url: Column) -> Column:
    """What follows the host up to ? # or the end; empty for null or without ://."""
    return F.coalesce(F.regexp_extract(url, _PARTS, 2), F.lit(""))


def alias_key(url: Column, assume_redirects: bool) -> Column:
    """The name of a url's own group: the url, or with assumed redirects its host and path in plain form. Null without ://."""
    plain = F.concat(F.regexp_replace(host(url), r"^(?:www|m)\.", ""), F.regexp_replace(F.regexp_replace(path(url), r"\.html?$", ""), r"/+$", ""))
    return F.when(F.instr(url, "://") > 0, plain if assume_redirects else url)


def rule_table(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    """rule_host, rule_path, verdict from (action, host, path) triples."""
    return spark.createDataFrame([(h, p, a) for a, h, p in rules], "rule_host string, rule_path string, verdict string")


def _attribute(tag: Column, name: str) -> Column:
    """The value of an attribute, quoted or not; empty if the tag lacks it. Quoted values of other attributes are stepped over."""
    found = F.regexp_extract(tag, rf"(?is)^<[a-z]+(?:[\s/]+(?!{name}[\s=])[^\s=>/]+(?:\s*=\s*(?:\"[^\"]*\"|'[^']*'|[^\s>\"']+))?)*[\s/]+{name}\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>\"']+)", 1)
    return F.replace(F.trim(F.regexp_replace(found, r"^[\"']|[\"']$", "")), F.lit("&amp;"), F.lit("&"))


def _resolved(url: Column, dst: Column) -> Column:
    """A link's target as an absolute url: its own scheme, the page's scheme, host or directory before it, dot segments taken out."""
    bare = F.regexp_replace(url, r"(?s)[?#].*$", "")
    origin = F.regexp_extract(url, r"(?s)^.*?://[^/?#]*", 0)
    folder = F.regexp_replace(F.substr(bare, F.length(origin) + 1), r"[^/]*$", "")
    joined = (
        F.when(F.length(dst) == 0, url)
        .when(dst.rlike(r"^[A-Za-z][A-Za-z0-9+.\-]*:"), dst)
        .when(dst.startswith("//"), F.concat(F.regexp_extract(url, r"(?s)^(.*?:)//", 1), dst))
        .when(dst.startswith("/"), F.concat(origin, dst))
        .when(dst.startswith("?"), F.concat(bare, dst))
        .when(dst.startswith("#"), F.concat(F.regexp_replace(url, r"(?s)#.*$", ""), dst))
        .otherwise(F.concat(origin, F.when(folder == "", F.lit("/")).otherwise(folder), dst))
    )
    head, rest = F.regexp_extract(joined, r"(?s)^.*?://[^/?#]*", 0), F.regexp_extract(joined, r"(?s)[?#].*$", 0)
    parts = F.split(F.regexp_extract(joined, _PARTS, 2), "/", -1)
    # The first part is what stands before the first slash; a dot segment at the end leaves a slash.
    walked = F.aggregate(
        F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))),
        F.array().cast("array<string>"),
        lambda done, x: F.when(x == "..", F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(0)))).when(x == ".", done).otherwise(F.concat(done, F.array(x))),
    )
    last = F.element_at(parts, -1)
    plain = F.concat(head, F.lit("/"), F.array_join(walked, "/"), F.when(last.isin(".", "..") & (F.size(walked) > 0), "/").otherwise(""), rest)
    return F.when(F.arrays_overlap(parts, F.array(F.lit("."), F.lit(".."))), plain).otherwise(joined)


def page_links(pages: DataFrame) -> DataFrame:
    """(src, dst): all canonical links and refresh redirects that pages (url, html) declare outside comments, relative ones resolved against the page."""
    tag = r"(?is)(<(?:link|meta)[\s/](?:[^>\"']|\"[^\"]*\"|'[^']*')*>)"
    some = pages.where("url is not null").where(F.col("html").rlike(r"(?i)canonical|refresh"))
    shown = F.regexp_replace("html", r"(?s)<!--.*?(?:-->|\z)", "")
    tags = some.select("url", F.explode(F.regexp_extract_all(shown, F.lit(tag), 1)).alias("tag"))
    canonical = F.when(F.col("tag").rlike("(?i)^<link") & _attribute(F.col("tag"), "rel").rlike(r"(?i)(?:^|\s)canonical(?:\s|$)"), _attribute(F.col("tag"), "href"))
    target = F.regexp_extract(_attribute(F.col("tag"), "content"), r"(?is)^[\s\d.]*[;,\s]\s*url\s*=\s*[\"']?([^\"'\s]+)", 1)
    refresh = F.when(F.col("tag").rlike("(?i)^<meta") & (F.lower(_attribute(F.col("tag"), "http-equiv")) == "refresh"), target)
    found = tags.where(F.col("tag").rlike(r"(?i)canonical|refresh")).select("url", F.coalesce(canonical, refresh).alias("dst")).where("dst <> ''")
    return found.select(F.col("url").alias("src"), _resolved(F.col("url"), F.col("dst")).alias("dst"))


def _matches(places: DataFrame, rules: DataFrame) -> DataFrame:
    """host, path, rule, own: the longest fitting rule of each distinct (host, path); allow goes first on ties."""
    labels = F.split("host", r"\.", -1)
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    few = rules.limit(BROADCAST_RULES + 1).count() <= BROADCAST_RULES
    hosts = places.where("host <> ''").select("host", "path", F.explode(suffixes).alias("rule_host"))
    fits = hosts.join(F.broadcast(rules) if few else rules, "rule_host").where(F.col("path").startswith(F.col("rule_path")))
    rule = F.concat("rule_host", "rule_path")
    best = F.max(F.struct(F.length(rule).alias("n"), (F.col("verdict") == "allow").alias("allow"), rule.alias("rule"), F.col("verdict")))
    return fits.groupBy("host", "path").agg(best.alias("best")).select("host", "path", F.col("best.rule").alias("rule"), F.col("best.verdict").alias("own"))


def judge(pages: DataFrame, rules: DataFrame, links: DataFrame | None = None, assume_redirects: bool = False) -> DataFrame:
    """``pages`` (url, ...) with host, path, rule (null if none fits) and verdict (allow or block).

    rules: rule_host, rule_path, verdict. links: (src, dst) urls that are equivalent. Null urls and urls without :// have
    no group and are allowed. Every row is judged for itself, so repeated rows stay; columns with the added names are replaced.
    """
    added = ("host", "path", "rule", "verdict")
    names = [c for c in pages.columns if c not in added]
    group = alias_key(F.col("url"), assume_redirects)
    urls = pages.select("url").union(links.select("src")).union(links.select("dst")) if links is not None else pages.select("url")
    urls = urls.where("url is not null").distinct().select(host(F.col("url")).alias("host"), path(F.col("url")).alias("path"), group.alias("key"))
    ruled = checkpointed(_matches(urls.select("host", "path").distinct(), rules))
    decided = urls.join(ruled, ["host", "path"]).where("key is not null").select("key", "own")
    aliases = None
    if links is not None:
        edges = links.select(alias_key(F.col("src"), assume_redirects).alias("u"), alias_key(F.col("dst"), assume_redirects).alias("v"))
        aliases = checkpointed(connected_components(edges))
        decided = decided.join(aliases, decided["key"] == aliases["node"], "left").select(F.coalesce("component", "key").alias("key"), "own")
    spread = decided.groupBy("key").agg(F.when(F.max(F.col("own") == "allow"), "allow").otherwise("block").alias("__shared")).withColumnRenamed("key", "__group")
    # Names of the caller's columns may be any but those that begin with two underscores.
    ruled = ruled.toDF("__rule_host", "__rule_path", "__rule", "__own")
    out = pages.select(*[pages[c] for c in names], host(F.col("url")).alias("__host"), path(F.col("url")).alias("__path"), group.alias("__key"))
    out = out.join(ruled, (F.col("__host") == F.col("__rule_host")) & (F.col("__path") == F.col("__rule_path")), "left")
    if aliases is not None:
        out = out.join(aliases.toDF("__node", "__component"), F.col("__key") == F.col("__node"), "left").withColumn("__key", F.coalesce("__component", "__key"))
    out = out.join(spread, F.col("__key") == F.col("__group"), "left")
    return out.select(*[F.col(f"`{c}`") for c in names], F.col("__host").alias("host"), F.col("__path").alias("path"), F.col("__rule").alias("rule"), F.coalesce("__own", "__shared", F.lit("allow")).alias("verdict"))
