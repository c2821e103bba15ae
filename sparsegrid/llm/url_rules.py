"""URL filters: listed rules and association rules mined from labelled pages.

Listed rules name a host and a beginning of the path; they hold for the host and
all its subdomains, and the longest wins.  Where none fits, association rules
decide: frequent sets of URL tokens that imply a bad label, found by FP-growth,
kept by support and confidence, pruned of rules that a smaller one makes needless
and of rules that do not hold on pages that were held out.  They are matched
through an inverted index from token to rules: a rule fires where as many of its
tokens are met as it has.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparsegrid.plans.lineage import cut_lineage

BAD, GOOD = "label:bad", "label:good"


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str  # with its leading slash

    @property
    def name(self) -> str:
        return self.host + self.path


def _lowered(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def with_parts(pages: DataFrame) -> DataFrame:
    """Adds host (A-Z lower-cased) and path; both empty for a null url or one without ``://``."""
    at = F.instr("url", "://")
    rest = F.substr(F.col("url"), at + 3)
    has = F.coalesce(at > 0, F.lit(False))
    host = _lowered(F.regexp_extract(rest, r"^([^/?#]*)", 1))
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return pages.withColumn("host", F.when(has, host).otherwise("")).withColumn("path", F.when(has, path).otherwise(""))


def longest_rule(rules: list[Rule]) -> Column:
    """The longest listed rule (name, verdict) that fits host and path, else null."""
    best = F.lit(None).cast("struct<size:int,rule:string,verdict:string>")
    for r in rules:
        fits = ((F.col("host") == r.host) | F.endswith("host", F.lit("." + r.host))) & F.startswith("path", F.lit(r.path))
        mine = F.when(fits, F.struct(F.lit(len(r.name)).alias("size"), F.lit(r.name).alias("rule"), F.lit(r.verdict).alias("verdict")))
        best = F.greatest(best, mine)
    return best


def url_tokens() -> Column:
    """Distinct tokens of a url: labels of the host, words of them, words of the path, names in the query."""
    labels = F.filter(F.split("host", r"\."), lambda x: x != "")
    whole = F.transform(labels, lambda x: F.concat(F.lit("host:"), x))
    words = F.transform(F.flatten(F.transform(labels, lambda x: F.filter(F.split(x, "[-_]"), lambda w: (w != "") & (w != x)))), lambda w: F.concat(F.lit("word:"), w))
    path = F.transform(F.filter(F.split(_lowered(F.col("path")), r"[^a-z]+"), lambda x: x != ""), lambda x: F.concat(F.lit("path:"), x))
    query = F.transform(F.regexp_extract_all("url", F.lit(r"[?&]([A-Za-z_]+)="), F.lit(1)), lambda x: F.concat(F.lit("query:"), x))
    return F.array_distinct(F.concat(whole, words, path, F.coalesce(query, F.array().cast("array<string>"))))


@dataclass
class MinedRules:
    """``rules``: rule, tokens, size, pages, bad, confidence (both measured on pages that were held out); ``index``: token, rule, size."""

    rules: DataFrame
    index: DataFrame


def _same_pages_as_one(known: DataFrame) -> DataFrame:
    """(page, bad, items): the tokens of each page; tokens that occur on the very same pages are one item, a tab-joined list.

    Parts of a template always come together; as single tokens they would double
    the number of frequent sets each.
    """
    tokens = known.select("page", "bad", F.explode(url_tokens()).alias("token"))
    where = tokens.groupBy("token").agg(F.count("*").alias("k"), F.sum(F.xxhash64("page").cast("decimal(38,0)")).alias("h"), F.sum(F.xxhash64("page", F.lit(1)).cast("decimal(38,0)")).alias("g"))
    items = where.groupBy("k", "h", "g").agg(F.array_join(F.array_sort(F.collect_set("token")), "\t").alias("item"), F.min("token").alias("token"))
    met = tokens.join(items.select("token", "item"), "token")
    return met.groupBy("page", "bad").agg(F.collect_set("item").alias("items"))


def mine_rules(labelled: DataFrame, min_pages: int = 20, min_support: float = 0.004, min_confidence: float = 0.6, min_lift: float = 1.5, max_size: int = 4, max_rules: int = 2000, held_out: int = 3) -> MinedRules | None:
    """Rules "tokens imply a bad page" from (url, bad); None where there are too few labelled urls.

    Every ``held_out``-th page, by a hash of its url, takes no part in mining.  A
    set counts as frequent on ``min_support`` of the mined pages and on
    ``min_pages`` of them at least.  A rule of more than ``max_size`` items, or
    with less confidence or lift, or made needless by a smaller one that is as
    sure, goes; of the others the ``max_rules`` surest are measured on the
    held-out pages through the inverted index and stay where they hold there as
    well: on ``min_pages / held_out`` pages, with ``min_confidence``.
    """
    known = with_parts(labelled.where("url IS NOT NULL AND bad IS NOT NULL")).withColumn("page", F.xxhash64("url", F.col("bad")))
    known = known.groupBy("page", "bad", "url", "host", "path").agg(F.count("*").alias("times")).withColumn("out", F.pmod(F.xxhash64("url", F.lit(29)), F.lit(held_out)) == 0)
    known = cut_lineage(known)
    counts = known.agg(F.count(F.when(~F.col("out"), 1)).alias("n"), F.count(F.when(~F.col("out") & F.col("bad"), 1)).alias("bad")).first()
    if counts["n"] < min_pages or counts["bad"] < min_pages:
        return None
    baskets = _same_pages_as_one(known.where("not out")).select(F.concat("items", F.array(F.when(F.col("bad"), BAD).otherwise(GOOD))).alias("items"))
    support = max(min_support, min_pages / counts["n"])
    found = FPGrowth(itemsCol="items", minSupport=support, minConfidence=min_confidence).fit(baskets).associationRules
    wanted = found.where((F.element_at("consequent", 1) == BAD) & (F.col("lift") >= min_lift) & ~F.array_contains("antecedent", GOOD) & (F.size("antecedent") <= max_size))
    tokens = F.array_sort(F.flatten(F.transform("antecedent", lambda i: F.split(i, "\t"))))
    wanted = wanted.select(tokens.alias("tokens"), "confidence", "support").withColumn("size", F.size("tokens")).withColumn("rule", F.xxhash64("tokens"))
    # a bounded table: the inverted index of the surest rules travels to the pages
    wanted = cut_lineage(wanted.orderBy(F.desc("confidence"), F.desc("support"), "size", "rule").limit(max_rules))
    # needless: another rule has some of the tokens only and is as sure
    parts = wanted.select("rule", "size", "confidence", F.explode("tokens").alias("token"))
    pairs = parts.alias("x").join(parts.alias("y"), "token").where("x.size < y.size and x.confidence >= y.confidence")
    needless = pairs.groupBy(F.col("x.rule").alias("small"), F.col("x.size").alias("n"), F.col("y.rule").alias("rule")).agg(F.count("*").alias("k")).where("k = n").select("rule").distinct()
    kept = wanted.join(needless, "rule", "left_anti")
    index = kept.select("rule", "size", F.explode("tokens").alias("token"))
    fired = _fired(known.where("out").select("page", "bad", "url", "host", "path"), ["page", "bad"], index)
    measured = fired.groupBy("rule").agg(F.count("*").alias("pages"), F.count(F.when(F.col("bad"), 1)).alias("bad")).where((F.col("pages") * held_out >= min_pages) & (F.col("bad") >= min_confidence * F.col("pages")))
    rules = cut_lineage(kept.select("rule", "tokens", "size").join(measured, "rule").withColumn("confidence", F.col("bad") / F.col("pages")))
    return MinedRules(rules, rules.select("rule", "size", F.explode("tokens").alias("token")))


def _fired(urls: DataFrame, keys: list[str], index: DataFrame) -> DataFrame:
    """(keys, rule): the rules of which a url holds all tokens; the index, of max_rules rules at most, travels to the urls."""
    met = urls.select(*keys, F.explode(url_tokens()).alias("token")).join(F.broadcast(index), "token")
    return met.groupBy(*keys, "rule", "size").agg(F.count("*").alias("k")).where("k = size").select(*keys, "rule")


def judge_urls(pages: DataFrame, rules: list[Rule], mined: MinedRules | None) -> DataFrame:
    """One row per row of ``pages`` (page_id, url): page_id, host, path, rule, verdict, fired.

    A listed rule's verdict stands; else the url is blocked where a mined rule
    fires, and allowed otherwise.  Equal urls are judged once and joined back, so
    a hot url costs no more than another; null urls, and those that a listed rule
    decides, are not joined; null and repeated page ids come back as they are;
    other columns are ignored; an empty table gives no rows.
    """
    listed = with_parts(pages.select("page_id", "url")).withColumn("best", longest_rule(rules))
    if mined is None:
        judged = listed.withColumn("fired", F.lit(0).cast("long"))
    else:
        open_ = listed.where("best IS NULL AND url IS NOT NULL")
        fired = _fired(open_.select("url", "host", "path").distinct(), ["url"], mined.index).groupBy("url").agg(F.count("*").alias("fired"))
        told = open_.join(fired, "url", "left").withColumn("fired", F.coalesce("fired", F.lit(0)))
        rest = listed.where("best IS NOT NULL OR url IS NULL").withColumn("fired", F.lit(0).cast("long"))
        judged = told.unionByName(rest)
    verdict = F.coalesce("best.verdict", F.when(F.col("fired") > 0, "block").otherwise("allow"))
    return judged.select("page_id", "host", "path", F.col("best.rule").alias("rule"), verdict.alias("verdict"), "fired")


def labelled_pages(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """(url, bad): pages whose path names a labelled document; low quality or toxic is bad."""
    number = F.regexp_extract("url", r"://[^?#]*/([0-9]{1,18})(?:[^0-9/?#][^/?#]*)?/?(?:[?#].*)?$", 1)
    named = pages.select("url", F.when(number != "", number).cast("long").alias("doc_id"))
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), ((F.col("quality") == 0) | (F.col("toxic") == 1)).alias("bad"))
    return named.join(marks, "doc_id").select("url", "bad")


def listed_rules() -> list[Rule]:
    # The listed rules, host and path.
    return [
        Rule("block", "com", "/en/"),
        Rule("allow", "example.com", "/en/7"),
        Rule("allow", "net", "/de/"),
        Rule("block", "example.net", "/de/8"),
        Rule("block", "org", "/es/"),
    ]
