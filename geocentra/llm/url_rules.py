"""URL filters, DataFrame and SQL functions only: host and path rules, and association rules mined by FP-growth."""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.llm.plan import load

# The item that stands for a bad label; no URL token holds an equals sign.
BAD = "=bad"


def host_of(url: Column) -> Column:
    """What stands after the first :// up to / ? # or the end, A-Z folded; empty without ://."""
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    """What stands after the host up to ? # or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def tokens_of(url: Column) -> Column:
    """The distinct runs of letters of a URL, A-Z folded; numbers name single pages and are left out."""
    lowered = F.translate(F.coalesce(url, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.array_distinct(F.filter(F.regexp_extract_all(lowered, F.lit(r"([^\x00-\x2F\x3A-\x60\x7B-\x7F]+)"), 1), lambda t: ~t.rlike(r"^[0-9]+$")))


def longest_rule(pages: DataFrame, rules: list[tuple[str, str]]) -> DataFrame:
    """The columns of `pages` (with host and path) plus rule and rule_verdict: the longest fitting rule's, or null.

    A rule "host/path" fits its host and all subdomains if the path starts with the
    rule's. The distinct host suffixes are looked up in the rules' hosts by a join.
    """
    spark = pages.sparkSession
    parts = [(r[: r.index("/")], r[r.index("/") :], r, verdict) for verdict, r in rules]
    table = spark.createDataFrame(parts, "rule_host string, rule_path string, rule string, rule_verdict string")
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    wanted = pages.select("host", "path").distinct()
    fits = wanted.select("host", "path", F.explode(suffixes).alias("rule_host")).join(table, "rule_host").where(F.col("path").startswith(F.col("rule_path")))
    best = fits.groupBy("host", "path").agg(F.max(F.struct(F.length("rule").alias("size"), "rule", "rule_verdict")).alias("best"))
    return pages.join(best, ["host", "path"], "left").select(*pages.columns, F.col("best.rule").alias("rule"), F.col("best.rule_verdict").alias("rule_verdict"))


def mine_rules(labelled: DataFrame, min_support: float = 0.002, min_confidence: float = 0.5) -> DataFrame:
    """rule_id, tokens, n, confidence, support: token combinations of URLs that imply a bad label.

    `labelled` has url and bad (boolean). Rules with fewer than `min_support` of the
    labelled rows or less than `min_confidence` are pruned, and so is a rule that
    contains another one.
    """
    baskets = labelled.where("bad is not null").select(F.array_union(tokens_of(F.col("url")), F.when(F.col("bad"), F.array(F.lit(BAD))).otherwise(F.array().cast("array<string>"))).alias("items"))
    schema = "rule_id long, tokens array<string>, n int, confidence double, support double"
    if baskets.where(F.size("items") > 0).isEmpty():
        return labelled.sparkSession.createDataFrame([], schema)
    mined = FPGrowth(itemsCol="items", minSupport=min_support, minConfidence=min_confidence).fit(baskets).associationRules
    rules = mined.where(F.col("consequent")[0] == BAD).select(F.array_sort("antecedent").alias("tokens"), F.size("antecedent").alias("n"), "confidence", "support")
    rules = rules.select(F.xxhash64("tokens").alias("rule_id"), "tokens", "n", "confidence", "support")
    other = rules.select(F.explode("tokens").alias("token"), F.col("rule_id").alias("inner_id"), F.col("n").alias("inner_n"))
    shared = rules.select("rule_id", "n", F.explode("tokens").alias("token")).join(other, "token").where("inner_n < n").groupBy("rule_id", "inner_id", "inner_n").count()
    return rules.join(shared.where("count = inner_n").select("rule_id").distinct(), "rule_id", "left_anti")


def matched_urls(pages: DataFrame, rules: DataFrame) -> DataFrame:
    """The distinct urls that hold all tokens of some rule: an inverted index that posts each rule under its rarest token only.

    A url that holds a rule's rarest token is compared with the whole rule, so that a
    token that is in most urls costs nothing unless it is a rule by itself.
    """
    urls = pages.select("url").where("url is not null").distinct().select("url", tokens_of(F.col("url")).alias("held"))
    named = rules.select("rule_id", "tokens", F.explode("tokens").alias("token"))
    often = urls.select(F.explode("held").alias("token")).join(named.select("token").distinct(), "token", "left_semi").groupBy("token").agg(F.count(F.lit(1)).alias("k"))
    index = named.join(often, "token").groupBy("rule_id").agg(F.min(F.struct("k", "token")).alias("rarest"), F.first("tokens").alias("tokens")).select(F.col("rarest.token").alias("token"), "tokens")
    hits = urls.select("url", "held", F.explode("held").alias("token")).join(index, "token")
    return hits.where(F.size(F.array_except("tokens", "held")) == 0).select("url").distinct()


def judge_urls(pages: DataFrame, rules: list[tuple[str, str]], labelled: DataFrame, min_support: float = 0.002, min_confidence: float = 0.5) -> DataFrame:
    """The columns page_id and url of `pages` plus host, path, rule and verdict.

    The longest fitting host and path rule decides; else mined token rules block, and
    what matches none is allowed. A null url, or one without ://, has an empty host and
    path, no rule, and is allowed unless its tokens match. Rows are kept as they are,
    repeated and null ids included; empty tables of pages or labels are fine.
    """
    rows = pages.select("page_id", "url").select("page_id", "url", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    ruled = longest_rule(rows.where("url is not null"), rules)
    mined = matched_urls(rows, mine_rules(labelled, min_support, min_confidence)).select("url", F.lit("block").alias("mined"))
    # Rows without a url, however many, meet nobody in the joins.
    none = rows.where("url is null").select("*", F.lit(None).cast("string").alias("rule"), F.lit(None).cast("string").alias("rule_verdict"), F.lit(None).cast("string").alias("mined"))
    judged = ruled.join(mined, "url", "left").unionByName(none)
    return judged.select("page_id", "url", "host", "path", "rule", F.coalesce("rule_verdict", "mined", F.lit("allow")).alias("verdict"))


# The rules of the query.
RULES = [("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/")]


def op9_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A page's label is that of the row of `labels` with its id: bad if toxic or of quality 0."""
    pages, labels = load(spark, sf_dir, "pages"), load(spark, sf_dir, "labels")
    labelled = pages.select("page_id", "url").join(labels.select(F.col("doc_id").alias("page_id"), ((F.col("toxic") == 1) | (F.col("quality") == 0)).alias("bad")), "page_id")
    return judge_urls(pages, RULES, labelled).select("page_id", "host", "path", "rule", "verdict")
