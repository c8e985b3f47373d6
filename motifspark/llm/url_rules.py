"""URL filter by association rules: FP-growth over URL tokens mined from labelled pages.

Each labelled url is a basket of tokens (its host's suffixes, its path segments without
figures, the names of its query's parameters) plus one class token.  Spark's FP-growth
finds frequent token sets; association rules whose consequent is the bad class are kept
if support (a number of labelled bad pages) and confidence pass, whatever their length, and if no shorter rule says the same (a superset
adds nothing where a subset already blocks).  Matching is by inverted index: one rule
token (the rarest one) opens the rule, the others are then required.

Hand-written rules (host, path) come first: the longest that fits decides.

Pages carry no labels of their own in the given tables: ``labels`` is joined by id, bad
means quality 0 or toxic 1.

Defined results.  Null urls and urls without ``://`` have an empty host and path, fit no
rule and are allowed.  Repeated rows are judged one by one.  Without labels, or without
frequent bad tokens, nothing is mined.  Empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, joined_hot, small

#: Verdict, host and the start of the path.
RULES = [
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
]
#: MIN_BAD counts labelled bad pages a rule fits, so that a small host can give a rule in a table of any size.
MIN_BAD, MIN_CONFIDENCE = 5, 0.6
BAD = "class=bad"


def ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def parsed(url: str = "url") -> tuple[Column, Column]:
    """Host and path; both empty without ``://``."""
    u = F.coalesce(F.col(url), F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, F.substr(u, at + 3)).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substr(rest, F.char_length(host) + 1), r"^[^?#]*", 0)
    return ascii_lower(host), path


def tokens(host: Column, path: Column, url: Column) -> Column:
    """Distinct tokens of one url, by prefix: h= host suffix, p= path segment, q= parameter."""
    parts = F.filter(F.split(host, r"\."), lambda x: x != "")
    suffixes = F.transform(F.sequence(F.lit(1), F.greatest(F.size(parts), F.lit(1))), lambda i: F.concat(F.lit("h="), F.array_join(F.slice(parts, i, 64), ".")))
    segments = F.transform(F.filter(F.split(path, "/"), lambda x: (x != "") & ~x.rlike("[0-9]")), lambda x: F.concat(F.lit("p="), x))
    names = F.transform(F.filter(F.split(F.regexp_extract(url, r"\?([^#]*)", 1), "&"), lambda x: x != ""), lambda x: F.concat(F.lit("q="), F.regexp_extract(x, "^[^=]*", 0)))
    return F.when(host == "", F.array().cast("array<string>")).otherwise(F.array_distinct(F.concat(suffixes, segments, names)))


def mine(baskets: DataFrame, min_bad: int = MIN_BAD, min_confidence: float = MIN_CONFIDENCE) -> DataFrame:
    """baskets: rows (items array<string>, bad boolean) -> rows (rule array<string>, confidence, lift, support)."""
    b = baskets.select(F.when(F.col("bad"), F.concat("items", F.array(F.lit(BAD)))).otherwise(F.col("items")).alias("items")).where(F.size("items") > 0)
    spark = baskets.sparkSession
    schema = "rule array<string>, confidence double, lift double, support double"
    n, bad = b.agg(F.count("*"), F.count_if(F.array_contains("items", BAD))).first()
    if bad < max(min_bad, 1):
        return spark.createDataFrame([], schema)
    # FP-growth rounds share x baskets up to a count: half a page less keeps the count exact.
    model = FPGrowth(itemsCol="items", minSupport=(max(min_bad, 1) - 0.5) / n, minConfidence=min_confidence).fit(b)
    rules = model.associationRules.where((F.size("consequent") == 1) & (F.col("consequent")[0] == BAD))
    return rules.select(F.array_sort("antecedent").alias("rule"), "confidence", "lift", "support")


def pruned(rules: DataFrame) -> DataFrame:
    """Without the rules of which a proper subset is a rule: it blocks all that they block."""
    parts = rules.select("rule", F.explode("rule").alias("t"))
    inside = parts.join(opening(rules, parts.groupBy("t").agg(F.count("*").alias("n"))).withColumnRenamed("rule", "sub"), "t")
    covered = inside.where((F.size("sub") < F.size("rule")) & (F.size(F.array_except("sub", "rule")) == 0)).select("rule").distinct()
    return rules.join(covered, "rule", "left_anti")


def opening(rules: DataFrame, frequency: DataFrame) -> DataFrame:
    """(rule, t): the rarest token of each rule."""
    return rules.withColumn("t", F.explode("rule")).join(frequency, "t", "left").groupBy("rule").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "t"))["t"].alias("t"))


def matched(urls: DataFrame, rules: DataFrame, frequency: DataFrame) -> DataFrame:
    """urls: rows (key, items) -> keys that some rule fits, by the inverted index of each rule's rarest token."""
    opened = small(opening(rules, frequency))
    hits = urls.withColumn("t", F.explode("items")).join(opened, "t").where(F.size(F.array_except("rule", "items")) == 0)
    return hits.select("key").distinct()


def by_hand(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """Longest fitting rule as text (null: none) and its verdict."""
    rule = verdict = F.lit(None).cast("string")
    for say, h, p in sorted(rules, key=lambda r: len(r[1] + r[2])):  # later ones are longer and win
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(p))
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(say)).otherwise(verdict)
    return rule, verdict


def judge(pages: DataFrame, labels: DataFrame, rules=RULES) -> DataFrame:
    """One row a page: page_id, host, path, rule, verdict, mined (whether a mined rule fits)."""
    host, path = parsed()
    d = pages.select("page_id", host.alias("host"), path.alias("path"), F.coalesce("url", F.lit("")).alias("url"))
    d = d.withColumn("items", tokens(F.col("host"), F.col("path"), F.col("url")))
    bad = labels.groupBy(F.col("doc_id").alias("page_id")).agg(F.max(F.coalesce(F.col("quality") == 0, F.lit(False)) | F.coalesce(F.col("toxic") == 1, F.lit(False))).alias("bad"))
    baskets = d.join(bad, "page_id").select("items", "bad")
    scratch = Scratch(pages.sparkSession, "url-rules")
    found = scratch.table(pruned(scratch.table(mine(baskets), "rules")), "pruned")
    if found.isEmpty():
        d = d.withColumn("mined", F.lit(False))
    else:
        frequency = d.select(F.explode("items").alias("t")).groupBy("t").agg(F.count("*").alias("n"))
        urls = d.select(F.col("url").alias("key"), "items").distinct()
        hit = matched(urls, found, frequency).select(F.col("key").alias("url"), F.lit(True).alias("mined"))
        d = joined_hot(d, scratch.table(hit, "hits"), "url", "left").withColumn("mined", F.coalesce("mined", F.lit(False)))  # many pages may have one url, or none
    rule, verdict = by_hand(F.col("host"), F.col("path"), rules)
    return d.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(verdict, F.when(F.col("mined"), "block").otherwise("allow")).alias("verdict"), "mined")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url"), spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality", "toxic"))
