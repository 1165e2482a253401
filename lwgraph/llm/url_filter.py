"""URL filtering by association rules (DataFrame and SQL functions, Spark's FP-growth).

A url becomes a small set of tokens: host labels, host suffixes, path words with their
digits folded, query keys, a fragment mark.  Labelled urls are mined with FP-growth,
the label being one more token; rules whose consequent is a label and that pass the
confidence and support limits are kept, without those that a shorter rule already
implies at no lower confidence.  Matching goes through an inverted index: each rule is
filed under its rarest token, a url meets only the rules filed under one of its
tokens, and an ``array_except`` confirms the whole antecedent.

The number of rules cannot grow with the data: a token set with support s occurs in a
share s of the rows, so at most (subsets a url has) / s sets can be frequent, and the
antecedents are limited to ``max_items`` tokens.  That bound is what allows the
broadcast of the index.

The labels of ``op4`` are the verdicts of the fixed policy rules on the urls they fit.
Mining uses every labelled row; FP-growth's trees merge equal token sets in the task that
reads them, so a set or host that many rows share does not meet in one task.

Defined results: a null url or one without ``://`` has empty host and path and no
tokens; what no rule of either kind covers gets ``default``; repeated urls are judged alike.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import load, materialize

# The policy (verdict, host, path prefix).
POLICY = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)
MAX_ITEMS = 3
SUPPORT, CONFIDENCE = 0.01, 0.8
DEFAULT = "allow"


def host_of(url: Column) -> Column:
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(rest, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def policy_rule(host: Column, path: Column, policy=POLICY) -> tuple[Column, Column]:
    """(rule, verdict) of the longest policy rule that fits, else nulls; longer hosts first, then longer paths."""
    ordered = sorted(policy, key=lambda r: (-len(r[1] + r[2]), r))
    rule = verdict = F.lit(None).cast("string")
    for says, h, p in reversed(ordered):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(says)).otherwise(verdict)
    return rule, verdict


def tokens(url: Column, host: Column, path: Column) -> Column:
    text = F.coalesce(url, F.lit(""))
    labels = F.filter(F.split(host, r"\."), lambda x: x != "")
    suffix = F.when(F.size(labels) >= 2, F.array(F.concat(F.lit("suffix:"), F.concat_ws(".", F.slice(labels, -2, 2))))).otherwise(F.array().cast("array<string>"))
    words = F.filter(F.split(F.lower(path), r"[/._-]+"), lambda x: x != "")
    folded = F.transform(words, lambda x: F.concat(F.lit("path:"), F.regexp_replace(x, "[0-9]+", "#")))
    asked = F.regexp_extract_all(text, F.lit(r"[?&]([^=&#?]+)="), F.lit(1))
    mark = F.when(text.contains("#"), F.array(F.lit("fragment"))).otherwise(F.array().cast("array<string>"))
    return F.array_distinct(F.concat(F.transform(labels, lambda x: F.concat(F.lit("host:"), x)), suffix, folded, F.transform(asked, lambda x: F.concat(F.lit("key:"), F.lower(x))), mark))


def mine(labelled: DataFrame, *, support: float = SUPPORT, confidence: float = CONFIDENCE, max_items: int = MAX_ITEMS) -> DataFrame:
    """rule_id, antecedent, label, confidence, support from (tokens, label) rows."""
    spark = labelled.sparkSession
    chosen = labelled.filter("label is not null")
    sample = materialize(chosen.select(F.concat("tokens", F.array(F.concat(F.lit("label:"), F.col("label")))).alias("items")), "transactions")
    empty = spark.createDataFrame([], "antecedent array<string>, label string, confidence double, support double")
    if sample.isEmpty():
        return empty.withColumn("rule_id", F.lit(0).cast("bigint"))
    # tokens below the support limit can be in no rule: drop them before the trees are built
    total = sample.count()
    frequent = (sample.select(F.explode("items").alias("item")).groupBy("item").count().filter(F.col("count") >= support * total).select("item"))
    numbered = sample.withColumn("row", F.monotonically_increasing_id())
    slim = (materialize(numbered, "numbered").select("row", F.explode("items").alias("item")).join(F.broadcast(frequent), "item")
            .groupBy("row").agg(F.collect_set("item").alias("items")))
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=confidence).fit(slim)
    rules = (model.associationRules.filter(F.col("consequent")[0].startswith("label:") & ~F.exists("antecedent", lambda x: x.startswith("label:")))
             .filter(F.size("antecedent") <= max_items)
             .select(F.array_sort("antecedent").alias("antecedent"), F.substring(F.col("consequent")[0], 7, 1000).alias("label"), "confidence", "support"))
    rules = materialize(rules, "rules")
    a, b = rules.alias("a"), rules.alias("b")
    implied = (a.withColumn("item", F.explode("antecedent")).join(b.withColumn("item", F.explode("antecedent")), "item")
               .filter("a.label = b.label and size(b.antecedent) < size(a.antecedent) and b.confidence >= a.confidence and size(array_except(b.antecedent, a.antecedent)) = 0")
               .select(F.col("a.antecedent").alias("antecedent"), F.col("a.label").alias("label")).distinct())
    kept = rules.join(implied, ["antecedent", "label"], "left_anti")
    return kept.withColumn("rule_id", F.xxhash64("antecedent", "label"))


def judge(pages: DataFrame, rules: DataFrame, item_counts: DataFrame, key: str = "page_id") -> DataFrame:
    """(key columns, method_verdict) for rows (key, tokens): the surest rule that fits wins."""
    filed = (rules.select("rule_id", "antecedent", "label", "confidence", "support", F.explode("antecedent").alias("item"))
             .join(item_counts, "item", "left")
             .withColumn("place", F.row_number().over(Window.partitionBy("rule_id").orderBy(F.coalesce("n", F.lit(0)), "item")))
             .filter("place = 1").drop("n", "place"))
    index = filed.groupBy("item").agg(F.collect_list(F.struct("confidence", "support", "label", "antecedent")).alias("filed"))
    met = (pages.select(key, "tokens", F.explode("tokens").alias("item")).join(F.broadcast(index), "item")
           .select(key, F.filter("filed", lambda r: F.size(F.array_except(r["antecedent"], F.col("tokens"))) == 0).alias("fit"))
           .filter(F.size("fit") > 0)
           .select(key, F.array_max(F.transform("fit", lambda r: F.struct(r["confidence"].alias("confidence"), r["support"].alias("support"), r["label"].alias("label")))).alias("best")))
    return met.groupBy(key).agg(F.max("best").alias("best")).select(key, F.col("best.label").alias("method_verdict"))


def filter_urls(pages: DataFrame, policy=POLICY, default: str = DEFAULT, **limits) -> DataFrame:
    """page_id, host, path, rule, verdict, judged_by of every row."""
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    rule, says = policy_rule(F.col("host"), F.col("path"), policy)
    read = pages.select("page_id", "url", host.alias("host"), path.alias("path"))
    parsed = read.select("page_id", "url", "host", "path", rule.alias("rule"), says.alias("says"), tokens(F.col("url"), F.col("host"), F.col("path")).alias("tokens"))
    rules = materialize(mine(parsed.select("tokens", F.col("says").alias("label")), **limits), "url-rules")
    wanted = rules.select(F.explode("antecedent").alias("item")).distinct()
    counts = parsed.select(F.explode("tokens").alias("item")).join(F.broadcast(wanted), "item").groupBy("item").agg(F.count(F.lit(1)).alias("n"))
    # Distinct token sets are judged once, whatever the number of urls that share them.
    open_sets = parsed.filter("says is null").select("tokens").distinct().withColumn("set_id", F.xxhash64("tokens"))
    judged = judge(open_sets.select(F.struct("set_id", "tokens").alias("key"), "tokens"), rules, counts, "key").select(F.col("key.tokens").alias("tokens"), "method_verdict")
    verdicts = materialize(judged, "url-verdicts")
    joined = parsed.join(verdicts, "tokens", "left")
    return joined.select("page_id", "host", "path", "rule", F.coalesce("says", "method_verdict", F.lit(default)).alias("verdict"),
                         F.when(F.col("says").isNotNull(), "policy").when(F.col("method_verdict").isNotNull(), "rules").otherwise("default").alias("judged_by"))


def op4_url_filter(spark, sf_dir):
    return filter_urls(load(spark, sf_dir, "pages", "page_id", "url"))


QUERIES = {"op4_url_filter": op4_url_filter}
ORACLES: dict[str, str] = {}
