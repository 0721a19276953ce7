"""URL filters: fixed host rules, and association rules mined by FP-growth.

URLs become sets of tokens (scheme, host and its suffixes, words of host and path,
extension, query keys). FP-growth mines token combinations that are frequent among
URLs labelled bad; their frequency among all labelled URLs gives the confidence.
Rules below the support or confidence, and rules that a shorter rule with as much
confidence implies, are pruned. A rule is filed in an inverted index under its
rarest token; a URL looks up its own tokens there and checks the rest of the rule.

Tokens of the very same labelled URLs are mined as one and stand in for each other in
the rules, so sets of any length are mined without a cap on their number of tokens.

Labels are joined by id: a page is bad if its label has low quality or is toxic. In the
given tables ids of labels are those of documents, which say nothing about URLs; there
no rule reaches the confidence, and the fixed rules alone decide (a test plants labels
that do depend on URLs).

Defined cases: null URLs and those without ``://`` have an empty host and path and
no tokens, and are allowed; repeated rows are judged alike; of rules of one confidence
the one of the greater text is named; a page with several labels counts once for each
distinct verdict; without labels no rules are mined; an empty table gives no rows; a
very long URL is split in one row's memory; other columns of the input play no part,
whatever their names.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.session import settle

#: Fixed rules of the contract: verdict, host, path.
HOST_RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Rules are broadcast up to this number, and joined by a shuffle beyond it; results are the same.
BROADCAST_RULES = 20_000


def split_url(pages: DataFrame, url_col: str = "url") -> DataFrame:
    """Adds ``host`` and ``path``."""
    url = F.coalesce(F.col(url_col), F.lit(""))
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), "^[^?#]*", 0)
    return pages.withColumn("host", F.translate(host, UPPER, LOWER)).withColumn("path", path)


def fixed_rule(rules=HOST_RULES):
    """Column of the longest fixed rule that fits ``host`` and ``path``: (rule, verdict)."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, host, path in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((F.col("host") == host) | F.endswith("host", F.lit("." + host))) & F.startswith("path", F.lit(path))
        out = F.when(fits, F.struct(F.lit(host + path).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def token_column(url_col: str = "url"):
    """Distinct tokens of ``host``, ``path`` and the rest of the URL."""
    labels = F.split("host", r"\.")
    n = F.size(labels)
    words = lambda c: F.filter(F.split(F.lower(c), r"[^a-z]+"), lambda w: F.length(w) > 1)
    tag = lambda prefix, c: F.transform(c, lambda w: F.concat(F.lit(prefix), w))
    query = F.regexp_extract(F.coalesce(F.col(url_col), F.lit("")), r"\?([^#]*)", 1)
    keys = F.filter(F.transform(F.split(query, "&"), lambda kv: F.regexp_extract(kv, "^[^=]*", 0)), lambda k: k != "")
    tokens = F.concat(
        F.array(F.concat(F.lit("h:"), F.col("host"))),
        F.array(F.concat(F.lit("tld:"), F.element_at(labels, -1))),
        tag("w:", words(F.col("host"))),
        tag("p:", words(F.col("path"))),
        tag("x:", F.filter(F.array(F.regexp_extract("path", r"\.([A-Za-z0-9]+)$", 1)), lambda x: x != "")),
        tag("q:", keys),
        F.when(n > 2, F.array(F.concat(F.lit("d:"), F.concat_ws(".", F.slice(labels, -3, 3))))).otherwise(F.array().cast("array<string>")),
    )
    return F.when(F.col("host") == "", F.array().cast("array<string>")).otherwise(F.array_distinct(tokens))


def token_classes(labelled: DataFrame, need: int) -> DataFrame:
    """``(token, count, lead)``: tokens of ``need`` rows at least; tokens of the very same rows share a lead.

    Without this, n tokens that always come together would make 2 ** n frequent sets.
    """
    row = [F.sum(F.xxhash64("tokens", F.lit(k)).cast("decimal(38,0)")).alias(f"r{k}") for k in (0, 1)]
    common = labelled.select("tokens", F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("count"), *row).where(F.col("count") >= need)
    common = settle(common, "url_tokens")
    leads = common.groupBy("count", "r0", "r1").agg(F.min("token").alias("lead"))
    return settle(common.join(leads, ["count", "r0", "r1"]).select("token", "count", "lead"), "url_classes")


def mined_rules(labelled: DataFrame, min_support: int = 20, min_share: float = 0.005, min_confidence: float = 0.8) -> DataFrame:
    """``(tokens, support, total, confidence, rare)`` of the pruned rules; labelled has (tokens, bad)."""
    spark = labelled.sparkSession
    labelled = settle(labelled.where(F.size("tokens") > 0).select("tokens", "bad", F.monotonically_increasing_id().alias("row")), "labelled_urls")
    n_bad = labelled.where("bad").count()
    schema = "tokens array<string>, support long, total long, confidence double, rare string"
    if not n_bad:
        return spark.createDataFrame([], schema)
    need = max(min_support, int(min_share * n_bad))
    classes = token_classes(labelled, need)
    led = labelled.select("row", "bad", F.explode("tokens").alias("token")).join(classes.select("token", "lead"), "token")
    led = settle(led.groupBy("row", "bad").agg(F.collect_set("lead").alias("tokens")), "led_urls")
    model = FPGrowth(itemsCol="tokens", minSupport=min(1.0, need / n_bad), minConfidence=1.0).fit(led.where("bad").select("tokens"))
    sets = settle(model.freqItemsets.select(F.sort_array("items").alias("tokens"), F.col("freq").alias("support")), "url_sets")
    counts = classes.where("token = lead").select("token", "count")
    hits = matched(led.select("tokens", "bad"), with_rarest(sets, counts), "tokens")
    rules = hits.groupBy("rule", "support", "rare").agg(F.count("*").alias("total")).withColumn("confidence", F.col("support") / F.col("total"))
    rules = settle(rules.where(F.col("confidence") >= min_confidence).withColumnRenamed("rule", "tokens"), "url_rules")
    # a shorter rule whose tokens are all in this one, with as much confidence, makes it redundant
    short = rules.select(F.col("tokens").alias("short"), F.col("confidence").alias("c"), F.col("rare").alias("token"))
    implied = (
        rules.select("tokens", "confidence", F.explode("tokens").alias("token"))
        .join(short, "token")
        .where((F.size("short") < F.size("tokens")) & (F.col("c") >= F.col("confidence")) & (F.size(F.array_except("short", "tokens")) == 0))
        .select("tokens")
        .distinct()
    )
    rules = rules.join(implied, "tokens", "left_anti").select("tokens", "support", "total", "confidence")
    # each token may stand in for its class again
    members = classes.groupBy("lead").agg(F.array_sort(F.collect_list("token")).alias("members"))
    lists = rules.withColumn("lead", F.explode("tokens")).join(members, "lead").groupBy("tokens", "support", "total", "confidence").agg(F.collect_list("members").alias("lists"))
    each = F.aggregate("lists", F.array(F.array().cast("array<string>")), lambda done, m: F.flatten(F.transform(done, lambda d: F.transform(m, lambda x: F.array_append(d, x)))))
    rules = lists.select(F.explode(each).alias("tokens"), "support", "total", "confidence").withColumn("tokens", F.sort_array("tokens"))
    return settle(with_rarest(rules, classes.select("token", "count")).select("tokens", "support", "total", "confidence", "rare"), "url_filter_rules")


def with_rarest(sets: DataFrame, counts: DataFrame) -> DataFrame:
    """``sets`` (with distinct ``tokens``) and the ``rare`` one of their tokens, under which they are filed."""
    least = sets.select("tokens", F.explode("tokens").alias("token")).join(counts, "token").groupBy("tokens").agg(F.min(F.struct("count", "token")).alias("r"))
    return sets.join(least, "tokens").withColumn("rare", F.col("r.token")).drop("r")


def matched(urls: DataFrame, rules: DataFrame, tokens_col: str) -> DataFrame:
    """Rows of ``urls`` for each rule that they fulfil, found by the rule's rarest token."""
    index = rules.withColumnRenamed("tokens", "rule")
    if rules.limit(BROADCAST_RULES + 1).count() <= BROADCAST_RULES:
        index = F.broadcast(index)
    found = urls.withColumn("_token", F.explode(tokens_col)).join(index, F.col("_token") == F.col("rare"))
    return found.where(F.size(F.array_except("rule", tokens_col)) == 0).drop("_token")


def url_verdicts(pages: DataFrame, labels: DataFrame, fixed=HOST_RULES, id_col: str = "page_id", url_col: str = "url", label_id: str = "doc_id", **mining) -> DataFrame:
    """``(page_id, host, path, rule, verdict, mined, confidence)`` for every page."""
    urls = split_url(pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"))).withColumn("tokens", token_column())
    truth = labels.select(F.col(label_id).alias("page_id"), ((F.col("quality") == 0) | (F.col("toxic") == 1)).alias("bad")).where("bad is not null").distinct()
    rules = mined_rules(urls.join(truth, "page_id").select("tokens", "bad"), **mining)
    best = matched(urls.select("page_id", "url", "tokens"), rules, "tokens").groupBy("page_id", "url").agg(F.max(F.struct("confidence", F.concat_ws(" ", "rule").alias("mined"))).alias("best"))
    best = best.select(F.col("page_id").alias("_page"), F.col("url").alias("_url"), "best")
    out = urls.join(best, F.col("page_id").eqNullSafe(F.col("_page")) & F.col("url").eqNullSafe(F.col("_url")), "left").withColumn("fixed", fixed_rule(fixed))
    verdict = F.coalesce("fixed.verdict", F.when(F.col("best").isNotNull(), "block").otherwise("allow"))
    return out.select("page_id", "host", "path", F.col("fixed.rule").alias("rule"), verdict.alias("verdict"), F.col("best.mined").alias("mined"), F.col("best.confidence").alias("confidence"))


def query(spark, sf_dir: str) -> DataFrame:
    return url_verdicts(spark.read.parquet(f"{sf_dir}/pages.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
