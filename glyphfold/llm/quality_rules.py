"""Quality rules with host-level verdicts, in DataFrame operations only.

Each text is measured, each document passes or fails the rules, and failures are
summed by host (the ``source`` column). A host's failure rate is shrunk towards
the corpus: a beta prior is fitted to all hosts by moments, so a host with few
documents is judged like the average one. Documents of hosts whose shrunk rate
is above ``max_rate`` are rejected along with those that fail the base rules.

Repeated windows of three words are told by the 64-bit hash of their words.

Defined cases: a null or empty text has no words and fails; a null host is a host of
its own; with no documents there are no hosts and the result is empty; repeated rows
count each time and are judged alike, ids don't matter; a host at exactly ``max_rate``
is kept; a very long text is measured as a whole in one row's memory; other columns of
the input are left alone, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.session import settle, whole_row

#: Character classes of the contract: white space between words, and symbols.
SPACE = r"[\x20\x09-\x0D]+"
SYMBOLS = "#*$%&|<>"
METRICS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def with_metrics(rows: DataFrame, *own: str) -> DataFrame:
    """The columns ``own`` (of other names than used here) and the metrics of every whole ``text``."""
    df = rows.withColumn("t", F.coalesce("text", F.lit("")))
    df = df.select(
        *own,
        F.filter(F.split("t", SPACE), lambda w: w != "").alias("w"),
        F.filter(F.split("t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("l"),
        F.char_length(F.translate("t", " \t\n\x0b\x0c\r", "")).cast("long").alias("word_chars"),
        (F.char_length("t") - F.char_length(F.translate("t", SYMBOLS, ""))).cast("long").alias("n_symbols"),
    )
    df = df.select(
        *own,
        F.size("w").cast("long").alias("n_words"),
        "word_chars",
        "n_symbols",
        (F.size("l") - F.size(F.array_distinct("l"))).cast("long").alias("n_dup_lines"),
        F.expr("if(size(w) < 4, array(), transform(sequence(0, size(w) - 3), i -> xxhash64(w[i], w[i + 1], w[i + 2])))").cast("array<long>").alias("h"),
    )
    pairs = "if(size(h) = size(array_distinct(h)), cast(array() as array<struct<h: bigint, i: int>>), array_sort(transform(h, (x, i) -> struct(x as h, i as i))))"
    df = df.withColumn("s", F.expr(pairs))
    again = """array_sort(transform(filter(s, (x, k) -> (k > 0 and s[greatest(k - 1, 0)].h = x.h)
                or (k < size(s) - 1 and s[least(k + 1, size(s) - 1)].h = x.h)), x -> x.i))"""
    covered = "aggregate(p, struct(0L as n, -3 as last), (a, i) -> struct(a.n + least(3, i - a.last) as n, i as last), a -> a.n)"
    return df.withColumn("p", F.expr(again)).withColumn("n_repeat_words", F.expr(covered)).select(*own, *METRICS)


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """``(doc_id, host, <metrics>)`` of every whole text."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(host_col).alias("host"), F.col(text_col).alias("text"))
    return with_metrics(rows, "doc_id", "host")


def judged(metrics: DataFrame) -> DataFrame:
    """Adds ``base_failed`` and ``rule_failed`` (base rules, or mostly symbols or long words)."""
    base = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    soft = (10 * F.col("n_symbols") > F.col("word_chars")) | (F.col("word_chars") > 15 * F.col("n_words"))
    return metrics.withColumn("base_failed", base).withColumn("rule_failed", base | soft)


def beta_prior(hosts: DataFrame) -> tuple[float, float]:
    """Prior failures and documents, by moments over all hosts; a few numbers reach the driver."""
    n, k, hosts_n, squares = hosts.agg(F.sum("n"), F.sum("k"), F.count("*"), F.sum(F.col("k") * F.col("k") / F.col("n"))).first()
    if not n:
        return 0.5, 1.0
    mean = k / n
    spread = squares / n - mean * mean - mean * (1 - mean) * hosts_n / n
    weight = min(max(mean * (1 - mean) / max(spread, 1e-9) - 1, 1.0), 1e6)
    return mean * weight, weight


def host_rates(flags: DataFrame) -> DataFrame:
    """``(host, n, k, rate)``: failures by host, shrunk by the fitted prior."""
    hosts = flags.groupBy("host").agg(F.count("*").alias("n"), F.sum(F.col("rule_failed").cast("long")).alias("k"))
    failures, weight = beta_prior(hosts)
    return hosts.withColumn("rate", (F.col("k") + failures) / (F.col("n") + weight))


def quality_verdicts(docs: DataFrame, max_rate: float = 0.6, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """``(doc_id, host, <metrics>, base_failed, host_failed, kept)`` for every document."""
    flags = settle(judged(measured(docs, id_col, text_col, host_col)), "quality")
    bad = host_rates(flags).where(F.col("rate") > max_rate).select(F.col("host").alias("bad_host"), F.lit(True).alias("hit"))
    joined = flags.join(bad, F.col("host").eqNullSafe(F.col("bad_host")), "left")
    host_failed = F.coalesce("hit", F.lit(False))
    return joined.select("doc_id", "host", *METRICS, "base_failed", host_failed.alias("host_failed"), (~F.col("base_failed") & ~host_failed).alias("kept"))


def quality_filter(docs: DataFrame, max_rate: float = 0.6, text_col: str = "text", host_col: str = "source") -> DataFrame:
    """The rows of ``docs`` that the rules keep, columns unchanged.

    Each row is judged by its own text and host, whatever ids it shares. The verdicts of
    the rules are written beside the rows, so texts are measured once and never shuffled
    unless the rejected hosts are too many to broadcast.
    """
    rows = docs.select(whole_row(docs), F.col(text_col).alias("text"), F.col(host_col).alias("host"))
    rows = settle(judged(with_metrics(rows, "row", "host")).select("row", "host", "base_failed", "rule_failed"), "quality_rows")
    bad = settle(host_rates(rows).where(F.col("rate") > max_rate).select(F.col("host").alias("bad_host")), "bad_hosts")  # of known size
    kept = rows.where(~F.col("base_failed")).join(bad, F.col("host").eqNullSafe(F.col("bad_host")), "left_anti")
    return kept.select("row.*")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return quality_verdicts(docs).select("doc_id", *METRICS, "base_failed", "kept")


ORACLE_SQL = r"""
with w as (
  select doc_id, source,
    list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as l,
    length(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) as word_chars,
    length(coalesce(text, '')) - length(regexp_replace(coalesce(text, ''), '[#*$%&|<>]', '', 'g')) as n_symbols
  from documents
), tri as (
  select doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as g
  from (select doc_id, w, unnest(range(1, len(w) - 1)) as i from w)
), rep as (
  select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, g) as c from tri) where c > 1
), cov as (
  select doc_id, count(distinct p) as n from (select doc_id, unnest([i, i + 1, i + 2]) as p from rep) group by doc_id
), m as (
  select w.doc_id, source, len(w)::bigint as n_words, word_chars::bigint as word_chars, n_symbols::bigint as n_symbols,
    (len(l) - len(list_distinct(l)))::bigint as n_dup_lines, coalesce(cov.n, 0)::bigint as n_repeat_words
  from w left join cov using (doc_id)
), f as (
  select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed,
    n_words < 50 or 100 * n_repeat_words > 50 * n_words or 10 * n_symbols > word_chars or word_chars > 15 * n_words as rule_failed
  from m
), h as (
  select source, count(*)::double as n, sum(rule_failed::int)::double as k from f group by source
), q as (
  select sum(k) / sum(n) as mean,
    sum(k * k / n) / sum(n) - power(sum(k) / sum(n), 2) - (sum(k) / sum(n)) * (1 - sum(k) / sum(n)) * count(*) / sum(n) as spread
  from h
), prior as (
  select mean, least(greatest(mean * (1 - mean) / greatest(spread, 1e-9) - 1, 1.0), 1e6) as weight from q
), bad as (
  select source from h, prior where (k + mean * weight) / (n + weight) > 0.6
)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  not base_failed and not exists (select 1 from bad where bad.source is not distinct from f.source) as kept
from f
"""
