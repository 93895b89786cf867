"""Quality rules with host-level verdicts, in DataFrame functions only.

Each document is measured and held against rules; rule failures are aggregated by host (the source
column), each host's failure rate is shrunk by a beta prior fitted to all hosts' rates (method of moments),
and a host whose shrunk rate is above ``HOST_RATE`` takes its remaining documents with it.

Defined results: a null or empty text has no words, so it fails the base rule; a null source is no host,
so its documents stand on their own; rows that repeat count each; other columns are ignored; an empty
table gives an empty result. Hot hosts are safe: counts are pre-aggregated before the shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.llm.common import SPACE_CHARS, table, text_or_empty, words, written

#: Base rule: fewest words, and the share of words in repeated windows of WINDOW words (a percentage).
MIN_WORDS, REPEAT_PERCENT, WINDOW = 20, 30, 8
SYMBOLS = "#*$%&|<>"
#: Soft rules count towards a host's rate only: symbols a hundred word characters, and repeated lines a hundred words.
SYMBOL_PERCENT, DUP_LINE_PERCENT = 10, 10
#: A host is rejected above this shrunk failure rate.
HOST_RATE = 0.6
#: Most hosts whose verdicts are broadcast (about 100 bytes each); beyond it they are joined by a shuffle.
BROADCAST_HOSTS = 500_000


def _without(text: Column, chars: str) -> Column:
    return F.translate(text, chars, "")


def measured(docs: DataFrame, keep: list[str]) -> DataFrame:
    """keep's columns, then n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (long), one row a document.

    n_repeat_words counts the words inside windows of WINDOW words that occur twice or more in the text. Windows are
    compared by XXH64; only texts with an equal pair are sorted.
    """
    step = docs.select(*keep, text_or_empty().alias("__text")).withColumn("__words", words(F.col("__text")))
    n = F.size("__words")
    hashes = F.when(n > WINDOW, F.transform(F.sequence(F.lit(1), n - WINDOW + 1), lambda i: F.xxhash64(F.slice("__words", i, WINDOW))))
    step = step.select(
        *keep,
        n.cast("long").alias("n_words"),
        F.length(_without(F.col("__text"), SPACE_CHARS)).cast("long").alias("word_chars"),
        (F.length("__text") - F.length(_without(F.col("__text"), SYMBOLS))).cast("long").alias("n_symbols"),
        F.filter(F.split("__text", "\n"), lambda x: F.btrim(x, F.lit(SPACE_CHARS)) != "").alias("__lines"),
        hashes.alias("__hashes"),
    )
    step = step.withColumn("__repeats", F.size(F.array_distinct("__hashes")) < F.size("__hashes"))
    at = F.transform("__hashes", lambda h, i: F.struct(h.alias("h"), i.alias("i")))
    step = step.withColumn("__sorted", F.when(F.col("__repeats"), F.sort_array(at)))

    def has_twin(x: Column, i: Column) -> Column:
        near = lambda j: F.coalesce(F.get("__sorted", j)["h"] == x["h"], F.lit(False))
        return near(i - 1) | near(i + 1)

    places = F.sort_array(F.transform(F.filter("__sorted", has_twin), lambda x: x["i"]))
    start = F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).cast("long").alias("total"))
    covered = F.aggregate(
        places,
        start,
        lambda s, p: F.struct(p.alias("last"), (s["total"] + F.least(F.lit(WINDOW), p - s["last"])).alias("total")),
        lambda s: s["total"],
    )
    return step.select(
        *keep,
        "n_words",
        "word_chars",
        "n_symbols",
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long").alias("n_dup_lines"),
        F.coalesce(F.when(F.col("__repeats"), covered), F.lit(0)).cast("long").alias("n_repeat_words"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))


def any_failed() -> Column:
    soft = (100 * F.col("n_symbols") > SYMBOL_PERCENT * F.col("word_chars")) | (100 * F.col("n_dup_lines") > DUP_LINE_PERCENT * F.col("n_words"))
    return base_failed() | soft


def rejected_hosts(rows: DataFrame, failed: Column, host: str = "source", rate: float = HOST_RATE) -> DataFrame:
    """host, shrunk_rate of the hosts whose failure rate, shrunk by the empirical beta prior, is above rate."""
    hosts = rows.where(F.col(host).isNotNull()).groupBy(F.col(host).alias("host"))
    hosts = written(hosts.agg(F.count("*").alias("n"), F.sum(F.when(failed, 1).otherwise(0)).alias("f")), "hosts")
    fit = hosts.agg(F.sum("f") / F.sum("n"), F.avg(F.col("f") / F.col("n")), F.var_pop(F.col("f") / F.col("n"))).first()
    mean, centre, spread = (float(x or 0) for x in fit)
    # a + b of the beta distribution that has the hosts' mean and variance; equal rates give the strongest prior
    weight = min(max(centre * (1 - centre) / spread - 1, 1.0), 1e6) if spread > 0 else 1e6
    shrunk = (F.col("f") + F.lit(mean * weight)) / (F.col("n") + F.lit(weight))
    return hosts.select("host", shrunk.alias("shrunk_rate")).where(F.col("shrunk_rate") > rate)


def _small(df: DataFrame, most: int) -> DataFrame:
    return F.broadcast(df) if df.count() <= most else df


def judged(docs: DataFrame) -> DataFrame:
    """doc_id, source, the five measures, base_failed, kept: one row a document."""
    rows = written(measured(docs, ["doc_id", "source"]), "measures")
    hosts = _small(rejected_hosts(rows, any_failed()), BROADCAST_HOSTS)
    rows = rows.join(hosts.select("host", F.lit(True).alias("bad_host")), rows["source"] == hosts["host"], "left")
    return rows.select(
        "doc_id", "source", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        base_failed().alias("base_failed"), (~base_failed() & F.col("bad_host").isNull()).alias("kept"),
    )


def kept_documents(docs: DataFrame) -> DataFrame:
    """The documents that pass, with their columns. Measures once: the texts wait in a scratch table until the hosts are judged."""
    own = docs.columns
    rows = docs.select(F.struct(*own).alias("__doc"), "source", "text")
    rows = measured(rows, ["__doc", "source"]).select("__doc", "source", base_failed().alias("__base"), any_failed().alias("__any"))
    rows = written(rows, "flagged")
    hosts = _small(rejected_hosts(rows, F.col("__any")), BROADCAST_HOSTS)
    return rows.where(~F.col("__base")).join(hosts, rows["source"] == hosts["host"], "left_anti").select("__doc.*")


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "documents")).drop("source")


OP10_SQL = r"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id, source, coalesce(text, '') AS t FROM documents
), w AS (
  SELECT *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws FROM d
), pos AS (
  SELECT rid, i, array_to_string(ws[i:i + 7], ' ') AS win FROM w, unnest(range(1, len(ws) - 6)) AS u(i)
), rep AS (
  SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, win) AS c FROM pos) WHERE c > 1
), cov AS (
  SELECT rid, count(DISTINCT i + k) AS n FROM rep, unnest(range(0, 8)) AS u(k) GROUP BY rid
), m AS (
  SELECT w.rid, doc_id, source, len(ws)::BIGINT AS n_words,
    length(array_to_string(ws, ''))::BIGINT AS word_chars,
    (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
    (len(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))
      - len(list_distinct(list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')))))::BIGINT AS n_dup_lines,
    coalesce(cov.n, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN cov ON w.rid = cov.rid
), v AS (
  SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed,
    n_words < 20 OR 100 * n_repeat_words > 30 * n_words OR 100 * n_symbols > 10 * word_chars OR 100 * n_dup_lines > 10 * n_words AS any_failed
  FROM m
), h AS (
  SELECT source, count(*) AS n, sum(any_failed::INT) AS f FROM v WHERE source IS NOT NULL GROUP BY source
), p AS (
  SELECT sum(f) / sum(n) AS mean,
    CASE WHEN var_pop(f / n) > 0 THEN least(greatest(avg(f / n) * (1 - avg(f / n)) / var_pop(f / n) - 1, 1.0), 1e6) ELSE 1e6 END AS weight
  FROM h
), bad AS (
  SELECT source FROM h, p WHERE (f + mean * weight) / (n + weight) > 0.6
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND (source IS NULL OR source NOT IN (SELECT source FROM bad)) AS kept
FROM v
"""
