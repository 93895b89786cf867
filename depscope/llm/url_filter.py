"""URL filter: host and path rules, and logistic regression on hashed character n-grams for all other URLs.

A rule fits its host and all subdomains where the path starts with the rule's path; the longest fitting rule decides.
URLs without a rule are judged by a model fitted on the driver to a small labelled URL table of (host, path, 1 to block): the
caller's, or ``labelled_urls``, which is made of common words and knows no table that it is used on.

Defined results: a null URL, or one without ``://``, has an empty host and path, fits no rule and is allowed; rows that repeat a
page_id each get their row; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import random
from collections.abc import Iterator
from functools import lru_cache
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.llm.common import ascii_lower, table

#: (rule, verdict): a host, a slash, and the rest of a path.
RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))
BUCKETS, SIZES = 1 << 14, (3, 4, 5)
ROUNDS, RATE, DECAY = 800, 12.0, 1e-4
CUT = 0.45


# words that make a host unwanted or not, and what either kind is commonly joined with
SPAM = "casino poker roulette slots jackpot lottery betting bookmaker gambling viagra cialis pharmacy pills steroid porn xxx sexcam escort adult nude payday loans creditfix replica counterfeit torrent warez keygen cracked adserver adclick banner popunder tracker clickbait".split()
PLAIN = (
    "news school library garden music history science travel recipes weather museum university hospital council forum wiki docs research journal kitchen theatre gallery church "
    "village mountain river cycling football chess astronomy biology grammar poetry novel painting carpenter bakery farm vineyard orchestra railway harbour embassy parliament archive"
).split()
JOINED = ["{}-online", "my{}", "the-{}", "{}247", "{}-club", "best{}", "{}hub", "{}-world", "free-{}", "{}"]
HOSTS = ["{}.example.com", "www.{}.example.com", "m.{}.example.org", "{}.example.de", "blog.{}.example.co"]
PATHS = ["/en/1234", "/de/77.html", "/fr/8/", "/", "/es/index.html"]


def labelled_urls(seed: int = 1) -> list[tuple[str, str, int]]:
    """(host, path, 1 to block): both kinds of words in the same compounds, hosts and paths, and as plain hosts also made-up names."""
    rnd = random.Random(seed)
    part = lambda: rnd.choice("bcdfghjklmnprstvw") + rnd.choice("aeiou") + rnd.choice(["", "", "n", "r", "l", "s", "t"])
    made = ["".join(part() for _ in range(rnd.randint(2, 4))) for _ in range(160)]
    out = []
    for words, label in ((SPAM, 1), (PLAIN, 0)):
        out += [(rnd.choice(HOSTS).format(form.format(w)), rnd.choice(PATHS), label) for w in words for form in JOINED]
        out += [("www.example.com", f"/{w}/{rnd.randint(1, 999)}", label) for w in words]
    return out + [(rnd.choice(HOSTS).format(w), rnd.choice(PATHS), 0) for w in made for _ in range(2)]


def grams(host: str, path: str) -> np.ndarray:
    """Distinct buckets of the n-grams of host and path, each end marked."""
    data = f"^{host}${path}$".encode()
    return np.unique(np.array([crc32(data[i : i + n]) % BUCKETS for n in SIZES for i in range(len(data) - n + 1)] or [0], dtype=np.int64))


@lru_cache(maxsize=4)
def fitted(labelled: tuple[tuple[str, str, int], ...] | None = None) -> tuple[np.ndarray, float]:
    """Weights and intercept: gradient steps on the mean log loss of the labelled URLs, half from each kind, each URL's n-grams scaled to unit length."""
    labelled = tuple(labelled_urls()) if labelled is None else labelled
    rows = [grams(h, p) for h, p, _ in labelled]
    if not rows:
        return np.zeros(BUCKETS), -1.0
    y = np.array([label for _, _, label in labelled], dtype=np.float64)
    at, of = np.concatenate(rows), np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    x = np.repeat([1 / np.sqrt(len(r)) for r in rows], [len(r) for r in rows])
    w, b = np.zeros(BUCKETS), 0.0
    # both kinds weigh the same, however many of each are labelled
    share = np.where(y == 1, 0.5 / max(y.sum(), 1), 0.5 / max((1 - y).sum(), 1))
    for _ in range(ROUNDS):
        err = share * (1 / (1 + np.exp(-(np.bincount(of, w[at] * x, minlength=len(y)) + b))) - y)
        w -= RATE * (np.bincount(at, err[of] * x, BUCKETS) + DECAY * w)
        b -= 0.1 * RATE * err.sum()
    return w, b


def host_and_path(url: Column) -> tuple[Column, Column]:
    whole = F.coalesce(url, F.lit(""))
    rest = F.when(F.instr(whole, "://") > 0, F.substring(whole, F.instr(whole, "://") + 3, F.length(whole))).otherwise("")
    raw_host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(raw_host) + 1, F.length(rest)), "^[^?#]*", 0)
    return ascii_lower(raw_host), path


def rule_of(host: Column, path: Column, rules: tuple[tuple[str, str], ...] = RULES) -> Column:
    """The longest rule that fits, null without one. Rules are a short list, unrolled into one expression."""
    found = F.lit(None).cast("string")
    for rule, _ in sorted(rules, key=lambda r: (len(r[0]), r[0])):
        rule_host, slash, rest = rule.partition("/")
        fits = ((host == rule_host) | host.endswith("." + rule_host)) & path.startswith(slash + rest)
        found = F.when(fits, F.lit(rule)).otherwise(found)
    return found


def judged(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES, labelled: tuple[tuple[str, str, int], ...] | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict, score: one row a page. The score is the model's, for pages without a rule; ``labelled`` replaces its training table (empty: all are allowed)."""
    weights, bias = fitted(labelled)

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            scores = []
            for host, path, rule in zip(*(batch.column(c).to_pylist() for c in ("host", "path", "rule")), strict=True):
                at = grams(host, path) if rule is None and host + path else None
                scores.append(None if at is None else float(1 / (1 + np.exp(-(weights[at].sum() / np.sqrt(len(at)) + bias)))))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], [*batch.schema.names, "score"])

    host, path = host_and_path(F.col("url"))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), host.alias("host"), path.alias("path"))
    rows = rows.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules))
    rows = rows.mapInArrow(batches, "page_id long, host string, path string, rule string, score double")
    verdict = F.when(F.col("score") >= CUT, "block").otherwise("allow")
    for rule, said in rules:
        verdict = F.when(F.col("rule") == rule, said).otherwise(verdict)
    return rows.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "score")


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "pages"))
