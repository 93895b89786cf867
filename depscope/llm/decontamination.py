"""Benchmark decontamination: a broadcast hash set of test n-grams against all windows of the training texts.

Words are runs of 0-9, a-z (A-Z lower-cased) and code points above 127. A window is WINDOW consecutive words
of an item; a shorter item is one window. Every window of a document is hashed and looked up in one pass; hits are verified
word by word, each distinct window once. Only DataFrame functions are used.

What is broadcast has rows of fixed width and a checked number: hashes of n-grams, up to BLOCK, and keys of contaminated documents,
up to BROADCAST_KEYS; beyond either, the same joins shuffle. Which items hold a window is looked up last, once for each distinct set
of windows that documents have, so that a window of many items or of many documents is not multiplied out.

Defined results: null and wordless texts have no windows; an empty benchmark hits nothing; repeated item_ids
count once; items with a null id count as one and add nothing to the list of ids; rows that repeat a doc_id are told apart
by their text's hash, and equal rows share one result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from depscope.llm.common import ascii_lower, packed, table, text_or_empty, written

WINDOW = 10
#: n-grams whose hashes are broadcast at most (about 50 bytes each in a hashed relation); beyond it windows and n-grams meet in a shuffle.
BLOCK = 2_000_000
#: Contaminated documents whose keys are broadcast at most (about 80 bytes each).
BROADCAST_KEYS = 1_000_000
BREAKS = "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"
BREAK_CHARS = "".join(map(chr, [*range(0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]))
#: The same before A-Z are lower-cased, for the places of words in the given text.
RAW_BREAKS = "[\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]+"


def normal_words(text: Column) -> Column:
    # for texts of one-byte characters lower() does what is asked, at a fraction of the cost
    low = F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(ascii_lower(text))
    low = F.btrim(low, F.lit(BREAK_CHARS))
    return F.when(low == "", F.array().cast("array<string>")).otherwise(F.split(low, BREAKS))


def _windows(rows: DataFrame, keep: list[str], lengths: list[int]) -> DataFrame:
    """keep, pos (1-based), len, gram (the words): every window of each length over rows.words."""
    fits = F.col("pos") + F.col("len") - 1 <= F.size("words")
    out = rows.where(F.size("words") >= min(lengths)).select(*keep, "words", F.explode(F.sequence(F.lit(1), F.size("words") - min(lengths) + 1)).alias("pos"))
    out = out.withColumn("len", F.lit(lengths[0]) if len(lengths) == 1 else F.explode(F.lit(lengths))).where(fits)
    return out.select(*keep, "pos", "len", F.slice("words", F.col("pos"), F.col("len")).alias("gram"))


def item_grams(benchmark: DataFrame) -> DataFrame:
    """gram, len, h, item: the distinct windows of each item."""
    items = benchmark.select(F.col("item_id").cast("string").alias("item"), normal_words(text_or_empty()).alias("words")).where("size(words) > 0")
    whole = items.where(F.size("words") < WINDOW).select("item", F.size("words").alias("len"), F.col("words").alias("gram"))
    grams = _windows(items, ["item"], [WINDOW]).select("item", "len", "gram").unionByName(whole)
    return grams.select("gram", "len", F.xxhash64("gram").alias("h"), "item").distinct()


def _hits(docs: DataFrame, grams: DataFrame, block: int) -> DataFrame:
    """doc_id, text_key, pos, len, gram, h: every verified occurrence of an n-gram in a document."""
    lengths = sorted(r[0] for r in grams.select("len").distinct().collect())  # WINDOW values at most
    rows = docs.select(F.col("doc_id"), F.xxhash64("text").alias("text_key"), normal_words(text_or_empty()).alias("words"))
    if not lengths:
        return rows.where(F.lit(False)).select("doc_id", "text_key", F.lit(0).alias("pos"), F.lit(0).alias("len"), F.col("words").alias("gram"), F.lit(0).cast("long").alias("h"))
    windows = _windows(rows, ["doc_id", "text_key"], lengths).withColumn("h", F.xxhash64("gram"))
    hashes = written(grams.select("h").distinct(), "hashes")
    hashes = F.broadcast(hashes) if hashes.count() <= block else hashes
    found = written(windows.join(hashes, "h", "left_semi").select("doc_id", "text_key", "pos", "len", "gram", "h"), "candidates")
    # windows whose hash alone is an n-gram's: as good as never any
    wrong = written(found.select("h", "gram").distinct().join(grams.select("h", "gram").distinct(), ["h", "gram"], "left_anti"), "wrong")
    return found if wrong.isEmpty() else found.join(wrong, ["h", "gram"], "left_anti").select(*found.columns)


def hits(docs: DataFrame, benchmark: DataFrame, block: int = BLOCK) -> DataFrame:
    """doc_id, text_key, pos, len, gram, h: every verified occurrence of an item's window in a document."""
    return _hits(docs, written(item_grams(benchmark), "grams"), block)


def _hit_documents(found: DataFrame) -> DataFrame:
    """hit_id, hit_key, n_hit, hs (the hashes of its windows, sorted), set_key: one row a contaminated document."""
    keys = [F.col("doc_id").alias("hit_id"), F.col("text_key").alias("hit_key")]
    covered = found.select(*keys, F.explode(F.sequence(F.col("pos"), F.col("pos") + F.col("len") - 1)).alias("p")).distinct()
    covered = covered.groupBy("hit_id", "hit_key").agg(F.count("*").alias("n_hit"))
    sets = found.select(*keys, "h").distinct().groupBy(F.col("hit_id").alias("i"), F.col("hit_key").alias("k")).agg(F.sort_array(F.collect_list("h")).alias("hs"))
    rows = covered.join(sets, F.col("hit_id").eqNullSafe(F.col("i")) & (F.col("hit_key") == F.col("k")))
    return rows.select("hit_id", "hit_key", "n_hit", "hs", F.sha2(F.array_join(F.transform("hs", lambda h: h.cast("string")), ","), 256).alias("set_key"))


def _item_sets(bad: DataFrame, grams: DataFrame) -> DataFrame:
    """set_key, n_items, items (sorted): the items that hold any window of a set, once for each distinct set."""
    sets = bad.groupBy("set_key").agg(F.first("hs").alias("hs")).select("set_key", F.explode("hs").alias("h"))
    pairs = sets.join(grams.select("h", "item").distinct(), "h").select("set_key", "item").distinct()
    return pairs.groupBy("set_key").agg(F.count("*").alias("n_items"), F.sort_array(F.collect_list("item")).alias("items"))


def _contaminated(docs: DataFrame, benchmark: DataFrame) -> tuple[DataFrame, DataFrame]:
    """_hit_documents and _item_sets."""
    grams = written(item_grams(benchmark), "grams")
    bad = written(_hit_documents(_hits(docs, grams, BLOCK)), "contaminated")
    return bad, written(_item_sets(bad, grams), "items")


def _marked(docs: DataFrame, bad: DataFrame) -> DataFrame:
    """doc_id, n_words, and the columns of bad (hit_id, hit_key, ...), null for documents that aren't in it."""
    bad = F.broadcast(bad) if bad.count() <= BROADCAST_KEYS else bad
    rows = docs.select("doc_id", F.xxhash64("text").alias("text_key"), F.size(normal_words(text_or_empty())).cast("long").alias("n_words"))
    return rows.join(bad, F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("text_key") == F.col("hit_key")), "left")


def counted(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256: one row a document; lists of items are hashed, not carried."""
    bad, sets = _contaminated(docs, benchmark)
    digests = sets.select("set_key", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"))
    bad = written(bad.select("hit_id", "hit_key", "n_hit", "set_key").join(digests, "set_key").drop("set_key"), "digests")
    n = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return _marked(docs, bad).select("doc_id", "n_words", n("n_hit"), n("n_items"), F.coalesce("items_sha256", F.sha2(F.lit(""), 256)).alias("items_sha256"))


def contamination(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, items: one row a document, with the ids of all items that it holds windows of."""
    bad, sets = _contaminated(docs, benchmark)
    rows = _marked(docs, bad.select("hit_id", "hit_key", "n_hit", F.col("set_key").alias("own_set")))
    rows = rows.join(sets.select("set_key", "items"), F.col("own_set") == F.col("set_key"), "left")
    return rows.select("doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def clean_documents(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without the documents that hold a benchmark window."""
    bad = written(hits(docs, benchmark).select(F.col("doc_id").alias("__hit_id"), F.col("text_key").alias("__hit_key")).distinct(), "contaminated")
    bad = F.broadcast(bad) if bad.count() <= BROADCAST_KEYS else bad
    rows = packed(docs, F.col("doc_id").alias("__id"), F.xxhash64("text").alias("__key"))
    return rows.join(bad, F.col("__id").eqNullSafe(F.col("__hit_id")) & (F.col("__key") == F.col("__hit_key")), "left_anti").select("__doc.*")


def without_spans(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs with the words of benchmark windows cut from their texts; the characters between words stay."""
    found = written(hits(docs, benchmark), "hits")
    places = found.select(F.col("doc_id").alias("__hit_id"), F.col("text_key").alias("__hit_key"), F.explode(F.sequence(F.col("pos"), F.col("pos") + F.col("len") - 1)).alias("p")).distinct()
    # runs of neighbouring places, so that a text is cut run by run
    run = F.col("p") - F.row_number().over(Window.partitionBy("__hit_id", "__hit_key").orderBy("p"))
    runs = places.withColumn("run", run).groupBy("__hit_id", "__hit_key", "run").agg(F.min("p").alias("a"), F.max("p").alias("b"))
    places = runs.groupBy("__hit_id", "__hit_key").agg(F.sort_array(F.collect_list(F.struct("a", "b"))).alias("__cut"))
    rows = packed(docs, F.col("doc_id").alias("__id"), F.xxhash64("text").alias("__key"), F.col("text").alias("__text"))
    rows = rows.join(places, F.col("__id").eqNullSafe(F.col("__hit_id")) & (F.col("__key") == F.col("__hit_key")), "left")
    # between breaks the pieces alternate: piece 0 may be empty, and then words are counted from piece 1
    rows = rows.withColumn("__pieces", F.split("__text", RAW_BREAKS)).withColumn("__gaps", F.regexp_extract_all("__text", F.lit(RAW_BREAKS), F.lit(0)))
    first = F.when(F.get("__pieces", F.lit(0)) == "", 0).otherwise(1)
    # a word and the gap behind it are one part; part i is word i + first
    parts = F.transform("__pieces", lambda w, i: F.struct(w.alias("w"), F.coalesce(F.get("__gaps", i), F.lit("")).alias("gap")))
    rows = rows.withColumn("__first", first).withColumn("__parts", F.when(F.col("__cut").isNotNull(), parts))
    whole = lambda part: F.array_join(F.transform(part, lambda x: F.concat(x["w"], x["gap"])), "")
    gaps = lambda part: F.array_join(F.transform(part, lambda x: x["gap"]), "")
    at = lambda p: F.greatest(p - F.col("__first") + 1, F.lit(1))  # noqa: E731  # a word's place among the parts
    between = lambda lo, hi: F.slice("__parts", lo, F.greatest(hi - lo, F.lit(0)))
    before = F.transform("__cut", lambda c, i: F.when(i == 0, 1).otherwise(at(F.get("__cut", i - 1)["b"]) + 1))
    kept = F.transform("__cut", lambda c, i: F.concat(whole(between(F.get("__before", i), at(c["a"]))), gaps(between(at(c["a"]), at(c["b"]) + 1))))
    rows = rows.withColumn("__before", before)
    rest = whole(between(at(F.element_at("__cut", -1)["b"]) + 1, F.size("__parts") + 1))
    text = F.when(F.col("__cut").isNull(), F.col("__text")).otherwise(F.concat(F.array_join(kept, ""), rest))
    return rows.select(F.col("__doc").withField("text", text).alias("__doc")).select("__doc.*")


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = counted(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", (F.col("n_hit") > 0).alias("contaminated"))


OP8_SQL = r"""
WITH low AS (
  SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents
), it AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark
), g AS (
  SELECT DISTINCT item_id, array_to_string(ws[i:i + 9], ' ') AS gram, 10 AS k FROM it, unnest(range(1, len(ws) - 8)) AS u(i)
  UNION SELECT item_id, array_to_string(ws, ' '), len(ws)::INT FROM it WHERE len(ws) BETWEEN 1 AND 9
), ks AS (
  SELECT DISTINCT k FROM g
), win AS (
  SELECT rid, k, i, array_to_string(ws[i:i + k - 1], ' ') AS gram FROM low, ks, unnest(range(1, len(ws) - k + 2)) AS u(i)
), hit AS (
  SELECT rid, win.k, i, item_id FROM win JOIN g ON win.gram = g.gram AND win.k = g.k
), cov AS (
  SELECT rid, count(DISTINCT i + j) AS n FROM hit, unnest(range(0, k)) AS u(j) GROUP BY rid
), items AS (
  SELECT rid, count(*) AS n, string_agg(item, ',' ORDER BY item) AS s FROM (SELECT DISTINCT rid, item_id::VARCHAR AS item FROM hit) GROUP BY rid
)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(cov.n, 0)::BIGINT AS n_hit, coalesce(items.n, 0)::BIGINT AS n_items,
  sha256(coalesce(items.s, '')) AS items_sha256, cov.n IS NOT NULL AS contaminated
FROM low LEFT JOIN cov ON low.rid = cov.rid LEFT JOIN items ON low.rid = items.rid
"""
