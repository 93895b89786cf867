"""Mixing sources to target weights, in DataFrame functions only.

Every document has a hash-random key. Within its source, documents lie in key order; distributed prefix sums of
their sizes cut each source at its exact budget. A source whose budget is above its size is taken in whole epochs
and then up to the cut. The prefix sums are of two levels, so that no source is one task: sizes are summed for
each range of keys (the key's first hex digits), the ranges' sums are accumulated, and a window accumulates
inside a range. Sources may be millions (hosts): their ranks and running sums are of two levels, too, over range partitions.

Defined results: null and empty texts have size 0 and take 0; documents without an id share one key, and are spread over ranges by
size or text; a null source is a source, ordered last; rows that
repeat a doc_id tie on their key and are ordered by size, equal rows are interchangeable; other columns are
ignored; an empty table gives an empty result, a table without words takes nothing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from depscope.llm.common import hash_key, packed, table, text_or_empty, written

WEIGHTS = (5, 2, 1)
#: A source is taken this often at most.
EPOCHS = 3
#: Hex digits of the key that make a range: 16 ** RANGE_DIGITS ranges a source.
RANGE_DIGITS = 3
#: Sources whose cuts are broadcast at most (about 100 bytes each); beyond it they are joined by a shuffle.
BROADCAST_SOURCES = 500_000
#: The MD5 of no id.
NO_ID = "d41d8cd98f00b204e9800998ecf8427e"
WORD = "[^ \\t-\\r]+"


def _sources(sized: DataFrame, weights: tuple[int, ...], epochs: int) -> DataFrame:
    """source, source_size, target: shares by weight, held at epochs times the size, the excess reshared.

    Resharing ends where every source has the lesser of weight * level and its cap. Sources reach their cap in the order of
    cap / weight, so the level follows from running sums over that order. Two rows of sums are all that is gathered.
    """
    s = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = _running(s, [F.col("source").asc_nulls_last()], {"rank": F.lit(1)})
    weight = F.element_at(F.array(*map(F.lit, weights)), F.pmod("rank", F.lit(len(weights))).cast("int") + 1)
    s = by_name.select("source", "source_size", weight.cast("long").alias("w"))
    ratio = F.col("source_size") / F.col("w")
    s = written(_running(s, [ratio.asc(), F.col("source").asc_nulls_last()], {"size_before": F.col("source_size"), "w_before": F.col("w"), "nth": F.lit(1)}), "sources")
    # the level that would suffice if a source and all after it were not held; the first source that isn't held decides
    every = s.agg(F.sum("source_size").alias("size"), F.sum("w").alias("w")).first()
    if every["w"] is None:
        return s.select("source", "source_size", F.lit(0.0).alias("target"))
    level = (F.lit(every["size"]) - epochs * F.col("size_before")).cast("double") / (F.lit(every["w"]) - F.col("w_before"))
    held = level * F.col("w") > epochs * F.col("source_size")
    decided = s.agg(F.min(F.when(~held, F.struct("nth", level.alias("level"))))["level"].alias("level")).first()["level"]
    cap = (epochs * F.col("source_size")).cast("double")
    return s.select("source", "source_size", (cap if decided is None else F.least(F.col("w") * F.lit(decided), cap)).alias("target"))


def _running(rows: DataFrame, order: list[Column], sums: dict[str, Column]) -> DataFrame:
    """rows with the sum of each column over all rows before, in a total order: inside range partitions, and over the partitions' own sums."""
    placed = written(rows.repartitionByRange(*order).withColumn("__part", F.spark_partition_id()), "ranges")
    parts = placed.groupBy(F.col("__part").alias("__p")).agg(*(F.sum(x).alias(f"__{c}") for c, x in sums.items()))
    # one row a partition
    earlier = Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)
    parts = F.broadcast(parts.select("__p", *(F.coalesce(F.sum(f"__{c}").over(earlier), F.lit(0)).alias(f"__{c}") for c in sums)))
    inside = Window.partitionBy("__part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    found = placed.select("*", *(F.coalesce(F.sum(x).over(inside), F.lit(0)).alias(c) for c, x in sums.items())).join(parts, F.col("__part") == F.col("__p"))
    return found.select(*rows.columns, *((F.col(c) + F.col(f"__{c}")).alias(c) for c in sums))


def _cell() -> Column:
    """A document's range: its key's first digits. The key that all documents without an id share has ranges of its own, in the order of the rest of the key, or of sizes."""
    first, own = F.substring("key", 1, RANGE_DIGITS), F.substring("key", 1, 32)
    rest = F.when(F.length("key") > 32, F.substring("key", 33, RANGE_DIGITS)).otherwise(F.lpad(F.col("size").cast("string"), 12, "0"))
    return F.when(own == NO_ID, F.concat(first, F.lit(":"), rest)).when((first == NO_ID[:RANGE_DIGITS]) & (own > NO_ID), F.concat(first, F.lit("~"))).otherwise(first)


def _placed(sized: DataFrame, keep: list[str], weights: tuple[int, ...], epochs: int) -> DataFrame:
    """keep, size, source_size, target, before (the sizes of the source's earlier documents in key order; 0 for a document without words).

    sized has source, size, key and keep; it is read several times, so it should be a table.
    """
    targets = written(_sources(sized, weights, epochs), "targets")
    cell = _cell()
    ranges = sized.groupBy("source", cell.alias("range")).agg(F.sum("size").alias("sum"))
    so_far = Window.partitionBy("source").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    ranges = ranges.select("source", "range", F.coalesce(F.sum("sum").over(so_far), F.lit(0)).alias("offset"))
    ranges = ranges.join(targets.withColumnRenamed("source", "__s"), F.col("source").eqNullSafe(F.col("__s")))
    ranges = ranges.select(F.col("source").alias("__source"), F.col("range").alias("__range"), "offset", "source_size", "target")
    within = Window.partitionBy("source", "range").orderBy("key", "size", *keep).rowsBetween(Window.unboundedPreceding, -1)
    # documents without words take none wherever they stand, and however many there are
    rows = sized.where("size > 0").withColumn("range", cell).withColumn("inside", F.coalesce(F.sum("size").over(within), F.lit(0)))
    rows = rows.join(ranges, F.col("source").eqNullSafe(F.col("__source")) & (F.col("range") == F.col("__range")))
    rows = rows.select(*keep, "size", "source_size", "target", (F.col("offset") + F.col("inside")).alias("before"))
    wordless = sized.where("size = 0").join(_small(targets.withColumnRenamed("source", "__s")), F.col("source").eqNullSafe(F.col("__s")))
    return rows.unionByName(wordless.select(*keep, "size", "source_size", "target", F.lit(0).cast("long").alias("before")))


def _small(sources: DataFrame) -> DataFrame:
    """A table of one row a source, broadcast up to BROADCAST_SOURCES rows."""
    return F.broadcast(sources) if sources.count() <= BROADCAST_SOURCES else sources


def _epochs_and_rest() -> tuple[Column, Column]:
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    rest = F.floor(F.col("target")) - whole * F.col("source_size")
    return whole, rest


def mixed(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, epochs: int = EPOCHS) -> DataFrame:
    """doc_id, size, source_size, target, taken: one row a document; the taken words of a source sum to its target, rounded down."""
    sized = docs.select("doc_id", "source", F.regexp_count(text_or_empty(), F.lit(WORD)).cast("long").alias("size"), hash_key(F.col("doc_id")).alias("key"))
    rows = _placed(written(sized, "sizes"), ["doc_id"], weights, epochs)
    whole, rest = _epochs_and_rest()
    part = F.greatest(F.lit(0), F.least(F.col("size"), rest - F.col("before")))
    return rows.select("doc_id", "size", "source_size", "target", (whole * F.col("size") + part).cast("long").alias("taken"))


def cuts(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, epochs: int = EPOCHS) -> DataFrame:
    """source, whole, cut: a source's documents come whole times, and those with a key up to cut once more (null: none)."""
    size = F.regexp_count(text_or_empty(), F.lit(WORD)).cast("long")
    sized = written(docs.select("source", size.alias("size"), _document_key().alias("key")), "sizes")
    rows = _placed(sized, ["source", "key"], weights, epochs)
    whole, rest = _epochs_and_rest()
    inside = F.when((F.col("before") < rest) & (F.col("size") > 0), F.col("key"))
    return rows.groupBy("source").agg(F.first(whole).cast("int").alias("whole"), F.max(inside).alias("cut"))


def _document_key() -> Column:
    return F.concat(hash_key(F.col("doc_id")), F.hex(F.xxhash64("text")))


def mixed_documents(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, epochs: int = EPOCHS) -> DataFrame:
    """The mix as rows of docs: a document comes once for each epoch that takes it, whole at the cut.

    The document at the cut is kept whole if any of its words is within the budget; equal rows are treated alike; documents
    without words come as often as their source's whole epochs. A source's cut is one key, so the texts aren't shuffled:
    they meet the sources' cuts in a broadcast join.
    """
    at = written(cuts(docs, weights, epochs), "cuts")
    at = at.select(F.col("source").alias("__source"), F.col("whole").alias("__whole"), F.col("cut").alias("__cut"))
    at = _small(at)
    copies = F.col("__whole") + F.when(F.col("__key") <= F.col("__cut"), 1).otherwise(0)
    rows = packed(docs, F.col("source").alias("__own"), _document_key().alias("__key"))
    rows = rows.join(at, F.col("__own").eqNullSafe(F.col("__source"))).withColumn("__copies", copies).where("__copies > 0")
    return rows.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__copies")))).select("__doc.*")


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixed(table(spark, sf_dir, "documents"))


OP7_SQL = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size, md5(coalesce(doc_id::VARCHAR, '')) AS key FROM documents
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size, [5, 2, 1][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT] AS w FROM d GROUP BY source
), n AS (
  SELECT *, row_number() OVER (ORDER BY source_size / w, source NULLS LAST) AS nth FROM s
), c AS (
  SELECT a.nth, a.source_size, a.w,
    (SELECT sum(source_size) FROM s)::BIGINT - 3 * coalesce(sum(b.source_size), 0)::BIGINT AS left_over,
    (SELECT sum(w) FROM s)::BIGINT - coalesce(sum(b.w), 0)::BIGINT AS w_left
  FROM n a LEFT JOIN n b ON b.nth < a.nth
  GROUP BY ALL
), l AS (
  SELECT arg_min(left_over::DOUBLE / w_left, nth) AS level FROM c WHERE left_over::DOUBLE / w_left * w <= 3 * source_size
), t AS (
  SELECT source, source_size, coalesce(least(w * level, (3 * source_size)::DOUBLE), (3 * source_size)::DOUBLE) AS target FROM s, l
), p AS (
  SELECT d.doc_id, d.size, t.source_size, t.target,
    coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.key, d.size, d.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before,
    CASE WHEN t.source_size > 0 THEN floor(t.target / t.source_size)::BIGINT ELSE 0 END AS whole
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target,
  (whole * size + greatest(0, least(size, floor(target)::BIGINT - whole * source_size - before)))::BIGINT AS taken
FROM p
"""
