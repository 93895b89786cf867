"""SimHash near-duplicates over a byte-position inverted index with count filtering.

A 64-bit fingerprint is eight bytes at eight positions. Two fingerprints that differ in at most
three bits share at least five positional bytes. The index has sixteen posting list entries a fingerprint, each keyed by three positional
bytes: the position triples inside the halves of two crossing splits of the eight positions. Of any five positions three or more lie in
one half of each split, so such a pair meets in at least two lists, while a pair that shares just three bytes meets in one at most.
Meetings are tallied for each pair; pairs that reach two are retained and verified by bit difference.

Posting lists longer than ``LONG_LIST`` are never paired: their members move on to lists of five shared
positional bytes (56 position sets), where one meeting is the minimum and pairs are verified as they meet. A pair that has a long list among its own is found there, so the
tally over short lists alone loses nothing. Lists that are still longer than ``SWARM`` hold fingerprints that
vary in 24 bits only; there each member joins, for every choice of three free bits, the group of equal
remaining bits. Members of such a group differ in those three bits at most, so a star to the smallest member
links the group without pairs. All three ways are exact, so no link is lost at any list length.

Defined results: a null, empty or wordless text has fingerprint zero and links like any other; rows
that repeat a doc_id each get their row; a component whose ids are all null has a null component_id;
columns other than doc_id and text are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations, repeat

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.llm.common import packed, table, written

MAX_BITS, SHINGLE = 3, 3
#: Lists of three positional bytes in which fingerprints within MAX_BITS bits meet at least.
LEAST_LISTS = 2
#: Longest posting list that is paired directly, at three and at five shared bytes. All pairs of the former are tallied, so it is short.
LONG_LIST, SWARM = 64, 4096
#: Rows of one fingerprint beyond which its label is handed to several tasks.
HOT = 1_000_000
#: Shingles whose bits are unpacked at once: 64 bytes each.
BLOCK = 200_000


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _mask(positions: tuple[int, ...]) -> int:
    return _signed(sum(0xFF << (8 * p) for p in positions))


SPLITS = (((0, 1, 2, 3), (4, 5, 6, 7)), ((0, 1, 4, 5), (2, 3, 6, 7)))
TRIPLES = [t for split in SPLITS for half in split for t in combinations(half, 3)]
FIVES = list(combinations(range(8), 5))


def _fingerprint_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    import numpy as np
    from xxhash import xxh64_digest

    def bits_over_half(digests: bytes, counts: list[int]) -> list[int]:
        # digests are big-endian; a row of 64 bits for each shingle, summed over each document
        ends = np.cumsum([c for c in counts if c])
        if not len(ends):
            return [0] * len(counts)
        bits = np.unpackbits(np.frombuffer(digests, dtype=np.uint8).reshape(-1, 8), axis=1)
        sums = np.add.reduceat(bits, np.r_[0, ends[:-1]], axis=0, dtype=np.int64)
        over = 2 * sums > np.array([c for c in counts if c])[:, None]
        made = iter(np.packbits(over, axis=1).view(">i8").ravel().tolist())
        return [next(made) if c else 0 for c in counts]

    for batch in batches:
        made: list[int] = []
        held: list[bytes] = []
        counts: list[int] = []
        total = 0
        for text in batch.column("text").cast(pa.binary()):
            w = (text.as_py() or b"").lower().split()
            shingles = list(map(b" ".join, zip(w, w[1:], w[2:]))) if len(w) >= SHINGLE else [b" ".join(w)] * bool(w)
            held.append(b"".join(map(xxh64_digest, shingles, repeat(42))))
            counts.append(len(shingles))
            total += len(shingles)
            if total >= BLOCK:
                made += bits_over_half(b"".join(held), counts)
                held, counts, total = [], [], 0
        made += bits_over_half(b"".join(held), counts)
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("text_key"), pa.array(made, pa.int64())], ["doc_id", "text_key", "fp"]
        )


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, text_key (XXH64 of the whole text), fp (the fingerprint as a signed long): one row a document."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), "text").mapInArrow(
        _fingerprint_batches, "doc_id long, text_key long, fp long"
    )


def _postings(fps: DataFrame, position_sets: list[tuple[int, ...]]) -> DataFrame:
    """slot, part (the fingerprint's bytes at the slot's positions), fp."""
    keyed = [F.struct(F.lit(i).alias("slot"), F.col("fp").bitwiseAND(F.lit(_mask(p))).alias("part")) for i, p in enumerate(position_sets)]
    return fps.select("fp", F.explode(F.array(*keyed)).alias("k")).select("k.slot", "k.part", "fp")


def _met(postings: DataFrame) -> DataFrame:
    """a, b: pairs of different fingerprints, once for each list that holds both."""
    a, b = postings.alias("a"), postings.alias("b")
    x, y = F.col("a.fp"), F.col("b.fp")
    return a.join(b, (F.col("a.slot") == F.col("b.slot")) & (F.col("a.part") == F.col("b.part")) & (x < y)).select(x.alias("a"), y.alias("b"))


def _meetings(postings: DataFrame) -> DataFrame:
    """a, b, lists: pairs of different fingerprints and the number of lists that hold both."""
    return _met(postings).groupBy("a", "b").agg(F.count("*").alias("lists"))


def _near(pairs: DataFrame) -> DataFrame:
    """The pairs that differ in MAX_BITS bits or fewer."""
    return pairs.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= MAX_BITS).select("a", "b")


def _verified(met: DataFrame, least: int) -> DataFrame:
    """The pairs that reach the least number of meetings, verified."""
    return _near(met.where(F.col("lists") >= least))


def _by_length(postings: DataFrame, most: int) -> tuple[DataFrame, DataFrame]:
    """Postings of lists with 2..most members, and those of longer lists."""
    sized = postings.groupBy("slot", "part").agg(F.count("*").alias("n")).where("n > 1")
    short = postings.join(sized.where(F.col("n") <= most).select("slot", "part"), ["slot", "part"], "left_semi")
    long = postings.join(sized.where(F.col("n") > most).select("slot", "part"), ["slot", "part"], "left_semi")
    return short, long


def links(fps: DataFrame, long_list: int = LONG_LIST, swarm: int = SWARM) -> DataFrame:
    """Edges (a, b) between different fingerprints, enough to connect all that are MAX_BITS or fewer apart.

    fps: distinct fingerprints in column fp. Every edge joins fingerprints within MAX_BITS bits.
    """
    short, long = _by_length(_postings(fps, TRIPLES), long_list)
    found = _verified(_meetings(short), LEAST_LISTS)
    long = written(long.select("fp").distinct(), "long")
    if long.isEmpty():
        return found.distinct()
    short, dense = _by_length(_postings(long, FIVES), swarm)
    found = found.unionByName(_near(_met(short)))
    dense = written(dense, "swarm")
    if not dense.isEmpty():
        found = found.unionByName(_stars(dense))
    return found.distinct()


def _stars(dense: DataFrame) -> DataFrame:
    """Stars among postings of one five-byte list: for each three of its 24 free bits, the equal rest is one group."""
    spark = dense.sparkSession
    free = [[8 * p + i for p in range(8) if p not in kept for i in range(8)] for kept in FIVES]
    masks = [(s, [_signed(~(1 << x | 1 << y | 1 << z) & (1 << 64) - 1) for x, y, z in combinations(bits, 3)]) for s, bits in enumerate(free)]
    wild = spark.createDataFrame(masks, "slot int, masks array<long>")
    rows = dense.join(F.broadcast(wild), "slot").select("slot", "part", "fp", F.explode("masks").alias("m"))
    groups = rows.groupBy("slot", "part", "m", F.col("fp").bitwiseAND(F.col("m")).alias("rest"))
    heads = groups.agg(F.min("fp").alias("a"), F.count("*").alias("n")).where("n > 1")
    rows = rows.withColumn("rest", F.col("fp").bitwiseAND(F.col("m")))
    return rows.join(heads, ["slot", "part", "m", "rest"]).where("a < fp").select("a", F.col("fp").alias("b")).distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, root: each node that has an edge, with the smallest node of its connected component.

    Alternates a large-star and a small-star step; both keep the components and at most as many edges, and a
    chain of length n needs about log n rounds. Each round is a table in the shared folder.
    """
    now = written(edges.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).where("hi <> lo").distinct(), "edges")
    before = None
    for _ in range(most_rounds):
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(now.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        heads = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(heads, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
        now = written(small.unionByName(heads.select("hi", F.col("m").alias("lo"))).distinct(), "round")
        state = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)")).alias("h")).first()
        if state == before:
            heads = now.groupBy("lo").agg(F.lit(1).alias("one")).select(F.col("lo").alias("node"), F.col("lo").alias("root"))
            return now.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionByName(heads)
        before = state
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")


def near_duplicates(docs: DataFrame, long_list: int = LONG_LIST, swarm: int = SWARM) -> DataFrame:
    """doc_id, text_key, fp, component_id, keep: one row a document. keep marks the one row key (doc_id, text_key) that stays of each component."""
    fps = written(fingerprints(docs), "fingerprints")
    least = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_key"))
    heads = written(fps.groupBy("fp").agg(least.alias("head"), F.count("*").alias("n")), "heads")
    return labelled(fps, heads, components(links(heads.select("fp"), long_list, swarm)))


def labelled(fps: DataFrame, heads: DataFrame, roots: DataFrame) -> DataFrame:
    """fps with component_id and keep, from the heads (fp, head, n: its rows) of equal fingerprints and the components (node, root) among these.

    A fingerprint of more than HOT rows is spread over several salted keys; there are at most rows / HOT such fingerprints.
    """
    rooted = heads.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "head", "n")
    # of each component the least head; a component's fingerprints join it by its root
    best = rooted.groupBy("root").agg(F.min("head").alias("best"))
    parts = F.ceil(F.col("n") / HOT).cast("int")
    labels = rooted.join(best, "root").select("fp", F.col("best.doc_id").alias("component_id"), F.col("best.text_key").alias("best_key"), F.explode(F.sequence(F.lit(0), parts - 1)).alias("salt"))
    hot = F.broadcast(heads.where(F.col("n") > HOT).select("fp", parts.alias("parts")))
    salt = F.coalesce(F.pmod(F.xxhash64("doc_id", "text_key"), F.col("parts")), F.lit(0)).cast("int")
    fps = fps.join(hot, "fp", "left").withColumn("salt", salt)
    same = F.col("doc_id").eqNullSafe(F.col("component_id")) & (F.col("text_key") == F.col("best_key"))
    return fps.join(labels, ["fp", "salt"]).select("doc_id", "text_key", "fp", "component_id", same.alias("keep"))


def deduplicated(docs: DataFrame, rule: Callable[[DataFrame], DataFrame] = near_duplicates) -> DataFrame:
    """docs with one document of each component that the rule finds: the one with the smallest doc_id (ties: the smaller text hash, then any of the equal rows).

    The texts are shuffled once, by row key; a second time only where rows that stay repeat both doc_id and text.
    """
    keys = rule(docs).where("keep").groupBy(F.col("doc_id").alias("keep_id"), F.col("text_key").alias("keep_key"))
    keys = written(keys.agg(F.count("*").alias("n")), "keep")
    rows = packed(docs, F.col("doc_id").cast("long").alias("__id"), F.xxhash64("text").alias("__key"))
    rows = rows.join(keys, F.col("__id").eqNullSafe(F.col("keep_id")) & (F.col("__key") == F.col("keep_key")), "left_semi")
    if not keys.where("n > 1").isEmpty():
        rows = rows.dropDuplicates(["__id", "__key"])
    return rows.select("__doc.*")


def hex16(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", hex16(F.col("fp")).alias("fingerprint"), "component_id")
