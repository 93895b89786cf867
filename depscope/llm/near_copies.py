"""Near copies by whole texts: an edge for five-word shingle sets of Jaccard similarity 0.8 or more.

Candidates come from op3's index first: each set has a 64-bit fingerprint (a bit is 1 if set in over half of its
shingle hashes), and fingerprints that differ in three bits or fewer are met by their positional bytes, tallied and
verified by ``simhash.links``. Most sets of similarity 0.8 differ in more bits than any such bound allows, so MinHash bands, 30
of six rows each, add to these: sets of similarity s meet in one with probability 1 - (1 - s^6)^30, which is 0.9999 at
0.8. Each candidate of either kind is verified on all the shingles of both texts, so every edge is right; a pair that
differs in four bits or more and meets in no band is the only kind that can be missed.

Equal sets are one node. In a band's bucket all nodes are first compared with one hub, another one in each bucket.
Where that leaves a bucket in more than one component, its nodes of different components are compared: pair by pair in
buckets of up to ``SHORT`` nodes, by what they share beyond the common text in longer ones. There a shingle is common if more than
``COMMON`` nodes of long buckets have it. Two nodes share at most their shared rare shingles, which are tallied for each pair, and the smaller number
of common ones that either has. Pairs whose bound stays below what the similarity needs are not linked; all others are
verified. So a large group whose members are alike, but not alike enough, costs its shingles instead of its pairs, and
no candidate is left out.

Pairs that common shingles alone could link are met in three steps. Each node is compared with its buckets' centres, the nodes nearest to the
common text; then with the best of the nodes that lack the same common shingle. Both only add links, which leave fewer components. For
the rest, nodes that link nothing but what their centre links are left out, and the others are met by equal parts of their common shingles
and told apart by sketches (``_common_pairs``), which loses no pair. Where many copies lie around a text that is none of them, each as far from it
as the similarity allows or nearer, in several components, a part is often equal by chance, and sketches of such pairs are still held against each other one by one.

Defined results: words are as in op3 (white space of bytes, A-Z lower-cased); a text of fewer than five words is one
shingle; null, empty and wordless texts are equal.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depscope.llm.common import written
from depscope.llm.simhash import components, labelled, links

SHINGLE, BANDS, ROWS = 5, 30, 6
#: Similarity of at least 4/5: nine times the shared shingles reach four times the sum of both sizes.
SHARED, SIZES = 9, 4
#: Rows of candidate texts that are broadcast; beyond it they are joined by a shuffle.
MOST_BROADCAST = 200_000
#: Shingles that pass all hash functions at once.
BLOCK = 256
#: Nodes of a bucket that are compared pair by pair.
SHORT = 16
#: Nodes of long buckets that have a shingle, beyond which it is common.
COMMON = 16


def _hashes(text: bytes):
    """The distinct shingle hashes of a text, in order."""
    import numpy as np
    from xxhash import xxh64_digest

    w = text.lower().split()
    shingles = map(b" ".join, zip(*(w[i:] for i in range(SHINGLE)))) if len(w) >= SHINGLE else [b" ".join(w)] * bool(w)
    return np.unique(np.frombuffer(b"".join(map(xxh64_digest, shingles, repeat(42))), dtype=np.uint64))


def _node(hashes) -> int:
    from xxhash import xxh64_intdigest

    x = xxh64_intdigest(hashes.tobytes(), 42)
    return x - (1 << 64) if x >> 63 else x


def _band_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    import numpy as np
    from xxhash import xxh64_intdigest

    rnd = np.random.default_rng(42)
    flip, times = (rnd.integers(0, 1 << 64, BANDS * ROWS, dtype=np.uint64) for _ in range(2))
    times |= np.uint64(1)

    def fingerprint(hashes) -> int:
        ones = np.zeros(64, dtype=np.int64)
        for at in range(0, len(hashes), BLOCK):
            ones += np.unpackbits(hashes[at : at + BLOCK, None].view(np.uint8), axis=1).sum(axis=0, dtype=np.int64)
        return int(np.packbits(2 * ones > len(hashes)).view(np.int64)[0])

    def bands(hashes) -> list[int]:
        if not len(hashes):
            return []
        least = np.full(BANDS * ROWS, (1 << 64) - 1, dtype=np.uint64)
        for at in range(0, len(hashes), BLOCK):
            np.minimum(least, ((hashes[at : at + BLOCK, None] ^ flip) * times).min(axis=0), out=least)
        keys = [xxh64_intdigest(row.tobytes(), i) for i, row in enumerate(least.reshape(BANDS, ROWS))]
        return np.array(keys, dtype=np.uint64).view(np.int64).tolist()

    for batch in batches:
        sets = [_hashes(t.as_py() or b"") for t in batch.column("text").cast(pa.binary())]
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("text_key"), pa.array(map(_node, sets), pa.int64()), pa.array(map(len, sets), pa.int32()), pa.array(map(fingerprint, sets), pa.int64()), pa.array(map(bands, sets), pa.list_(pa.int64()))],
            ["doc_id", "text_key", "fp", "n", "bits", "bands"],
        )


def _set_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = [_hashes(t.as_py() or b"") for t in batch.column("text").cast(pa.binary())]
        yield pa.RecordBatch.from_arrays([batch.column("fp"), pa.array([s.view("int64").tolist() for s in sets], pa.list_(pa.int64()))], ["fp", "hashes"])


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), "text")


def _alike_in_size(n: Column, m: Column) -> Column:
    """What sets of similarity 4/5 have: the smaller holds at least 4/5 of the larger."""
    return 5 * F.least(n, m) >= 4 * F.greatest(n, m)


def _sets(nodes: DataFrame, docs: DataFrame, heads: DataFrame) -> DataFrame:
    """fp, hashes: the shingle hashes of nodes (column fp), from their heads' texts."""
    asked = nodes.select("fp").distinct().join(heads.drop("n"), "fp")
    asked = written(asked.select("fp", F.col("head.doc_id").alias("head_id"), F.col("head.text_key").alias("head_key")), "asked")
    few = asked.count() <= MOST_BROADCAST
    own = F.col("doc_id").eqNullSafe(F.col("head_id")) & (F.col("text_key") == F.col("head_key"))
    texts = _keyed(docs).join(F.broadcast(asked) if few else asked, own).select("fp", "text")
    return written(texts.mapInArrow(_set_batches, "fp long, hashes array<long>").dropDuplicates(["fp"]), "sets")


def _verified(pairs: DataFrame, docs: DataFrame, heads: DataFrame, sets: DataFrame | None = None) -> DataFrame:
    """The pairs (a, b) of nodes that are similar by all shingles of their heads' texts; sets has these where they are at hand."""
    if sets is None:
        sets = _sets(pairs.select(F.explode(F.array("a", "b")).alias("fp")), docs, heads)
    both = pairs.join(sets.select(F.col("fp").alias("a"), F.col("hashes").alias("x")), "a").join(sets.select(F.col("fp").alias("b"), F.col("hashes").alias("y")), "b")
    return both.where(SHARED * F.size(F.array_intersect("x", "y")) >= SIZES * (F.size("x") + F.size("y"))).select("a", "b")


def _ordered(x: str, y: str) -> list[Column]:
    return [F.least(x, y).alias("a"), F.greatest(x, y).alias("b")]


def bit_pairs(nodes: DataFrame) -> DataFrame:
    """Pairs (a, b) of nodes (fp, n, bits): of each fingerprint its least node with the others, and the least nodes of fingerprints that op3's index links."""
    firsts = written(nodes.groupBy("bits").agg(F.min(F.struct("fp", "n")).alias("first"), F.count("*").alias("nodes")), "fingerprints")
    same = nodes.join(firsts.where("nodes > 1"), "bits").where(F.col("fp") != F.col("first.fp"))
    same = same.where(_alike_in_size(F.col("n"), F.col("first.n"))).select(*_ordered("fp", "first.fp"))
    x, y = (firsts.select(F.col("bits").alias(c), F.col("first").alias(f"first_{c}")) for c in ("a", "b"))
    met = links(firsts.select(F.col("bits").alias("fp"))).join(x, "a").join(y, "b")
    met = met.where(_alike_in_size(F.col("first_a.n"), F.col("first_b.n"))).select(*_ordered("first_a.fp", "first_b.fp"))
    return same.unionByName(met)


def _rooted(nodes: DataFrame, roots: DataFrame) -> DataFrame:
    """nodes (fp and more) with the root of their component; a node without an edge is its own."""
    return nodes.join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))


def _merged(roots: DataFrame, edges: DataFrame) -> DataFrame:
    """roots (node, root) after more edges: components are found among the roots that these join."""
    for end in ("a", "b"):
        ends = edges.join(roots.select(F.col("node").alias(end), "root"), end, "left").withColumn(end, F.coalesce("root", end))
        edges = ends.select("a", "b")
    top = components(edges)
    below = roots.join(top.select(F.col("node").alias("root"), F.col("root").alias("top")), "root", "left")
    alone = top.join(roots.select("node"), "node", "left_anti")
    return written(below.select("node", F.coalesce("top", "root").alias("root")).unionByName(alone), "roots")


def _open(postings: DataFrame, roots: DataFrame) -> DataFrame:
    """key, fp, n, root, nodes: the buckets of several components, but for those of two nodes, which have been compared."""
    rooted = _rooted(postings.select("key", "fp", "n"), roots)
    mixed = rooted.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("nodes")).where("lo < hi and nodes > 2")
    return written(rooted.join(mixed.select("key", "nodes"), "key"), "mixed")


def _known(crowd: DataFrame, sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Of the nodes of long buckets: fp, n, common (its common shingles), c (their number), slack; and fp, n, s: the rare shingles that several have.

    By common shingles alone two sets are similar if 9 times the shared ones reach 4 (n + m). So their common shingles differ in at most
    (slack + slack) / 9, where slack is 9 c - 8 n, and a partner's m is at most (9 c - 4 n) / 4.
    """
    held = written(sets.join(crowd, "fp").select("fp", "n", F.explode("hashes").alias("s")), "held")
    had = held.groupBy("s").agg(F.count("*").alias("df"))
    rare = written(held.join(had.where(F.col("df").between(2, COMMON)).select("s"), "s"), "rare")
    common = held.join(had.where(F.col("df") > COMMON).select("s"), "s").groupBy("fp").agg(F.collect_list("s").alias("common"))
    known = crowd.join(common, "fp", "left").withColumn("common", F.coalesce("common", F.array().cast("array<long>"))).withColumn("c", F.size("common"))
    return written(known.withColumn("slack", SHARED * F.col("c") - 2 * SIZES * F.col("n")), "known"), rare


def _rare_pairs(rare: DataFrame, known: DataFrame, roots: DataFrame) -> DataFrame:
    """Pairs of different components that share a rare shingle and may be similar."""
    rooted = _rooted(rare, roots)
    x, y = rooted.alias("x"), rooted.alias("y")
    other = (F.col("x.s") == F.col("y.s")) & (F.col("x.fp") < F.col("y.fp")) & (F.col("x.root") != F.col("y.root")) & _alike_in_size(F.col("x.n"), F.col("y.n"))
    tally = x.join(y, other).groupBy(F.col("x.fp").alias("a"), F.col("y.fp").alias("b")).agg(F.count("*").alias("shared"), F.first(F.col("x.n") + F.col("y.n")).alias("both"))
    tally = tally.join(known.select(F.col("fp").alias("a"), F.col("c").alias("ca")), "a").join(known.select(F.col("fp").alias("b"), F.col("c").alias("cb")), "b")
    return tally.where(SHARED * (F.col("shared") + F.least("ca", "cb")) >= SIZES * F.col("both")).select("a", "b")


def _centred(open_: DataFrame, known: DataFrame) -> DataFrame:
    """fp, n, m, root, slack, centre (slack, fp, n, root): nodes that common shingles alone may link, once for each centre that one of their buckets has.

    A bucket's centre is its node of most slack. m is the largest partner; nodes without one in any of their buckets are left out.
    """
    most = open_.join(known.select("fp", "slack", F.floor((SHARED * F.col("c") - SIZES * F.col("n")) / SIZES).alias("m")), "fp").where(5 * F.col("m") >= 4 * F.col("n"))
    least = most.groupBy("key").agg(F.min("n").alias("least"))
    most = written(most.join(least, "key").where("m >= least").select("key", "fp", "n", "m", "root", "slack"), "most")
    centres = most.groupBy("key").agg(F.max(F.struct("slack", "fp", "n", "root")).alias("top"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi")
    return written(most.join(centres.select("key", F.col("top").alias("centre")), "key").drop("key").distinct(), "centred")


def _beside_centre(centred: DataFrame, known: DataFrame) -> DataFrame:
    """centred with common and whole: the node's and the centre's common shingles."""
    rows = centred.join(known.select("fp", "common"), "fp")
    return rows.join(known.select(F.col("fp").alias("centre_fp"), F.col("common").alias("whole")), F.col("centre.fp") == F.col("centre_fp")).drop("centre_fp")


def _centre_stars(centred: DataFrame, known: DataFrame) -> DataFrame:
    """Pairs of each node with its centres."""
    apart = (F.col("root") != F.col("centre.root")) & _alike_in_size(F.col("n"), F.col("centre.n"))
    return centred.where(apart).select(*_ordered("fp", "centre.fp")).distinct()


def _lack_stars(centred: DataFrame, known: DataFrame) -> DataFrame:
    """Pairs of each node with those of most slack among the nodes that lack the same shingle of a centre: where the text that all have in common
    is no node, copies edited in one place link those that are edited there, too. Of a node's centres the best counts."""
    single = centred.groupBy("fp", "n", "root", "slack").agg(F.max("centre").alias("centre"))
    lacks = _beside_centre(single, known).withColumn("lacks", F.array_except("whole", "common")).where(4 * F.size("lacks") <= F.size("whole"))
    lacks = written(lacks.select("fp", "n", "root", "slack", F.col("centre.fp").alias("centre"), F.explode("lacks").alias("s")), "lacks")
    best = lacks.groupBy("centre", "s").agg(F.max(F.struct("slack", "fp", "n", "root")).alias("best"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi")
    apart = (F.col("root") != F.col("best.root")) & _alike_in_size(F.col("n"), F.col("best.n"))
    return lacks.join(best.drop("lo", "hi"), ["centre", "s"]).where(apart).select(*_ordered("fp", "best.fp")).distinct()


def _part_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each level from the node's own on: its common shingles dealt into 1, 2, 3, 5, 9, ... parts by hash, and a sum of each part.

    Beside it a sketch of 256 bits, of which each shingle flips one: those of two nodes differ in no more bits than the nodes in shingles.
    """
    import numpy as np

    for batch in batches:
        at, levels, parts, sums, sketches = [], [], [], [], []
        for i, (common, own, asked) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("common", "level", "levels")))):
            hashes = np.array(common, dtype=np.int64).view(np.uint64)
            mixed = (hashes ^ (hashes >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15)
            odd = np.bincount((mixed >> np.uint64(40)).astype(np.int64) % 256, minlength=256) % 2 == 1
            sketch = np.packbits(odd).view(np.int64).tolist()
            for level in asked:
                if level >= own:
                    made = np.zeros((1 << level - 1) + 1 if level else 1, dtype=np.uint64)
                    np.add.at(made, (hashes % np.uint64(len(made))).astype(np.int64), mixed ^ (mixed >> np.uint64(32)))
                    at += [i] * len(made)
                    levels += [level] * len(made)
                    parts += range(len(made))
                    sums += made.view(np.int64).tolist()
                    sketches += [sketch] * len(made)
        kept = batch.select(["fp", "n", "m", "root", "slack", "level", "centre"]).take(pa.array(at, pa.int64()))
        yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(levels, pa.int32()), pa.array(parts, pa.int32()), pa.array(sums, pa.int64()), pa.array(sketches, pa.list_(pa.int64()))], [*kept.schema.names, "at_level", "part", "sum", "sketch"])


def _common_pairs(centred: DataFrame, known: DataFrame) -> DataFrame:
    """Pairs of different components that may be similar by common shingles alone.

    A node whose common shingles are all its centre's, which is no larger and in its component, is left out: what it links, the centre links.
    Two that differ in h shingles at most have the same in one of h + 1 parts, so nodes are met by equal parts. A node's level tells how
    many parts suffice for it and any node of no more slack; a pair is met at the higher of both levels. Pairs whose sketches differ in more than h bits go.
    """
    inner = (F.col("fp") != F.col("centre.fp")) & (F.col("root") == F.col("centre.root")) & (F.col("n") >= F.col("centre.n")) & (F.size(F.array_except("common", "whole")) == 0)
    left = _beside_centre(centred, known).where(~inner).select("fp", "n", "m", "root", "slack", "common", F.col("centre.fp").alias("centre"))
    most = F.floor(2 * F.greatest("slack", F.lit(0)) / SHARED)  # differing shingles
    left = written(left.withColumn("level", F.when(most == 0, 0).otherwise(F.ceil(F.log2(most)) + 1).cast("int")), "left")
    levels = left.groupBy("centre").agg(F.collect_set("level").alias("levels"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi")
    schema = "fp long, n int, m long, root long, slack int, level int, centre long, at_level int, part int, sum long, sketch array<long>"
    parts = written(left.join(levels.select("centre", "levels"), "centre").mapInArrow(_part_batches, schema), "parts")
    x, y = parts.alias("x"), parts.alias("y")
    met = [F.col(f"x.{c}") == F.col(f"y.{c}") for c in ("centre", "at_level", "part", "sum")]
    other = (F.col("x.root") < F.col("y.root")) & (F.col("x.m") >= F.col("y.n")) & (F.col("y.m") >= F.col("x.n")) & _alike_in_size(F.col("x.n"), F.col("y.n"))
    other = other & (F.col("x.slack") + F.col("y.slack") >= 0) & (F.greatest("x.level", "y.level") == F.col("x.at_level"))
    differ = sum((F.bit_count(F.col("x.sketch")[i].bitwiseXOR(F.col("y.sketch")[i])) for i in range(4)), F.lit(0))
    other = other & (SHARED * differ <= F.col("x.slack") + F.col("y.slack"))
    for c in met:
        other = c & other
    return x.join(y, other).select(*_ordered("x.fp", "y.fp")).distinct()


def _short_pairs(open_: DataFrame, crowd: DataFrame) -> DataFrame:
    """Pairs of different components in short buckets that may be similar. Two nodes of long buckets are met by their shingles, whatever bucket they share."""
    short = open_.where(F.col("nodes") <= SHORT).join(crowd.select("fp", F.lit(True).alias("long")), "fp", "left")
    x, y = short.alias("x"), short.alias("y")
    other = (F.col("x.key") == F.col("y.key")) & (F.col("x.root") < F.col("y.root")) & _alike_in_size(F.col("x.n"), F.col("y.n"))
    return x.join(y, other & (F.col("x.long").isNull() | F.col("y.long").isNull())).select(*_ordered("x.fp", "y.fp"))


def near_copies(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, fp (the shingle set's key), component_id, keep: one row a document, as simhash.near_duplicates has them."""
    rows = written(_keyed(docs).mapInArrow(_band_batches, "doc_id long, text_key long, fp long, n int, bits long, bands array<long>"), "bands")
    fps = rows.select("doc_id", "text_key", "fp")
    heads = written(fps.groupBy("fp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_key")).alias("head"), F.count("*").alias("n")), "heads")
    nodes = written(rows.select("fp", "n", "bits").distinct(), "nodes")
    postings = rows.select("fp", "n", F.explode("bands").alias("key")).groupBy("key", "fp").agg(F.first("n").alias("n"))
    buckets = postings.groupBy("key").agg(F.min(F.struct(F.xxhash64("key", "fp").alias("h"), "fp", "n")).alias("hub"), F.count("*").alias("nodes"))
    shared = written(postings.join(buckets.where("nodes > 1"), "key").select("key", "fp", "n", "hub"), "postings")
    stars = shared.where((F.col("fp") != F.col("hub.fp")) & _alike_in_size(F.col("n"), F.col("hub.n")))
    done = written(bit_pairs(nodes).unionByName(stars.select(*_ordered("fp", "hub.fp"))).distinct(), "stars")
    roots = components(_verified(done, docs, heads))
    open_ = _open(shared, roots)
    crowd = written(open_.where(F.col("nodes") > SHORT).select("fp", "n").distinct(), "crowd")
    more = None
    if not crowd.isEmpty():
        sets = _sets(crowd, docs, heads)
        known, rare = _known(crowd, sets)
        for stars in (_centre_stars, _lack_stars):
            centred = _centred(open_, known)
            pairs = written(stars(centred, known).join(done, ["a", "b"], "left_anti"), "stars")
            found = written(_verified(pairs, docs, heads, sets), "found")
            if not found.isEmpty():
                roots = _merged(roots, found)
                open_ = _open(shared, roots)
            done = done.unionByName(pairs)
        more = _rare_pairs(rare, known, roots).unionByName(_common_pairs(_centred(open_, known), known))
    short = _short_pairs(open_, crowd)
    more = written((short if more is None else short.unionByName(more)).distinct(), "met").join(done, ["a", "b"], "left_anti")
    more = written(more, "pairs")
    if not more.isEmpty():
        roots = _merged(roots, _verified(more, docs, heads))
    return labelled(fps, heads, roots)
