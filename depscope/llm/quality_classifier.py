"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

score = sigmoid(w0 + sum w_i x_i + 1/2 sum_f ((sum_i v_if x_i)^2 - sum_i v_if^2 x_i^2)): the sum-of-squares identity gives
all pairwise interactions in time linear in a document's features. Features are the document's words hashed into
``BUCKETS`` (log counts, unit length), structure statistics of the text and its length as metadata; labels, lang, source and
doc_id are never inputs. Training takes at most ``TRAIN_ROWS`` labelled rows, chosen by hash, whose crc32(doc_id) mod 5 is not 0; executors
make the features, the driver fits a model of fixed size.

Defined results: null and empty texts have all-zero words and get a score like any other; rows that repeat a doc_id each get their
row; labelled rows without a document or without a quality are left out; without labels every score is 0.5; other columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from operator import eq
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.llm.common import hash_key, table

BUCKETS, FACTORS = 4096, 8
#: Most labelled rows that training takes; their features (about 4 kB each) are gathered on the driver.
TRAIN_ROWS = 6000
#: Features of a block of documents that are scored at once: FACTORS doubles each, a few times over (about 50 MB).
BLOCK = 100_000
EPOCHS, BATCH, RATE, DECAY, SEED = 12, 64, 0.02, 1e-4, 7
CUT = 0.3
#: Distinct words whose bucket a worker remembers at most.
REMEMBERED = 300_000
STATS = ("log_chars", "log_words", "word_length", "upper", "digits", "symbols", "marks", "bars", "distinct", "top_word", "neighbours", "lines", "non_ascii", "short")
UPPER, DIGITS, SYMBOLS, MARKS = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b"#$%&*<>", b"!?"


def _structure(data: bytes, words: list[bytes], counts: Counter) -> list[float]:
    chars, n = max(len(data), 1), max(len(words), 1)
    share = lambda of: (len(data) - len(data.translate(None, of))) / chars
    ascii_only = len(data.translate(None, bytes(range(128, 256))))
    return [
        np.log1p(len(data)) / 10,
        np.log1p(len(words)) / 10,
        min(len(data) / n / 10, 5.0),
        2 * share(UPPER),
        2 * share(DIGITS),
        5 * share(SYMBOLS),
        5 * share(MARKS),
        5 * share(b"|"),
        len(counts) / n,
        max(counts.values(), default=0) / n,
        sum(map(eq, words, words[1:])) / n,
        min(10 * data.count(b"\n") / n, 5.0),
        (len(data) - ascii_only) / chars,
        1.0 if len(words) < 20 else 0.0,
    ]


def features(data: bytes, known: dict[bytes, int]) -> tuple[list[int], list[float]]:
    """Indices and values of a text's features; known remembers the buckets of words."""
    words = data.lower().split()
    counts = Counter(words)
    if len(known) > REMEMBERED:
        known.clear()
    sums: dict[int, int] = {}
    for word, c in counts.items():
        b = known.get(word)
        if b is None:
            b = known[word] = crc32(word) % BUCKETS
        sums[b] = sums.get(b, 0) + c
    values = np.log1p(np.fromiter(sums.values(), dtype=np.float64, count=len(sums)))
    values /= max(float(np.sqrt((values**2).sum())), 1e-9)
    return [*sums, *range(BUCKETS, BUCKETS + len(STATS))], [*values.tolist(), *_structure(data, words, counts)]


class Machine:
    """Weights of a factorisation machine: w0, w (n), v (n x FACTORS)."""

    def __init__(self, n: int, seed: int = SEED):
        self.w0, self.w = 0.0, np.zeros(n)
        self.v = np.random.default_rng(seed).normal(0, 0.05, (n, FACTORS))

    def raw(self, at: np.ndarray, x: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Log odds of each row and the rows' sums of v x. Rows begin at starts; every row has features."""
        vx = self.v[at] * x[:, None]
        sums = np.add.reduceat(vx, starts, axis=0)
        pairs = 0.5 * (sums**2 - np.add.reduceat(vx**2, starts, axis=0)).sum(axis=1)
        return self.w0 + np.add.reduceat(self.w[at] * x, starts) + pairs, sums


def _packed(rows: list[tuple[list[int], list[float]]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    at = np.concatenate([np.asarray(i, dtype=np.int64) for i, _ in rows])
    x = np.concatenate([np.asarray(v, dtype=np.float64) for _, v in rows])
    return at, x, np.cumsum([0] + [len(i) for i, _ in rows[:-1]])


def fitted(at_all: np.ndarray, x_all: np.ndarray, ends: np.ndarray, labels: np.ndarray) -> Machine:
    """Adagrad on the log loss, in seeded order: equal input gives an equal model. Row i has at_all and x_all from ends[i] to ends[i + 1]."""
    m = Machine(BUCKETS + len(STATS))
    y = labels.astype(np.float64)
    m.w0 = float(np.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
    gw, gv, g0 = np.full_like(m.w, 1e-6), np.full_like(m.v, 1e-6), 1e-6
    order = np.random.default_rng(SEED)
    for _ in range(EPOCHS):
        at_row = order.permutation(len(y))
        for b in range(0, len(y), BATCH):
            chosen = at_row[b : b + BATCH]
            parts = [slice(ends[i], ends[i + 1]) for i in chosen]
            at, x = np.concatenate([at_all[p] for p in parts]), np.concatenate([x_all[p] for p in parts])
            starts = np.cumsum([0] + [p.stop - p.start for p in parts[:-1]])
            odds, sums = m.raw(at, x, starts)
            err = (1 / (1 + np.exp(-np.clip(odds, -30, 30))) - y[chosen]) / len(chosen)
            of = np.repeat(np.arange(len(chosen)), np.diff([*starts, len(at)]))
            dw = np.zeros_like(m.w)
            np.add.at(dw, at, err[of] * x)
            dv = np.zeros_like(m.v)
            np.add.at(dv, at, (err[of] * x)[:, None] * (sums[of] - m.v[at] * x[:, None]))
            dw += DECAY * m.w
            dv += DECAY * m.v
            gw += dw**2
            gv += dv**2
            g0 += err.sum() ** 2
            m.w -= RATE * 5 * dw / np.sqrt(gw)
            m.v -= RATE * dv / np.sqrt(gv)
            m.w0 -= RATE * err.sum() / np.sqrt(g0)
    return m


def _feature_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    known: dict[bytes, int] = {}
    for batch in batches:
        done = 0
        for rows in _blocks(batch, known):
            part = batch.slice(done, len(rows))
            done += len(rows)
            at, x = pa.array([i for i, _ in rows], pa.list_(pa.int32())), pa.array([v for _, v in rows], pa.list_(pa.float32()))
            yield pa.RecordBatch.from_arrays([*(part.column(c) for c in ("label_id", "quality", "text_key")), at, x], ["label_id", "quality", "text_key", "at", "x"])


def _blocks(batch: pa.RecordBatch, known: dict[bytes, int]) -> Iterator[list[tuple[list[int], list[float]]]]:
    """The features of a batch's texts, in blocks that end once they hold BLOCK features; a text has at most BUCKETS + len(STATS)."""
    rows, n = [], 0
    for t in batch.column("text").cast(pa.large_binary()):
        rows.append(features(t.as_py() or b"", known))
        n += len(rows[-1][0])
        if n >= BLOCK:
            yield rows
            rows, n = [], 0
    if rows:
        yield rows


def trained(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS) -> Machine | None:
    """A machine fitted to at most ``most`` labelled rows outside the held-out fifth; None without labels of both kinds."""
    known = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    known = known.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0).orderBy(hash_key(F.col("doc_id")), "doc_id").limit(most)
    known = known.select(F.col("doc_id").alias("label_id"), F.col("quality").cast("int").alias("quality"))
    # bounded by ``most`` rows of two numbers
    rows = docs.select("doc_id", "text").join(F.broadcast(known), F.col("doc_id") == F.col("label_id")).select("label_id", "quality", F.xxhash64("text").alias("text_key"), "text")
    rows = rows.mapInArrow(_feature_batches, "label_id long, quality int, text_key long, at array<int>, x array<float>")
    # a doc_id that documents repeat trains once, by its text of the least hash: rows that are gathered are bounded, too
    rows = rows.groupBy("label_id").agg(F.min_by(F.struct("quality", "at", "x"), "text_key").alias("row")).select("label_id", "row.*")
    got = rows.toArrow().sort_by([("label_id", "ascending")]).combine_chunks()
    y = got.column("quality").to_numpy()
    if len(np.unique(y)) < 2:
        return None
    at, x = (pa.concat_arrays(got.column(c).chunks) for c in ("at", "x"))
    return fitted(at.flatten().to_numpy(), x.flatten().to_numpy(), np.cumsum([0, *at.value_lengths().to_pylist()]), y)


def scored(docs: DataFrame, model: Machine | None) -> DataFrame:
    """doc_id, score: one row a document."""

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[bytes, int] = {}
        for batch in it:
            score = np.full(batch.num_rows, 0.5)
            done = 0
            for rows in _blocks(batch, known) if model is not None else ():
                odds, _ = model.raw(*_packed(rows))
                score[done : done + len(rows)] = 1 / (1 + np.exp(-np.clip(odds, -30, 30)))
                done += len(rows)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(score, pa.float64())], ["doc_id", "score"])

    return docs.selectExpr("cast(doc_id as long) AS doc_id", "text").mapInArrow(batches, "doc_id long, score double")


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = trained(docs, table(spark, sf_dir, "labels"))
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    return scored(docs, model).select("doc_id", held_out.alias("held_out"), "score", F.when(F.col("score") >= CUT, 1).otherwise(0).cast("int").alias("predicted"))
