"""Edit-aware token counts: a segment tree of pre-tokens for each document.

A tokenizer first splits a text into pre-tokens by a pattern and then encodes each one by itself, so a document's
count is the sum over its pre-tokens. Leaves hold runs of about ``LEAF`` pre-tokens as (characters, pre-tokens, tokens);
inner nodes hold sums. An edit descends to the last leaf that begins ``CONTEXT`` characters or more before it, splits again from there,
and stops as soon as a new boundary meets an old leaf boundary behind the edit: the pattern looks ahead only, so the rest is
unchanged. Only that stretch is encoded again; the leaves' sums and those on their paths up are updated.

Leaves begin at safe places only: where the character before is no white space, or the leaf's first isn't. A run of white
space is thus never cut inside, and what stands before a safe place depends on ``CONTEXT`` characters behind it at most.

Defined results: null and empty texts have no tokens; edits are (start, end, replacement) in code points of the given text, must not overlap
and may be empty; places beyond the text are clipped; rows that repeat a doc_id each get their row; other columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import os
from collections.abc import Callable, Iterator

import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.llm.common import table, text_or_empty
from depscope.llm.pii import BASE, BASE_GATE, _spans

VOCABULARY = os.environ.get("DEPSCOPE_VOCABULARY", "/opt/tokenizers/byte_bpe_50k.tiktoken")
#: Fixed value: the public pre-token pattern of the vocabulary.
PATTERN = r"'(?:s|t|re|ve|m|ll|d)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
LEAF, CONTEXT = 64, 4
#: Pre-tokens whose counts a worker remembers at most (about 100 bytes each).
REMEMBERED = 400_000
#: A vocabulary file is broadcast up to this size.
VOCABULARY_BYTES = 64 << 20


class Counter:
    """Counts the tokens of pre-tokens, remembering those seen."""

    def __init__(self, ranks: bytes, pattern: str = PATTERN):
        import tiktoken

        merges = {base64.b64decode(a): int(b) for a, b in (line.split() for line in ranks.splitlines() if line)}
        self.encode = tiktoken.Encoding("pieces", pat_str=r"[\s\S]+", mergeable_ranks=merges, special_tokens={})._core_bpe.encode_single_piece
        self.pattern = regex.compile(pattern)
        self.known: dict[str, int] = {}

    def of(self, piece: str) -> int:
        n = self.known.get(piece)
        if n is None:
            if len(self.known) >= REMEMBERED:
                self.known.clear()
            n = self.known[piece] = len(self.encode(piece.encode("utf-8", "replace")))
        return n

    def total(self, pieces: list[str]) -> int:
        try:
            return sum(map(self.known.__getitem__, pieces))
        except KeyError:
            return sum(map(self.of, pieces))


def _safe(before: str, piece: str) -> bool:
    return not before[-1].isspace() or not piece[0].isspace()


class Tree:
    """Sums of (characters, pre-tokens, tokens) over a document's leaves, in heap order: node i has the children 2i and 2i + 1."""

    def __init__(self, counter: Counter, text: str):
        self.counter, self.text = counter, text
        self.encoded = 0
        self._build(self._leaves(counter.pattern.findall(text)))

    @classmethod
    def of_leaves(cls, counter: Counter, text: str, leaves: list[tuple[int, int, int]]) -> Tree:
        """A tree from stored leaves; nothing is encoded."""
        tree = cls.__new__(cls)
        tree.counter, tree.text, tree.encoded = counter, text, 0
        tree._build(leaves)
        return tree

    def _leaves(self, pieces: list[str]) -> list[tuple[int, int, int]]:
        out, begin, n = [], 0, len(pieces)
        while begin < n:
            end = min(begin + LEAF, n)
            while end < n and not _safe(pieces[end - 1], pieces[end]):
                end += 1
            part = pieces[begin:end]
            out.append((sum(map(len, part)), len(part), self.counter.total(part)))
            begin = end
        self.encoded += n
        return out

    def _build(self, leaves: list[tuple[int, int, int]]) -> None:
        self.size = 1 << max(len(leaves) - 1, 0).bit_length()
        none = (0, 0, 0)
        self.nodes = [none] * self.size + leaves + [none] * (self.size - len(leaves))
        for i in range(self.size - 1, 0, -1):
            self._sum(i)

    def _sum(self, i: int) -> None:
        a, b = self.nodes[2 * i], self.nodes[2 * i + 1]
        self.nodes[i] = (a[0] + b[0], a[1] + b[1], a[2] + b[2])

    @property
    def counts(self) -> tuple[int, int, int]:
        """Characters, pre-tokens and tokens of the whole text."""
        return self.nodes[1]

    @property
    def leaves(self) -> list[tuple[int, int, int]]:
        return [x for x in self.nodes[self.size :] if x[0]]

    def _leaf_at(self, place: int) -> tuple[int, int]:
        """Index and start of the leaf that holds a place, or of the last one."""
        i, start = 1, 0
        while i < self.size:
            i *= 2
            if place >= start + self.nodes[i][0] and self.nodes[i + 1][0]:
                start += self.nodes[i][0]
                i += 1
        return i, start

    def edit(self, start: int, end: int, replacement: str) -> None:
        """Replaces text[start:end]; counts follow."""
        n = len(self.text)
        start = min(max(start, 0), n)
        end = min(max(end, start), n)
        first, at = self._leaf_at(max(start - CONTEXT, 0))
        self.text = self.text[:start] + replacement + self.text[end:]
        shift = len(replacement) - (end - start)
        # the old leaf boundaries behind the edit, in new places
        last, behind = self._leaf_at(end)
        behind += self.nodes[last][0]
        pieces: list[str] = []
        for m in self.counter.pattern.finditer(self.text, at):
            while last + 1 < 2 * self.size and self.nodes[last + 1][0] and behind + shift < m.start():
                last += 1
                behind += self.nodes[last][0]
            if m.start() == behind + shift and m.start() >= start + len(replacement):
                break
            pieces.append(m.group())
        else:
            last = 2 * self.size - 1  # split up to the end of the text
        made = self._leaves(pieces)
        slots = last - first + 1
        if len(made) > slots:
            # no free slots: the tree grows, from sums alone
            self._build([x for x in self.nodes[self.size : first] if x[0]] + made + [x for x in self.nodes[last + 1 : 2 * self.size] if x[0]])
            return
        self.nodes[first : last + 1] = made + [(0, 0, 0)] * (slots - len(made))
        if slots - len(made) and any(x[0] for x in self.nodes[last + 1 : 2 * self.size]):
            self._build([x for x in self.nodes[self.size :] if x[0]])  # an emptied slot would hide the leaves behind it
            return
        lo, hi = first // 2, last // 2
        while lo:
            for i in range(lo, hi + 1):
                self._sum(i)
            lo, hi = lo // 2, hi // 2

    def edit_all(self, edits: list[tuple[int, int, str]]) -> None:
        """Edits in places of the present text, applied from the last to the first."""
        for start, end, replacement in sorted(edits, key=lambda e: (e[0], e[1]), reverse=True):
            self.edit(start, end, replacement)


def vocabulary(spark: SparkSession, path: str = VOCABULARY) -> bytes:
    """The rank file's bytes, read through Spark's file systems; its size is checked before it is broadcast."""
    place = spark._jvm.org.apache.hadoop.fs.Path(path if "://" in path else f"file://{path}")
    size = place.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(place).getLen()
    if size > VOCABULARY_BYTES:
        raise ValueError(f"{path} has {size} bytes; {VOCABULARY_BYTES} is the most that is broadcast")
    stream = place.getFileSystem(spark._jsc.hadoopConfiguration()).open(place)
    try:
        return bytes(spark._jvm.org.apache.commons.io.IOUtils.toByteArray(stream))
    finally:
        stream.close()


_COUNTERS: dict[bytes, Counter] = {}


def _counter(ranks: bytes) -> Counter:
    """One counter a worker process and vocabulary."""
    if ranks not in _COUNTERS:
        _COUNTERS[ranks] = Counter(ranks)
    return _COUNTERS[ranks]


STATE = "doc_id long, text string, leaves array<struct<chars:int,pieces:int,tokens:int>>"
COUNTS = "doc_id long, n_chars long, n_pieces long, n_tokens long, n_edits long, n_tokens_edited long, n_encoded_again long"


def _mapped(spark: SparkSession, rows: DataFrame, schema: str, one: Callable[[Counter, dict], dict], path: str) -> DataFrame:
    ranks = spark.sparkContext.broadcast(vocabulary(spark, path))

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = _counter(ranks.value)
        for batch in it:
            columns = [batch.column(c) for c in batch.schema.names]
            out = [one(counter, dict(zip(batch.schema.names, (c[i].as_py() for c in columns), strict=True))) for i in range(batch.num_rows)]
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=made)

    from pyspark.sql.pandas.types import to_arrow_schema

    made = to_arrow_schema(spark.createDataFrame([], schema).schema)
    return rows.mapInArrow(batches, schema)


def _leaf_rows(tree: Tree) -> list[dict]:
    return [{"chars": c, "pieces": p, "tokens": t} for c, p, t in tree.leaves]


def counted(docs: DataFrame, path: str = VOCABULARY) -> DataFrame:
    """doc_id, text, leaves: the trees' leaves, to be kept as a table beside the texts."""

    def one(counter: Counter, row: dict) -> dict:
        text = row["text"] or ""
        return {"doc_id": row["doc_id"], "text": text, "leaves": _leaf_rows(Tree(counter, text))}

    return _mapped(docs.sparkSession, docs.selectExpr("cast(doc_id as long) AS doc_id", "text"), STATE, one, path)


def edited(state: DataFrame, edits: DataFrame, path: str = VOCABULARY) -> DataFrame:
    """The state after edits (doc_id, start, end, replacement, one row an edit); documents without edits pass unread by Python."""
    listed = edits.groupBy(F.col("doc_id").alias("edit_id")).agg(F.collect_list(F.struct("start", "end", "replacement")).alias("edits"))
    touched = F.col("doc_id") == F.col("edit_id")

    def one(counter: Counter, row: dict) -> dict:
        tree = Tree.of_leaves(counter, row["text"], [(x["chars"], x["pieces"], x["tokens"]) for x in row["leaves"]])
        tree.edit_all([(e["start"], e["end"], e["replacement"] or "") for e in row["edits"]])
        return {"doc_id": row["doc_id"], "text": tree.text, "leaves": _leaf_rows(tree)}

    changed = _mapped(state.sparkSession, state.join(listed, touched).drop("edit_id"), STATE, one, path)
    # the others meet the ids of edits alone
    return state.join(listed.select("edit_id"), touched, "left_anti").unionByName(changed)


def totals(state: DataFrame) -> DataFrame:
    """doc_id, n_chars, n_pieces, n_tokens from stored leaves."""
    names = {"n_chars": "chars", "n_pieces": "pieces", "n_tokens": "tokens"}
    return state.select("doc_id", *(_leaf_sum(field).alias(name) for name, field in names.items()))


def _leaf_sum(field: str) -> Column:
    return F.aggregate("leaves", F.lit(0).cast("long"), lambda s, x: s + x[field])


def recounted(rows: DataFrame, path: str = VOCABULARY) -> DataFrame:
    """Counts before and after edits, in one pass: rows has doc_id, text, edits (array of start, end, replacement)."""

    def one(counter: Counter, row: dict) -> dict:
        tree = Tree(counter, row["text"] or "")
        chars, pieces, tokens = tree.counts
        tree.encoded = 0
        edits = [(e["start"], e["end"], e["replacement"] or "") for e in row["edits"] or []]
        tree.edit_all(edits)
        return {"doc_id": row["doc_id"], "n_chars": chars, "n_pieces": pieces, "n_tokens": tokens, "n_edits": len(edits), "n_tokens_edited": tree.counts[2], "n_encoded_again": tree.encoded}

    return _mapped(rows.sparkSession, rows.selectExpr("cast(doc_id as long) AS doc_id", "text", "edits"), COUNTS, one, path)


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of every whole document, before and after its e-mail addresses are replaced."""
    docs = table(spark, sf_dir, "documents").select("doc_id", text_or_empty().alias("text"))
    found = _spans(F.col("text"), BASE["email"], BASE_GATE["email"](F.col("text")))
    edits = F.transform(found, lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), F.lit("<email>").alias("replacement")))
    return recounted(docs.withColumn("edits", edits))
