"""Secret scan: base patterns plus assignment-aware lexing.

The lexer reads source and configuration syntax into assignments (name, literal terms): ``name = "x"``,
``name: x``, ``name := 'a' + "b"``, ``{"name": "x"}``; strings may hold escapes, and be quoted by three quotes or backticks; an unquoted
value ends at white space or a delimiter. Names bound to literals are constants; a later assignment of a
constant, or of a concatenation with one, carries the constant's literals along. A literal is scored by the most
sensitive name it reaches and by its own form (length, entropy, kinds of characters, placeholders); literals at
``THRESHOLD`` or above that no base span covers whole are added as spans of kind ``literal``.

Defined results: a null or empty text has no spans; rows that repeat a doc_id each get their row; other columns are
ignored; an empty table gives an empty result. Cost is linear in the text: the lexer's patterns don't step back, and
sensitivity passes along each use of a constant once. Names, literals and concatenations may have any length.
"""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from depscope.llm.common import table

# fixed values of the base patterns
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
LEAST = {"assign": 12, "access": 18, "hex": 16}
KINDS = ("assign", "access", "hex", "literal")
WORDS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
LONG_HEX = re.compile(rb"[0-9a-f]{16}")

#: Parts of a name that make it sensitive, and how much. A name's parts are its words, by case and separators; a run of parts counts joined.
SENSITIVE = {"password": 3, "passwd": 3, "pwd": 3, "pass": 2, "passphrase": 3, "passcode": 3, "secret": 3, "secrets": 3, "token": 3, "tokens": 3, "apikey": 3, "privatekey": 3, "accesskey": 3, "secretkey": 3, "signingkey": 3, "encryptionkey": 3, "credential": 3, "credentials": 3, "authorization": 2, "auth": 2, "bearer": 3, "key": 1, "salt": 1}
PARTS = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+|[0-9]+")
PLACEHOLDER = re.compile(r"example|sample|change_?me|placeholder|your|dummy|test|xxxx|\*\*\*|<|>|\$\{|\{\{", re.IGNORECASE)
THRESHOLD = 5.0

PAIR = re.compile(r"""(?<![A-Za-z0-9_.-])["']?([A-Za-z_][A-Za-z0-9_.-]*+)["']?[ \t]*+(?::=|=>|=|:)(?!=)[ \t]*+(?=[^\s,;)\]}])""")
# a string in three quotes, in quotes with escapes, or a bare value up to white space or a delimiter
TERM = re.compile(
    r'''"""((?:[^"\\]|\\.|"(?!""))*+)"""|"((?:[^"\\\n]|\\.)*+)"|'((?:[^'\\\n]|\\.)*+)'|`([^`\n]*+)`|([^\s"'`,;()\[\]{}+]++(?:\+[^\s"'`,;()\[\]{}+]++)*+)''',
    re.DOTALL,
)
PLUS = re.compile(r"[ \t]*+\+[ \t]*+(?=[\"'`A-Za-z0-9])")


def sensitivity(name: str) -> int:
    """The weight of the most sensitive part of a name, of one word or of neighbouring words joined (api_key, apiKey)."""
    parts = [p.lower() for p in PARTS.findall(name)]
    joined = [a + b for a, b in zip(parts, parts[1:], strict=False)]
    return max((SENSITIVE.get(p, 0) for p in (*parts, *joined)), default=0)


def entropy(literal: str) -> float:
    n = len(literal)
    return -sum(c / n * math.log2(c / n) for c in Counter(literal).values()) if n else 0.0


def score(weight: int, literal: str, quoted: bool) -> float:
    """Sensitivity of the target, plus the literal's form. Short, plain-word and placeholder literals score low."""
    if weight == 0 or len(literal) < 8 or PLACEHOLDER.search(literal) or any(c.isspace() for c in literal):
        return 0.0
    kinds = bool(re.search("[0-9]", literal)) + bool(re.search("[a-z]", literal)) + bool(re.search("[A-Z]", literal)) + bool(re.search("[^A-Za-z0-9]", literal))
    plain = kinds < 2 or not re.search("[0-9]", literal)
    return weight + min(entropy(literal), 4.0) / 2 + min(len(literal), 32) / 16 + (0.5 if quoted else 0.0) - (2.5 if plain else 0.0)


def assignments(text: str) -> list[tuple[str, list[tuple[int, int, bool]]]]:
    """(name, terms), constants before their uses; a term is (start, end, quoted) of a literal or of a bare word.

    In a chain (``a = b = "x"``) the last name has the terms, and each name before it has the next name as its term.
    """
    found, at = [], 0
    while m := PAIR.search(text, at):
        names = [m.span(1)]
        while inner := PAIR.match(text, m.end()):
            names.append(inner.span(1))
            m = inner
        terms: list[tuple[int, int, bool]] = []
        at = m.end()
        while t := TERM.match(text, at):
            group = t.lastindex
            terms.append((*t.span(group), group < 5))
            at = t.end()
            if not (p := PLUS.match(text, at)):
                break
            at = p.end()
        for start, end in reversed(names):
            if terms:
                found.append((text[start:end], terms))
            terms = [(start, end, False)]
    return found


def literal_spans(text: str) -> list[tuple[int, int, float]]:
    """(start, end, score) of literals that reach a sensitive name, directly or through constants."""
    pairs = assignments(text)
    own: list[list[tuple[int, int, bool]]] = []
    carried: list[list[int]] = []
    latest: dict[str, int] = {}
    for i, (name, terms) in enumerate(pairs):
        # a bare word that names a constant stands for what the constant's latest assignment holds
        used = [None if quoted else latest.get(text[start:end]) for start, end, quoted in terms]
        own.append([t for t, j in zip(terms, used, strict=True) if j is None])
        carried.append([j for j in used if j is not None])
        latest[name] = i
    # constants come before their uses, so one pass from the last assignment back hands every sensitivity down
    weights = [sensitivity(name) for name, _ in pairs]
    for i in range(len(pairs) - 1, -1, -1):
        for j in carried[i]:
            weights[j] = max(weights[j], weights[i])
    best: dict[tuple[int, int], float] = {}
    for weight, literals in zip(weights, own, strict=True):
        for start, end, quoted in literals if weight else ():
            value = score(weight, text[start:end], quoted)
            if value >= THRESHOLD:
                best[start, end] = max(value, best.get((start, end), 0.0))
    return [(*k, v) for k, v in sorted(best.items())]


def base_spans(text: str) -> list[tuple[str, int, int]]:
    found = [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m.group(2)) >= LEAST["assign"]]
    found += [("access", *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST["access"]]
    found += [("hex", *m.span()) for m in HEX.finditer(text) if m.end() - m.start() >= LEAST["hex"]]
    return found


def added_spans(text: str, base: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """Literal spans that base spans don't cover whole; a base span that merely touches one leaves it."""
    merged: list[list[int]] = []
    for start, end in sorted((s, e) for _, s, e in base):
        if merged and start <= merged[-1][1]:
            merged[-1][1] = max(end, merged[-1][1])
        else:
            merged.append([start, end])
    out = []
    for start, end, _ in literal_spans(text):
        i = bisect_left(merged, [start + 1]) - 1  # the last covered stretch that begins at or before the literal
        if i < 0 or merged[i][1] < end:
            out.append(("literal", start, end))
    return out


def _joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in sorted(spans, key=lambda x: (x[1], KINDS.index(x[0]), x[2])))


def _scan_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for raw in batch.column("text").cast(pa.binary()):
            data = raw.as_py() or b""
            low = data.lower()
            named = any(w in low for w in WORDS)
            base: list[tuple[str, int, int]] = []
            more: list[tuple[str, int, int]] = []
            # texts are decoded only where a cheap test on the bytes leaves something to find
            if named or b"AKIA" in data or b"=" in data or b":" in data or LONG_HEX.search(data):
                text = data.decode("utf-8", "replace")
                base = base_spans(text)
                more = added_spans(text, base)
            n = Counter(k for k, _, _ in base)
            rows.append((n["assign"], n["access"], n["hex"], hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(base + more)))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
        kinds = [pa.int64()] * 3 + [pa.string()] * 2
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))],
            ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
        )


def scanned(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans: one row a document."""
    schema = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"
    return docs.selectExpr("cast(doc_id as long) AS doc_id", "text").mapInArrow(_scan_batches, schema)


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scanned(table(spark, sf_dir, "documents"))
