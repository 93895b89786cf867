"""Brute-force versions of the corpus operators, in plain Python, and messy inputs."""

from __future__ import annotations

import hashlib
import re
from collections import Counter, defaultdict

import xxhash

SPACE = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
NORMAL = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"
MESSY = [
    (1, None, "en", "s1", None),
    (2, "", "en", "s1", 0),
    (3, " \t\n ", None, None, 4),
    (4, "one two", "en", None, 7),
    (4, "one two", "en", None, 7),
    (None, "a row without an id but with some words in it", "en", "s2", 45),
    (None, None, None, None, None),
    (5, "word " * 30_000, "en", "s2", 150_000),
    (6, "x" * 200_000, "en", "s2", 200_000),
    (7, "1" * 50_000 + " " + "a@" * 20_000, "en", "s2", 90_001),
    (8, "the same line\n" * 40, "fr", "s3", 560),
    (9, " ".join(f"w{i}" for i in range(60)), "de", "s3", 200),
    (10, " ".join(f"w{i}" for i in range(60)), "de", "s3", 200),
    (11, "Ünïcödé ÀÉÎ ß 😀 mail@example.org +49 30 901820 10.0.0.1", "de", "s4", 50),
]
EXTRA = "n_words int, fp int, component_id int, size int, key int, words int, text_key int, keep int, base int, run int, tier int, shard int, arrival int, score int, quality int, hit_id int, keep_id int, keep_key int, __id int, __key int, __text int, __hit_id int, __hit_key int, __source int, __whole int, __cut int, __copies int, __copy int, __doc int, __own int, h int, pos int, spans int, edits int"


def messy(spark, extra: bool = False):
    n = len(EXTRA.split(",")) if extra else 0
    rows = [r + (0,) * n for r in MESSY]
    return spark.createDataFrame(rows, COLUMNS + (", " + EXTRA if extra else "")).coalesce(2)


def empty(spark):
    return spark.createDataFrame([], COLUMNS)


def words(text):
    return SPACE.findall(text or "")


def normal(text):
    return NORMAL.findall((text or "").translate(LOWER))


def sha(x: str) -> str:
    return hashlib.sha256(x.encode()).hexdigest()


def fingerprint(text) -> int:
    w = (text or "").encode().lower().split()
    if not w:
        return 0
    shingles = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [b" ".join(w)]
    n = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s, 42)
        for b in range(64):
            n[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * n[b] > len(shingles))


def component_of(fps: list[int]) -> list[int]:
    """For each distinct fingerprint, the index of its component's first."""
    up = list(range(len(fps)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 3:
                a, b = find(i), find(j)
                up[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(fps))]


def near_duplicate_ids(docs: list[tuple]) -> dict:
    """doc_id -> component_id, for documents (doc_id, text) with ids."""
    fp = {i: fingerprint(t) for i, t in docs}
    distinct = sorted(set(fp.values()))
    comp = dict(zip(distinct, component_of(distinct), strict=True))
    least: dict[int, int] = {}
    for i, f in fp.items():
        least[comp[f]] = min(i, least.get(comp[f], i))
    return {i: least[comp[f]] for i, f in fp.items()}


def quality(text) -> dict:
    w = words(text)
    windows = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    hit = {i + k for i in range(len(w) - 7) if windows[tuple(w[i : i + 8])] > 1 for k in range(8)}
    lines = [x for x in (text or "").split("\n") if SPACE.search(x)]
    return {"n_words": len(w), "word_chars": sum(map(len, w)), "n_symbols": len(re.findall(r"[#*$%&|<>]", text or "")), "n_dup_lines": len(lines) - len(set(lines)), "n_repeat_words": len(hit), "base_failed": len(w) < 20 or 100 * len(hit) > 30 * len(w)}


def benchmark_windows(items: list[tuple]) -> dict[tuple, set]:
    out = defaultdict(set)
    for item, text in items:
        w = normal(text)
        for i in range(max(len(w) - 9, 1 if w else 0)):
            out[tuple(w[i : i + 10])].add(str(item))
    return out


def contamination(text, windows: dict[tuple, set]) -> tuple[int, int, list[str]]:
    w = normal(text)
    hit, items = set(), set()
    for k in {len(x) for x in windows}:
        for i in range(len(w) - k + 1):
            found = windows.get(tuple(w[i : i + k]))
            if found:
                hit.update(range(i, i + k))
                items |= found
    return len(w), len(hit), sorted(items)


def targets(sizes: dict, weights=(5, 2, 1), cap=3) -> dict:
    """Water filling by repeated resharing."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(order)}
    total, held, free = sum(sizes.values()), {}, set(order)
    while True:
        left, ws = total - sum(held.values()), sum(w[s] for s in free)
        over = {s for s in free if ws and left * w[s] / ws > cap * sizes[s]}
        if not over:
            return {s: held[s] if s in held else left * w[s] / ws if ws else 0.0 for s in order}
        held |= {s: cap * sizes[s] for s in over}
        free -= over


def mix_order(doc_id, text) -> str:
    key = hashlib.md5(("" if doc_id is None else str(doc_id)).encode()).hexdigest()
    h = xxhash.xxh64_intdigest(text.encode(), 42) if text is not None else 42
    return key + f"{h:X}"


def mixed_copies(docs: list[tuple]) -> dict:
    """(doc_id -> copies) for documents (doc_id, text, source) in whole documents."""
    by = defaultdict(list)
    for i, t, s in docs:
        by[s].append((mix_order(i, t), len(words(t)), i))
    sizes = {s: sum(n for _, n, _ in rows) for s, rows in by.items()}
    out = {}
    for s, target in targets(sizes).items():
        whole = int(target // sizes[s]) if sizes[s] else 0
        rest, before = int(target) - whole * sizes[s], 0
        cut = ""
        for key, n, _ in sorted(by[s]):
            if before < rest and n:
                cut = key
            before += n
        for key, _, i in by[s]:
            out[i] = whole + (key <= cut)
    return out
