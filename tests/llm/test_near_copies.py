"""The near-duplicate stage of the pipeline against all pairs of five-word shingle sets."""

from __future__ import annotations

import random

import pytest

import corpus_pipeline as P
from depscope.llm import near_copies as near
from depscope.llm.near_copies import near_copies
from tests.llm import helpers as H


def shingles(text) -> frozenset:
    w = (text or "").encode().lower().split()
    return frozenset(zip(*(w[i:] for i in range(5)))) if len(w) >= 5 else frozenset([tuple(w)] * bool(w))


def brute_force(docs: list[tuple]) -> dict:
    """doc_id -> the smallest doc_id of its component, for documents (doc_id, text) with ids."""
    sets = sorted((i, shingles(t)) for i, t in docs)
    up = {i: i for i, _ in sets}

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for k, (i, x) in enumerate(sets):
        for j, y in sets[:k]:
            if x == y or 5 * len(x & y) >= 4 * len(x | y):
                a, b = find(i), find(j)
                up[max(a, b)] = min(a, b)
    return {i: find(i) for i in up}


def edited(words: list[str], places: int, rnd: random.Random) -> list[str]:
    out = list(words)
    for p in rnd.sample(range(len(out)), places):
        out[p] = f"edit{rnd.random()}"
    return out


def test_stage_drops_near_copies_that_differ_in_more_than_three_bits(spark):
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("doc_id in (2, 56)")
    assert len({c for c in H.near_duplicate_ids([(r.doc_id, r.text) for r in rows.collect()]).values()}) == 2
    assert [r.doc_id for r in P.near_duplicates(spark, rows, "").collect()] == [2]


def test_components_match_all_pairs(spark):
    """Given documents; a group of copies, some of which are near no hub; a chain; texts that share just a passage."""
    rnd = random.Random(3)
    texts = [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect()]
    base = [f"b{i}" for i in range(200)]
    texts += [" ".join(edited(base, rnd.choice([0, 1, 2, 4, 6, 9]), rnd)) for _ in range(60)]
    now = [f"c{i}" for i in range(300)]
    for _ in range(12):
        texts.append(" ".join(now))
        now = edited(now, 5, rnd)
    passage = [f"p{i}" for i in range(100)]
    texts += [" ".join(passage + [f"own{rnd.random()}" for _ in range(rnd.choice([20, 40, 90]))]) for _ in range(40)]
    texts += [None, "", "one two", "ONE  two", "one two three"]
    docs = list(enumerate(texts))
    got = {r.doc_id: r.component_id for r in near_copies(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == brute_force(docs)


def test_run_matches_all_pairs(spark):
    """The whole pipeline, with near copies by all pairs of shingle sets."""
    small = "/root/testdata/sf0.001"
    rows = [(r.doc_id, r.text, r.source) for r in spark.read.parquet(f"{small}/documents.parquet").collect()]
    rows = [r for r in rows if not H.quality(r[1])["base_failed"]]
    comp = brute_force([(i, t) for i, t, _ in rows])
    rows = [r for r in rows if comp[r[0]] == r[0]]
    windows = H.benchmark_windows([tuple(r) for r in spark.read.parquet(f"{small}/benchmark.parquet").select("item_id", "text").collect()])
    rows = [r for r in rows if not H.contamination(r[1], windows)[1]]
    copies = H.mixed_copies(rows)
    want = sorted((i, t) for i, t, _ in rows for _ in range(copies[i]))
    assert sorted((r.doc_id, r.text) for r in P.run(spark, small).collect()) == want


def _node_rows(spark, texts):
    """near_copies' own first pass: one row a text."""
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    made = near._keyed(docs).mapInArrow(near._band_batches, "doc_id long, text_key long, fp long, n int, bits long, bands array<long>")
    return docs, made.localCheckpoint()


def test_fingerprints_within_three_bits_are_met_by_the_index(spark):
    """The stage takes candidates from op3's index; every pair of fingerprints within three bits is connected."""
    rnd = random.Random(5)
    texts = []
    for g in range(30):
        base = [f"g{g}w{i}" for i in range(400)]
        texts += [" ".join(base), " ".join(edited(base, 1, rnd)), " ".join(edited(base, 3, rnd))]
    _, rows = _node_rows(spark, texts)
    nodes = rows.select("fp", "n", "bits").distinct()
    met = {(r.a, r.b) for r in near.bit_pairs(nodes).collect()}
    bits = {r.fp: r.bits for r in nodes.collect()}
    up = {f: f for f in bits}

    def find(f):
        while up[f] != f:
            f = up[f]
        return f

    for a, b in met:
        up[find(a)] = find(b)
    close = [(a, b) for a in bits for b in bits if a < b and ((bits[a] ^ bits[b]) & (1 << 64) - 1).bit_count() <= 3]
    assert len(close) >= 10 and all(((bits[a] ^ bits[b]) & (1 << 64) - 1).bit_count() <= 3 for a, b in met)
    assert all(find(a) == find(b) for a, b in close)


def test_a_group_alike_but_not_alike_enough_is_not_compared_pair_by_pair(spark, monkeypatch):
    """400 copies of a text that isn't among them, none near another, but for 20 with a near copy of their own; components as in brute force."""
    rnd = random.Random(9)
    base = [f"b{i}" for i in range(300)]
    texts = [" ".join(edited(base, 9, rnd)) for _ in range(400)]
    texts += [" ".join(edited(t.split(), 1, rnd)) for t in texts[:20]]
    docs = list(enumerate(texts))
    compared = []
    verified = near._verified
    monkeypatch.setattr(near, "_verified", lambda pairs, *rest: compared.append(pairs.count()) or verified(pairs, *rest))
    got = {r.doc_id: r.component_id for r in near_copies(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == brute_force(docs)
    assert len(set(got.values())) == 400
    assert sum(compared) < 30 * len(docs)


def _apart(rnd: random.Random) -> list[str]:
    """400 copies that keep more than 8/9 of a text, which is none of them, none near another; some edited in the same places, or nearly, in other words."""
    base, texts = [f"b{i}" for i in range(300)], []
    for k in range(400):
        places = rnd.sample(range(5, 294), 6)
        moved = [*places[:5], places[5] + 1]
        for own in [places] + [places] * (k < 20) + [moved] * (k < 10):
            texts.append(" ".join(f"edit{rnd.random()}" if i in own else w for i, w in enumerate(base)))
    return texts


def _around(rnd: random.Random) -> list[str]:
    """300 copies of a text, which is none of them, with one edit, all near each other; 300 with six, near to those edited in one of these places."""
    base = [f"b{i}" for i in range(300)]
    return [" ".join(edited(base, k, rnd)) for k in (1, 6) for _ in range(300)]


@pytest.mark.parametrize("made", [_apart, _around])
def test_copies_that_common_shingles_could_link_are_not_compared_pair_by_pair(spark, monkeypatch, made):
    docs = list(enumerate(made(random.Random(4))))
    compared = []
    verified = near._verified
    monkeypatch.setattr(near, "_verified", lambda pairs, *rest: compared.append(pairs.count()) or verified(pairs, *rest))
    got = {r.doc_id: r.component_id for r in near_copies(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == brute_force(docs)
    print(f"{len(docs)} copies, {len(set(got.values()))} components, compared {compared}")
    assert sum(compared) < 50 * len(docs)


@pytest.mark.parametrize("seed", [1, 2])
def test_common_pairs_hold_every_pair_that_common_shingles_link(spark, seed):
    """No pair of different components is lost by levels, parts and left-out nodes: all pairs by brute force, for sets drawn around one text."""
    rnd = random.Random(seed)
    base, made = [rnd.getrandbits(62) for _ in range(90)], {}
    for fp in range(150):
        lacks = {i % 90 for at in rnd.sample(range(90), rnd.choice([0, 1, 1, 2])) for i in range(at, at + rnd.choice([1, 3, 5]))}
        common = sorted(h for i, h in enumerate(base) if i not in lacks)
        made[fp] = (len(common) + rnd.choice([0, 0, 2, len(lacks)]), common, fp if rnd.random() < 0.5 else rnd.randrange(5))
    known = [(fp, n, common, len(common), 9 * len(common) - 8 * n) for fp, (n, common, _) in made.items()]
    known = spark.createDataFrame(known, "fp long, n int, common array<long>, c int, slack int").localCheckpoint()
    open_ = spark.createDataFrame([(7, fp, n, root, 150) for fp, (n, _, root) in made.items()], "key long, fp long, n int, root long, nodes long")
    got = {(r.a, r.b) for r in near._common_pairs(near._centred(open_, known), known).collect()}

    def find(i, up):
        while up[i] != i:
            i = up[i]
        return i

    def joined(pairs):
        up = {r: r for _, _, r in made.values()}
        for a, b in pairs:
            x, y = find(made[a][2], up), find(made[b][2], up)
            up[max(x, y)] = min(x, y)
        return {r: find(r, up) for r in up}

    def links(a, b):
        return 9 * len({*made[a][1]} & {*made[b][1]}) >= 4 * (made[a][0] + made[b][0])

    want = [(a, b) for a in made for b in made if a < b and made[a][2] != made[b][2] and links(a, b)]
    assert len(want) > 100
    assert joined(want) == joined(p for p in got if links(*p))
