"""The pipeline against its brute-force version, and every stage on odd inputs."""

from __future__ import annotations

import pytest

import corpus_pipeline as P
from depscope.llm import queries
from tests.llm import helpers as H

SMALL = "/root/testdata/sf0.001"


def test_run_matches_brute_force(spark):
    rows = [(r.doc_id, r.text, r.source) for r in spark.read.parquet(f"{SMALL}/documents.parquet").collect()]
    rows = [r for r in rows if not H.quality(r[1])["base_failed"]]
    comp = H.near_duplicate_ids([(i, t) for i, t, _ in rows])
    rows = [r for r in rows if comp[r[0]] == r[0]]
    windows = H.benchmark_windows([tuple(r) for r in spark.read.parquet(f"{SMALL}/benchmark.parquet").select("item_id", "text").collect()])
    rows = [r for r in rows if not H.contamination(r[1], windows)[1]]
    copies = H.mixed_copies(rows)
    want = sorted((i, t) for i, t, _ in rows for _ in range(copies[i]))
    got = P.run(spark, SMALL)
    assert sorted((r.doc_id, r.text) for r in got.collect()) == want
    assert got.columns[:5] == ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.mark.parametrize("make", [H.messy, lambda s: H.messy(s, True), H.empty], ids=["messy", "extra", "empty"])
@pytest.mark.parametrize("stage", [s for _, s in P.STAGES], ids=[n for n, _ in P.STAGES])
def test_stages_on_odd_inputs(spark, stage, make):
    docs = make(spark)
    got = stage(spark, docs, SMALL)
    assert got.columns[: len(docs.columns)] == docs.columns
    assert len(got.collect()) <= 3 * docs.count() + 3


def test_all_ten_operators_are_registered():
    assert {q.split("_")[0] for q in queries.queries()} == {f"op{i}" for i in range(1, 11)}
    assert [n for n, _ in P.STAGES] == ["quality rules", "near-duplicates", "benchmark decontamination", "source mixing", "sharding"]
