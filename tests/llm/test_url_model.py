"""The URL model on names that its training table doesn't hold, and odd pages."""

from __future__ import annotations

import random

from depscope.llm import url_filter as u

UNWANTED = "casinos pokerstar rouletten slotking jackpots lotteries betting24 bookmakers gamblers viagras pharmacies diet-pills steroids pornos xxxcam escorts adults-only nudes paydays loaner replicas torrents warezone keygens adservers adclicks bannerads popunders trackers".split()
WANTED = "newsroom schooling librarian gardener musician historic sciences traveller weathered museums universities hospitals councils forums researcher kitchens galleries villages mountains riverside cyclist footballer bakeries farmers railways harbours archives lighthouse philosophy teacher furniture pottery".split()
FORMS = ["{}-palace", "royal-{}", "{}city", "{}.direct", "go{}", "{}-group", "{}99", "{}"]


def held_out() -> list[tuple[str, int]]:
    rnd = random.Random(9)
    names = [(rnd.choice(FORMS).format(w), label) for label, words in ((1, UNWANTED), (0, WANTED)) for w in words for _ in range(4)]
    return [(f"https://www.{n}.test/{rnd.choice(['a', 'shop', 'x/1'])}", label) for n, label in names]


def test_words_of_the_test_are_not_in_the_training_table():
    seen = " ".join(h for h, _, _ in u.labelled_urls())
    assert not [n for n, _ in held_out() if n.split(".")[1] in seen.split(".")]
    pages = ("casino-win", "free-bets", "cheap-pills", "ads-track", "adult-x")
    assert not [p for p in pages if p in seen]


def test_held_out_accuracy(spark):
    rows = held_out()
    df = spark.createDataFrame([(i, url) for i, (url, _) in enumerate(rows)], "page_id long, url string")
    got = {r.page_id: r.verdict for r in u.judged(df, ()).collect()}
    right = sum((got[i] == "block") == bool(label) for i, (_, label) in enumerate(rows))
    print(f"URL model, unseen names: accuracy {right / len(rows):.3f}")
    assert right / len(rows) >= 0.9


def test_own_labelled_table(spark):
    df = spark.createDataFrame([(1, "https://zebra.test/"), (2, "https://tulip.test/")], "page_id long, url string")
    own = tuple((f"{w}{i}.test", "/", label) for i in range(20) for w, label in (("zebra", 1), ("tulip", 0)))
    assert [r.verdict for r in u.judged(df, (), own).orderBy("page_id").collect()] == ["block", "allow"]
    assert {r.verdict for r in u.judged(df, (), ()).collect()} == {"allow"}


def test_repeated_rows_and_clashing_names(spark):
    columns = "page_id long, url string, html string, host string, path string, rule string, verdict string, score double"
    rows = [(1, "https://a.net/x", None, "h", "p", "r", "v", 9.0)] * 3 + [(None, None, "", None, None, None, None, None), (2, "", None, "", "", "", "", 0.0), (3, "https://" + "a" * 200_000, None, "", "", "", "", 0.0)]
    df = spark.createDataFrame(rows, columns)
    got = u.judged(df).collect()
    assert len(got) == 6 and [r.verdict for r in got if r.page_id == 1] == ["block"] * 3
    assert [(r.host, r.path, r.rule, r.verdict) for r in got if r.page_id in (None, 2)] == [("", "", None, "allow")] * 2
    assert u.judged(df.where("page_id > 5")).collect() == []
