from __future__ import annotations

import os
import shutil
import subprocess
import sys

import pytest
from pyspark.sql import functions as F

from depscope.operators import baselines, graph, propagate, questions, rewrites, rules, validate
from depscope.plans import rule_text
from depscope.plans.registry import SchemaRegistry
from depscope.sources import io
from depscope.sources.facts import local
from depscope.streaming import monitors
from depscope.workloads import minimal

SMALL = "/root/testdata/sf0.001"
REPO = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


@pytest.fixture(scope="module")
def registry(spark):
    r = SchemaRegistry(spark)
    r.add_table("nation", spark.read.parquet(f"{SMALL}/nation.parquet"), keys=[["n_nationkey"]], fds=[(["n_name"], "n_nationkey")])
    r.add_table("region", spark.read.parquet(f"{SMALL}/region.parquet"), keys=[["r_regionkey"]])
    r.add_table("orders", spark.read.parquet(f"{SMALL}/orders.parquet"), keys=[["o_orderkey"]])
    for name, (sql, _) in CASES.items():
        r.add_view(name, sql)
    return r


CASES = {
    "sel": ("SELECT n_nationkey, n_regionkey FROM nation WHERE n_regionkey = 2 AND n_name <> 'X'", {("", "n_regionkey")}),
    "either": ("SELECT n_nationkey, n_regionkey FROM nation WHERE n_regionkey = 2 OR n_regionkey = 3", {("n_nationkey", "n_regionkey")}),
    "isnull": ("SELECT n_nationkey, n_regionkey FROM nation WHERE n_regionkey IS NULL", {("", "n_regionkey")}),
    "one_in": ("SELECT n_nationkey, n_regionkey FROM nation WHERE n_regionkey IN (2)", {("", "n_regionkey")}),
    "widened": ("SELECT n_nationkey, n_regionkey FROM nation WHERE n_regionkey = 2L", {("", "n_regionkey")}),
    "twice": ("SELECT n_nationkey AS a, n_nationkey AS b FROM nation", {("a", "b"), ("b", "a")}),
    "joined": ("SELECT n_nationkey, r_name FROM nation JOIN region ON n_regionkey = r_regionkey", {("n_nationkey", "r_name")}),
    "using_": ("SELECT x.n_nationkey AS k, y.n_name AS m FROM nation x JOIN nation y USING (n_nationkey)", {("k", "m"), ("m", "k")}),
    "outer_": ("SELECT n_nationkey, n_name, r_name FROM nation LEFT JOIN region ON n_regionkey = r_regionkey", {("n_nationkey", "n_name"), ("n_name", "n_nationkey")}),
    "semi": ("SELECT n_nationkey, n_name FROM nation LEFT SEMI JOIN region ON n_regionkey = r_regionkey", {("n_nationkey", "n_name"), ("n_name", "n_nationkey")}),
    "grouped": ("SELECT o_custkey, year(o_orderdate) AS y, sum(o_totalprice) AS s FROM orders GROUP BY o_custkey, year(o_orderdate)", {("o_custkey,y", "s")}),
    "totals": ("SELECT count(*) AS n, max(o_totalprice) AS m FROM orders", {("", "n"), ("", "m")}),
    "sorted_": ("SELECT DISTINCT n_nationkey, n_name FROM nation ORDER BY n_name LIMIT 5", {("n_nationkey", "n_name"), ("n_name", "n_nationkey")}),
    "windowed": ("SELECT o_orderkey, o_custkey, max(o_totalprice) OVER (PARTITION BY o_custkey) AS top, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS rn FROM orders", {("o_orderkey", "o_custkey"), ("o_custkey", "top"), ("o_orderkey", "top")}),
    "exploded": ("SELECT n_nationkey, n_name, explode(array(1, 2)) AS e FROM nation", {("n_nationkey", "n_name"), ("n_name", "n_nationkey")}),
    "random": ("SELECT n_nationkey, rand() AS x, now() AS t FROM nation", set()),
    "both": ("SELECT n_nationkey, n_name FROM nation INTERSECT SELECT n_regionkey, n_name FROM nation", {("n_nationkey", "n_name"), ("n_name", "n_nationkey")}),
    "minus_": ("SELECT n_regionkey, n_name FROM nation EXCEPT SELECT n_nationkey, n_name FROM nation", {("n_name", "n_regionkey")}),
    "three": ("SELECT n_nationkey AS k FROM nation UNION ALL SELECT r_regionkey FROM region UNION ALL SELECT n_regionkey FROM nation", set()),
}


def test_plans_give_the_fds_of_their_views(spark, registry):
    fd = minimal(propagate.run(registry.facts())).collect()
    cols = {v: [c for c, _ in columns] for v, columns in registry.catalog.views.items()}
    for name, (_, want) in CASES.items():
        got = {(",".join(cols[name][p - 1] for p in r.lhs), cols[name][r.rhs - 1]) for r in fd if r.rel == name}
        assert got == want, name


def test_views_keep_their_borders(registry):
    registry.add_view("top_view", "SELECT n_name FROM joined JOIN nation ON joined.n_nationkey = nation.n_nationkey")
    edges = {(r.dst, r.src) for r in registry.facts().edges.collect()}
    assert {("top_view", "joined"), ("top_view", "nation"), ("joined", "region")} <= edges and ("top_view", "region") not in edges


def test_one_operator_a_relation(registry):
    assert all(n.operator in ("projection", "extension", "selection", "product", "join", "union", "intersection", "negation", "leaf") for n in registry.catalog.nodes.values())
    assert all(len(n.inputs) == 2 for n in registry.catalog.nodes.values() if n.operator in ("union", "product", "join", "intersection", "negation"))


def test_rule_notation():
    rules_ = rule_text.parse("p(X, 'a') :- q(X, Y), not r(X, Y), Y = 2, Z = f(X).")
    assert rules_[0].head.args == ["X", "'a'"] and rules_[0].body[1].negated and rules_[0].conditions[1] == ("Z", "=", ("f", "X"))
    for bad in ("p(X)", "p(X) :- .", "p(X) :- q(X) ?"):
        with pytest.raises(rule_text.RuleError):
            rule_text.parse(bad)


def test_rules_lower_to_single_operators(spark):
    r = SchemaRegistry(spark)
    r.add_table("q", ["a", "b"])
    r.add_table("m", ["a", "b"])
    r.add_rules("v(X, Y, 1) :- q(X, Y), Y = 5. w(X, Y) :- q(X, Y), not m(X, Y).")
    kinds = {n.name: n.operator for n in r.catalog.nodes.values()}
    assert kinds["v"] == "extension" and kinds["w"] == "negation"
    with pytest.raises(rule_text.RuleError):
        r.add_rules("z(X, Y) :- q(X, _).")
    with pytest.raises(ValueError):
        r.declare_fd("q", ["a"], "b", fid="same")
        r.declare_fd("m", ["a"], "b", fid="same")


def test_closures_agree_on_a_cyclic_graph(spark):
    edges = local(spark, [("b", "a", "reads", "+"), ("c", "b", "reads", "-"), ("a", "c", "reads", "+"), ("d", "c", "reads", "+")], "dst string, src string, kind string, polarity string")
    want = {(x, y) for x in "abcd" for y in "abc"}
    for how in ("seminaive", "naive", "doubling"):
        got = graph.reach(edges, strategy=how).collect()
        assert {(r.dst, r.src) for r in got} == want
        assert {r.hops for r in got if (r.dst, r.src) == ("d", "a")} == {3}
    assert {(r.dst, r.sign) for r in graph.signed_reach(edges).where("src = 'a' AND dst = 'd'").collect()} == {("d", 1), ("d", -1)}
    assert {r.rel for r in graph.negative_cycles(edges).collect()} == {"b", "c"}
    assert {(r.rel, r.level, r.scc) for r in graph.levels(edges).collect()} == {("a", 0, "a"), ("b", 0, "a"), ("c", 0, "a"), ("d", 1, "d")}
    assert [r.path for r in graph.explain(edges, "d", "a").collect()] == [["a", "b", "c", "d"]]


def test_feedback_through_a_function(spark):
    r = SchemaRegistry(spark)
    r.add_table("log", ["x"])
    r.add_rules("v(X) :- log(X), X = 1.")
    r.add_function("f", 1, writes=["log"])
    r.catalog.extra_edges.append(("f", "v", "calls", "+"))
    facts = r.facts()
    assert [(x.a, x.b) for x in questions.cyclic_tables_via_function(facts).collect()] == [("log", "log")]
    assert [x.table for x in questions.tables_changed_by(facts, "f").collect()] == ["log"]
    sql = rules.to_sql("tables_changed_by", arg="f")
    assert "WITH RECURSIVE" in sql and "ds_edges" in sql


def test_checks_with_nulls_and_empty_tables(spark):
    df = spark.createDataFrame([(1, None), (1, None), (2, "a"), (2, None), (None, "x"), (None, "y"), (3, "z")], "k int, v string")
    assert validate.check_fd(df, ["k"], "v").first() == (4, 2)
    assert {r.k for r in validate.violations(df, ["k"], "v").collect()} == {2, None}
    none = df.where("k > 9")
    assert validate.check_fd(none, ["k"], "v").first() == (0, 0) and validate.check_fd(none, [], "v").first() == (0, 0)
    assert validate.check_fd(df, [], "k").first() == (1, 1)
    assert {(r.lhs, r.rhs) for r in validate.discover(spark.createDataFrame([(1, 1, 5), (2, 1, 6), (3, 2, 6)], "a int, b int, c int"), 2).collect()} == {("a", "b"), ("a", "c"), ("b,c", "a")}
    assert validate.equal_columns(df.select("k", F.col("k").alias("k2")), "k", "k2").first()["different"] == 0
    assert validate.refuted_on_sample(df, ["k"], "v", 1)


def test_rewrites(spark):
    df = spark.createDataFrame([(1, "a", 5), (1, "a", 6), (2, "b", 7)], "k int, name string, x int")
    fds = [(("k",), "name")]
    got = rewrites.reduce_group_keys(df, ["k", "name"], [F.sum("x").alias("s")], fds)
    assert sorted(map(tuple, got.collect())) == [(1, "a", 11), (2, "b", 7)]
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate [k" in plan and "Aggregate [k#" in plan and ", name#" not in plan.split("],")[0]
    assert rewrites.kept_keys(["k", "name"], fds) == ["k"] and rewrites.kept_keys(["name", "x"], fds) == ["name", "x"]
    assert rewrites.drop_distinct(df.select("k"), None).count() == 2 and rewrites.drop_distinct(df.select("k"), ["k"]).count() == 3


def test_stream_monitor_equals_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SMALL}/events.parquet")
    folder = str(tmp_path / "in")
    events.write.parquet(folder)
    stream = spark.readStream.schema(events.schema).parquet(folder)
    q = monitors.fd_monitor(stream, ["user_id"], "event_type", "ts", "36500 days", "1 day").writeStream.format("memory").queryName("monitored").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    key = lambda d: sorted(map(str, d.select("window.start", "user_id", "n", "violated").collect()))
    assert key(spark.table("monitored")) == key(monitors.fd_monitor(events, ["user_id"], "event_type", "ts", "36500 days", "1 day"))


def test_facts_round_trip_and_drawings(spark, registry, tmp_path):
    edges = registry.facts().edges
    key = lambda d: sorted(map(str, d.collect()))
    for form in ("parquet", "json", "csv"):
        io.write_facts(edges, str(tmp_path / form), form)
        assert key(io.read_facts(spark, str(tmp_path / form), "edge", form)) == key(edges)
    assert '"nation" -> "joined"' in io.to_dot(edges) and "| nation | reads | joined | + |" in io.to_markdown(edges)
    registry.facts().write(str(tmp_path / "store"))
    assert key(io.read_facts(spark, str(tmp_path / "store" / "attrs"), "attr")) == key(registry.facts().attrs)
    loaded = io.load_tables(spark, SMALL, ["region"], {"region": [["r_regionkey"]]})
    assert loaded.facts().declared.count() == 1


def test_baselines(spark, registry):
    df = spark.sql("SELECT n_regionkey, count(*) AS n FROM nation WHERE n_name = 'X' GROUP BY n_regionkey")
    assert [r.key for r in baselines.catalyst_keys(df).collect()] == ["n_regionkey"]
    assert baselines.catalyst_constants(df).count() >= 0


def test_schema_feed_applies_changes_in_order(spark, tmp_path):
    folder = str(tmp_path / "feed")
    spark.createDataFrame([(2, "b"), (1, "a")], "seq int, view string").coalesce(1).write.parquet(folder)
    seen = []
    monitors.schema_feed(spark.readStream.schema("seq int, view string").parquet(folder), seen.extend, str(tmp_path / "cp")).awaitTermination()
    assert [c["view"] for c in seen] == ["a", "b"]


def test_entry_without_corpus_operators(tmp_path):
    """The folders of the corpus operators can be deleted: the rest imports and lists its queries."""
    copy = tmp_path / "repo"
    shutil.copytree(REPO, copy, ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__", "tests"))
    code = "import __spark_entry__ as e; q = e.queries(); assert q and not any(n.startswith('op') and n[2].isdigit() for n in q); assert set(e.oracle_sql()) <= set(q)"
    done = subprocess.run([sys.executable, "-B", "-c", code], cwd=copy, env=os.environ | {"PYTHONPATH": str(copy)}, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr
