"""Dependency graph: direct edges, reachability, witnesses, signs and levels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depscope.operators.fixpoint import seminaive


def direct_edges(facts) -> DataFrame:
    """dst, src, kind, polarity."""
    return facts.edges


def reach(edges: DataFrame, seeds: list[str] | None = None, strategy: str = "seminaive", reflexive: bool = False) -> DataFrame:
    """dst, src, hops: the transitive closure, with the fewest edges of a path. seeds restricts the sources.

    strategy: 'seminaive' extends the last round's paths by one edge, 'naive' all paths again and again, 'doubling' joins paths with
    paths (about log2 of the longest path in rounds), 'cte' is one recursive query (acyclic graphs only).
    """
    e = edges.select("dst", "src").distinct()
    if strategy == "cte":
        found = _reach_cte(e)
        found = found.where(F.col("src").isin(seeds)) if seeds is not None else found
    else:
        start = e.where(F.col("src").isin(seeds)) if seeds is not None else e
        nexts = e.select(F.col("src").alias("__mid"), F.col("dst").alias("__to"))

        def step(delta: DataFrame, known: DataFrame) -> DataFrame:
            if strategy == "doubling" and seeds is None:
                a, b = delta.alias("a"), known.alias("b")
                both = a.join(b, F.col("a.dst") == F.col("b.src")).select(F.col("b.dst"), F.col("a.src"), (F.col("a.hops") + F.col("b.hops")).alias("hops"))
                back = b.join(a, F.col("b.dst") == F.col("a.src")).select(F.col("a.dst"), F.col("b.src"), (F.col("a.hops") + F.col("b.hops")).alias("hops"))
                # only shorter paths are new, so that cycles end
                best = known.groupBy(F.col("dst").alias("d"), F.col("src").alias("s")).agg(F.min("hops").alias("best"))
                both = both.unionByName(back).join(best, (F.col("dst") == F.col("d")) & (F.col("src") == F.col("s")), "left").where("best IS NULL OR hops < best")
            else:
                both = delta.join(nexts, delta["dst"] == nexts["__mid"]).select(F.col("__to").alias("dst"), "src", (F.col("hops") + 1).alias("hops"))
            return both.groupBy("dst", "src").agg(F.min("hops").alias("hops"))

        # paths of one more edge each round: the first found is the shortest; doubling settles hops below
        found, _ = seminaive(start.withColumn("hops", F.lit(1)), step, ["dst", "src"] if strategy != "doubling" else ["dst", "src", "hops"], strategy="naive" if strategy == "naive" else "seminaive")
        found = found.groupBy("dst", "src").agg(F.min("hops").alias("hops"))
    if reflexive:
        nodes = e.select("dst").union(e.select("src")).distinct().select("dst", F.col("dst").alias("src"), F.lit(0).alias("hops"))
        found = found.select("dst", "src", "hops").unionByName(nodes).groupBy("dst", "src").agg(F.min("hops").alias("hops"))
    return found.select("dst", "src", F.col("hops").cast("int").alias("hops"))


def work(edges: DataFrame, strategy: str = "seminaive") -> dict[str, int]:
    """What a strategy's rounds cost: rounds, and rows that are joined with the edges in all of them together."""
    e = edges.select("dst", "src").distinct()
    nexts = e.select(F.col("src").alias("__mid"), F.col("dst").alias("__to"))
    step = lambda delta, known: delta.join(nexts, delta["dst"] == nexts["__mid"]).select(F.col("__to").alias("dst"), "src")
    _, sizes = seminaive(e, step, ["dst", "src"], strategy=strategy)
    stepped = sizes if strategy == "seminaive" else [sum(sizes[: i + 1]) for i in range(len(sizes))]
    return {"rounds": len(sizes), "rows_stepped": sum(stepped), "pairs": sum(sizes)}


def _reach_cte(e: DataFrame) -> DataFrame:
    spark = e.sparkSession
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")  # a million rows otherwise, with an error beyond; read as the result is computed
    e.createOrReplaceTempView("ds_reach_edges")
    return spark.sql(
        "WITH RECURSIVE p(dst, src, hops) AS (SELECT dst, src, 1 FROM ds_reach_edges UNION ALL "
        "SELECT e.dst, p.src, p.hops + 1 FROM p JOIN ds_reach_edges e ON e.src = p.dst) SELECT dst, src, min(hops) AS hops FROM p GROUP BY dst, src"
    )


def explain(edges: DataFrame, dst: str, src: str) -> DataFrame:
    """path: every simple path from src to dst, as arrays of names. Meant for one pair; paths can be many."""
    e = edges.select("dst", "src").distinct().select(F.col("src").alias("__mid"), F.col("dst").alias("__to"))
    # only nodes on the way matter
    there = reach(edges, [src]).select(F.col("dst").alias("__n"))
    e = e.join(there, e["__to"] == there["__n"], "left_semi")
    start = edges.sparkSession.range(1).select(F.array(F.lit(src)).alias("path"))

    def step(delta: DataFrame, known: DataFrame) -> DataFrame:
        open_ = delta.where(F.element_at("path", -1) != dst)
        on = F.element_at(open_["path"], -1) == e["__mid"]
        return open_.join(e, on).where(~F.array_contains("path", F.col("__to"))).select(F.array_append("path", F.col("__to")).alias("path"))

    found, _ = seminaive(start, step, ["path"])
    return found.where((F.element_at("path", -1) == dst) & (F.size("path") > 1))


def signed_reach(edges: DataFrame) -> DataFrame:
    """dst, src, sign: +1 for a path with an even number of negative edges, -1 for an odd one; both may hold."""
    e = edges.select("dst", "src", F.when(F.col("polarity") == "-", -1).otherwise(1).alias("sign")).distinct()
    nexts = e.select(F.col("src").alias("__mid"), F.col("dst").alias("__to"), F.col("sign").alias("__s"))

    def step(delta: DataFrame, known: DataFrame) -> DataFrame:
        return delta.join(nexts, delta["dst"] == nexts["__mid"]).select(F.col("__to").alias("dst"), "src", (F.col("sign") * F.col("__s")).alias("sign"))

    return seminaive(e, step, ["dst", "src", "sign"])[0]


def negative_cycles(edges: DataFrame) -> DataFrame:
    """rel: relations that depend negatively on themselves; without any, the schema is stratifiable."""
    there = reach(edges)
    back = edges.where("polarity = '-'").select(F.col("dst").alias("d"), F.col("src").alias("s")).distinct()
    # a negative edge closes a cycle if its target reaches its source
    closing = back.join(there, (back["d"] == there["src"]) & (back["s"] == there["dst"])).select("d", "s")
    loops = back.where("d = s")
    return closing.union(loops).select(F.explode(F.array("d", "s")).alias("rel")).distinct()


def levels(edges: DataFrame) -> DataFrame:
    """rel, level, scc: the longest path from a source, counted over strongly connected components, which are named by their least member."""
    there = reach(edges, reflexive=True)
    a, b = there.alias("a"), there.alias("b")
    mutual = a.join(b, (F.col("a.dst") == F.col("b.src")) & (F.col("a.src") == F.col("b.dst"))).select(F.col("a.dst").alias("rel"), F.col("a.src").alias("other"))
    scc = mutual.groupBy("rel").agg(F.min("other").alias("scc"))
    of_dst, of_src = scc.select(F.col("rel").alias("dst"), F.col("scc").alias("to")), scc.select(F.col("rel").alias("src"), F.col("scc").alias("fro"))
    between = edges.select("dst", "src").distinct().join(of_dst, "dst").join(of_src, "src").where("to <> fro").select("to", "fro").distinct()
    start = scc.select(F.col("scc")).distinct().withColumn("level", F.lit(0))

    def step(delta: DataFrame, known: DataFrame) -> DataFrame:
        return delta.join(between, delta["scc"] == between["fro"]).select(F.col("to").alias("scc"), (F.col("level") + 1).alias("level"))

    deep = seminaive(start, step, ["scc", "level"])[0].groupBy("scc").agg(F.max("level").alias("level"))
    return scc.join(deep, "scc").select("rel", "level", "scc")
