"""Propagation of functional dependencies through every relation of a catalog.

Relations are taken level by level, all relations of a level in one job: facts are carried from the levels below, added for equalities,
constants and calls, and closed, each relation's fixpoint inside one task. The number of jobs is the depth of the view hierarchy, not
the number of relations or of derivation rounds. A linear recursion is settled at its own level by candidate facts. With
strategy 'joint' all rules run together, round by round, in DataFrame operations alone; with 'memory' they run over the driver's catalog.
All give the same facts; 'auto' takes 'memory' up to IN_MEMORY relations and 'levels' beyond.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from depscope.functions import traces
from depscope.operators import closure, combine, graph
from depscope.operators.fixpoint import Growing, seminaive
from depscope.operators.traits import KEEPING
from depscope.sources.facts import local, struct


@dataclass(frozen=True)
class Options:
    """closure_scope: 'paper' or 'all'. traces: 'full' or 'none'. unions: 'trace', 'naive' or 'drop'. recursion: 'fixpoint', 'single_pass' or 'none'."""

    closure_scope: str = "paper"
    traces: str = "full"
    unions: str = "trace"
    discriminated: bool = True
    recursion: str = "fixpoint"
    assume_deterministic: bool = False
    require_shared_origin: bool = False
    max_lhs: int | None = None
    prune: bool = True
    max_rounds: int | None = None
    strategy: str = "auto"


#: Relations, helpers of the normal form included, up to which 'auto' runs the rules in the driver's memory.
IN_MEMORY = 5_000
NO_INTS = closure.NO_INTS


def _fact(df: DataFrame, rel, lhs, rhs, trace, rule: str) -> DataFrame:
    return df.select(rel.alias("rel"), lhs.cast(NO_INTS).alias("lhs"), rhs.alias("rhs"), trace.alias("trace"), F.array().cast(NO_INTS).alias("mids"), F.lit("fact").alias("status"), F.lit(rule).alias("rule"), F.lit(0).alias("level"))


def from_equalities(eq: DataFrame) -> DataFrame:
    """x = y gives x -> y and y -> x; the trace is the left column."""
    a, b = F.col("pos1"), F.col("pos2")
    ways = [_fact(eq, F.col("rel"), F.array(x), y, F.array(traces.column(x)), "equality") for x, y in ((a, b), (b, a))]
    return ways[0].unionByName(ways[1])


def from_constants(const: DataFrame) -> DataFrame:
    """x = value gives {} -> x; the trace is the typed value."""
    return _fact(const, F.col("rel"), F.array(), F.col("pos"), F.array(traces.constant(F.col("value"), F.col("type"))), "constant")


def from_calls(calls: DataFrame, assume_deterministic: bool = False) -> DataFrame:
    """A function's inputs determine its output; only deterministic functions, unless all are assumed to be."""
    kept = calls if assume_deterministic else calls.where("deterministic")
    kept = kept.where(~F.array_contains("inputs", F.col("output")))
    head = F.concat(F.col("fingerprint"), F.lit("/"), F.size("inputs").cast("string"))
    trace = F.concat(F.array(head), F.transform("inputs", traces.column))
    return _fact(kept, F.col("rel"), F.array_sort(F.array_distinct("inputs")), F.col("output"), trace, "call")


def carry_same_positions(fd: DataFrame, ops: DataFrame) -> DataFrame:
    """Through operators that keep positions; a difference takes the minuend's only."""
    keep = ops.where(F.col("operator").isin(*KEEPING) & F.col("m").isNull() & ~((F.col("operator") == "negation") & (F.col("operand") == 2)))
    moved = fd.join(keep.select("dst", "src", "operator"), fd["rel"] == F.col("src"))
    return moved.select(F.col("dst").alias("rel"), "lhs", "rhs", "trace", "mids", "status", F.col("operator").alias("rule"), (F.col("level") + 1).alias("level"))


def carry_mapped(fd: DataFrame, ops: DataFrame) -> DataFrame:
    """Through operators that change positions: FDs whose columns all survive, renamed."""
    moved = fd.join(ops.where("m IS NOT NULL").select("dst", "src", "operator", "m"), fd["rel"] == F.col("src"))
    has = lambda c: F.map_contains_key("m", c)
    at = lambda c: F.element_at(F.col("m"), c)
    moved = moved.where(F.forall("lhs", has) & F.map_contains_key(F.col("m"), F.col("rhs")))
    return moved.select(
        F.col("dst").alias("rel"), F.array_sort(F.transform("lhs", at)).alias("lhs"), at(F.col("rhs")).alias("rhs"), traces.rename(F.col("trace"), F.col("m")).alias("trace"),
        F.array_sort(F.transform(F.filter("mids", has), at)).alias("mids"), "status", F.col("operator").alias("rule"), (F.col("level") + 1).alias("level"),
    )


def shared_origins(facts) -> DataFrame:
    """a, b: pairs of relations that have a common ancestor, itself included."""
    there = graph.reach(facts.ops.select("dst", "src"), reflexive=True)
    x, y = there.alias("x"), there.alias("y")
    unions = facts.ops.where("operator = 'union'")
    pair = unions.where("operand = 1").select("dst", F.col("src").alias("a")).join(unions.where("operand = 2").select(F.col("dst").alias("d2"), F.col("src").alias("b")), F.col("dst") == F.col("d2")).select("a", "b")
    out = pair.join(x, F.col("a") == F.col("x.dst")).join(y, (F.col("b") == F.col("y.dst")) & (F.col("x.src") == F.col("y.src")))
    return out.select("a", "b").distinct()


class Propagation:
    """The rules over one catalog's facts, with given options."""

    def __init__(self, facts, options: Options = Options()):
        self.facts, self.o = facts, options
        self.rounds: list[list[int]] = []
        self._start: DataFrame | None = None
        self._recursive = [r[0] for r in facts.catalog.recdefs]
        self.ops = facts.ops.where(~F.col("dst").isin(self._recursive)) if self._recursive else facts.ops
        self.in_scope = closure.scope(facts, options.closure_scope)

    @cached_property
    def _origins(self) -> DataFrame | None:
        return shared_origins(self.facts) if self.o.require_shared_origin else None

    def start(self) -> DataFrame:
        """Declared FDs, and those of equalities, constants and calls."""
        if self._start is None:
            self._start = self._first()
        return self._start

    def _first(self) -> DataFrame:
        f = self.facts
        out = f.declared.unionByName(from_equalities(f.eqconds)).unionByName(from_constants(f.constconds))
        out = out.unionByName(from_calls(f.node_calls, self.o.assume_deterministic))
        out = out.where(F.col("rhs").isNotNull())
        return out if self.o.traces == "full" else out.withColumn("trace", F.array().cast("array<string>"))

    def step(self, delta: DataFrame, known: DataFrame, ops: DataFrame | None = None) -> DataFrame:
        """One round of all rules."""
        o, ops = self.o, self.ops if ops is None else ops
        out = carry_same_positions(delta, ops).unionByName(carry_mapped(delta, ops))
        d, k = (x.join(self.in_scope, "rel", "left_semi") for x in (delta, known))
        out = out.unionByName(closure.step(d, k, o.prune, o.traces == "full", True, o.max_lhs))
        if o.unions == "trace" and o.traces == "full":
            out = out.unionByName(combine.both_ways(delta, known, lambda a, b: combine.union_by_trace(a, b, ops, self._origins)))
            if o.discriminated:
                out = out.unionByName(combine.both_ways(delta, known, lambda a, b: combine.union_discriminated(a, b, ops)))
        if o.unions == "naive":
            out = out.unionByName(combine.both_ways(delta, known, lambda a, b: combine.union_naive(a, b, ops)))
        # a trace that names a lost column cannot be a fact
        return out.where(F.forall("trace", lambda t: t.isNotNull()))

    def settle(self, start: DataFrame, ops: DataFrame | None = None) -> DataFrame:
        found, sizes = seminaive(start, lambda d, k: self.step(d, k, ops), closure.KEY, self.o.max_rounds)
        self.rounds.append(sizes)
        return found

    # --- level by level -----------------------------------------------------------

    def levels(self) -> list[list[str]]:
        """Relations by level, recursive ones after their base case; their steps come above them."""
        nodes, out = self.facts.catalog.nodes, []
        back = {r[0]: r[2] for r in self.facts.catalog.recdefs}
        depth: dict[str, int] = dict.fromkeys(self.facts.catalog.bases, 0)
        todo = list(nodes)
        while todo:
            rel = todo[-1]
            below = [s for s in nodes[rel].inputs if s != back.get(rel)]
            open_ = [s for s in below if s not in depth]
            if rel in depth:
                todo.pop()
            elif open_:
                todo += open_
            else:
                depth[rel] = 1 + max((depth[s] for s in below), default=-1)
                todo.pop()
        for rel, d in depth.items():
            out += [[] for _ in range(d + 1 - len(out))]
            out[d].append(rel)
        return out

    def _level_facts(self, rels: list[str], below: DataFrame, added: DataFrame) -> DataFrame:
        """All facts of one level's relations, given those below. Only the rules that the level's operators need are planned."""
        o, nodes = self.o, self.facts.catalog.nodes
        own = [nodes[r] for r in rels if r in nodes]
        ops = self.facts.ops.where(F.col("dst").isin(rels))
        parts = [added.where(F.col("rel").isin(rels))] if any(n.eqs or n.consts or n.calls for n in own) or len(own) < len(rels) else []
        if any(n.operator in KEEPING for n in own):
            parts.append(carry_same_positions(below, ops))
        if any(m is not None for n in own for m in n.maps):
            parts.append(carry_mapped(below, ops))
        if any(n.operator == "union" for n in own):
            near = below.where(F.col("rel").isin([s for n in own for s in n.inputs]))
            if o.unions == "trace" and o.traces == "full":
                parts.append(combine.union_by_trace(near, near, ops, self._origins))
                if o.discriminated:
                    parts.append(combine.union_discriminated(near, near, ops))
            if o.unions == "naive":
                parts.append(combine.union_naive(near, near, ops))
        if not parts:
            return below.where(F.lit(False))
        made = parts[0]
        for p in parts[1:]:
            made = made.unionByName(p)
        made = made.select(*closure.COLUMNS).where(F.forall("trace", lambda t: t.isNotNull()))
        closing = [r for r in rels if r in self._scope_names]
        if closing:
            rest = made.where(~F.col("rel").isin(closing)) if len(closing) < len(rels) else None
            made = closure.close_grouped(made.where(F.col("rel").isin(closing)), o.prune, o.traces == "full", True, o.max_lhs)
            made = made if rest is None else made.unionByName(rest)
        return made

    @property
    def _scope_names(self) -> set[str]:
        """closure.scope() for the planner, from the catalog."""
        cat, wide = self.facts.catalog, self.o.closure_scope == "all"
        kinds = {"join", "intersection", "product", "union", "recursion"} if wide else {"join"}
        return set(cat.bases) | {n.name for n in cat.nodes.values() if n.operator in kinds or n.eqs or n.consts or n.closing or (wide and n.calls)}

    def climb(self, levels: list[list[str]], table: Growing, added: DataFrame) -> None:
        """Adds the facts of each level to table."""
        from depscope.operators import recursion  # it reads this module's options only

        recs = {r[0]: r for r in self.facts.catalog.recdefs}
        for rels in levels:
            plain = [r for r in rels if r not in recs]
            if plain:
                table.add(self._level_facts(plain, table.all(), added))
            own = [recs[r] for r in rels if r in recs]
            if own and self.o.recursion != "none":
                table.add(recursion.conclude(self, table.all(), own, self.o.recursion)[0])

    def _climbed(self) -> DataFrame:
        added = self.start()
        table = Growing(self.facts.spark, added.schema)
        table.add(added.where(F.lit(False)))
        levels = self.levels()
        self.climb(levels, table, added)
        self.rounds.append([len(x) for x in levels])
        return table.all()

    def pushed(self, facts_so_far: DataFrame, candidates: DataFrame, inside: list[str], recursive: list[str]) -> DataFrame:
        """Facts and candidates of the relations inside recursions' steps, level by level."""
        start = facts_so_far.where(~F.col("rel").isin([*inside, *recursive])).unionByName(candidates)
        table = Growing(self.facts.spark, candidates.schema)
        for rels in self.levels():
            own = [r for r in rels if r in inside]
            if own:
                table.add(self._level_facts(own, start.unionByName(table.all()) if table.paths else start, self.start()))
        return table.all()

    def run(self) -> DataFrame:
        from depscope.operators import inmemory, recursion

        strategy = self.o.strategy
        if strategy == "auto":
            strategy = "memory" if len(self.facts.catalog.nodes) + len(self.facts.catalog.bases) <= IN_MEMORY else "levels"
        if strategy == "memory":
            return local(self.facts.spark, inmemory.least(inmemory.Climb(self).run()), struct("fd"))
        if strategy == "levels":
            return _least(self._climbed())
        found = self.settle(self.start())
        if self.o.recursion != "none":
            for rec in recursion.ordered(self.facts.catalog):
                kept, _ = recursion.conclude(self, found, [rec], self.o.recursion)
                found = self.settle(found.unionByName(kept)) if not kept.isEmpty() else found
        return _least(found)


def _least(found: DataFrame) -> DataFrame:
    """One row for each (rel, lhs, rhs, trace, status): the first derivation's rule and round, the fewest mids."""
    return found.groupBy("rel", "lhs", "rhs", "trace", "status").agg(F.min(F.struct("level", "rule", "mids")).alias("b")).select("rel", "lhs", "rhs", "trace", F.col("b.mids").alias("mids"), "status", F.col("b.rule").alias("rule"), F.col("b.level").alias("level"))


def run(facts, **options) -> DataFrame:
    """FD facts of every relation: rel, lhs, rhs, trace, mids, status, rule, level."""
    return Propagation(facts, Options(**options)).run()


def named(fd: DataFrame, facts) -> DataFrame:
    """rel, lhs, rhs, trace, rule with column names, for base relations and registered views."""
    cols = facts.attrs.groupBy(F.col("rel").alias("of")).agg(F.map_from_entries(F.collect_list(F.struct("pos", "name"))).alias("names"))
    return fd.join(cols, fd["rel"] == cols["of"]).select(
        "rel", F.array_join(F.transform("lhs", lambda c: F.element_at(F.col("names"), c)), ",").alias("lhs"), F.element_at("names", F.col("rhs")).alias("rhs"), traces.render(F.col("trace")).alias("trace"), "rule",
    )


STEPS = "step int, rel string, lhs string, rhs int, rule string, premises string, term string"


def explain_fd(facts, rel: str, lhs: list[int], rhs: int, **options) -> DataFrame:
    """step, rel, lhs, rhs, rule, premises, term: a derivation of an FD, rule by rule; premises are the numbers of earlier steps. Empty if it isn't derived.

    The shortest of its derivations by level is told, from the rules run over the catalog in memory.
    """
    from depscope.operators import inmemory

    rows = inmemory.Climb(Propagation(facts, Options(**options))).run()
    goals = [r for r in rows if r["rel"] == rel and r["lhs"] == tuple(sorted(lhs)) and r["rhs"] == rhs and r["status"] == "fact"]
    if not goals:
        return local(facts.spark, [], STEPS)
    steps = inmemory.derivation(min(goals, key=lambda r: (r["level"], len(r["trace"]), r["trace"])))
    number = {id(r): i for i, r in enumerate(steps, 1)}
    told = [(i, r["rel"], ",".join(map(str, r["lhs"])), r["rhs"], r["rule"], ",".join(str(number[id(w)]) for w in r.get("why", ())), " ".join(r["trace"])) for i, r in enumerate(steps, 1)]
    return local(facts.spark, told, STEPS)


def explain_path(edges: DataFrame, dst: str, src: str) -> DataFrame:
    """path_no, step, dst, src, kind: the edges of every path that makes dst depend on src."""
    paths = graph.explain(edges, dst, src).select(F.row_number().over(Window.orderBy(F.array_join("path", " "))).alias("path_no"), "path")
    hops = paths.select("path_no", F.posexplode(F.zip_with(F.slice("path", 1, F.size("path") - 1), F.slice("path", 2, F.size("path")), lambda a, b: F.struct(a.alias("src"), b.alias("dst")))).alias("step", "hop"))
    kinds = edges.select(F.col("dst").alias("d"), F.col("src").alias("s"), "kind").distinct()
    return hops.join(kinds, (F.col("hop.dst") == F.col("d")) & (F.col("hop.src") == F.col("s"))).select("path_no", (F.col("step") + 1).alias("step"), "hop.dst", "hop.src", "kind")


def explain(row) -> str:
    """A fact in words: what it says, the rule that made it, the term that computes it and the base FDs it rests on."""
    origins = sorted({t[2:].rpartition("/")[0] for t in row["trace"] if t.startswith("F:")})
    left = "{" + ",".join(map(str, row["lhs"])) + "}"
    return f"{row['rel']}: {left} -> {row['rhs']} by {row['rule']} in round {row['level']}; term {traces.pretty(row['trace'])}; rests on {', '.join(origins) or 'no base FD'}"
