"""The schema registry: tables, views, functions and triggers are compiled to facts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from depscope.operators import recursion
from depscope.plans import rule_text
from depscope.plans.plan_reader import Reader
from depscope.sources.facts import Base, Call, Catalog, FactStore, OpNode


class SchemaRegistry:
    """Collects schema objects; facts() gives their fact tables. Names share one space, as temporary views do.

    outer_joins: 'kept' reads an outer join as its kept side (a full one as nothing), 'united' as the inner join united with the padded rest
    of each kept side, which gives more FDs and more relations.
    """

    def __init__(self, spark: SparkSession, outer_joins: str = "kept"):
        self.spark, self.catalog, self.outer_joins = spark, Catalog(), outer_joins
        self._ids: set[str] = set()

    # --- base relations -----------------------------------------------------------

    def add_table(self, name: str, df: DataFrame | list[str], keys: list[list[str]] | None = None, fds: list[tuple[list[str], str]] | None = None) -> None:
        """A base relation: a DataFrame (also made a temporary view) or column names alone. A key gives one FD for each other column."""
        if isinstance(df, DataFrame):
            df.createOrReplaceTempView(name)
            columns = [(f.name, f.dataType.simpleString()) for f in df.schema.fields]
        else:
            columns = [(c, "any") for c in df]
        self.catalog.bases[name] = Base(name, columns)
        for key in keys or []:
            self.declare_key(name, key)
        for lhs, rhs in fds or []:
            self.declare_fd(name, lhs, rhs)

    def _position(self, rel: str, column: str | int) -> int:
        return column if isinstance(column, int) else [c for c, _ in self.catalog.bases[rel].columns].index(column) + 1

    def declare_fd(self, rel: str, lhs: list, rhs, fid: str | None = None) -> list[str]:
        """One FD, and one unique id, for each right-side column; sources keep their declared order."""
        sides = rhs if isinstance(rhs, list) else [rhs]
        left = tuple(dict.fromkeys(self._position(rel, c) for c in lhs))
        made = []
        for r in (self._position(rel, c) for c in sides):
            if r in left:
                continue
            one = fid if fid and len(sides) == 1 else f"{fid or rel}.{''.join(map(str, left))}>{r}"
            if one in self._ids:
                if any(f == (left, r, one) for f in self.catalog.bases[rel].fds):
                    continue
                raise ValueError(f"FD id {one} is taken")
            self._ids.add(one)
            self.catalog.bases[rel].fds.append((left, r, one))
            made.append(one)
        return made

    def declare_key(self, rel: str, columns: list) -> list[str]:
        key = [self._position(rel, c) for c in columns]
        return self.declare_fd(rel, key, [p for p in range(1, len(self.catalog.bases[rel].columns) + 1) if p not in key])

    # --- derived relations --------------------------------------------------------

    def add_view(self, name: str, query: str | DataFrame) -> DataFrame:
        """A view by SQL or DataFrame; it becomes a temporary view and its analysed plan is read."""
        df = self.spark.sql(query) if isinstance(query, str) else query
        self._adopt(name, Reader(self.catalog, name, self.outer_joins).read(df))
        df.createOrReplaceTempView(name)
        return df

    def add_rules(self, text: str) -> None:
        """Views in rule notation, possibly recursive."""
        nodes = rule_text.lower(self.catalog, text)
        heads = {r.head.rel for r in rule_text.parse(text)}
        for n in nodes:
            self.catalog.nodes[n.name] = n
            if n.name in heads:
                self.catalog.views[n.name] = n.columns
                self._lift_calls(n.name)
        self._find_recursion()

    def add_recursive(self, name: str, base: str | DataFrame, step: str) -> None:
        """A linear recursion: the step reads ``name``. Contents aren't computed here; the step's plan is read against the base's columns."""
        df = self.spark.sql(base) if isinstance(base, str) else base
        base_name, step_name = f"{name}$base", f"{name}$step"
        self._nodes(Reader(self.catalog, base_name, self.outer_joins).read(df))
        self.catalog.nodes[name] = OpNode(name, "union", [base_name, step_name], len(df.columns), columns=[(f.name, f.dataType.simpleString()) for f in df.schema.fields])
        df.createOrReplaceTempView(name)
        self._nodes(Reader(self.catalog, step_name, self.outer_joins).read(self.spark.sql(step)))
        self.catalog.views[name] = self.catalog.nodes[name].columns
        self._find_recursion()

    def _nodes(self, nodes: list[OpNode]) -> None:
        self.catalog.nodes.update({n.name: n for n in nodes})

    def _adopt(self, name: str, nodes: list[OpNode]) -> None:
        self._nodes(nodes)
        self.catalog.views[name] = nodes[-1].columns
        self._lift_calls(name)

    def _lift_calls(self, name: str) -> None:
        """Calls of the view's own nodes, at the view's positions."""
        cat = self.catalog

        def at_view(rel: str, m: dict[int, int], seen: frozenset) -> None:
            node = cat.nodes.get(rel)
            if node is None or rel in seen or (rel in cat.views and rel != name):
                return
            for c in node.calls:
                if c.output in m:
                    known = tuple(sorted(m[i] for i in c.inputs if i in m))
                    call = Call(known, m[c.output], c.fn, c.fingerprint, c.deterministic)
                    if (name, call) not in cat.view_calls:
                        cat.view_calls.append((name, call))
            for src, up in zip(node.inputs, node.maps, strict=True):
                at_view(src, {b: m[h] for b, h in up.items() if h in m} if up is not None else m, seen | {rel})

        at_view(name, {i: i for i in range(1, cat.nodes[name].arity + 1)}, frozenset())

    def _find_recursion(self) -> None:
        self.catalog.recdefs = recursion.detect(self.catalog)

    # --- functions and triggers ---------------------------------------------------

    def add_function(self, name: str, arity: int, reads: list[str] | None = None, writes: list[str] | None = None, kind: str | None = None, deterministic: bool = True, body_sql: str | None = None) -> None:
        """A user function: arity, side effects and a marker of its kind. body_sql also creates it as a temporary SQL function."""
        if body_sql:
            self.spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body_sql}")
        self.catalog.funcs.append((name, arity, kind, deterministic))
        self.catalog.extra_edges += [(name, r, "reads", "+") for r in reads or []] + [(w, name, "writes", "+") for w in writes or []]

    def add_call(self, view: str, inputs: list, output, fn: str) -> None:
        """A call that a view's text doesn't show, such as one of a procedural function."""
        names = [c for c, _ in self.catalog.views[view]]
        at = lambda c: c if isinstance(c, int) else names.index(c) + 1
        fixed = next((f[3] for f in self.catalog.funcs if f[0] == fn), True)
        call = Call(tuple(at(i) for i in inputs), at(output), fn, f"C:{fn}", fixed)
        self.catalog.view_calls.append((view, call))
        self.catalog.nodes[view].calls.append(call)

    def add_trigger(self, name: str, on: str, event: str, action: str, target: str) -> None:
        self.catalog.triggers.append((name, on, event, action, target))

    def facts(self) -> FactStore:
        return FactStore(self.spark, self.catalog)
