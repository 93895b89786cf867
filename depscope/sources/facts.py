"""Fact tables: their schemas, the operator nodes they are made from, and a store that holds them as DataFrames.

Positions are 1-based. Facts are metadata: their number grows with the schema's views, not with the data.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType, _parse_datatype_string

SCHEMAS = {
    "edge": "dst string, src string, kind string, polarity string",
    "base_rel": "name string, arity int",
    "derived_rel": "name string, arity int",
    "attr": "rel string, pos int, name string, type string",
    "func": "name string, arity int, kind string, deterministic boolean",
    "trigger": "name string, on_rel string, event string, action string, action_rel string",
    "call": "rel string, inputs array<int>, output int, fn string, fingerprint string, deterministic boolean",
    "op": "dst string, src string, operator string, operand int, m map<int,int>",
    "eqcond": "rel string, pos1 int, pos2 int",
    "constcond": "rel string, pos int, value string, type string",
    "recdef": "rel string, base_rel string, step_rel string",
    "fd": "rel string, lhs array<int>, rhs int, trace array<string>, mids array<int>, status string, rule string, level int",
}


def struct(name: str) -> StructType:
    return _parse_datatype_string(SCHEMAS[name])


def local(spark: SparkSession, rows: list, schema: StructType | str) -> DataFrame:
    """A DataFrame of a few driver-side rows (tuples or dicts) as a local relation."""
    kind = _parse_datatype_string(schema) if isinstance(schema, str) else schema
    names = kind.fieldNames()
    made = [r if isinstance(r, dict) else dict(zip(names, r, strict=True)) for r in rows]
    made = [{k: list(v.items()) if isinstance(v, dict) else v for k, v in r.items()} for r in made]
    return spark.createDataFrame(pa.Table.from_pylist(made, schema=to_arrow_schema(kind)), schema=kind)


@dataclass(frozen=True)
class Call:
    inputs: tuple[int, ...]
    output: int
    fn: str
    fingerprint: str
    deterministic: bool = True
    #: Positions whose values the output is made of; for an aggregate these are its arguments, not the grouping columns.
    reads: tuple[int, ...] | None = None


@dataclass
class OpNode:
    """One derived relation and the one operator that defines it.

    maps has, for each input, body position -> head position; None where the operator keeps positions.
    """

    name: str
    operator: str
    inputs: list[str]
    arity: int
    maps: list[dict[int, int] | None] = field(default_factory=list)
    eqs: list[tuple[int, int]] = field(default_factory=list)
    consts: list[tuple[int, str | None, str]] = field(default_factory=list)
    calls: list[Call] = field(default_factory=list)
    columns: list[tuple[str, str]] = field(default_factory=list)
    #: Whether transitive FDs are looked for here whatever the scope.
    closing: bool = False

    def __post_init__(self) -> None:
        self.maps = self.maps or [None] * len(self.inputs)


@dataclass
class Base:
    name: str
    columns: list[tuple[str, str]]
    fds: list[tuple[tuple[int, ...], int, str]] = field(default_factory=list)


@dataclass
class Catalog:
    """What was registered, on the driver; FactStore makes DataFrames of it."""

    bases: dict[str, Base] = field(default_factory=dict)
    nodes: dict[str, OpNode] = field(default_factory=dict)
    views: dict[str, list[tuple[str, str]]] = field(default_factory=dict)
    funcs: list[tuple[str, int, str | None, bool]] = field(default_factory=list)
    triggers: list[tuple[str, str, str, str, str]] = field(default_factory=list)
    extra_edges: list[tuple[str, str, str, str]] = field(default_factory=list)
    view_calls: list[tuple[str, Call]] = field(default_factory=list)
    recdefs: list[tuple[str, str, str]] = field(default_factory=list)

    def only_for(self, rels: list[str]) -> Catalog:
        """The part that relations rest on, for questions about a few views of a large schema."""
        kept, todo = set(), list(rels)
        while todo:
            rel = todo.pop()
            if rel not in kept:
                kept.add(rel)
                todo += self.nodes[rel].inputs if rel in self.nodes else []
        return Catalog(
            {k: v for k, v in self.bases.items() if k in kept}, {k: v for k, v in self.nodes.items() if k in kept}, {k: v for k, v in self.views.items() if k in kept},
            self.funcs, self.triggers, self.extra_edges, [x for x in self.view_calls if x[0] in kept], [x for x in self.recdefs if x[0] in kept],
        )

    def arity(self, rel: str) -> int:
        return len(self.bases[rel].columns) if rel in self.bases else self.nodes[rel].arity


class FactStore:
    """The catalog as fact DataFrames."""

    def __init__(self, spark: SparkSession, catalog: Catalog):
        self.spark, self.catalog = spark, catalog

    def _df(self, name: str, rows: list) -> DataFrame:
        return local(self.spark, rows, struct(name))

    @cached_property
    def base_rels(self) -> DataFrame:
        return self._df("base_rel", [(b.name, len(b.columns)) for b in self.catalog.bases.values()])

    @cached_property
    def derived_rels(self) -> DataFrame:
        """The registered views. Helper relations of the normal form are in ops only."""
        return self._df("derived_rel", [(v, len(c)) for v, c in self.catalog.views.items()])

    @cached_property
    def attrs(self) -> DataFrame:
        named = [*((b.name, b.columns) for b in self.catalog.bases.values()), *self.catalog.views.items()]
        return self._df("attr", [(rel, i, n, t) for rel, cols in named for i, (n, t) in enumerate(cols, 1)])

    @cached_property
    def funcs(self) -> DataFrame:
        return self._df("func", self.catalog.funcs)

    @cached_property
    def triggers(self) -> DataFrame:
        return self._df("trigger", self.catalog.triggers)

    @cached_property
    def calls(self) -> DataFrame:
        """Calls at the registered views' own positions."""
        return self._df("call", [(v, list(c.inputs), c.output, c.fn, c.fingerprint, c.deterministic) for v, c in self.catalog.view_calls])

    @cached_property
    def node_calls(self) -> DataFrame:
        """Calls at the positions of the normal form's relations."""
        return self._df("call", [(n.name, list(c.inputs), c.output, c.fn, c.fingerprint, c.deterministic) for n in self.catalog.nodes.values() for c in n.calls])

    @cached_property
    def value_flows(self) -> DataFrame:
        """rel, fro, to: within a relation, the column to is made of the column fro, by a copy or a call."""
        rows = [(n.name, fro, c.output) for n in self.catalog.nodes.values() for c in n.calls for fro in (c.inputs if c.reads is None else c.reads)]
        rows += [(n.name, a, b) for n in self.catalog.nodes.values() if n.operator == "extension" for a, b in n.eqs]
        return local(self.spark, rows, "rel string, fro int, to int")

    @cached_property
    def ops(self) -> DataFrame:
        return self._df("op", [(n.name, src, n.operator, i, m) for n in self.catalog.nodes.values() for i, (src, m) in enumerate(zip(n.inputs, n.maps, strict=True), 1)])

    @cached_property
    def posmaps(self) -> DataFrame:
        ops = self.ops.where("m IS NOT NULL").select(F.col("dst").alias("head"), F.col("src").alias("body"), F.explode("m").alias("body_pos", "head_pos"))
        return ops.select("head", "body", "head_pos", "body_pos")

    @cached_property
    def eqconds(self) -> DataFrame:
        return self._df("eqcond", [(n.name, a, b) for n in self.catalog.nodes.values() for a, b in n.eqs])

    @cached_property
    def constconds(self) -> DataFrame:
        return self._df("constcond", [(n.name, p, v, t) for n in self.catalog.nodes.values() for p, v, t in n.consts])

    @cached_property
    def closing(self) -> DataFrame:
        return local(self.spark, [(n.name,) for n in self.catalog.nodes.values() if n.closing], "rel string")

    @cached_property
    def recdefs(self) -> DataFrame:
        return self._df("recdef", self.catalog.recdefs)

    @cached_property
    def declared(self) -> DataFrame:
        """The base FDs: trace = the FD's own symbol, then its sources in declared order."""
        rows = [
            (b.name, sorted(lhs), rhs, [f"F:{fid}/{len(lhs)}", *(f"#{c}" for c in lhs)], [], "fact", "declared", 0)
            for b in self.catalog.bases.values()
            for lhs, rhs, fid in b.fds
        ]
        return self._df("fd", rows)

    @cached_property
    def edges(self) -> DataFrame:
        """dst, src, kind, polarity between registered objects: views' sources, calls, triggers, side effects."""
        return self._df("edge", sorted(set(self._edge_rows())))

    def _edge_rows(self) -> list[tuple[str, str, str, str]]:
        cat, out = self.catalog, list(self.catalog.extra_edges)
        for view in cat.views:
            out += [(view, src, "reads", sign) for src, sign in _sources(cat, view)]
        named = {f[0] for f in cat.funcs}
        out += [(c.fn, v, "calls", "+") for v, c in cat.view_calls if c.fn in named]
        for name, on_rel, _, _, action_rel in cat.triggers:
            out += [(name, on_rel, "fires", "+"), (action_rel, name, "writes", "+")]
        return out

    def register_views(self, prefix: str = "ds_") -> None:
        """The facts as temporary views, for rules written in SQL."""
        for name in ("edges", "base_rels", "derived_rels", "attrs", "funcs", "triggers", "calls", "ops", "posmaps", "eqconds", "constconds", "recdefs"):
            getattr(self, name).createOrReplaceTempView(prefix + name)

    def write(self, path: str) -> None:
        """Each fact kind as a Parquet table under path."""
        for name in ("edges", "base_rels", "derived_rels", "attrs", "funcs", "triggers", "calls", "ops", "eqconds", "constconds", "recdefs", "declared"):
            getattr(self, name).write.mode("overwrite").parquet(f"{path}/{name}")


def _sources(cat: Catalog, view: str) -> set[tuple[str, str]]:
    """The registered relations that a view's own nodes read, with the sign of the reading."""
    found, todo, seen = set(), [(view, "+")], set()
    while todo:
        rel, sign = todo.pop()
        if (rel, sign) in seen:
            continue
        seen.add((rel, sign))
        for i, src in enumerate(cat.nodes[rel].inputs):
            below = ("-" if sign == "+" else "+") if cat.nodes[rel].operator == "negation" and i == 1 else sign
            if src in cat.bases or src in cat.views:
                found.add((src, below))
            else:
                todo.append((src, below))
    return found


def diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """Fact rows that one version has and the other hasn't: change is 'removed' or 'added'."""
    gone = old.exceptAll(new).select(F.lit("removed").alias("change"), "*")
    return gone.unionByName(new.exceptAll(old).select(F.lit("added").alias("change"), "*"))


def check_fd_invariants(fd: DataFrame) -> DataFrame:
    """FD rows that break the form: a right side inside the left, or a left side that isn't a sorted set."""
    return fd.where(F.array_contains("lhs", F.col("rhs")) | (F.col("lhs") != F.array_sort(F.array_distinct("lhs"))))
