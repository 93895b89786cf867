"""User-defined rules over the facts, and the shipped questions as plain SQL."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.operators.fixpoint import Growing
from depscope.operators.traits import KEEPING
from depscope.sources.facts import Catalog


class Rules:
    """Rules by name; each becomes a temporary view that later rules can read. Facts are the views ds_<fact>."""

    def __init__(self, facts, prefix: str = "ds_"):
        self.spark: SparkSession = facts.spark
        facts.register_views(prefix)

    def define(self, name: str, sql: str) -> DataFrame:
        """A rule that reads facts and earlier rules."""
        df = self.spark.sql(sql)
        df.createOrReplaceTempView(name)
        return df

    def define_recursive(self, name: str, base_sql: str, step_sql: str, max_rounds: int | None = None) -> DataFrame:
        """A rule that reads itself: in step_sql, <name> is the rows that were new in the last round (semi-naive, linear)."""
        delta = self.spark.sql(base_sql).distinct()
        table = Growing(self.spark, delta.schema)
        delta = table.add(delta)
        for _ in range(max_rounds) if max_rounds else count():
            delta.createOrReplaceTempView(name)
            made = self.spark.sql(step_sql).toDF(*delta.columns).distinct()
            known = table.all()
            on = [made[c].eqNullSafe(known[c]) for c in delta.columns]
            delta = table.add(made.join(known, on, "left_anti"))
            if delta.isEmpty():
                table.all().createOrReplaceTempView(name)
                return table.all()
        raise RuntimeError(f"rule {name} did not settle in {max_rounds} rounds")


REACH = "WITH RECURSIVE path(dst, src) AS (SELECT dst, src FROM {edges} UNION SELECT e.dst, p.src FROM path p JOIN {edges} e ON e.src = p.dst) "
QUESTIONS = {
    "reused_attribute_names": "SELECT DISTINCT a.rel AS r1, b.rel AS r2, a.name AS name FROM {attrs} a JOIN {attrs} b ON a.name = b.name AND a.rel <> b.rel",
    "views_calling_functions": "SELECT DISTINCT d.name AS view FROM {derived_rels} d JOIN {calls} c ON c.rel = d.name",
    "affected_views": REACH + "SELECT DISTINCT p.dst AS view FROM path p JOIN {derived_rels} d ON d.name = p.dst WHERE p.src = '{arg}'",
    "tables_changed_by": REACH + "SELECT DISTINCT p.dst AS \"table\" FROM path p JOIN {base_rels} b ON b.name = p.dst WHERE p.src = '{arg}'",
    "tables_linked_by_function": REACH
    + "SELECT DISTINCT x.dst AS a, y.src AS b, f.name AS fn FROM path x JOIN {funcs} f ON x.src = f.name JOIN path y ON y.dst = f.name JOIN {base_rels} p ON p.name = x.dst JOIN {base_rels} q ON q.name = y.src",
}


def to_sql(question: str, prefix: str = "ds_", arg: str = "") -> str:
    """A question as standard SQL with WITH RECURSIVE ... UNION, for databases that have it."""
    names = {n: prefix + n for n in ("edges", "attrs", "derived_rels", "base_rels", "calls", "funcs")}
    return QUESTIONS[question].format(**names, arg=arg)


def literal_table(df: DataFrame, columns: list[str]) -> str:
    """A small fact table as a parenthesised SQL VALUES list, so that a question's text can stand alone."""
    rows = df.select(*(F.col(c).cast("string") for c in columns)).collect()
    quote = lambda v: "NULL" if v is None else "'" + v.replace("'", "''") + "'"
    values = ", ".join("(" + ", ".join(map(quote, r)) + ")" for r in rows) or "(" + ", ".join("NULL" for _ in columns) + ")"
    return f"(SELECT * FROM (VALUES {values}) AS t({', '.join(columns)}))"


# --- the FD rules as SQL ------------------------------------------------------------

#: Operators that keep positions, as SQL sees them.
_KEEPING = ", ".join(f"'{k}'" for k in KEEPING)
_FIRST = """
  SELECT rel, list_sort(lhs) AS lhs, rhs, list_concat(['F:' || fid || '/' || len(lhs)], list_transform(lhs, lambda c: '#' || c)) AS trace, CAST([] AS INT[]) AS mids FROM {declared}
  UNION SELECT rel, [pos1], pos2, ['#' || pos1], CAST([] AS INT[]) FROM {eqconds}
  UNION SELECT rel, [pos2], pos1, ['#' || pos2], CAST([] AS INT[]) FROM {eqconds}
  UNION SELECT rel, CAST([] AS INT[]), pos, [CASE WHEN value IS NULL THEN 'N:' || type ELSE 'K:' || type || ':' || value END], CAST([] AS INT[]) FROM {constconds}
  UNION SELECT rel, list_sort(list_distinct(inputs)), output, list_concat([fingerprint || '/' || len(inputs)], list_transform(inputs, lambda c: '#' || c)), CAST([] AS INT[])
    FROM {node_calls} WHERE deterministic AND NOT list_contains(inputs, output)"""
_ROUND = """
  SELECT * FROM {f}
  UNION
  SELECT o.dst, f.lhs, f.rhs, f.trace, f.mids FROM {f} f JOIN {ops} o ON o.src = f.rel
    WHERE o.m IS NULL AND o.operator IN ({keeping}) AND NOT (o.operator = 'negation' AND o.operand = 2)
  UNION
  SELECT o.dst, list_sort(list_transform(f.lhs, lambda c: o.m[c])), o.m[f.rhs],
      list_transform(f.trace, lambda t: CASE WHEN t LIKE '#%' THEN '#' || o.m[TRY_CAST(substr(t, 2) AS INT)] ELSE t END),
      list_sort(list_filter(list_transform(f.mids, lambda c: o.m[c]), lambda c: c IS NOT NULL))
    FROM {f} f JOIN {ops} o ON o.src = f.rel
    WHERE o.m IS NOT NULL AND o.m[f.rhs] IS NOT NULL AND len(list_filter(f.lhs, lambda c: o.m[c] IS NULL)) = 0
      AND len(list_filter(f.trace, lambda t: t LIKE '#%' AND o.m[TRY_CAST(substr(t, 2) AS INT)] IS NULL)) = 0
  UNION
  SELECT rel, lhs, rhs, trace, mids FROM (
    SELECT a.rel, list_sort(list_distinct(list_concat(a.lhs, list_filter(g.lhs, lambda c: c <> a.rhs)))) AS lhs, g.rhs,
        flatten(list_transform(g.trace, lambda t: CASE WHEN t = '#' || a.rhs THEN a.trace ELSE [t] END)) AS trace,
        list_sort(list_distinct(list_concat(a.mids, g.mids, [a.rhs]))) AS mids
      FROM {f} a JOIN {f} g ON a.rel = g.rel AND list_contains(g.lhs, a.rhs) AND NOT list_contains(a.lhs, g.rhs)
      WHERE a.rel IN (SELECT rel FROM closing)) c
    WHERE NOT list_contains(lhs, rhs) AND NOT list_contains(mids, rhs) AND NOT list_has_any(lhs, mids)
  UNION
  SELECT a.rel, [a.rhs], b.rhs, ['#' || a.rhs], CAST([] AS INT[]) FROM {f} a JOIN {f} b ON a.rel = b.rel AND a.lhs = b.lhs AND a.trace = b.trace AND a.rhs <> b.rhs
    WHERE a.rel IN (SELECT rel FROM closing)
  UNION
  SELECT o.dst, a.lhs, a.rhs, a.trace, list_sort(list_distinct(list_concat(a.mids, b.mids)))
    FROM {ops} o JOIN {ops} p ON o.dst = p.dst AND o.operand = 1 AND p.operand = 2 AND o.operator = 'union'
    JOIN {f} a ON a.rel = o.src JOIN {f} b ON b.rel = p.src AND a.lhs = b.lhs AND a.rhs = b.rhs AND a.trace = b.trace"""
_CLOSING = """
  SELECT name AS rel FROM {base_rels} UNION SELECT dst FROM {ops} WHERE operator = 'join' UNION SELECT rel FROM {eqconds} UNION SELECT rel FROM {constconds}"""


def fd_rules_sql(rounds: int, tables: dict[str, str] | None = None, facts: dict[str, str] | None = None) -> str:
    """The propagation rules as one SQL statement without recursion, a common table for each round: facts that hold after ``rounds`` rounds.

    ``tables`` names the fact tables declared, ops, eqconds, constconds, node_calls and base_rels where they are called otherwise; ``facts`` gives
    their contents as queries (literal_facts), for a database that has no such tables. The transitive rule reads all facts twice,
    which recursive SQL doesn't allow; a schema of known depth needs a known number of rounds. List functions and maps are DuckDB's.
    """
    tables = {n: n for n in ("declared", "ops", "eqconds", "constconds", "node_calls", "base_rels")} | (tables or {})
    parts = [f"{name} AS ({query})" for name, query in (facts or {}).items()]
    parts += [f"closing AS ({_CLOSING.format(**tables)})", f"f0 AS MATERIALIZED ({_FIRST.format(**tables)})"]
    parts += [f"f{i + 1} AS MATERIALIZED ({_ROUND.format(f=f'f{i}', keeping=_KEEPING, **tables)})" for i in range(rounds)]
    return "WITH " + ", ".join(parts) + f" SELECT DISTINCT rel, array_to_string(lhs, ',') AS lhs, rhs, array_to_string(trace, ' ') AS trace FROM f{rounds}"


def literal_facts(catalog: Catalog) -> dict[str, str]:
    """A catalog's facts as SELECTs over literal rows, by the names that fd_rules_sql gives them."""

    def value(v) -> str:
        if v is None:
            return "NULL"
        if isinstance(v, bool):
            return str(v)
        if isinstance(v, dict):
            return "MAP {" + ", ".join(f"{k}: {x}" for k, x in v.items()) + "}"
        if isinstance(v, (list, tuple)):
            return "[" + ", ".join(map(str, v)) + "]"
        return str(v) if isinstance(v, int) else "'" + v.replace("'", "''") + "'"

    def table(columns: str, rows: list[tuple]) -> str:
        names, types = zip(*(c.split(" ", 1) for c in columns.split(", ")), strict=True)
        parts = [", ".join(f"CAST({value(v)} AS {t}) AS {n}" for n, t, v in zip(names, types, r, strict=True)) for r in rows or [(None,) * len(names)]]
        return " UNION ALL ".join(f"SELECT {p}" + ("" if rows else " WHERE false") for p in parts)

    nodes = list(catalog.nodes.values())
    return {
        "declared": table("rel VARCHAR, lhs INT[], rhs INT, fid VARCHAR", [(b.name, list(lhs), rhs, fid) for b in catalog.bases.values() for lhs, rhs, fid in b.fds]),
        "ops": table("dst VARCHAR, src VARCHAR, operator VARCHAR, operand INT, m MAP(INT,INT)", [(n.name, s, n.operator, i, m) for n in nodes for i, (s, m) in enumerate(zip(n.inputs, n.maps, strict=True), 1)]),
        "eqconds": table("rel VARCHAR, pos1 INT, pos2 INT", [(n.name, a, b) for n in nodes for a, b in n.eqs]),
        "constconds": table("rel VARCHAR, pos INT, value VARCHAR, type VARCHAR", [(n.name, p, v, t) for n in nodes for p, v, t in n.consts]),
        "node_calls": table("rel VARCHAR, inputs INT[], output INT, fingerprint VARCHAR, deterministic BOOLEAN", [(n.name, list(c.inputs), c.output, c.fingerprint, c.deterministic) for n in nodes for c in n.calls]),
        "base_rels": table("name VARCHAR", [(b,) for b in catalog.bases]),
    }
