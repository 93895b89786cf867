"""Reading and writing facts and graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from depscope.plans.registry import SchemaRegistry
from depscope.sources.facts import SCHEMAS, struct

#: Edges that a drawing holds at most; a larger graph must be filtered first.
DRAWN = 5_000


def load_tables(spark: SparkSession, folder: str, names: list[str], keys: dict[str, list[list[str]]] | None = None) -> SchemaRegistry:
    """A registry over Parquet tables <folder>/<name>.parquet."""
    r = SchemaRegistry(spark)
    for name in names:
        r.add_table(name, spark.read.parquet(f"{folder}/{name}.parquet"), (keys or {}).get(name))
    return r


def load_catalog(spark: SparkSession, database: str | None = None) -> SchemaRegistry:
    """A registry over the session catalog: tables as base relations, persistent and temporary views left to add_view."""
    r = SchemaRegistry(spark)
    for t in spark.catalog.listTables(database):
        if t.tableType not in ("VIEW", "TEMPORARY"):
            r.add_table(t.name, spark.table(t.name if database is None else f"{database}.{t.name}"))
    return r


def read_facts(spark: SparkSession, path: str, kind: str, form: str = "parquet") -> DataFrame:
    """A dump of one fact kind, with its fixed schema; Parquet, JSON or (kinds without arrays and maps) CSV."""
    if kind not in SCHEMAS:
        raise ValueError(f"{kind} is none of {', '.join(SCHEMAS)}")
    reader = spark.read.schema(struct(kind))
    return reader.option("header", True).csv(path) if form == "csv" else reader.format(form).load(path)


def write_facts(df: DataFrame, path: str, form: str = "parquet") -> None:
    writer = df.write.mode("overwrite")
    writer.option("header", True).csv(path) if form == "csv" else writer.format(form).save(path)


def _bounded(edges: DataFrame) -> list:
    rows = edges.select("dst", "src", "kind", "polarity").orderBy("src", "dst", "kind").limit(DRAWN + 1).collect()
    if len(rows) > DRAWN:
        raise ValueError(f"more than {DRAWN} edges; filter them before drawing")
    return rows


def to_dot(edges: DataFrame) -> str:
    """The graph in DOT, arrows from source to dependant; negative edges are dashed."""
    quote = lambda x: '"' + x.replace('"', '\\"') + '"'
    lines = [f"  {quote(r.src)} -> {quote(r.dst)} [label={quote(r.kind)}{', style=dashed' if r.polarity == '-' else ''}];" for r in _bounded(edges)]
    return "digraph dependencies {\n" + "\n".join(lines) + "\n}\n"


def to_markdown(edges: DataFrame) -> str:
    lines = [f"| {r.src} | {r.kind} | {r.dst} | {r.polarity} |" for r in _bounded(edges)]
    return "| from | kind | to | sign |\n| --- | --- | --- | --- |\n" + "\n".join(lines) + "\n"
