"""Sharding by size-tiered compaction.

A store is a folder of immutable runs, each a folder of Parquet shards, and of numbered manifests that name the live runs.
An arrival is appended as a run of small shards. Runs lie in tiers by size (a tier's runs are up to ``FANOUT`` times the
tier below); a tier with ``FANOUT`` runs or more is merged into one run of shards of about ``TARGET_BYTES``, and
tiers are looked at again until none is full. A merge reads and writes each row once and shuffles nothing: tasks take
whole small shards together. A manifest is written beside and moved to its number, which is claimed first, so a
reader sees one version or the next, and of two writers one fails. A run becomes visible by a manifest only; what a lost driver or
executor leaves behind is never read, and ``recover`` clears it. Merged runs stay until ``vacuum``, so that readers of earlier versions go on.

Defined results: null texts count 0 bytes; an empty table makes a version without runs; rows that repeat stay as often as
they came; all columns are kept as they are, and an added column whose name is taken gets underscores behind it; an arrival may be of any size.
"""

from __future__ import annotations

import json
import math
import uuid
from dataclasses import asdict, dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.llm.common import hash_key, scratch_path, table, text_or_empty

#: Size of a shard of a merged run; a run of this many bytes or fewer is one shard.
TARGET_BYTES = 64 << 20
#: Runs that fill a tier, and the size of the lowest tier's largest run.
FANOUT, BASE_BYTES = 4, 1 << 20


@dataclass(frozen=True)
class Run:
    """A live run: its folder, rows, bytes of text, and how many merges deep it is."""

    name: str
    path: str
    rows: int
    size: int
    level: int


def free_name(name: str, taken: list[str]) -> str:
    """name, with underscores behind it until no column has it."""
    low = {c.lower() for c in taken}
    while name.lower() in low:
        name += "_"
    return name


def tier(size: int) -> int:
    """How many powers of FANOUT a size is over BASE_BYTES."""
    t = 0
    while size >= BASE_BYTES * FANOUT**t:
        t += 1
    return t


class Store:
    """A shard store in a folder that all executors share."""

    def __init__(self, spark: SparkSession, path: str, target_bytes: int = TARGET_BYTES):
        self.spark, self.path, self.target_bytes = spark, path.rstrip("/"), target_bytes
        self._fs = self._hadoop(self.path).getFileSystem(spark._jsc.hadoopConfiguration())

    def _hadoop(self, path: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(path)

    def versions(self) -> list[int]:
        return sorted(int(n[:-5]) for n in self._names("manifests") if n.endswith(".json"))

    def runs(self, version: int | None = None) -> list[Run]:
        """The runs of a version, the latest by default."""
        known = self.versions()
        if not known and version is None:
            return []
        stream = self._fs.open(self._hadoop(f"{self.path}/manifests/{version or known[-1]:08d}.json"))
        try:
            text = self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return [Run(**r) for r in json.loads(text)["runs"]]

    def commit(self, runs: list[Run], after: int) -> int:
        """Makes runs version after + 1; fails if another writer has claimed that number."""
        version = after + 1
        folder = f"{self.path}/manifests"
        if not self._fs.createNewFile(self._hadoop(f"{folder}/{version:08d}.claim")):
            raise RuntimeError(f"version {version} of {self.path} is taken")
        draft = self._hadoop(f"{folder}/{version:08d}.{uuid.uuid4().hex}.draft")
        out = self._fs.create(draft, False)
        out.write(bytearray(json.dumps({"version": version, "runs": [asdict(r) for r in runs]}).encode()))
        out.close()
        if not self._fs.rename(draft, self._hadoop(f"{folder}/{version:08d}.json")):
            raise RuntimeError(f"version {version} of {self.path} could not be moved into place")
        return version

    def _latest(self) -> int:
        return (self.versions() or [0])[-1]

    def append(self, df: DataFrame, arrival: Column, size: Column) -> int:
        """Writes df's arrivals, one run for each value of arrival (short, file-name safe strings), and commits them together."""
        before, folder = self._latest(), f"{self.path}/runs/{uuid.uuid4().hex}"
        name = free_name("arrival", df.columns)
        rows = df.withColumn(name, arrival)
        rows.write.partitionBy(name).parquet(folder)
        # one row an arrival comes back
        back = self.spark.read.schema(rows.schema).parquet(folder)
        sums = back.groupBy(F.col(name).alias("a")).agg(F.count("*").alias("n"), F.sum(size).alias("b")).orderBy("a").collect()
        made = [Run(r["a"], f"{folder}/{name}={r['a']}", r["n"], int(r["b"] or 0), 0) for r in sums]
        return self.commit([*self.runs(), *made], before)

    def full_tier(self) -> list[Run]:
        """The runs of the lowest tier that is full."""
        by: dict[int, list[Run]] = {}
        for r in self.runs():
            by.setdefault(tier(r.size), []).append(r)
        return next((sorted(by[t], key=lambda r: r.name) for t in sorted(by) if len(by[t]) >= FANOUT), [])

    def compact(self, schema) -> int:
        """Merges full tiers until none is left; each merge is a version. Returns the latest version."""
        while merged := self.full_tier():
            before, size = self._latest(), sum(r.size for r in merged)
            level = 1 + max(r.level for r in merged)
            run = Run(f"m{level}-{merged[0].name}", f"{self.path}/runs/{uuid.uuid4().hex}", sum(r.rows for r in merged), size, level)
            rows = self.spark.read.schema(schema).parquet(*(r.path for r in merged))
            rows.coalesce(max(1, math.ceil(size / self.target_bytes))).write.parquet(run.path)
            gone = {r.path for r in merged}
            self.commit([r for r in self.runs() if r.path not in gone] + [run], before)
        return self._latest()

    def tidy(self, schema) -> int:
        """Rewrites runs whose shards are far below target size, each by itself: an arrival that no merge has taken yet comes in a shard for each
        task that wrote it. A run keeps its name, size and level; all rewritten runs are one version. Returns the latest version."""
        before, runs = self._latest(), self.runs()
        made = {}
        for r in runs:
            wanted = max(1, math.ceil(r.size / self.target_bytes))
            if self._shards(r) > 2 * wanted:
                path = f"{self.path}/runs/{uuid.uuid4().hex}"
                self.spark.read.schema(schema).parquet(r.path).coalesce(wanted).write.parquet(path)
                made[r.path] = replace(r, path=path)
        return self.commit([made.get(r.path, r) for r in runs], before) if made else before

    def _shards(self, run: Run) -> int:
        return sum(s.getPath().getName().endswith(".parquet") for s in self._fs.listStatus(self._hadoop(run.path)))

    def vacuum(self, keep: int = 1) -> None:
        """Drops all but the latest keep versions, then the runs that only those name. Claims stay: a number is never given twice."""
        known = self.versions()
        old = known[: max(len(known) - keep, 0)]
        live = {r.path for v in known[len(old) :] for r in self.runs(v)}
        gone = {r.path for v in old for r in self.runs(v)} - live
        for v in old:
            self._fs.delete(self._hadoop(f"{self.path}/manifests/{v:08d}.json"), False)
        for path in gone:
            self._fs.delete(self._hadoop(path), True)

    def recover(self) -> None:
        """Clears what lost writers left: drafts, claims above the latest version, and run folders that no version names. Only while nothing writes."""
        latest = self._latest()
        for name in self._names("manifests"):
            if name.endswith(".draft") or (name.endswith(".claim") and int(name[:-6]) > latest):
                self._fs.delete(self._hadoop(f"{self.path}/manifests/{name}"), False)
        start = len(f"{self.path}/runs/")
        live = {r.path[start:].split("/")[0] for v in self.versions() for r in self.runs(v)}
        for name in set(self._names("runs")) - live:
            self._fs.delete(self._hadoop(f"{self.path}/runs/{name}"), True)

    def _names(self, part: str) -> list[str]:
        folder = self._hadoop(f"{self.path}/{part}")
        return [s.getPath().getName() for s in self._fs.listStatus(folder)] if self._fs.exists(folder) else []

    def read(self, schema, version: int | None = None) -> DataFrame:
        """The rows of a version with their run, tier and shard. A store has few runs: under FANOUT for each tier."""
        names = [free_name(n, schema.names) for n in ("run", "tier", "shard")]

        def placed(rows: DataFrame, run: str, level: int, shard: Column) -> DataFrame:
            return rows.select("*", *(c.alias(n) for c, n in zip((F.lit(run), F.lit(level), shard), names, strict=True)))

        shard = F.element_at(F.split(F.input_file_name(), "/"), -1)
        parts = [placed(self.spark.read.schema(schema).parquet(r.path), r.name, tier(r.size), shard) for r in self.runs(version)]
        if not parts:
            return placed(self.spark.createDataFrame([], schema), "", 0, F.lit(""))
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


def text_bytes() -> Column:
    return F.octet_length(text_or_empty()).cast("long")


def arrival_of(doc_id: Column) -> Column:
    """A stand-in for the time of arrival, by hash: one arrival of half the rows, four of a sixteenth, sixteen of a sixty-fourth."""
    key = hash_key(doc_id)
    first, second = F.substring(key, 1, 1), F.substring(key, 2, 1)
    quarter = F.floor(F.conv(second, 16, 10).cast("int") / 4).cast("string")
    return F.when(first < "8", F.lit("a")).when(first < "c", F.concat(F.lit("b"), first)).otherwise(F.concat(F.lit("c"), first, quarter))


def sharded(docs: DataFrame, path: str | None = None, target_bytes: int = TARGET_BYTES) -> DataFrame:
    """docs through a store: appended by arrival, compacted, and read back with run, tier and shard."""
    spark = docs.sparkSession
    store = Store(spark, path or scratch_path(spark, "shards"), target_bytes)
    schema = docs.schema
    store.append(docs, arrival_of(F.col("doc_id")), text_bytes())
    store.compact(schema)
    store.tidy(schema)
    store.vacuum()
    return store.read(schema)


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sharded(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", text_bytes().alias("n_bytes"), arrival_of(F.col("doc_id")).alias("arrival"), "run", "tier")


def _oracle(rounds: int = 3) -> str:
    """DuckDB SQL of op1: each round merges the lowest full tier, as often as arrivals can fill one."""
    tiers = lambda size: "(" + " + ".join(f"({size} >= {BASE_BYTES * FANOUT**t})::INT" for t in range(14)) + ")"
    sql = f"""
WITH k AS (
  SELECT doc_id, coalesce(strlen(text), 0)::BIGINT AS n_bytes, md5(coalesce(doc_id::VARCHAR, '')) AS key FROM documents
), d AS (
  SELECT doc_id, n_bytes, CASE WHEN key[1] < '8' THEN 'a' WHEN key[1] < 'c' THEN 'b' || key[1]
    ELSE 'c' || key[1] || floor((position(key[2] IN '0123456789abcdef') - 1) / 4)::INT END AS arrival FROM k
), r0 AS (
  SELECT arrival, arrival AS run, 0 AS level, sum(n_bytes)::BIGINT AS size FROM d GROUP BY arrival
), t0 AS (
  SELECT *, {tiers("size")} AS tier FROM r0
)"""
    for i in range(1, rounds + 1):
        sql += f""", g{i} AS (
  SELECT min(tier) AS tier FROM (SELECT tier FROM t{i - 1} GROUP BY tier HAVING count(DISTINCT run) >= {FANOUT})
), m{i} AS (
  SELECT 'm' || (max(level) + 1) || '-' || min(run) AS run, max(level) + 1 AS level, sum(size)::BIGINT AS size
  FROM (SELECT DISTINCT run, level, size FROM t{i - 1} WHERE tier = (SELECT tier FROM g{i}))
), t{i} AS (
  SELECT arrival, coalesce(m{i}.run, t.run) AS run, coalesce(m{i}.level, t.level) AS level, coalesce(m{i}.size, t.size) AS size,
    {tiers(f"coalesce(m{i}.size, t.size)")} AS tier
  FROM t{i - 1} t LEFT JOIN m{i} ON t.tier = (SELECT tier FROM g{i})
)"""
    return sql + f"\nSELECT doc_id, n_bytes, arrival, run, tier::INT AS tier FROM d JOIN t{rounds} USING (arrival)\n"


OP1_SQL = _oracle()
