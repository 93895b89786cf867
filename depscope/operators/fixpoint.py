"""Semi-naive iteration over tables in the shared folder."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


class NoSharedFolder(RuntimeError):
    """A cluster whose session names no folder that driver and executors share."""


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which driver and executors share; where it is unset, a temporary folder in local mode and an error on a cluster."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise NoSharedFolder(f"set spark.checkpoint.dir to a folder that all executors of {master} share")
        found = tempfile.mkdtemp(prefix="depscope-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def _hadoop(spark: SparkSession, path: str) -> tuple:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


_SEEN: set[str] = set()


def scratch_root(spark: SparkSession) -> str:
    """This application's folder below shared_dir. It goes when the driver's JVM ends, or with forget_scratch."""
    root = f"{shared_dir(spark)}/depscope-{spark.sparkContext.applicationId}"
    if root not in _SEEN:
        fs, at = _hadoop(spark, root)
        fs.mkdirs(at)
        fs.deleteOnExit(at)
        _SEEN.add(root)
    return root


def delete(spark: SparkSession, path: str) -> None:
    fs, at = _hadoop(spark, path)
    fs.delete(at, True)


def forget_scratch(spark: SparkSession) -> None:
    """Deletes this application's scratch tables; call it once no returned DataFrame is needed any more."""
    root = scratch_root(spark)
    delete(spark, root)
    _SEEN.discard(root)


class Growing:
    """A table that only grows, one Parquet folder a round; every round cuts the lineage."""

    def __init__(self, spark: SparkSession, schema):
        self.spark, self.schema, self.paths = spark, schema, []
        self.root = f"{scratch_root(spark)}/facts-{uuid.uuid4().hex}"

    def add(self, rows: DataFrame) -> DataFrame:
        path = f"{self.root}/{len(self.paths)}"
        rows.write.parquet(path)
        self.paths.append(path)
        return self._read([path])

    def all(self) -> DataFrame:
        return self._read(self.paths)

    def _read(self, paths: list[str]) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(*paths)


class Rounds(RuntimeError):
    """A fixpoint that did not settle in the rounds allowed."""


def seminaive(start: DataFrame, step: Callable[[DataFrame, DataFrame], DataFrame], key: list[str], most: int | None = None, strategy: str = "seminaive") -> tuple[DataFrame, list[int]]:
    """The least fixpoint: start, and what step(delta, known) adds, until nothing is new.

    step must return start's columns; rows with an equal key are one. With strategy 'naive' the whole table is stepped each round.
    There is no bound on rounds unless ``most`` gives one. Returns the rows and the number of new rows in each round.
    """
    table = Growing(start.sparkSession, start.schema)
    delta = table.add(start.dropDuplicates(key))
    sizes = [delta.count()]
    while sizes[-1]:
        if most is not None and len(sizes) > most:
            raise Rounds(f"no fixpoint after {most} rounds; new rows by round: {sizes[-5:]}")
        known = table.all()
        made = step(known if strategy == "naive" else delta, known).select(*start.columns).dropDuplicates(key)
        k = known.select(*(known[c].alias(f"__{c}") for c in key))
        on = [made[c].eqNullSafe(k[f"__{c}"]) for c in key]
        delta = table.add(made.join(k, on, "left_anti"))
        sizes.append(delta.count())
    return table.all(), sizes[:-1]
