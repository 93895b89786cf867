"""FDs against data: one shuffle by the left side, partial aggregation, only the FD's columns read.

NULLs compare as equal, as in grouping. A group violates lhs -> rhs if it holds two different values, or NULL and a value.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depscope.sources.facts import local


def _comparable(df: DataFrame, column: str) -> Column:
    """The column, as text where its type has no order (maps)."""
    return F.to_json(column) if dict(df.dtypes)[column].startswith("map") else F.col(column)


def _broken(value: Column) -> Column:
    """An aggregate: whether a group holds more than one value, NULL counted as one."""
    low, high = F.min(value), F.max(value)
    return (F.count(value) > 0) & ((low != high) | (F.count(value) < F.count(F.lit(1))))


def check_fds(df: DataFrame, lhs: list[str], rhs: list[str]) -> DataFrame:
    """rhs, n_groups, violating_groups for FDs with one left side: all of them in one pass."""
    flags = [_broken(_comparable(df, r)).alias(f"b{i}") for i, r in enumerate(rhs)]
    if lhs:
        groups = df.groupBy(*(_comparable(df, c).alias(f"k{i}") for i, c in enumerate(lhs))).agg(*flags)
    else:
        groups = df.agg(*flags, F.count("*").alias("n")).where("n > 0")
    sums = groups.agg(F.count("*").alias("n_groups"), *(F.sum(F.when(F.col(f"b{i}"), 1).otherwise(0)).alias(f"v{i}") for i in range(len(rhs))))
    rows = F.explode(F.array(*(F.struct(F.lit(r).alias("rhs"), F.coalesce(F.col(f"v{i}"), F.lit(0)).cast("long").alias("violating_groups")) for i, r in enumerate(rhs)))).alias("x")
    return sums.select("n_groups", rows).select("x.rhs", "n_groups", "x.violating_groups")


def check_fd(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """groups, violating_groups."""
    return check_fds(df, lhs, [rhs]).select(F.col("n_groups").alias("groups"), "violating_groups")


#: Left-side columns of one pass: each is a bit of the grouping id.
MOST_KEYS = 60


def check_view(df: DataFrame, fds: list[tuple[tuple[str, ...], str]]) -> DataFrame:
    """lhs, rhs, n_groups, violating_groups for FDs of any left sides over one view: the view is computed once, and grouped by all its left sides together."""
    by: dict[frozenset, list[tuple[tuple[str, ...], str]]] = {}
    for lhs, rhs in fds:
        by.setdefault(frozenset(lhs), []).append((tuple(lhs), rhs))
    if len(by) == 1:
        lhs = fds[0][0]
        return check_fds(df, list(lhs), sorted({r for _, r in fds})).select(F.lit(",".join(lhs)).alias("lhs"), "rhs", "n_groups", "violating_groups")
    keys, values = sorted({c for lhs in by for c in lhs}), sorted({r for _, r in fds})
    if len(keys) > MOST_KEYS:
        half = len(fds) // 2
        return check_view(df, fds[:half]).unionByName(check_view(df, fds[half:]))
    at, rows = {c: f"k{i}" for i, c in enumerate(keys)}, df.select(*(_comparable(df, c).alias(f"k{i}") for i, c in enumerate(keys)), *(_comparable(df, c).alias(f"r{i}") for i, c in enumerate(values)))
    flags = [_broken(F.col(f"r{i}")).alias(f"b{i}") for i in range(len(values))]
    groups = rows.groupingSets([[F.col(at[c]) for c in sorted(lhs)] for lhs in by], *(F.col(f"k{i}") for i in range(len(keys)))).agg(F.grouping_id().alias("gid"), *flags)
    sums = groups.groupBy("gid").agg(F.count("*").alias("n_groups"), *(F.sum(F.when(F.col(f"b{i}"), 1).otherwise(0)).cast("long").alias(f"v{i}") for i in range(len(values))))
    # the grouping id has a bit for each key column, 1 where a set leaves it out
    gid = lambda lhs: sum(1 << (len(keys) - 1 - i) for i, c in enumerate(keys) if c not in lhs)
    of = F.map_from_entries(F.collect_list(F.struct(F.col("gid").cast("long").alias("gid"), F.struct("n_groups", F.array(*(F.col(f"v{i}") for i in range(len(values)))).alias("v")).alias("s"))))
    asked = [F.struct(F.lit(gid(lhs)).cast("long").alias("gid"), F.lit(",".join(own)).alias("lhs"), F.lit(rhs).alias("rhs"), F.lit(values.index(rhs)).alias("at")) for lhs, some in by.items() for own, rhs in dict.fromkeys(some)]
    # one entry for each left side; an empty view has none, and its FDs no groups
    found = sums.agg(of.alias("of")).select("of", F.explode(F.array(*asked)).alias("x")).select("x.*", F.try_element_at("of", F.col("x.gid")).alias("s"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return found.select("lhs", "rhs", zero(F.col("s.n_groups")).alias("n_groups"), zero(F.get("s.v", F.col("at"))).alias("violating_groups"))


def check_many(views: dict[str, DataFrame], fds: list[tuple[str, tuple[str, ...], str]]) -> DataFrame:
    """rel, lhs, rhs, n_groups, violating_groups; the FDs of one relation share a pass over it."""
    by: dict[str, list[tuple[tuple[str, ...], str]]] = {}
    for rel, lhs, rhs in fds:
        by.setdefault(rel, []).append((tuple(lhs), rhs))
    out = None
    for rel, own in sorted(by.items()):
        one = check_view(views[rel], own).select(F.lit(rel).alias("rel"), "lhs", "rhs", "n_groups", "violating_groups")
        out = one if out is None else out.unionByName(one)
    return out


def violations(df: DataFrame, lhs: list[str], rhs: str, limit: int | None = None) -> DataFrame:
    """The violating groups: lhs, n_values, n_rows, example_a, example_b. With a limit, the widest groups first."""
    value = _comparable(df, rhs)
    n = F.count_distinct(value) + F.max(F.when(value.isNull(), 1).otherwise(0))
    out = df.groupBy(*lhs).agg(n.alias("n_values"), F.count("*").alias("n_rows"), F.min(value).alias("example_a"), F.max(value).alias("example_b")).where("n_values > 1")
    return out.orderBy(F.desc("n_values"), F.desc("n_rows"), *lhs).limit(limit) if limit else out


def refuted_on_sample(df: DataFrame, lhs: list[str], rhs: str, one_in: int = 100) -> bool:
    """Whether whole groups, picked by hash of the left side, already refute the FD. A sample never confirms one."""
    part = df.where(F.pmod(F.xxhash64(*lhs), F.lit(one_in)) == 0)
    return check_fd(part, lhs, rhs).first()["violating_groups"] > 0


def discover(df: DataFrame, max_lhs: int | None = None, columns: list[str] | None = None) -> DataFrame:
    """lhs, rhs: all minimal FDs on the data, brute force, one pass for each number of columns on the left; max_lhs bounds that number."""
    columns = columns or df.columns
    found: list[tuple[tuple[str, ...], str]] = []
    for n in range(min(len(columns) - 1, len(columns) if max_lhs is None else max_lhs) + 1):
        asked = [(lhs, r) for lhs in combinations(columns, n) for r in columns if r not in lhs and not any(set(k) <= set(lhs) and r == y for k, y in found)]
        if asked:
            broken = {(x["lhs"], x["rhs"]) for x in check_view(df, asked).collect() if x["violating_groups"]}
            found += [(lhs, r) for lhs, r in asked if (",".join(lhs), r) not in broken]
    return local(df.sparkSession, [(",".join(lhs), r) for lhs, r in sorted(found)], "lhs string, rhs string")


def instance_only(df: DataFrame, reported: list[tuple[tuple[str, ...], str]], max_lhs: int | None = None) -> DataFrame:
    """lhs, rhs: minimal FDs of the data that don't follow from the reported ones; what a schema can't tell of its present rows."""
    from depscope.operators import armstrong

    at = {c: i for i, c in enumerate(df.columns)}
    fds = [(frozenset(at[c] for c in lhs), at[r]) for lhs, r in reported]
    rows = [(x["lhs"], x["rhs"]) for x in discover(df, max_lhs).collect()]
    rows = [(lhs, rhs) for lhs, rhs in rows if not armstrong.implies_fd(fds, {at[c] for c in lhs.split(",") if c}, at[rhs])]
    return local(df.sparkSession, rows, "lhs string, rhs string")


def equal_columns(df: DataFrame, a: str, b: str) -> DataFrame:
    """different: rows in which two columns that should be equal differ."""
    return df.agg(F.sum(F.when(F.col(a).eqNullSafe(F.col(b)), 0).otherwise(1)).cast("long").alias("different"))


def key_state(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """lhs, low, high, n, n_null: state of a check that later partitions can be merged into."""
    v = _comparable(df, rhs)
    return df.groupBy(*lhs).agg(F.min(v).alias("low"), F.max(v).alias("high"), F.count("*").alias("n"), F.sum(F.when(v.isNull(), 1).otherwise(0)).alias("n_null"))


def merged_state(states: list[DataFrame], lhs: list[str]) -> DataFrame:
    out = states[0]
    for s in states[1:]:
        out = out.unionByName(s)
    return out.groupBy(*lhs).agg(F.min("low").alias("low"), F.max("high").alias("high"), F.sum("n").alias("n"), F.sum("n_null").alias("n_null"))


def broken_keys(state: DataFrame) -> DataFrame:
    return state.where((F.col("low") != F.col("high")) | ((F.col("n_null") > 0) & (F.col("n_null") < F.col("n"))))
