"""Trace terms as columns: prefix-notation token arrays.

Tokens: ``F:<id>/<n>`` a base FD with n sources, ``#<pos>`` a column, ``K:<type>:<value>`` a constant, ``N:<type>`` NULL, ``C:<fn>/<n>`` a call,
``A:<fn>@<relation>/<n>`` an aggregate, whose value belongs to that relation, ``D:<n>`` a value chosen by a discriminating column. A token's arity is the number
after its last slash; columns and constants have none.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def column(pos: Column) -> Column:
    """The token of a column."""
    return F.concat(F.lit("#"), pos.cast("string"))


def constant(value: Column, kind: Column) -> Column:
    return F.when(value.isNull(), F.concat(F.lit("N:"), kind)).otherwise(F.concat(F.lit("K:"), kind, F.lit(":"), value))


def is_constant(token: Column) -> Column:
    return token.startswith("K:") | token.startswith("N:")


def rename(trace: Column, m: Column) -> Column:
    """Column tokens replaced through a map position -> position; order and length stay."""

    def one(t: Column) -> Column:
        return F.when(t.startswith("#"), column(F.element_at(m, F.try_to_number(F.substring(t, 2, 10), F.lit("9999999999")).cast("int")))).otherwise(t)

    return F.transform(trace, one)


def substitute(trace: Column, pos: Column, replacement: Column) -> Column:
    """Every occurrence of a column's token replaced by a term."""
    token = column(pos)
    return F.flatten(F.transform(trace, lambda t: F.when(t == token, replacement).otherwise(F.array(t))))


def render(trace: Column) -> Column:
    return F.array_join(trace, " ")


def parse(tokens: list[str]) -> tuple:
    """A token list as a nested tuple (token, arguments...)."""
    place = 0

    def term() -> tuple:
        nonlocal place
        token = tokens[place]
        place += 1
        n = int(token.rpartition("/")[2]) if token[:2] in ("F:", "C:", "A:", "D:") else 0
        return (token, *(term() for _ in range(n)))

    out = term()
    if place != len(tokens):
        raise ValueError(f"{len(tokens) - place} tokens too many: {tokens}")
    return out


def pretty(tokens: list[str]) -> str:
    """A term with parentheses."""

    def text(t: tuple) -> str:
        return t[0].rpartition("/")[0] + "(" + ", ".join(map(text, t[1:])) + ")" if len(t) > 1 else t[0]

    return text(parse(tokens))


def depth(tokens: list[str]) -> int:
    def of(t: tuple) -> int:
        return 1 + max(map(of, t[1:]), default=0)

    return of(parse(tokens))


def evaluate(tokens: list[str], row: dict[int, object], functions: dict[str, Callable]) -> object:
    """The term's value on one row (position -> value), given each symbol's function."""

    def value(t: tuple) -> object:
        token = t[0]
        if token.startswith("#"):
            return row[int(token[1:])]
        if token.startswith("K:"):
            return token.split(":", 2)[2]
        if token.startswith("N:"):
            return None
        return functions[token](*map(value, t[1:]))

    return value(parse(tokens))
