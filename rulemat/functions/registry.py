"""Functions that rules may call in arithmetic: built-in ones, and a user's own."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

Builder = Callable[..., Column]

_BUILT_IN: dict[str, Builder] = {
    "abs": F.abs, "round": F.round, "floor": F.floor, "ceil": F.ceil, "sqrt": F.sqrt, "pow": F.pow, "exp": F.exp, "ln": F.log,
    "greatest": F.greatest, "least": F.least, "concat": F.concat, "lower": F.lower, "upper": F.upper, "trim": F.trim, "length": F.length,
    "year": F.year, "month": F.month, "day": F.dayofmonth, "coalesce": F.coalesce, "substring": lambda s, a, n: s.substr(a.cast("int"), n.cast("int")),
    "int": lambda c: c.cast("bigint"), "double": lambda c: c.cast("double"), "string": lambda c: c.cast("string"), "xxhash64": F.xxhash64, "datediff": F.datediff,
}
_DOUBLE = {"sqrt", "pow", "exp", "ln", "double"}
_LONG = {"floor", "ceil", "length", "year", "month", "day", "int", "xxhash64", "datediff"}
_STRING = {"concat", "lower", "upper", "trim", "substring", "string"}
_user: dict[str, tuple[Builder, str]] = {}


def register(name: str, builder: Builder, returns: str) -> None:
    """Add a function: anything that maps Columns to a Column (a native expression, or a
    pandas UDF where none exists) and its Spark type."""
    _user[name] = (builder, returns)


def call(name: str, args: list[Column]) -> Column:
    if name in _user:
        return _user[name][0](*args)
    if name not in _BUILT_IN:
        raise ValueError(f"unknown function {name}")
    return _BUILT_IN[name](*args)


def returns(name: str, args: list[str | None]) -> str | None:
    if name in _user:
        return _user[name][1]
    for names, kind in ((_DOUBLE, "double"), (_LONG, "bigint"), (_STRING, "string")):
        if name in names:
            return kind
    return args[0] if args else None
