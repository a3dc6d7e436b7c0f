"""Builtin functions of queries, over columns lexical and num of the dictionary. All are JVM-side expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Name -> function of the argument columns (lexical forms) and of constants.
BUILTINS = {
    "str": lambda x: x,
    "lcase": lambda x: F.lower(x),
    "ucase": lambda x: F.upper(x),
    "strlen": lambda x: F.length(x),
    "concat": lambda *x: F.concat(*x),
    "substr": lambda x, start, n: F.substring(x, start, n),
    "strstarts": lambda x, prefix: x.startswith(prefix),
    "strends": lambda x, suffix: x.endswith(suffix),
    "contains": lambda x, part: x.contains(part),
    "regex": lambda x, pattern: F.regexp_like(x, F.lit(pattern)),
    "year": lambda x: F.year(F.to_timestamp(x)),
    "month": lambda x: F.month(F.to_timestamp(x)),
    "json_field": lambda x, path: F.get_json_object(x, path),
    "num": lambda x: F.expr("1") * x.cast("double"),
    "same": lambda x, y: x == y,
    "differs": lambda x, y: x != y,
    "less": lambda x, y: x.cast("double") < (y.cast("double") if isinstance(y, Column) else F.lit(y)),
    "greater": lambda x, y: x.cast("double") > (y.cast("double") if isinstance(y, Column) else F.lit(y)),
}


def call(name: str, *args) -> Column:
    if name not in BUILTINS:
        raise ValueError(f"unknown builtin {name!r}")
    return BUILTINS[name](*args)
