"""Expressions of queries as columns. An error makes a value unbound (null), never an exception."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from graphloop.plans.query import Call, Const, Expr, Var


def _divide(a: Column, b: Column) -> Column:
    return F.try_divide(a.cast("double"), b.cast("double"))


def _text(x: Column) -> Column:
    return x.cast("string")


def _position(x: Column, mark: Column) -> Column:
    return F.position(mark, x)


FUNCTIONS = {
    "+": lambda a, b: F.try_add(a, b),
    "-": lambda a, b: F.try_subtract(a, b),
    "*": lambda a, b: F.try_multiply(a, b),
    "/": _divide,
    "neg": lambda a: -a,
    "=": lambda a, b: a == b,
    "!=": lambda a, b: a != b,
    "<": lambda a, b: a < b,
    "<=": lambda a, b: a <= b,
    ">": lambda a, b: a > b,
    ">=": lambda a, b: a >= b,
    "&&": lambda a, b: a & b,
    "||": lambda a, b: a | b,
    "!": lambda a: ~a,
    "sameterm": lambda a, b: a.eqNullSafe(b) & a.isNotNull(),
    "in": lambda a, *xs: a.isin(*xs),
    "coalesce": lambda *xs: F.coalesce(*xs),
    "if": lambda c, a, b: F.when(c.isNull(), F.lit(None)).when(c, a).otherwise(b),
    "bound": lambda a: a.isNotNull(),
    "abs": F.abs,
    "ceil": F.ceil,
    "floor": F.floor,
    "round": F.round,
    "sqrt": F.sqrt,
    "ln": F.ln,
    "exp": F.exp,
    "pow": F.pow,
    "mod": lambda a, b: F.when(b != 0, F.pmod(a, b)),
    "str": _text,
    "strlen": F.length,
    "substr": lambda x, start, n=None: F.substring(x, start, F.length(x) if n is None else n),
    "ucase": F.upper,
    "lcase": F.lower,
    "strstarts": lambda a, b: F.startswith(a, b),
    "strends": lambda a, b: F.endswith(a, b),
    "contains": lambda a, b: F.contains(a, b),
    "strbefore": lambda a, b: F.when(_position(a, b) > 0, F.substring(a, F.lit(1), _position(a, b) - 1)).otherwise(F.lit("")),
    "strafter": lambda a, b: F.when(_position(a, b) > 0, F.substring(a, _position(a, b) + F.length(b), F.length(a))).otherwise(F.lit("")),
    "concat": lambda *xs: F.concat(*xs),
    "replace": lambda x, pattern, by: F.regexp_replace(x, pattern, by),
    "regex": lambda x, pattern: F.regexp_like(x, pattern),
    "encode_for_uri": lambda x: F.replace(F.url_encode(x), F.lit("+"), F.lit("%20")),
    "lang": lambda x: x,
    "langmatches": lambda a, b: F.when(b == F.lit("*"), F.length(a) > 0).otherwise(F.lower(a) == F.lower(b)),
    "year": F.year,
    "month": F.month,
    "day": F.dayofmonth,
    "hours": F.hour,
    "minutes": F.minute,
    "seconds": F.second,
    "days_between": lambda a, b: F.datediff(a, b),
    "md5": lambda x: F.md5(x.cast("binary")),
    "sha1": lambda x: F.sha1(x.cast("binary")),
    "sha256": lambda x: F.sha2(x.cast("binary"), 256),
    "integer": lambda x: x.try_cast("long"),
    "double": lambda x: x.try_cast("double"),
    "boolean": lambda x: x.try_cast("boolean"),
    "datetime": lambda x: x.try_cast("timestamp_ntz"),
    "isnumeric": lambda x: x.try_cast("double").isNotNull(),
}


def column(e: Expr, known: set[str]) -> Column:
    """The column of an expression over the variables ``known``; others are unbound."""
    if isinstance(e, Var):
        return F.col(f"`{e.name}`") if e.name in known else F.lit(None)
    if isinstance(e, Const):
        return F.lit(e.value)
    if isinstance(e, Call):
        fn = e.fn.lower()
        if fn in CUSTOM:
            return CUSTOM[fn](*(column(a, known) for a in e.args))
        if fn == "json":
            return F.get_json_object(column(e.args[0], known).cast("string"), e.args[1].value)
        if fn not in FUNCTIONS:
            raise ValueError(f"unknown function {e.fn}")
        return FUNCTIONS[fn](*(column(a, known) for a in e.args))
    raise TypeError(f"not an expression: {e!r}")


CUSTOM: dict = {}


def register(name: str, fn) -> None:
    """Adds a function of columns, such as a UDF, to the expression language."""
    CUSTOM[name.lower()] = fn


def variables(e) -> set[str]:
    """Variables that an expression reads."""
    if isinstance(e, Var):
        return {e.name}
    if isinstance(e, Call):
        return set().union(*(variables(a) for a in e.args)) if e.args else set()
    return set()


def invents(e) -> bool:
    """Whether the value may be one that no variable had: anything but a variable or choice among them."""
    if isinstance(e, Var):
        return False
    if isinstance(e, Call) and e.fn.lower() in ("coalesce", "if"):
        return any(invents(a) for a in e.args[1 if e.fn.lower() == "if" else 0 :])
    return True
