"""IR expressions as Spark columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

from worldfold.plans import ir


class NotExpressible(Exception):
    pass


BINARY: dict[str, Callable[[Column, Column], Column]] = {
    "Add": lambda a, b: a + b, "Subtract": lambda a, b: a - b, "Multiply": lambda a, b: a * b, "Divide": lambda a, b: a / b, "Remainder": lambda a, b: a % b,
    "EqualTo": lambda a, b: a == b, "EqualNullSafe": lambda a, b: a.eqNullSafe(b), "LessThan": lambda a, b: a < b, "LessThanOrEqual": lambda a, b: a <= b,
    "GreaterThan": lambda a, b: a > b, "GreaterThanOrEqual": lambda a, b: a >= b, "And": lambda a, b: a & b, "Or": lambda a, b: a | b,
    "IntegralDivide": lambda a, b: F.call_function("div", a, b), "StartsWith": lambda a, b: a.startswith(b), "EndsWith": lambda a, b: a.endswith(b), "Contains": lambda a, b: a.contains(b),
    "Like": lambda a, b: F.like(a, b), "RLike": lambda a, b: F.rlike(a, b),
}
CALLED = {
    "Abs": "abs", "Coalesce": "coalesce", "Concat": "concat", "ConcatWs": "concat_ws", "Upper": "upper", "Lower": "lower", "Length": "length", "StringTrim": "trim", "Substring": "substring", "Year": "year", "Month": "month",
    "DayOfMonth": "day", "Quarter": "quarter", "Hour": "hour", "Minute": "minute", "DateAdd": "date_add", "DateSub": "date_sub", "DateDiff": "datediff", "TruncTimestamp": "date_trunc", "TruncDate": "trunc", "Round": "round", "Floor": "floor", "Ceil": "ceil",
    "Sqrt": "sqrt", "Pow": "power", "Greatest": "greatest", "Least": "least", "GetJsonObject": "get_json_object", "RegExpReplace": "regexp_replace", "RegExpExtract": "regexp_extract", "NullIf": "nullif", "Nvl": "nvl", "ToDate": "to_date",
}
COMPARE = {"LessThan": "<", "LessThanOrEqual": "<=", "EqualTo": "=", "GreaterThan": ">", "GreaterThanOrEqual": ">="}
FLIPPED = {"<": ">", "<=": ">=", "=": "=", "<>": "<>", ">": "<", ">=": "<="}


def to_column(e, env: Callable[[int], Column], lifted: bool = False) -> Column:
    """``env`` gives the column of an attribute. Inside a lifted expression division by zero is null, not an error."""
    if isinstance(e, ir.Item):
        return to_column(e.expr, env, lifted)
    if isinstance(e, ir.Attr):
        return env(e.id)
    if isinstance(e, ir.Lit):
        if e.value is None:
            return F.lit(None).cast("string" if e.type == "void" else e.type)
        if e.type == "string":
            return F.lit(e.value)
        if e.type == "boolean":
            return F.lit(str(e.value).lower() == "true")
        return F.lit(str(e.value)).cast(e.type)
    if not isinstance(e, ir.Call):
        raise NotExpressible(type(e).__name__)
    a = [to_column(x, env, lifted) for x in e.args]
    if e.op == "Divide" and lifted:
        return F.try_divide(a[0], a[1])
    if e.op in BINARY:
        return BINARY[e.op](a[0], a[1])
    if e.op == "Not":
        return ~a[0]
    if e.op == "IsNull":
        return a[0].isNull()
    if e.op == "IsNotNull":
        return a[0].isNotNull()
    if e.op == "UnaryMinus":
        return -a[0]
    if e.op == "Cast":
        return a[0].cast(e.extra[0])
    if e.op == "In":
        return a[0].isin(*a[1:])
    if e.op == "If":
        return F.when(a[0], a[1]).otherwise(a[2])
    if e.op == "CaseWhen":
        out = None
        for i in range(0, len(a) - 1, 2):
            out = F.when(a[i], a[i + 1]) if out is None else out.when(a[i], a[i + 1])
        return out.otherwise(a[-1]) if len(a) % 2 else out
    if e.op in CALLED:
        return F.call_function(CALLED[e.op], *a)
    raise NotExpressible(e.op)
