"""Small SQL expressions over Python rows, for deltas that never leave the driver.

Only arithmetic, comparisons and connectives over columns and numbers are read; anything else, and any row in
which a value is missing or a remainder would be of a negative number, is left to Spark.
"""

from __future__ import annotations

import ast
import re
from collections.abc import Callable
from decimal import ROUND_HALF_UP, Context, Decimal
from functools import cache
from typing import Any


class NotLocal(ValueError):
    """Spark has to evaluate this."""


_allowed = (ast.Expression, ast.BinOp, ast.UnaryOp, ast.BoolOp, ast.Compare, ast.Name, ast.Load, ast.Constant, ast.Add, ast.Sub, ast.Mult, ast.Mod, ast.USub, ast.And, ast.Or, ast.Not, ast.Lt, ast.LtE, ast.Gt, ast.GtE, ast.Eq, ast.NotEq)


@cache
def compiled(expression: str) -> tuple[Callable[[dict[str, Any]], Any], frozenset[str]]:
    """The expression as a function of a row, and the columns it reads."""
    text = re.sub(r"<>", "!=", expression)
    text = re.sub(r"(?<![<>!=])=(?!=)", "==", text)
    text = re.sub(r"(?i)\b(and|or|not)\b", lambda m: m.group().lower(), text)
    try:
        tree = ast.parse(text.strip(), mode="eval")
    except SyntaxError as e:
        raise NotLocal(expression) from e
    for n in ast.walk(tree):
        if not isinstance(n, _allowed) or isinstance(n, ast.Compare) and len(n.ops) > 1 or isinstance(n, ast.Constant) and not isinstance(n.value, (int, float)):
            raise NotLocal(expression)
    names = frozenset(n.id for n in ast.walk(tree) if isinstance(n, ast.Name))
    code = compile(tree, "<expression>", "eval")
    remainder = any(isinstance(n, ast.Mod) for n in ast.walk(tree))

    def run(row: dict[str, Any]) -> Any:
        for c in names:
            if not isinstance(row[c], (int, float)) or remainder and row[c] < 0:
                raise NotLocal(expression)
        return eval(code, {"__builtins__": {}}, row)  # noqa: S307  only nodes of the list above

    return run, names


CTX = Context(prec=60, rounding=ROUND_HALF_UP)
_PLACES, _LOSS = 12, 1e-9  # as in operators.aggregate
_LAST = Decimal(1).scaleb(-_PLACES)


def exact(value: Any) -> Decimal:
    """A number as the decimal that it is added as; one that the decimal can't hold is an error."""
    if not isinstance(value, float):
        return Decimal(value)
    if value - value != 0 or abs(value) >= 1e16:
        raise ValueError(f"not exact as decimal: {value}")
    out = CTX.quantize(Decimal(repr(value)), _LAST)
    if abs(float(out) - value) > abs(value) * _LOSS:
        raise ValueError(f"not exact as decimal: {value}")
    return out


def scaled(value: Decimal | int) -> int:
    """A decimal as a whole number of its last place."""
    out = CTX.scaleb(Decimal(value), _PLACES)
    if out != out.to_integral_value():
        raise NotLocal("more decimal places than sums keep")
    return int(out)


def unscaled(value: int) -> Decimal:
    return CTX.scaleb(Decimal(value), -_PLACES)
