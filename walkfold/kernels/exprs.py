"""The kernel expression language: small trees that become Columns, SQL text, or plain Python values."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from typing import Any

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The capacity of a path without edges: the top of the natural numbers.
TOP = 2**63 - 1


@dataclass(frozen=True)
class KExpr:
    """op and arguments; ``none`` in an argument makes arithmetic none."""

    op: str
    args: tuple = ()

    def __repr__(self) -> str:
        if self.op in ("lit", "edge", "slot"):
            return str(self.args[0])
        return f"{self.op}({', '.join(map(repr, self.args))})"

    @property
    def size(self) -> int:
        return 1 + sum(a.size for a in self.args if isinstance(a, KExpr))


def lit(value: Any) -> KExpr:
    return KExpr("lit", (value,))


def slot(name: str = "n") -> KExpr:
    return KExpr("slot", (name,))


def edge(name: str) -> KExpr:
    """weight, capacity, src, dst, outdeg (of the source), indeg (of the target), order (number of vertices)."""
    return KExpr("edge", (name,))


def call(op: str, *args: KExpr) -> KExpr:
    return KExpr(op, args)


NONE = lit(None)
_BINARY = {"+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "/": lambda a, b: a / b, "=": lambda a, b: a == b, "<": lambda a, b: a < b, ">": lambda a, b: a > b}


def to_column(e: KExpr, env: dict[str, Column]) -> Column:
    if e.op == "lit":
        return F.lit(e.args[0])
    if e.op in ("slot", "edge"):
        return env[e.args[0]]
    a = [to_column(x, env) for x in e.args]
    if e.op == "given":  # none stays none
        return F.when(a[0].isNotNull(), a[1])
    if e.op in _BINARY:
        return _BINARY[e.op](*a)
    if e.op == "neg":
        return -a[0]
    if e.op in ("min", "max"):  # the guard: none in one argument is none
        value = F.least(*a) if e.op == "min" else F.greatest(*a)
        return F.when(reduce(lambda x, y: x & y, (x.isNotNull() for x in a)), value)
    if e.op == "and":
        return a[0] & a[1]
    if e.op == "or":
        return a[0] | a[1]
    if e.op == "not":
        return ~a[0]
    if e.op == "if":
        return F.when(a[0], a[1]).otherwise(a[2])
    raise ValueError(f"no kernel operation {e.op}")


def to_sql(e: KExpr, names: dict[str, str] | None = None) -> str:
    """SQL text; ``names`` says what slots and attributes are called there."""
    names = names or {}
    if e.op == "lit":
        return "NULL" if e.args[0] is None else f"{e.args[0]!r}D" if isinstance(e.args[0], float) and names else str(e.args[0])
    if e.op in ("slot", "edge"):
        return names.get(e.args[0], e.args[0])
    a = [to_sql(x, names) for x in e.args]
    if e.op == "given":
        return f"CASE WHEN {a[0]} IS NOT NULL THEN {a[1]} END"
    if e.op in _BINARY:
        return f"({a[0]} {e.op} {a[1]})"
    if e.op == "neg":
        return f"(-{a[0]})"
    if e.op in ("min", "max"):
        return f"{'least' if e.op == 'min' else 'greatest'}({', '.join(a)})"
    if e.op in ("and", "or"):
        return f"({a[0]} {e.op.upper()} {a[1]})"
    if e.op == "not":
        return f"(NOT {a[0]})"
    if e.op == "if":
        return f"CASE WHEN {a[0]} THEN {a[1]} ELSE {a[2]} END"
    raise ValueError(f"no kernel operation {e.op}")


def evaluate(e: KExpr, env: dict[str, Any]) -> Any:
    if e.op == "lit":
        return e.args[0]
    if e.op in ("slot", "edge"):
        return env[e.args[0]]
    if e.op == "given":
        return None if evaluate(e.args[0], env) is None else evaluate(e.args[1], env)
    if e.op == "=" and any(x == NONE for x in e.args):
        raise ValueError("none is not compared")
    if e.op == "if":
        return evaluate(e.args[1] if evaluate(e.args[0], env) else e.args[2], env)
    a = [evaluate(x, env) for x in e.args]
    if any(x is None for x in a):
        return None
    if e.op == "/":
        return None if a[1] == 0 else a[0] / a[1]
    if e.op in _BINARY:
        return _BINARY[e.op](*a)
    return {"neg": lambda: -a[0], "min": lambda: min(a), "max": lambda: max(a), "and": lambda: a[0] and a[1], "or": lambda: a[0] or a[1], "not": lambda: not a[0]}[e.op]()


def evaluate_arrays(e: KExpr, env: dict[str, Any]) -> Any:
    """The value over numpy arrays without missing elements; a division by zero is not a number."""
    if e.op == "lit":
        return e.args[0]
    if e.op in ("slot", "edge"):
        return env[e.args[0]]
    a = [evaluate_arrays(x, env) for x in e.args]
    if e.op == "given":
        return a[1]
    if e.op == "if":
        return np.where(a[0], a[1], a[2])
    if e.op == "/":
        with np.errstate(divide="ignore", invalid="ignore"):
            return np.true_divide(a[0], a[1])
    if e.op in _BINARY:
        return _BINARY[e.op](*a)
    return {"neg": lambda: -a[0], "not": lambda: np.logical_not(a[0]), "min": lambda: reduce(np.minimum, a), "max": lambda: reduce(np.maximum, a), "and": lambda: np.logical_and(*a), "or": lambda: np.logical_or(*a)}[e.op]()


def edge_columns(e: KExpr) -> set[str]:
    """The edge's own columns that the expression reads: no others are scanned."""
    if e.op == "edge":
        return {e.args[0]}
    return set().union(*(edge_columns(x) for x in e.args if isinstance(x, KExpr))) if e.op not in ("lit", "slot") else set()


def simplify(e: KExpr) -> KExpr:
    """Fold constants and drop neutral elements."""
    if e.op in ("lit", "slot", "edge"):
        return e
    a = tuple(simplify(x) for x in e.args)
    if all(x.op == "lit" for x in a) and e.op != "/" and e.op != "given":
        return lit(evaluate(KExpr(e.op, a), {}))
    zero, one = lit(0), lit(1)
    if e.op == "+" and zero in a:
        return a[1] if a[0] == zero else a[0]
    if e.op == "*" and one in a:
        return a[1] if a[0] == one else a[0]
    if e.op in ("min", "max") and a[0] == a[1]:
        return a[0]
    return KExpr(e.op, a)
