"""Hand kernels: analyses that are stated by kernels alone. Those of path functions come from the synthesis."""

from __future__ import annotations

from dataclasses import dataclass

from walkfold.kernels.exprs import KExpr, call, edge, lit, slot

N = slot("n")

@dataclass(frozen=True)
class Kernels:
    """init, propagate, reduce (a name), epilogue and rollback of one slot."""

    init: KExpr
    prop: KExpr
    reduce: str
    epilogue: KExpr = N
    rollback: KExpr | None = None


def sssp(source: int) -> Kernels:
    return Kernels(call("if", call("=", slot("id"), lit(source)), lit(0), lit(None)), call("+", N, edge("weight")), "min")


def page_rank(gamma: float = 0.85) -> Kernels:
    """The teleport share is added after each round; a vertex sends its rank in equal parts."""
    share = call("/", lit(1.0), edge("order"))
    return Kernels(share, call("/", N, edge("outdeg")), "sum", call("+", call("*", lit(gamma), N), call("*", lit(1 - gamma), share)), call("-", slot("acc"), slot("old")))
