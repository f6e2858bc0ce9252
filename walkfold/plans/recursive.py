"""Recursive SQL of a path reduction: for explaining, and as a baseline another engine can run."""

from __future__ import annotations

from walkfold.kernels.exprs import to_sql
from walkfold.spec.terms import PathReduce
from walkfold.synth.enumerate import derive, result_kind

_AGG = {"min": "min", "max": "max", "or": "bool_or", "and": "bool_and", "sum": "sum"}


def to_recursive_sql(spec: PathReduce, edges: str = "edges", vertices: str = "vertices", rounds: int = 40) -> str:
    """Rounds of (old rows and relaxed rows) grouped by vertex; the last round is read."""
    source = spec.paths.source
    v = "id" if source is None else str(source)
    made = derive(((spec.reduce, spec.fn),), sourced=False)
    zero = to_sql(made.inits[0]).replace("id", v) if result_kind(spec.fn) != "bool" else "TRUE"
    start = f"SELECT 0, {v}, {zero}" + (f" FROM {vertices}" if source is None else "")
    step = to_sql(made.props[0]).replace("weight", "e.weight").replace("capacity", "e.capacity").replace("src", "e.src")
    return (
        f"WITH RECURSIVE t(k, id, n) AS ({start} UNION ALL SELECT k + 1, id, {_AGG[spec.reduce]}(n) FROM (SELECT k, id, n FROM t UNION ALL SELECT k, e.dst, {step} FROM t JOIN {edges} e ON e.src = t.id) x "
        f"WHERE k < {rounds} GROUP BY k, id) SELECT id, n AS value FROM t WHERE k = {rounds}"
    )
