"""Specifications as trees: path reductions, maps over vertices, reductions over vertices.

A term of kind m has a value for each vertex; a term of kind r is one scalar or set. None stands for "no value".
"""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

REDUCTIONS = ("min", "max", "or", "and", "sum", "union", "intersect")
PATH_FUNCTIONS = ("length", "weight", "capacity", "head", "penult", "one", "true", "heavy")
OPERATIONS = ("min", "max", "and", "or", "+", "-", "*", "/", "=", "<", ">", ">=", "<=", "union", "intersect")


@dataclass(frozen=True)
class Term:
    pass


@dataclass(frozen=True)
class Paths(Term):
    """All paths to each vertex, from ``source`` if there is one."""

    source: int | None = None


@dataclass(frozen=True)
class ArgsPaths(Term):
    """Those of ``inner`` that attain the optimum of a path function."""

    reduce: str
    fn: str
    inner: Term


@dataclass(frozen=True)
class PathReduce(Term):
    """m: a path function's values reduced over paths."""

    reduce: str
    fn: str
    paths: Term = field(default_factory=Paths)


@dataclass(frozen=True)
class ArgPath(Term):
    """m: a path function of one path that attains an optimum (ties: the least value)."""

    reduce: str
    fn: str
    out: str
    paths: Term = field(default_factory=Paths)


@dataclass(frozen=True)
class Card(Term):
    """m: how many paths."""

    paths: Term


@dataclass(frozen=True)
class Lit(Term):
    value: Any


@dataclass(frozen=True)
class Var(Term):
    name: str


@dataclass(frozen=True)
class Vertex(Term):
    """m: the vertex itself."""


@dataclass(frozen=True)
class BinOp(Term):
    op: str
    left: Term
    right: Term


@dataclass(frozen=True)
class UnOp(Term):
    op: str
    arg: Term


@dataclass(frozen=True)
class Let(Term):
    """Names a sub-term."""

    name: str
    value: Term
    body: Term


@dataclass(frozen=True)
class VertexReduce(Term):
    """r: an m term reduced over vertices, those for which ``where`` holds."""

    reduce: str
    body: Term
    where: Term | None = None


@dataclass(frozen=True)
class OverSources(Term):
    """A reduction over a finite set of sources of a term that names its source by a variable."""

    reduce: str
    variable: str
    sources: tuple[int, ...]
    body: Term


@dataclass(frozen=True)
class SourcePaths(Term):
    """All paths from the source that a variable of OverSources names."""

    variable: str


# -- what fusion makes of them -------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Factored(Term):
    """One path reduction in a loop: a variable and ((R, F), ...), compared lexicographically."""

    name: str
    keys: tuple[tuple[str, str], ...]
    source: int | None = None


@dataclass(frozen=True)
class PathLet(Term):
    """m: loops (each a tuple of factored reductions that iterate together), then an expression over their variables."""

    loops: tuple[tuple[Factored, ...], ...]
    body: Term


@dataclass(frozen=True)
class VertexPass(Term):
    """Vertex reductions made in one traversal: (name, R, name of the mapped value)."""

    items: tuple[tuple[str, str, str], ...]


@dataclass(frozen=True)
class TripleLet(Term):
    """r: iterate, map, reduce, and an expression over the results. Without passes it is m and ``body`` is over the maps."""

    loops: tuple[tuple[Factored, ...], ...]
    maps: tuple[tuple[str, Term], ...]
    passes: tuple[VertexPass, ...]
    body: Term


@dataclass(frozen=True)
class Rounds(Term):
    """Triple-lets in order; ``names`` are the scalars that later rounds read."""

    lets: tuple[TripleLet, ...]
    names: tuple[str, ...] = ()


def children(t: Term) -> list[tuple[str, Term]]:
    return [(k, v) for k, v in vars(t).items() if isinstance(v, Term)]


def replace(t: Term, **new) -> Term:
    return type(t)(**(vars(t) | new))


def is_r(t: Term) -> bool:
    """Whether a term is a scalar rather than a map over vertices."""
    if isinstance(t, VertexReduce) or (isinstance(t, TripleLet) and t.passes):
        return True
    if isinstance(t, Lit):
        return True
    if isinstance(t, (BinOp, UnOp)):
        return all(is_r(c) for _, c in children(t))
    if isinstance(t, Let):
        return is_r(t.body)
    if isinstance(t, OverSources):
        return is_r(t.body)
    return isinstance(t, Var) and t.name.startswith("$")
