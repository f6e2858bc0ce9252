"""User kernels outside the kernel grammar: a pandas propagation function and a grouped pandas reduction.

Columns stay on the JVM; these are for functions that no Column expresses. The reduction is used
as a grouped aggregate, so it must be commutative and associative: ``admit_reduction`` checks that on samples first.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkfold.synth.conditions import Refused, reduction_laws


def prop_udf(f: Callable[[pd.Series, pd.Series], pd.Series], kind: str = "double"):
    """A propagation kernel n, attribute -> n' on Arrow batches; none stays none."""

    def run(n: pd.Series, attribute: pd.Series) -> pd.Series:
        return f(n, attribute).where(n.notna())

    run.__annotations__ = {"n": pd.Series, "attribute": pd.Series, "return": pd.Series}
    return F.pandas_udf(run, kind)


def admit_reduction(r: Callable) -> dict[str, bool]:
    laws = reduction_laws(r)
    if not (laws["commutative"] and laws["associative"]):
        raise Refused("a reduction must be commutative and associative to be aggregated in parts")
    return laws


def reduce_with(messages: DataFrame, r: Callable, kind: str = "double") -> DataFrame:
    """dst and the reduction of n over its messages, by a grouped pandas aggregate."""
    admit_reduction(r)

    def run(n: pd.Series) -> float:
        out = None
        for x in n.dropna():
            out = x if out is None else r(out, x)
        return out

    run.__annotations__ = {"n": pd.Series, "return": float}
    return messages.groupBy("dst").agg(F.pandas_udf(run, kind)("n").alias("n"))
