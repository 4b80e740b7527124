"""The problem selector: replacement and role name one problem."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame

from wsample.operators.bounded import bounded_sample
from wsample.operators.kernels import race_kernel
from wsample.operators.proportional import proportional_sample
from wsample.operators.race import race_sample
from wsample.operators.replacement import replacement_sample


def weighted_sample(df: DataFrame, m: int, *, weight: Column | str, id_cols: Sequence[str], replacement: str | int | Column = "none", role: str = "draw", method: str = "auto", **kw) -> DataFrame:
    """A weighted sample of ``m``.

    ``replacement``: none, full, or the most slots an item may take.  ``role``: whether the weight is the chance at each draw
    (``draw``) or in the final sample (``inclusion``).  With full replacement the roles are one; bounds are for the draw role.
    """
    if role not in ("draw", "inclusion"):
        raise ValueError(f"unknown role: {role!r}")
    if isinstance(replacement, str) and replacement not in ("none", "full"):
        raise ValueError(f"unknown replacement: {replacement!r}")
    if replacement == "full":
        return replacement_sample(df, m, weight=weight, id_cols=id_cols, method=method, **kw)
    if replacement == "none":
        if role == "inclusion":
            return proportional_sample(df, m, weight=weight, id_cols=id_cols, mode="distributed" if method == "auto" else method, **kw)
        if method in ("reservoir", "jump"):
            return race_kernel(df, m, weight=weight, id_cols=id_cols, jump=method == "jump", **kw)
        return race_sample(df, m, weight=weight, id_cols=id_cols, **kw)
    if role == "inclusion":
        raise ValueError("bounded multiplicity is defined for the draw role")
    return bounded_sample(df, m, weight=weight, id_cols=id_cols, k=replacement, method="candidates" if method == "auto" else method, **kw)
