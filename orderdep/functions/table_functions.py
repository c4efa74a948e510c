"""SQL table functions and vectorised functions; the built-in forms are the main path."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ..inference import closure
from ..mapping import is_trivial, to_canonical
from ..model import Constancy, ListOD


class CanonicalOf:
    """od_canonical(lhs, rhs): the non-trivial canonical members of a list dependency, one row each."""

    def eval(self, lhs: list[str], rhs: list[str]) -> Iterator[tuple]:
        for od in sorted(to_canonical(ListOD(tuple(lhs or ()), tuple(rhs or ()))), key=str):
            if is_trivial(od):
                continue
            context = ",".join(sorted(od.context))
            if isinstance(od, Constancy):
                yield "constancy", context, None, od.attribute
            else:
                a, b = sorted(od.pair)
                yield "compat", context, a, b


class ClosureOf:
    """od_closure(context, lhs_lists, rhs): the attributes constant in a context under rules lhs_lists[i] -> rhs[i]."""

    def eval(self, context: list[str], contexts: list[list[str]], attributes: list[str]) -> Iterator[tuple]:
        rules = [Constancy(frozenset(c), a) for c, a in zip(contexts or [], attributes or [])]
        for a in sorted(closure(rules, context or [])):
            yield (a,)


od_canonical = F.udtf(CanonicalOf, returnType="kind string, context string, `left` string, `right` string")
od_closure = F.udtf(ClosureOf, returnType="attribute string")


def count_inversions(x: np.ndarray, y: np.ndarray) -> int:
    """Pairs with x_s < x_t and y_s > y_t, by merging halves of the order of (x, y)."""
    y = y[np.lexsort((y, x))]
    total, width = 0, 1
    while width < len(y):
        for at in range(0, len(y), 2 * width):
            left, right = y[at : at + width], y[at + width : at + 2 * width]
            if len(right):
                total += int((len(left) - np.searchsorted(left, right, side="right")).sum())
                y[at : at + 2 * width] = np.sort(y[at : at + 2 * width])
        width *= 2
    return total


@F.pandas_udf(LongType())
def inversions(x: pd.Series, y: pd.Series) -> int:
    """Grouped aggregate for small classes."""
    return count_inversions(pd.factorize(x, sort=True)[0], pd.factorize(y, sort=True)[0])


def register(spark: SparkSession) -> None:
    """od_canonical and od_closure as table functions, inversions as an aggregate."""
    spark.udtf.register("od_canonical", od_canonical)
    spark.udtf.register("od_closure", od_closure)
    spark.udf.register("inversions", inversions)
