"""Checks of single dependencies and of many at once.

Inputs may have any orderable columns.  A constancy compares the least and greatest value of each class; a
compatibility compares neighbouring groups.  Nulls equal each other and come first: values are wrapped in a struct with
their null flag where min and max would skip them.
"""

from __future__ import annotations

from collections.abc import Iterable, Mapping, Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..mapping import compat_part, is_trivial
from ..model import OD_SCHEMA, Canonical, Compat, Constancy, ListOD, od_row
from . import segscan
from .encode import SMALL, canonical, rank_encode, with_code

#: Dependencies that one plan of check_many holds.
PLAN_TASKS = 24


def ordered(df: DataFrame, name: str) -> Column:
    """A value that min, max and comparison take with null lowest."""
    return F.struct(F.col(name).isNotNull().alias("have"), canonical(F.col(name), df.schema[name].dataType).alias("value"))


def listed(df: DataFrame, names: Sequence[str]) -> Column:
    return F.struct(*[ordered(df, n).alias(f"f{k}") for k, n in enumerate(names)]) if names else F.lit(0)


def lex_le(s: Sequence[Column], t: Sequence[Column]) -> Column:
    """Whether the list of values s comes before t or equals it, first place first; the empty list equals itself."""
    wrap = lambda cs: F.struct(*[F.struct(c.isNotNull().alias("have"), c.alias("value")).alias(f"f{k}") for k, c in enumerate(cs)])
    return wrap(s) <= wrap(t) if s else F.lit(True)


def lex_lt(s: Sequence[Column], t: Sequence[Column]) -> Column:
    return ~lex_le(t, s)


@dataclass(frozen=True)
class ODCheck:
    holds: bool
    n_split_groups: int
    n_swap_groups: int


def list_groups(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str], small: int = SMALL) -> DataFrame:
    """One row per value of lhs: least and greatest rhs, and whether it splits or swaps.

    Groups counted to be at most ``small`` are read by one window; more of them by a bucketed scan over their codes.
    """
    g = df.groupBy(listed(df, lhs).alias("x")).agg(F.min(listed(df, rhs)).alias("lo"), F.max(listed(df, rhs)).alias("hi"))
    if g.count() <= small:
        before = Window.orderBy("x").rowsBetween(Window.unboundedPreceding, -1)
        flagged = g.withColumn("swap", F.coalesce(F.max("hi").over(before) > F.col("lo"), F.lit(False)))
    else:
        flagged = segscan.prefix_exceeds(with_code(g, "x", "k"), [], "k", "lo", "hi").withColumnRenamed("exceeds", "swap").drop("k")
    return flagged.withColumn("split", F.col("lo") != F.col("hi"))


def check_list_od(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> ODCheck:
    """Directly from the definition, by a scan over the reduced groups of lhs."""
    if not rhs:
        return ODCheck(True, 0, 0)
    r = list_groups(df, lhs, rhs).agg(F.count_if("split").alias("a"), F.count_if("swap").alias("b")).first()
    return ODCheck(not r["a"] and not r["b"], r["a"], r["b"])


def holds_list_od(df: DataFrame, lhs: Sequence[str], rhs: Sequence[str]) -> bool:
    """Through the canonical family, each member checked by partitioned plans."""
    from ..mapping import to_canonical

    return all(check(df, o) for o in to_canonical(ListOD(tuple(lhs), tuple(rhs))))


def check_order_equiv(df: DataFrame, x: Sequence[str], y: Sequence[str]) -> bool:
    return holds_list_od(df, x, y) and holds_list_od(df, y, x)


def check_list_compat(df: DataFrame, x: Sequence[str], y: Sequence[str]) -> bool:
    return all(check(df, o) for o in compat_part(ListOD(tuple(x), tuple(y))) if not is_trivial(o))


def constancy_bad(df: DataFrame, context: Iterable[str], attribute: str) -> DataFrame:
    """The classes in which the attribute has two values or more."""
    v = ordered(df, attribute)
    g = df.groupBy(*sorted(context)).agg(F.min(v).alias("__lo"), F.max(v).alias("__hi"))
    return g.where("__lo <> __hi")


def check_constancy(df: DataFrame, context: Iterable[str], attribute: str) -> bool:
    return attribute in set(context) or constancy_bad(df, context, attribute).limit(1).count() == 0


def check_fd(df: DataFrame, lhs: Iterable[str], rhs: Iterable[str]) -> bool:
    return all(check_constancy(df, lhs, b) for b in rhs)


def compat_groups(df: DataFrame, context: Iterable[str], a: str, b: str) -> DataFrame:
    """(context, a as code ``__a``, least and greatest b)."""
    context = sorted(context)
    codes = rank_encode(df.select(*context, a, b), [*context, a, b], dense=False)
    return codes.groupBy(*context, F.col(a).alias("__a")).agg(F.min(b).alias("__lo"), F.max(b).alias("__hi"))


def check_compat(df: DataFrame, context: Iterable[str], a: str, b: str) -> bool:
    if is_trivial(Compat.of(context, a, b)):
        return True
    return segscan.is_monotone(compat_groups(df, context, a, b), sorted(context), "__a", "__lo", "__hi")


def check(df: DataFrame, od: Canonical) -> bool:
    if is_trivial(od):
        return True
    return check_constancy(df, od.context, od.attribute) if isinstance(od, Constancy) else check_compat(df, od.context, *sorted(od.pair))


def verdict_plan(codes: DataFrame, tasks: Sequence[tuple[int, Canonical]], cuts: Mapping[str, Sequence[int]] | None = None, values: Mapping[str, int] | None = None) -> DataFrame:
    """(task, bad) for dependencies on a table of codes; those that group by the same set share its aggregate.
    ``cuts`` has the bounds of a column's buckets, for codes that are not dense; ``values`` how many values columns have, and
    a pair is then read along the end with fewer.

    A pair with context C and attributes a, b is read from the groups of C and a, those of a constancy from the
    groups of its context, so one exchange serves all dependencies of a set.
    """
    by_set: dict[frozenset[str], list[tuple[int, Canonical, str | None, str]]] = {}
    for k, od in tasks:
        if isinstance(od, Constancy):
            by_set.setdefault(od.context, []).append((k, od, None, od.attribute))
    for k, od in tasks:
        if isinstance(od, Compat):
            a, b = sorted(od.pair, key=lambda c: (values[c] if values else 0, c))
            if not values and od.context | {b} in by_set and od.context | {a} not in by_set:
                a, b = b, a
            by_set.setdefault(od.context | {a}, []).append((k, od, a, b))
    rows: list[DataFrame] = []
    for keys, own in by_set.items():
        needed = sorted({b for *_, b in own})
        agg = codes.groupBy(*sorted(keys)).agg(*[f for b in needed for f in (F.min(b).alias(f"__lo_{b}"), F.max(b).alias(f"__hi_{b}"))])
        flat = [(k, b) for k, od, a, b in own if a is None]
        if flat:
            bad = agg.agg(*[F.coalesce(F.max(F.col(f"__lo_{b}") != F.col(f"__hi_{b}")), F.lit(False)).alias(f"t{k}") for k, b in flat])
            rows.append(bad.select(F.explode(F.array(*[F.struct(F.lit(k).alias("task"), F.col(f"t{k}").alias("bad")) for k, _ in flat])).alias("r")).select("r.*"))
        for k, od, a, b in own:
            if a is not None:
                rows.append(segscan.breaks(agg, sorted(od.context), a, f"__lo_{b}", f"__hi_{b}", cuts=cuts and cuts[a]).select(F.lit(k).alias("task"), "bad"))
    return reduce(DataFrame.unionByName, rows)


def check_many(df: DataFrame, ods: Sequence[Canonical], *, encoded: bool = False) -> DataFrame:
    """OD_SCHEMA with ``holds``: few plans for all, each on a table of codes."""
    names = [c for c in df.columns if any(c in o.context or (c == o.attribute if isinstance(o, Constancy) else c in o.pair) for o in ods)]
    codes = df if encoded else rank_encode(df, names)
    spark = df.sparkSession
    bad: set[int] = set()
    todo = [(k, o) for k, o in enumerate(ods) if not is_trivial(o)]
    for at in range(0, len(todo), PLAN_TASKS):
        bad |= {r["task"] for r in verdict_plan(codes, todo[at : at + PLAN_TASKS]).where("bad").collect()}
    return spark.createDataFrame([(*od_row(o, df.columns), k not in bad) for k, o in enumerate(ods)], OD_SCHEMA + ", holds boolean")
