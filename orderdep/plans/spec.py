"""A small logical description of star queries, and the DataFrame it stands for."""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Dimension:
    """A dimension joined to the fact by ``fact_key`` = ``key``."""

    name: str
    fact_key: str
    key: str


@dataclass(frozen=True)
class Range:
    """low <= column <= high."""

    column: str
    low: object
    high: object


@dataclass(frozen=True)
class QuerySpec:
    fact: str
    dimension: Dimension | None = None
    ranges: tuple[Range, ...] = ()
    group: tuple[str, ...] = ()
    #: Columns that leave the grouping but stay in the output: one value a group.
    carried: tuple[str, ...] = ()
    aggregates: tuple[tuple[str, str], ...] = ()
    having: str | None = None
    order: tuple[str, ...] = ()
    distinct: tuple[str, ...] = ()
    #: An extra filter on the fact that a rewrite found.
    fact_range: Range | None = None
    #: A filter that no row passes: a probe found no dimension row.
    empty: bool = False


@dataclass(frozen=True)
class Trace:
    rule: str
    what: str


@dataclass
class Catalog:
    """Tables with the dependencies that hold on them, and facts whose keys are covered by a dimension and not null."""

    tables: Mapping[str, DataFrame]
    ods: Mapping[str, set] = field(default_factory=dict)
    covered: set[tuple[str, str, str]] = field(default_factory=set)  # (fact, fact key, dimension)
    sorted_by: Mapping[str, tuple[str, ...]] = field(default_factory=dict)


def to_df(spec: QuerySpec, catalog: Catalog) -> DataFrame:
    df = catalog.tables[spec.fact]
    if spec.empty:
        df = df.where(F.lit(False))
    if spec.fact_range is not None:
        df = df.where(F.col(spec.fact_range.column).between(spec.fact_range.low, spec.fact_range.high))
    if spec.dimension is not None:
        d = spec.dimension
        df = df.join(catalog.tables[d.name], F.col(d.fact_key) == F.col(d.key))
    for r in spec.ranges:
        df = df.where(F.col(r.column).between(r.low, r.high))
    if spec.distinct:
        df = df.select(*spec.distinct).distinct()
    if spec.group or spec.aggregates:
        aggs: list[Column] = [F.min(c).alias(c) for c in spec.carried] + [F.expr(e).alias(n) for n, e in spec.aggregates]
        df = df.groupBy(*spec.group).agg(*aggs)
    if spec.having:
        df = df.where(spec.having)
    if spec.group or spec.aggregates:
        df = df.select(*sorted({*spec.group, *spec.carried}), *[n for n, _ in spec.aggregates])
    return df.orderBy(*spec.order) if spec.order else df
