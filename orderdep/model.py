"""Order dependencies as values: two canonical forms over attribute sets, and the list form."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True, order=True)
class Constancy:
    """Within every class of equal ``context`` values, ``attribute`` has one value."""

    context: frozenset[str]
    attribute: str

    def __str__(self) -> str:
        return f"{{{', '.join(sorted(self.context))}}}: [] -> {self.attribute}"


@dataclass(frozen=True)
class Compat:
    """Within every class of equal ``context`` values, the two attributes of ``pair`` never disagree on order."""

    context: frozenset[str]
    pair: frozenset[str]

    @staticmethod
    def of(context: Iterable[str], a: str, b: str) -> Compat:
        return Compat(frozenset(context), frozenset((a, b)))

    def __str__(self) -> str:
        ends = sorted(self.pair)
        return f"{{{', '.join(sorted(self.context))}}}: {ends[0]} ~ {ends[-1]}"


Canonical = Constancy | Compat


@dataclass(frozen=True)
class ListOD:
    """Any order of the rows that is sorted by ``lhs`` is sorted by ``rhs``."""

    lhs: tuple[str, ...]
    rhs: tuple[str, ...]

    def __str__(self) -> str:
        return f"[{', '.join(self.lhs)}] -> [{', '.join(self.rhs)}]"


OD_SCHEMA = 'kind string, context string, "left" string, "right" string, level int, context_size int'.replace('"', "`")


def od_row(od: Canonical, order: list[str]) -> tuple:
    """The row of OD_SCHEMA; sets are listed in the order of the columns."""
    place = {c: k for k, c in enumerate(order)}
    context = sorted(od.context, key=place.__getitem__)
    if isinstance(od, Constancy):
        return "constancy", ",".join(context), None, od.attribute, len(context) + 1, len(context)
    a, b = sorted(od.pair, key=place.__getitem__)
    return "compat", ",".join(context), a, b, len(context) + 2, len(context)


def od_frame(spark: SparkSession, ods: Iterable[Canonical], order: list[str]) -> DataFrame:
    return spark.createDataFrame(sorted((od_row(o, order) for o in ods), key=str), OD_SCHEMA)


def bits(mask: int) -> list[int]:
    out = []
    while mask:
        low = mask & -mask
        out.append(low.bit_length() - 1)
        mask ^= low
    return out


def mask_of(names: Iterable[str], columns: list[str]) -> int:
    return sum(1 << columns.index(n) for n in set(names))


def names_of(mask: int, columns: list[str]) -> frozenset[str]:
    return frozenset(columns[k] for k in bits(mask))
