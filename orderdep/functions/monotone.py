"""Functions of one ordered argument that keep its order, and what that says without looking at data."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from datetime import date, timedelta

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..model import Canonical, Compat, Constancy


@dataclass(frozen=True)
class Monotone:
    """``argument`` orders ``name`` = build(argument).  ``preimage`` gives the least argument of a value and the first behind it."""

    name: str
    argument: str
    build: Callable[[Column], Column]
    preimage: Callable[[int], tuple] | None = None

    def ods(self) -> set[Canonical]:
        return {Constancy(frozenset([self.argument]), self.name), Compat.of((), self.argument, self.name)}

    def between(self, low: int, high: int) -> Column:
        """low <= name <= high as a range of the argument itself, which scans can use."""
        if self.preimage is None:
            raise ValueError(f"{self.name} has no known preimage")
        c = F.col(self.argument)
        return (c >= F.lit(self.preimage(low)[0])) & (c < F.lit(self.preimage(high)[1]))


def year_of(argument: str) -> Monotone:
    return Monotone(f"year({argument})", argument, F.year, lambda y: (date(y, 1, 1), date(y + 1, 1, 1)))


def year_month_of(argument: str) -> Monotone:
    def span(ym: int) -> tuple:
        y, m = divmod(ym, 100)
        return date(y, m, 1), date(y + m // 12, m % 12 + 1, 1)

    return Monotone(f"year_month({argument})", argument, lambda c: F.year(c) * 100 + F.month(c), span)


def day_of(argument: str) -> Monotone:
    first = date(1970, 1, 1)
    return Monotone(f"day({argument})", argument, F.to_date, lambda d: (first + timedelta(d), first + timedelta(d + 1)))


def floor_by(argument: str, width: int) -> Monotone:
    return Monotone(f"floor({argument}/{width})", argument, lambda c: F.floor(c / width), lambda k: (k * width, (k + 1) * width))


def prefix_of(argument: str, length: int) -> Monotone:
    return Monotone(f"prefix({argument},{length})", argument, lambda c: F.substring(c, 1, length))
