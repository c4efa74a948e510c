"""Sound rules on list dependencies, as generators of consequences; property tests draw on them."""

from __future__ import annotations

from .model import ListOD

Names = tuple[str, ...]


def reflexivity(x: Names, y: Names) -> ListOD:
    return ListOD(x + y, x)


def prefix(od: ListOD, z: Names) -> ListOD:
    return ListOD(z + od.lhs, z + od.rhs)


def transitivity(first: ListOD, second: ListOD) -> ListOD | None:
    return ListOD(first.lhs, second.rhs) if first.rhs == second.lhs else None


def normalization(w: Names, x: Names, y: Names, v: Names) -> tuple[ListOD, ListOD]:
    """A list that comes a second time says nothing new."""
    long, short = w + x + y + x + v, w + x + y + v
    return ListOD(long, short), ListOD(short, long)


def suffix(od: ListOD) -> tuple[ListOD, ListOD]:
    return ListOD(od.lhs, od.rhs + od.lhs), ListOD(od.rhs + od.lhs, od.lhs)


def union(first: ListOD, second: ListOD) -> ListOD | None:
    return ListOD(first.lhs, first.rhs + second.rhs) if first.lhs == second.lhs else None


def replaced(left: Names, old: ListOD, back: ListOD, right: Names) -> tuple[ListOD, ListOD] | None:
    """Order-equivalent lists stand for each other inside any list."""
    if (old.lhs, old.rhs) != (back.rhs, back.lhs):
        return None
    a, b = left + old.lhs + right, left + old.rhs + right
    return ListOD(a, b), ListOD(b, a)


def compatibility(x: Names, y: Names) -> tuple[ListOD, ListOD]:
    """Two lists are order compatible where both of these hold."""
    return ListOD(x + y, y + x), ListOD(y + x, x + y)


def downward_closure(x: Names, y: Names, keep_x: int, keep_y: int) -> tuple[ListOD, ListOD]:
    """Compatible lists stay compatible when both are cut to their first members."""
    return compatibility(x[:keep_x], y[:keep_y])
