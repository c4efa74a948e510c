"""Between list dependencies and their canonical families."""

from __future__ import annotations

from .model import Canonical, Compat, Constancy, ListOD


def is_trivial(od: Canonical) -> bool:
    """Holds on every table: a constant of its own context, or a pair with a member of the context or with itself."""
    if isinstance(od, Constancy):
        return od.attribute in od.context
    return len(od.pair) == 1 or bool(od.pair & od.context)


def constancy_part(od: ListOD) -> set[Constancy]:
    """That lhs determines rhs: each right attribute is constant in the context of all left ones."""
    return {Constancy(frozenset(od.lhs), b) for b in od.rhs}


def compat_part(od: ListOD) -> set[Compat]:
    """That lhs and rhs never disagree: every pair of places, in the context of all that stand before either."""
    return {Compat.of(od.lhs[:i] + od.rhs[:j], a, b) for i, a in enumerate(od.lhs) for j, b in enumerate(od.rhs)}


def to_canonical(od: ListOD, keep_trivial: bool = False) -> set[Canonical]:
    return {c for c in constancy_part(od) | compat_part(od) if keep_trivial or not is_trivial(c)}


def to_list_form(od: Canonical) -> list[ListOD]:
    """List dependencies that say the same; one order of the context is enough."""
    c = tuple(sorted(od.context))
    if isinstance(od, Constancy):
        return [ListOD(c, (*c, od.attribute))]
    a, b = sorted(od.pair) if len(od.pair) == 2 else tuple(od.pair) * 2
    return [ListOD((*c, a, b), (*c, b, a)), ListOD((*c, b, a), (*c, a, b))]


def mapping_size(od: ListOD) -> int:
    """Members before trivial and equal ones are dropped."""
    return len(od.rhs) + len(od.lhs) * len(od.rhs)
