"""The baseline over lists of columns: candidates [X] -> [Y] with disjoint sides, from short lists to long ones.

Reading of the method: a list of l columns is cut at each place, which gives l - 1 candidates (the front orders the rest, in
both directions over all lists).  A candidate broken by a swap stays broken when both sides grow at the end; one broken
by a split alone may hold with a longer left side, but its right side need not grow under that left side.  Pruned
candidates are not tested.  Repeated columns, shared prefixes, constants and pure compatibilities are never
candidates, so the result is incomplete.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..inference import implies
from ..mapping import to_canonical
from ..model import Canonical, Compat, Constancy, ListOD
from ..operators.encode import orderable
from ..operators.validate import check_list_od
from .verdicts import LOCAL_ROWS, LocalVerdicts


@dataclass
class ListDiscovery:
    columns: list[str]
    ods: list[ListOD] = field(default_factory=list)
    visited: int = 0
    checks: int = 0
    pruned: int = 0
    ms: float = 0.0
    finished: bool = True

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(list(o.lhs), list(o.rhs)) for o in self.ods], "lhs array<string>, rhs array<string>")


class _Lists:
    """Verdicts (split, swap) on lists of columns of a relation in memory; ranks of a list are refined from its front."""

    def __init__(self, local: LocalVerdicts):
        self.local, self.known = local, {(): np.zeros(local.rows, np.int64)}

    def rank(self, columns: tuple[int, ...]) -> np.ndarray:
        if columns not in self.known:
            code = self.local.codes[columns[-1]]
            whole = self.rank(columns[:-1]) * (int(code.max()) + 1 if len(code) else 1) + code
            if len(self.known) > 2_000:
                self.known = {(): self.known[()]}
            self.known[columns] = np.unique(whole, return_inverse=True)[1] if len(whole) else whole
        return self.known[columns]

    def broken(self, x: tuple[int, ...], y: tuple[int, ...]) -> tuple[bool, bool]:
        a, b = self.rank(x), self.rank(y)
        order = np.lexsort((b, a))
        a, b = a[order], b[order]
        same = a[1:] == a[:-1]
        return bool((same & (b[1:] != b[:-1])).any()), bool((~same & (b[1:] < b[:-1])).any())


def list_lattice_discover(df: DataFrame, columns: list[str] | None = None, *, swap_prune: bool = True, split_prune: bool = True, time_budget_s: float = 60.0, max_nodes: int = 2_000_000, max_length: int | None = None) -> ListDiscovery:
    columns = list(columns or orderable(df))
    out, began, m = ListDiscovery(columns), time.monotonic(), len(columns)
    if df.limit(LOCAL_ROWS + 1).count() <= LOCAL_ROWS:
        broken = _Lists(LocalVerdicts.of(df, columns, stripped=False)).broken
    else:

        def broken(x, y):
            r = check_list_od(df, [columns[k] for k in x], [columns[k] for k in y])
            return r.n_split_groups > 0, r.n_swap_groups > 0

    swapped: set[tuple] = set()
    split: set[tuple] = set()
    valid: set[tuple] = set()
    lists: list[tuple[int, ...]] = [(k,) for k in range(m)]
    while lists and (max_length is None or len(lists[0]) < max_length):
        lists = [(*x, k) for x in lists for k in range(m) if k not in x]
        for whole in lists:
            out.visited += 1
            if time.monotonic() - began > time_budget_s or out.visited > max_nodes:
                out.finished, out.ms = False, (time.monotonic() - began) * 1000
                return out
            for cut in range(1, len(whole)):
                x, y = whole[:cut], whole[cut:]
                if swap_prune and any((x[:i], y[:j]) in swapped for i in range(1, len(x) + 1) for j in range(1, len(y) + 1) if (i, j) != (len(x), len(y))):
                    out.pruned += 1
                    continue
                # under a left side that does not determine the front of the right, a longer right cannot hold either
                if split_prune and any((x, y[:j]) in split for j in range(1, len(y))):
                    out.pruned += 1
                    continue
                # the left side's front already orders all of the right: nothing new
                if any((x[:i], y) in valid for i in range(1, len(x))):
                    out.pruned += 1
                    continue
                out.checks += 1
                has_split, has_swap = broken(x, y)
                if has_swap:
                    swapped.add((x, y))
                if has_split:
                    split.add((x, y))
                if not has_split and not has_swap:
                    valid.add((x, y))
                    out.ods.append(ListOD(tuple(columns[k] for k in x), tuple(columns[k] for k in y)))
    out.ms = (time.monotonic() - began) * 1000
    return out


@dataclass(frozen=True)
class Comparison:
    n_list: int
    n_fd: int
    n_ocd: int
    n_redundant: int
    missed: frozenset[Canonical]


def compare_results(lists: list[ListOD], minimal: set[Canonical]) -> Comparison:
    """The baseline's result in canonical form beside a full one: how many, how many not minimal, what it misses."""
    mapped: set[Canonical] = set().union(*(to_canonical(o) for o in lists)) if lists else set()
    n_fd = sum(isinstance(o, Constancy) for o in mapped)
    return Comparison(len(lists), n_fd, sum(isinstance(o, Compat) for o in mapped), len(mapped - minimal), frozenset(o for o in minimal if not implies(mapped, o)))
