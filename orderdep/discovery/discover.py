"""Complete discovery of minimal canonical dependencies, level by level over sets of columns.

A level's questions are put together and answered in one go: constancies of all its sets, then pairs.  Pairs look at
the open constants of the level below, so they need only the constants removed there.  Only metadata is kept from level
to level; a level can be saved and taken up again.
"""

from __future__ import annotations

import json
import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession

from ..model import Canonical, Compat, Constancy, bits, names_of, od_frame
from ..operators.encode import orderable
from . import lattice
from .verdicts import Verdicts, verdicts


@dataclass(frozen=True)
class Prune:
    candidates: bool = True
    levels: bool = True
    keys: bool = True
    stripped: bool = True


ALL = Prune()


@dataclass
class LevelStats:
    level: int
    nodes: int = 0
    fd_checks: int = 0
    pair_checks: int = 0
    by_key: int = 0
    pruned: int = 0
    n_fd: int = 0
    n_ocd: int = 0
    ms: float = 0.0


@dataclass
class Discovery:
    columns: list[str]
    ods: set[Canonical] = field(default_factory=set)
    levels: list[LevelStats] = field(default_factory=list)
    ms: float = 0.0
    finished: bool = True

    @property
    def fds(self) -> set[Constancy]:
        return {o for o in self.ods if isinstance(o, Constancy)}

    @property
    def ocds(self) -> set[Compat]:
        return {o for o in self.ods if isinstance(o, Compat)}

    @property
    def checks(self) -> int:
        return sum(s.fd_checks + s.pair_checks for s in self.levels)

    def to_df(self, spark: SparkSession) -> DataFrame:
        return od_frame(spark, self.ods, self.columns)

    def levels_df(self, spark: SparkSession) -> DataFrame:
        rows = [(s.level, s.nodes, s.fd_checks, s.pair_checks, s.by_key, s.pruned, s.n_fd, s.n_ocd, s.ms) for s in self.levels]
        return spark.createDataFrame(rows, "level int, nodes int, fd_checks int, pair_checks int, by_key int, pruned int, n_fd int, n_ocd int, ms double")


def search(v: Verdicts, columns: list[str], *, prune: Prune = ALL, max_level: int | None = None, time_budget_s: float | None = None, pairs: bool = True, start: dict | None = None, save: Callable[[dict], None] | None = None) -> Discovery:
    """The search itself.  ``pairs=False`` leaves compatibilities out.  ``save`` gets the state after each level."""
    began, m = time.monotonic(), len(columns)
    out = Discovery(list(columns))
    everything = (1 << m) - 1
    below, masks = lattice.seed(m)[0], [1 << k for k in range(m)]
    size = 1
    if start:
        out.ods = {_read(o) for o in start["ods"]}
        below = {int(k): lattice.Node(c, set(p)) for k, (c, p) in start["below"].items()}
        masks, size = start["masks"], start["size"]
    found: set[tuple] = set()  # without candidate pruning a constant may be met twice
    while masks and (max_level is None or size <= max_level):
        if time_budget_s is not None and time.monotonic() - began > time_budget_s:
            out.finished = False
            break
        t, stats = time.monotonic(), LevelStats(size, len(masks))
        level = {x: lattice.inherit(x, size, below, prune.candidates, everything) for x in masks}
        key_of: dict[int, bool] = {}

        def key(mask: int) -> bool:
            if mask not in key_of:
                key_of[mask] = prune.keys and v.key(mask)
            return key_of[mask]

        if hasattr(v, "prepare"):
            v.prepare([(x ^ 1 << a, a) for x, node in level.items() for a in bits(x & node.constants)])
        asked, given = [], []
        for x, node in level.items():
            for a in bits(x & node.constants):
                (given if key(x ^ 1 << a) else asked).append((x, a))
        holds = v.constant([(x ^ 1 << a, a) for x, a in asked])
        stats.fd_checks, stats.by_key = len(asked), len(given)
        valid = [t for t, ok in zip(asked, holds) if ok] + given
        for x, a in valid:
            found.add(("fd", x ^ 1 << a, a))
            stats.n_fd += 1
        if prune.candidates:
            for x, a in valid:
                level[x].constants &= ~(1 << a) & x  # nothing outside can be a new constant above
        asked = []
        for x, node in level.items() if pairs and size > 1 else ():
            for p in sorted(node.pairs):
                a, b = bits(p)
                if prune.candidates and not (below[x ^ 1 << b].constants >> a & 1 and below[x ^ 1 << a].constants >> b & 1):
                    node.pairs.discard(p)
                elif prune.candidates and key(x ^ p):
                    node.pairs.discard(p)
                    stats.by_key += 1
                else:
                    asked.append((x, p, a, b))
        stats.pair_checks = len(asked)
        for (x, p, a, b), ok in zip(asked, v.compatible([(x ^ p, a, b) for x, p, a, b in asked])):
            if ok:
                found.add(("compat", x ^ p, a, b))
                level[x].pairs.discard(p)
                stats.n_ocd += 1
        out.ods |= {Constancy(names_of(f[1], columns), columns[f[2]]) if f[0] == "fd" else Compat.of(names_of(f[1], columns), columns[f[2]], columns[f[3]]) for f in found}
        found.clear()
        alive = level
        if prune.levels and prune.candidates and size >= 2:
            alive = {x: n for x, n in level.items() if n.constants or n.pairs}
        stats.pruned = len(level) - len(alive)
        stats.ms = (time.monotonic() - t) * 1000
        out.levels.append(stats)
        below, masks, size = alive, lattice.grow(alive, size), size + 1
        if save:
            save({"size": size, "masks": masks, "below": {str(k): (n.constants, sorted(n.pairs)) for k, n in below.items()}, "ods": [_written(o) for o in out.ods]})
    out.ms = (time.monotonic() - began) * 1000
    return out


def discover(df: DataFrame, columns: list[str] | None = None, *, validator: str = "auto", falsify: bool = True, prune: Prune = ALL, **options) -> Discovery:
    """All minimal canonical dependencies of a relation.  Columns without an order are refused if named, else left out."""
    have = orderable(df)
    if columns and set(columns) - set(have):
        raise ValueError(f"no order on {sorted(set(columns) - set(have))}")
    columns = list(columns or have)
    began = time.monotonic()
    v = verdicts(df, columns, validator, falsify=falsify, stripped=prune.stripped)
    out = search(v, columns, prune=prune, **options)
    return replace(out, ms=(time.monotonic() - began) * 1000)


def _written(o: Canonical) -> list:
    return [sorted(o.context), o.attribute] if isinstance(o, Constancy) else [sorted(o.context), *sorted(o.pair)]


def _read(row: list) -> Canonical:
    return Constancy(frozenset(row[0]), row[1]) if len(row) == 2 else Compat.of(row[0], row[1], row[2])


def save_state(path: str) -> Callable[[dict], None]:
    def save(state: dict) -> None:
        with open(path, "w", encoding="utf-8") as f:
            json.dump(state, f)

    return save


def load_state(path: str) -> dict:
    with open(path, encoding="utf-8") as f:
        return json.load(f)
