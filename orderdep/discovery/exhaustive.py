"""Without pruning: every non-trivial candidate gets a verdict; and verdicts straight from the definitions."""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame

from ..model import Canonical, Compat, Constancy, names_of
from ..operators.encode import orderable
from .verdicts import LocalVerdicts, verdicts

MOST_COLUMNS = 10
MOST_ROWS = 2_000


def candidate_counts(columns: int) -> tuple[int, int]:
    """Non-trivial candidates: constancies and compatibilities."""
    m = columns
    return m * 2 ** (m - 1) if m else 0, m * (m - 1) // 2 * 2 ** (m - 2) if m > 1 else 0


def enumerate_all(df: DataFrame, columns: list[str] | None = None, validator: str = "auto") -> set[Canonical]:
    """All valid non-trivial dependencies, minimal or not."""
    columns = columns or orderable(df)
    m = len(columns)
    if m > MOST_COLUMNS:
        raise ValueError(f"{m} columns have {sum(candidate_counts(m)):,} candidates; at most {MOST_COLUMNS} columns are enumerated")
    v = verdicts(df, columns, validator)
    ones = [(c, a) for c in range(1 << m) for a in range(m) if not c >> a & 1]
    twos = [(c, a, b) for c in range(1 << m) for a, b in combinations(range(m), 2) if not c >> a & 1 and not c >> b & 1]
    out: set[Canonical] = {Constancy(names_of(c, columns), columns[a]) for (c, a), ok in zip(ones, v.constant(ones)) if ok}
    return out | {Compat.of(names_of(c, columns), columns[a], columns[b]) for (c, a, b), ok in zip(twos, v.compatible(twos)) if ok}


def brute_force(df: DataFrame, columns: list[str] | None = None) -> set[Canonical]:
    """The same from all pairs of rows; for tests on small relations."""
    columns = columns or orderable(df)
    v = LocalVerdicts.of(df, columns)
    if v.rows > MOST_ROWS:
        raise ValueError(f"at most {MOST_ROWS} rows")
    return pairwise(v.codes, columns)


def pairwise(codes: list[np.ndarray], columns: list[str]) -> set[Canonical]:
    n, m = len(codes[0]) if codes else 0, len(columns)
    s, t = np.triu_indices(n, 1)
    sign = [np.sign(c[s] - c[t]) for c in codes]
    out: set[Canonical] = set()
    for mask in range(1 << m):
        same = np.ones(len(s), bool)
        for k in range(m):
            if mask >> k & 1:
                same &= sign[k] == 0
        rest = [k for k in range(m) if not mask >> k & 1]
        out |= {Constancy(names_of(mask, columns), columns[a]) for a in rest if not (same & (sign[a] != 0)).any()}
        out |= {Compat.of(names_of(mask, columns), columns[a], columns[b]) for a, b in combinations(rest, 2) if not (same & (sign[a] * sign[b] < 0)).any()}
    return out
