"""The baseline that finds functional dependencies alone, by counts of classes."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame

from ..operators.encode import orderable
from .discover import ALL, Discovery, Prune, search
from .verdicts import verdicts


def fd_discover(df: DataFrame, columns: list[str] | None = None, *, validator: str = "auto", prune: Prune = ALL, **options) -> Discovery:
    """Minimal functional dependencies: the search without pairs, so a set leaves as soon as no constant is open."""
    columns = list(columns or orderable(df))
    began = time.monotonic()
    out = search(verdicts(df, columns, validator), columns, prune=prune, pairs=False, **options)
    out.ms = (time.monotonic() - began) * 1000
    return out
