"""Measures of results and runs."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..inference import implies, is_minimal
from ..model import Canonical, Constancy
from ..operators.validate import check


def summarise(ods: DataFrame) -> DataFrame:
    """Rows of OD_SCHEMA -> n_fd, n_ocd, and the size of the largest context."""
    return ods.agg(F.count_if(F.col("kind") == "constancy").alias("n_fd"), F.count_if(F.col("kind") == "compat").alias("n_ocd"), F.coalesce(F.max("context_size"), F.lit(0)).alias("largest_context"))


@dataclass(frozen=True)
class Quality:
    recall: float
    soundness: float
    conciseness: float


def quality(found: Iterable[Canonical], reference: Iterable[Canonical], df: DataFrame | None = None) -> Quality:
    """Share of the full result that ``found`` implies, share of ``found`` that holds, share of ``found`` that is minimal.

    What holds is read off the full result; with ``df`` it is checked on the relation instead.
    """
    found, reference = set(found), set(reference)
    share = lambda n, of: n / of if of else 1.0
    valid = [o for o in found if (check(df, o) if df is not None else implies(reference, o))]
    minimal = sum(is_minimal(o, reference) for o in valid)
    return Quality(share(sum(implies(found, o) for o in reference), len(reference)), share(len(valid), len(found)), share(minimal, len(found)))


@dataclass(frozen=True)
class Timing:
    mean_ms: float
    least_ms: float
    runs: int
    censored: bool


def timed(f: Callable[[], Any], runs: int = 10, budget_s: float | None = None, warm: bool = True) -> Timing:
    """Mean time of some runs after one that warms up; stops, and says so, when the budget is used up."""
    began, took = time.monotonic(), []
    if warm:
        f()
    for _ in range(runs):
        if budget_s is not None and time.monotonic() - began > budget_s:
            break
        t = time.monotonic()
        f()
        took.append((time.monotonic() - t) * 1000)
    return Timing(sum(took) / len(took) if took else float("nan"), min(took, default=float("nan")), len(took), len(took) < runs)


def growth_fit(series: DataFrame, x: str, y: str, by: str | None = None) -> DataFrame:
    """(slope, r2) of log y on log x for a power law in rows, and of log y on x for exponential growth in columns."""
    positive = series.where((F.col(x) > 0) & (F.col(y) > 0)).select(*([by] if by else []), F.col(x).cast("double").alias("__x"), F.log(F.col(y).cast("double")).alias("__y"))
    lx = F.log("__x")
    fits = [F.regr_slope("__y", lx).alias("power"), F.regr_r2("__y", lx).alias("power_r2"), F.regr_slope("__y", F.col("__x")).alias("rate"), F.regr_r2("__y", F.col("__x")).alias("rate_r2")]
    return positive.groupBy(*([by] if by else [])).agg(*fits)


def job_costs(spark, group: str) -> dict[str, int]:
    """Jobs, stages and tasks of a job group set with ``spark.sparkContext.setJobGroup``."""
    tracker = spark.sparkContext.statusTracker()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {s for j in jobs if (info := tracker.getJobInfo(j)) for s in info.stageIds}
    tasks = sum(i.numTasks for s in stages if (i := tracker.getStageInfo(s)))
    return {"jobs": len(jobs), "stages": len(stages), "tasks": tasks}


def by_kind(ods: Iterable[Canonical]) -> tuple[int, int]:
    ods = list(ods)
    n = sum(isinstance(o, Constancy) for o in ods)
    return n, len(ods) - n
