"""The experiments on the stand-in relations, over all their relations and sizes."""

from __future__ import annotations

from ..sources import relations as R
from .experiment_runs import RESULT, run_exp

QUERIES, SQL = {}, {}
#: Seconds after which a registered search starts no further level; bench/ gives 60.
BUDGET_S = 20.0


def _registered(exp: str) -> None:
    def run(spark, d):
        return spark.createDataFrame(run_exp(spark, d, exp, budget_s=BUDGET_S), RESULT)

    run.__doc__ = f"Experiment {exp}, all relations and sizes: times, counts and variants side by side."
    QUERIES[f"q_exp_{exp}"] = run


for _exp in ("rows", "columns", "lists", "fd_only", "pruning", "redundancy", "levels", "rewrites"):
    _registered(_exp)


def q_relation_sizes(spark, d):
    """Rows and columns of the stand-ins."""
    return spark.createDataFrame([(n, f(spark, d).count(), len(f(spark, d).columns)) for n, f in R.RELATIONS.items()], "relation string, n_rows long, n_columns long")


QUERIES["q_relation_sizes"] = q_relation_sizes
SQL["q_relation_sizes"] = """SELECT 'flightlike' AS relation, count(*) AS n_rows, CAST(40 AS BIGINT) AS n_columns FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey WHERE year(l_shipdate) = 1996
UNION ALL SELECT 'voterlike', count(*), 20 FROM customer UNION ALL SELECT 'clinical_like', least(count(*), 155), 20 FROM customer UNION ALL SELECT 'synth_like', count(*), 30 FROM lineitem"""
