"""Registered searches and experiments run over whole relations."""

import pytest

from orderdep import queries as reference
from orderdep.discovery.discover import discover
from orderdep.queries import experiments
from orderdep.queries.experiment_runs import run_exp
from orderdep.sources import relations as R

OVER_1000_ROWS = "/root/testdata/sf0.01"


def test_flight_search_reads_all_rows(spark):
    whole = R.flightlike(spark, OVER_1000_ROWS)
    assert whole.count() > 1000
    x = discover(whole, R.FLIGHTLIKE_10)
    for name, df in (("q_discover_flightlike", x.to_df(spark)), ("q_discover_flightlike_levels", x.levels_df(spark).drop("ms"))):
        assert sorted(map(repr, reference.QUERIES[name](spark, OVER_1000_ROWS).collect())) == sorted(map(repr, df.collect()))


def test_experiments_run_over_all_relations_and_sizes(spark, sf_dir):
    got = {(r["relation"], r["variant"]) for r in reference.QUERIES["q_exp_rows"](spark, sf_dir).collect()}
    assert got == {(n, f"{p}%") for n in ("flightlike", "voterlike", "synth_like") for p in (20, 40, 60, 80, 100)}
    assert {r["n_columns"] for r in reference.QUERIES["q_exp_redundancy"](spark, sf_dir).collect()} == set(range(5, 11))


@pytest.mark.parametrize("exp", ["rows", "columns", "lists", "fd_only", "pruning", "redundancy", "levels", "rewrites"])
def test_registered_experiments_are_not_the_quick_form(spark, sf_dir, monkeypatch, exp):
    asked = []
    monkeypatch.setattr(experiments, "run_exp", lambda spark, d, exp, **options: asked.append((exp, options)) or [])
    reference.QUERIES[f"q_exp_{exp}"](spark, sf_dir)
    assert asked == [(exp, {"budget_s": experiments.BUDGET_S})]


@pytest.mark.parametrize("exp", ["columns", "lists", "fd_only", "pruning", "levels"])
def test_quick_form(spark, sf_dir, exp):
    rows = run_exp(spark, sf_dir, exp, quick=True)
    assert rows and all(r[0] == exp and r[5] >= 0 and r[8] > 0 for r in rows)
    by = {r[4]: r for r in rows}
    if exp == "fd_only":
        assert by["FD only"][9] == "equal FD sets" and by["FD only"][6] == by["set lattice"][6]
    if exp == "pruning":
        # without candidates a search meets every valid dependency, not only the minimal ones
        assert len({r[6:8] for name, r in by.items() if name != "no pruning"}) == 1
        assert by["no pruning"][6] > by["all"][6] and by["no pruning"][7] > by["all"][7] and by["no pruning"][8] > by["all"][8]
    if exp == "levels":
        assert rows[-1][9].endswith("stopped at level 3")


def test_a_stopped_search_says_so(spark, sf_dir):
    assert run_exp(spark, sf_dir, "columns", quick=True, budget_s=0.0)[-1][9] == "stopped by its budget"
