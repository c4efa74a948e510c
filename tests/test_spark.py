"""Operators on Spark against the definitions and the worked examples."""

import datetime
import json
import math

import pytest
from pyspark.sql import functions as F

from orderdep.discovery.discover import discover, load_state, save_state
from orderdep.discovery.exhaustive import brute_force, enumerate_all
from orderdep.discovery.fd_only import fd_discover
from orderdep.discovery.list_lattice import compare_results, list_lattice_discover
from orderdep.functions.monotone import year_month_of, year_of
from orderdep.inference import implies
from orderdep.mapping import to_canonical
from orderdep.model import Compat, Constancy
from orderdep.operators import partitions as P
from orderdep.operators import segscan, validate as V, violations as W
from orderdep.operators.encode import orderable, rank_encode
from orderdep.plans.rewrite import plan_shape, rewrite, satisfies_order
from orderdep.plans.spec import to_df
from orderdep.queries.rewriting import catalog, flagship_spec
from orderdep.sources import relations as R
from orderdep.sources.catalog import load_catalog, save_catalog


@pytest.fixture(scope="module")
def salary(spark):
    return R.salary_tax(spark).cache()


def pairs(df):
    return {(r["s"], r["t"]) for r in df.collect()}


def test_worked_examples(salary):
    for x, y in ((["sal"], ["tax"]), (["sal"], ["grp", "subg"]), (["yr", "sal"], ["yr", "bin"])):
        assert V.check_list_od(salary, x, y).holds and V.holds_list_od(salary, x, y)
    assert pairs(W.split_pairs(salary, "tid", ["posit"], ["posit", "sal"])) == {("t1", "t4"), ("t2", "t5"), ("t3", "t6")}
    assert ("t1", "t2") in pairs(W.swap_pairs(salary, "tid", ["sal"], ["subg"]))
    assert V.check_constancy(salary, ["posit"], "bin") and V.check_compat(salary, ["yr"], "bin", "sal")
    assert not V.check_constancy(salary, ["posit"], "sal") and not V.check_compat(salary, [], "sal", "subg")
    assert V.check_list_compat(salary, [], ["sal"]) and V.check_list_od(salary, ["sal"], []).holds


def test_partitions(salary, spark):
    stripped = P.strip(P.partition_of(salary, "tid", ["sal"]))
    assert {r["row_id"] for r in stripped.collect()} == {"t2", "t6"}
    tau = R.tau_demo(spark)
    assert [r["rows"] for r in P.sorted_partition(tau, "tid", "a").orderBy("rank").collect()] == [["t3", "t5", "t8"], ["t1", "t6"], ["t4"], ["t7"], ["t2"]]
    inside = {(r["x"], r["rank"]): r["rows"] for r in P.sorted_in_context(tau, "tid", ["x"], "a").collect()}
    assert inside[(3, 1)] == ["t3", "t5"] and inside[(3, 2)] == ["t4"] and inside[(4, 1)] == ["t6"]
    assert P.is_superkey(salary, ["id", "yr"]) and not P.is_superkey(salary, ["id"])
    whole = P.product(P.partition_of(salary, "tid", ["id"]), P.partition_of(salary, "tid", ["yr"]))
    assert whole.select("class_id").distinct().count() == 6


def test_discovery_by_spark_equals_memory_and_definitions(salary, spark, sf_dir):
    columns = ["id", "yr", "bin", "sal", "tax"]
    local, far = discover(salary, columns), discover(salary, columns, validator="spark")
    assert local.ods == far.ods and (len(local.fds), len(local.ocds)) == (16, 10)
    assert {o for o in brute_force(salary, columns)} == enumerate_all(salary, columns)
    orders = R.table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority").limit(400)
    a = discover(orders, validator="spark", falsify=True)
    b = discover(orders, validator="spark", falsify=False)
    assert a.ods == b.ods == discover(orders).ods
    assert fd_discover(orders).ods == a.fds
    twice = orders.union(orders)
    assert discover(twice).ods == a.ods


def test_check_many_agrees(salary):
    columns = ["id", "yr", "bin", "sal", "tax"]
    ods = sorted(enumerate_all(salary, columns), key=str)[:20] + [Compat.of([], "sal", "bin"), Constancy(frozenset(["bin"]), "sal"), Constancy(frozenset(["bin"]), "bin")]
    got = V.check_many(salary.select(*columns), ods)
    assert [r["holds"] for r in got.collect()].count(False) == sum(not V.check(salary, o) for o in ods)


def test_nulls_and_special_numbers(spark):
    nan = float("nan")
    rows = [(None, 1.0, "a"), (None, 1.0, "b"), (0.0, 2.0, None), (-0.0, 2.0, "ab"), (nan, 3.0, "b"), (nan, 3.0, "ba")]
    df = spark.createDataFrame(rows, "x double, y double, s string")
    codes = [(r["x"], r["y"]) for r in rank_encode(df, ["x", "y"]).collect()]
    assert sorted(codes) == [(1, 1), (1, 1), (2, 2), (2, 2), (3, 3), (3, 3)]
    assert V.check_constancy(df, ["x"], "y") and V.check_compat(df, [], "x", "y")
    assert discover(df).ods == discover(df, validator="spark").ods
    assert Constancy(frozenset(["x"]), "y") in discover(df).ods
    kinds = spark.createDataFrame([(True, datetime.date(2020, 1, 1), [1])], "b boolean, d date, arr array<int>")
    assert orderable(kinds) == ["b", "d"]
    with pytest.raises(ValueError):
        discover(kinds, ["arr"])
    empty = df.where("x > 5 and x < 4")
    assert discover(empty).ods == {Constancy(frozenset(), c) for c in ("x", "y", "s")} == discover(empty, validator="spark").ods


def test_segscan_buckets(spark):
    import random

    rng = random.Random(3)
    for _ in range(4):
        rows = [(rng.randrange(2), a, (lo := rng.randrange(6) + a // 2), lo + rng.randrange(2)) for a in range(12)]
        df = spark.createDataFrame(rows, "c int, a long, lo int, hi int")
        want = {(c, a): any(c2 == c and a2 < a and hi2 > lo for c2, a2, _, hi2 in rows) for c, a, lo, _ in rows}
        assert {(r["c"], r["a"]): r["exceeds"] for r in segscan.prefix_exceeds(df, ["c"], "a", "lo", "hi", width=3).collect()} == want
        assert segscan.is_monotone(df, ["c"], "a", "lo", "hi", width=3) == (not any(want.values()))
    none = spark.createDataFrame([], "c int, a long, lo int, hi int")
    assert segscan.is_monotone(none, [], "a", "lo", "hi")


def test_violation_counts_and_witness(spark):
    rows = [(i, i % 3, (i * 7) % 5, (i * 11) % 7) for i in range(40)]
    df = spark.createDataFrame(rows, "id int, c int, a int, b int")
    splits = sum(x[1] == y[1] and x[2] != y[2] for k, x in enumerate(rows) for y in rows[k + 1 :])
    assert W.split_count(df, ["c"], "a").first()["n_pairs"] == splits
    swaps = sum(x[1] == y[1] and x[2] < y[2] and x[3] > y[3] for x in rows for y in rows)
    od = Compat.of(["c"], "a", "b")
    assert W.swap_count(df, od).first()["n_pairs"] == swaps == W.swap_pairs(df, "id", ["a"], ["b"], ["c"]).count()
    s, t = W.witness(df, od, "id").first()
    assert (s, t) in pairs(W.swap_pairs(df, "id", ["a"], ["b"], ["c"])) or (t, s) in pairs(W.swap_pairs(df, "id", ["a"], ["b"], ["c"]))
    assert W.witness(df, Constancy(frozenset(["id"]), "a"), "id").count() == 0
    assert W.violation_summary(df, Constancy(frozenset(["c"]), "a")).count() == 3


def test_list_groups_in_buckets(spark):
    df = spark.createDataFrame([(i % 9 or None, (i * 5) % 7, i % 4) for i in range(60)], "a int, b int, c int")
    for lhs, rhs in ((["a"], ["c"]), (["b", "a"], ["c", "a"]), ([], ["c"])):
        one, other = (sorted(map(repr, V.list_groups(df, lhs, rhs, small=n).select("x", "lo", "hi", "split", "swap").collect())) for n in (1000, 0))
        assert one == other


@pytest.mark.parametrize("kind", ["int", "double", "string"])
def test_swaps_of_a_whole_table_in_buckets(spark, kind, monkeypatch):
    """No context, values that need a dictionary, nulls and both zeros; buckets of two values."""
    for scan in (segscan.prefix_top, segscan.prefix_exceeds):
        monkeypatch.setattr(scan, "__defaults__", (2,))
    made = {"int": lambda n: n, "double": lambda n: -0.0 if n == 4 else n / 2 - 2, "string": lambda n: f"v{n:02d}"}[kind]
    rows = [(i, None if i % 13 == 5 else made((i * 7) % 11), (i * 5) % 8) for i in range(40)] + [(40, made(4) if kind != "double" else 0.0, 3)]
    df = spark.createDataFrame(rows, f"id int, a {kind}, b int")
    first = lambda v: (v is not None, v)
    before = lambda x, y: y[1] is not None and (x[1] is None or x[1] < y[1])
    swapped = {first(y[1]) for x in rows for y in rows if before(x, y) and x[2] > y[2]}
    od = Compat.of([], "a", "b")
    got = W.violation_summary(df, od).first()
    assert (got["n_groups"], got["n_swapped"]) == (len({first(r[1]) for r in rows}), len(swapped))
    s, t = W.witness(df, od, "id").first()
    assert before(rows[s], rows[t]) and rows[s][2] > rows[t][2]


def test_list_baseline(spark, sf_dir):
    cal = R.calendar(spark, sf_dir)
    columns = ["d_date", "d_year", "d_quarter", "d_month"]
    full, lists = discover(cal, columns), list_lattice_discover(cal, columns)
    assert lists.finished and all(implies(full.ods, c) for o in lists.ods for c in to_canonical(o))
    got = compare_results(lists.ods, full.ods)
    assert got.n_fd + got.n_ocd >= len(lists.ods) and got.n_list == len(lists.ods)
    slow = list_lattice_discover(cal, columns, swap_prune=False, split_prune=False)
    assert slow.checks >= lists.checks
    assert not list_lattice_discover(R.clinical_like(spark, sf_dir), time_budget_s=0.0).finished


def test_rewrites_give_equal_results(spark, sf_dir):
    c = catalog(spark, sf_dir)
    spec = flagship_spec(1_000_000)
    new, trace = rewrite(spec, c)
    assert {t.rule for t in trace} == {"group_by", "order_by", "range_join"}
    assert new.group == ("d_year", "d_month") and new.order == ("d_year", "d_month") and new.fact_range is not None
    a, b = to_df(spec, c), to_df(new, c)
    assert [tuple(r) for r in a.collect()] == [tuple(r) for r in b.collect()] and a.columns == b.columns
    ods = c.ods["calendar"]
    assert satisfies_order(["d_date_sk"], ["d_year", "d_quarter", "d_month"], ods) and not satisfies_order(["d_quarter"], ["d_month"], ods)
    plain = rewrite(spec, c, [])[0]
    assert plain == spec
    from dataclasses import replace

    total = replace(spec, group=(), order=(), having=None)
    gone = rewrite(total, c)[0]
    assert gone.dimension is None and plan_shape(to_df(gone, c))["joins"] < plan_shape(to_df(total, c))["joins"]
    assert [tuple(r) for r in to_df(total, c).collect()] == [tuple(r) for r in to_df(gone, c).collect()]


def test_function_ranges_reach_the_scan(spark, sf_dir):
    o = R.table(spark, sf_dir, "orders")
    f = year_month_of("o_orderdate")
    got = o.where(f.between(199511, 199602))
    assert got.count() == o.where(f.build(F.col("o_orderdate")).between(199511, 199602)).count()
    text = o.where(year_of("o_orderdate").between(1996, 1996))._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(o_orderdate" in text


def test_catalog_and_state(spark, sf_dir, tmp_path):
    cal = R.calendar(spark, sf_dir)
    columns = ["d_date", "d_year", "d_quarter", "d_month"]
    state = str(tmp_path / "state.json")
    found = discover(cal, columns, save=save_state(state))
    assert json.load(open(state))["ods"] and discover(cal, columns, start=load_state(state)).ods == found.ods
    save_catalog(spark, found.ods, columns, str(tmp_path / "catalog"))
    assert load_catalog(spark, str(tmp_path / "catalog")) == found.ods


def test_relations_have_their_columns(spark, sf_dir):
    assert {n: len(f(spark, sf_dir).columns) for n, f in R.RELATIONS.items()} == {"flightlike": 40, "voterlike": 20, "clinical_like": 20, "synth_like": 30}
    assert len(R.some_columns(R.synth_like(spark, sf_dir), 7, 1).columns) == 7
    assert not math.isnan(R.share_of_rows(R.calendar(spark, sf_dir), 50).count())
