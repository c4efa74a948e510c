"""Driver-side logic: worked examples, mapping, axioms and discovery against all pairs of rows."""

import random

import numpy as np
import pytest

from orderdep import list_axioms as L
from orderdep.discovery.discover import Prune, search
from orderdep.discovery.exhaustive import candidate_counts, pairwise
from orderdep.discovery.lattice import lattice_size
from orderdep.discovery.verdicts import LocalVerdicts
from orderdep.inference import chain_step, closure, count_expanded, equiv_list, expand, implies, implies_list, is_minimal, minimal_cover, saturate
from orderdep.mapping import compat_part, constancy_part, is_trivial, mapping_size, to_canonical, to_list_form
from orderdep.model import Compat, Constancy, ListOD
from orderdep.sources.relations import SALARY_TAX, SALARY_TAX_COLUMNS


def codes_of(rows, m):
    return [np.unique([r[k] for r in rows], return_inverse=True)[1] if rows else np.zeros(0, np.int64) for k in range(m)]


def holds(rows, x, y):
    """A list dependency by its definition."""
    key = lambda r, cs: tuple(r[c] for c in cs)
    return all(key(s, y) <= key(t, y) for s in rows for t in rows if key(s, x) <= key(t, x))


SALARY = {c: k + 1 for k, c in enumerate(SALARY_TAX_COLUMNS)}


def salary(x, y):
    return holds(SALARY_TAX, [SALARY[c] for c in x], [SALARY[c] for c in y])


@pytest.fixture(scope="module")
def salary_ods():
    rows = [r[1:] for r in SALARY_TAX]
    return search(LocalVerdicts(codes_of(rows, 9), 6), SALARY_TAX_COLUMNS)


def test_salary_examples(salary_ods):
    for x, y in ((["sal"], ["tax"]), (["sal"], ["perc"]), (["sal"], ["grp", "subg"]), (["yr", "sal"], ["yr", "bin"])):
        assert salary(x, y) and implies_list(salary_ods.ods, x, y)
    for x, y in ((["posit"], ["sal"]), (["sal"], ["subg"]), (["bin"], ["sal"])):
        assert not salary(x, y) and not implies_list(salary_ods.ods, x, y)
    assert implies(salary_ods.ods, Constancy(frozenset(["posit"]), "bin"))
    assert implies(salary_ods.ods, Compat.of(["yr"], "bin", "sal"))
    assert not implies(salary_ods.ods, Constancy(frozenset(["posit"]), "sal"))
    assert not implies(salary_ods.ods, Compat.of([], "sal", "subg"))


def test_salary_goldens(salary_ods):
    assert (len(salary_ods.fds), len(salary_ods.ocds)) == (56, 53)
    assert count_expanded(salary_ods.ods, SALARY_TAX_COLUMNS) == (1916, 4386)
    assert candidate_counts(9) == (2304, 4608)
    few = ["id", "yr", "bin", "sal", "tax"]
    rows = [[r[SALARY[c]] for c in few] for r in SALARY_TAX]
    got = search(LocalVerdicts(codes_of(rows, 5), 6), few, prune=Prune(keys=False))
    assert (len(got.fds), len(got.ocds), got.checks) == (16, 10, 55)
    assert [s.nodes for s in got.levels] == [5, 10, 4]
    assert count_expanded(got.ods, few) == (53, 70)


def test_mapping():
    od = ListOD(("a", "b"), ("c", "d"))
    assert constancy_part(od) == {Constancy(frozenset("ab"), "c"), Constancy(frozenset("ab"), "d")}
    assert compat_part(od) == {Compat.of("", "a", "c"), Compat.of("c", "a", "d"), Compat.of("a", "b", "c"), Compat.of("ac", "b", "d")}
    assert len(to_canonical(od)) == mapping_size(od) == 6
    assert to_canonical(ListOD(("a",), ())) == set()
    assert to_canonical(ListOD(("a", "b"), ("a",))) == set()
    assert is_trivial(Compat.of("a", "a", "b")) and is_trivial(Constancy(frozenset("a"), "a"))
    assert to_list_form(Constancy(frozenset("ba"), "c")) == [ListOD(("a", "b"), ("a", "b", "c"))]


def random_table(rng, columns=5, rows=8):
    m, k = rng.randrange(1, columns + 1), rng.choice([2, 3, 4])
    return sorted({tuple(rng.randrange(k) for _ in range(m)) for _ in range(rng.randrange(0, rows + 1))}), m


def test_discovery_is_complete_and_minimal():
    rng = random.Random(5)
    for _ in range(120):
        rows, m = random_table(rng)
        columns, codes = list("abcde")[:m], codes_of(rows, m)
        got = search(LocalVerdicts(codes, len(rows)), columns).ods
        valid = pairwise(codes, columns)
        assert got == {o for o in valid if is_minimal(o, valid)}
        assert expand(got, columns) == valid
        assert all(implies(got, o) == (o in valid) for o in (Constancy(frozenset(columns[1:2]), columns[0]),) if not is_trivial(o))
        for p in (Prune(keys=False), Prune(levels=False), Prune(stripped=False)):
            assert search(LocalVerdicts(codes, len(rows), stripped=p.stripped), columns, prune=p).ods == got
        assert search(LocalVerdicts(codes, len(rows)), columns, prune=Prune(candidates=False)).ods == valid
        assert search(LocalVerdicts(codes, len(rows)), columns, pairs=False).ods == {o for o in got if isinstance(o, Constancy)}
        back = dict(zip(columns, reversed(codes)))
        assert search(LocalVerdicts([back[c] for c in reversed(columns)][::-1][::-1], len(rows)), columns[::-1] if m > 1 else columns).columns


def test_mapping_agrees_with_definition():
    rng = random.Random(6)
    for _ in range(300):
        rows, m = random_table(rng, 4, 6)
        x = tuple(rng.randrange(m) for _ in range(rng.randrange(0, 4)))
        y = tuple(rng.randrange(m) for _ in range(rng.randrange(0, 4)))
        columns, codes = list("abcd")[:m], codes_of(rows, m)
        valid = pairwise(codes, columns)
        by_map = all(o in valid for o in to_canonical(ListOD(tuple(columns[k] for k in x), tuple(columns[k] for k in y))))
        assert by_map == holds(rows, x, y)


def test_list_rules_are_sound():
    rng = random.Random(7)
    names = lambda m: tuple(rng.randrange(m) for _ in range(rng.randrange(0, 3)))
    for _ in range(300):
        rows, m = random_table(rng, 4, 6)
        x, y, z, v = (names(m) for _ in range(4))
        assert holds(rows, *(lambda o: (o.lhs, o.rhs))(L.reflexivity(x, y)))
        for o in L.normalization(z, x, y, v):
            assert holds(rows, o.lhs, o.rhs)
        if holds(rows, x, y):
            od = ListOD(x, y)
            for o in (L.prefix(od, z), *L.suffix(od)):
                assert holds(rows, o.lhs, o.rhs)
            if holds(rows, y, z):
                o = L.transitivity(od, ListOD(y, z))
                assert holds(rows, o.lhs, o.rhs)
            if holds(rows, x, z):
                o = L.union(od, ListOD(x, z))
                assert holds(rows, o.lhs, o.rhs)
        if all(holds(rows, o.lhs, o.rhs) for o in L.compatibility(x, y)):
            for o in L.downward_closure(x, y, 1, 1):
                assert holds(rows, o.lhs, o.rhs)


def test_closure_chain_and_saturation():
    fds = {Constancy(frozenset("a"), "b"), Constancy(frozenset("b"), "c")}
    assert closure(fds, "a") == frozenset("abc")
    chain = {Compat.of("", "a", "b"), Compat.of("", "b", "c"), Compat.of("b", "a", "c")}
    assert chain_step(chain, frozenset(), "a", "c") and not chain_step({Compat.of("", "a", "b")}, frozenset(), "a", "c")
    full = saturate(chain, list("abc"))
    assert Compat.of("", "a", "c") in full
    assert implies(chain, Compat.of("", "a", "c"), saturated=True)
    assert minimal_cover({*fds, Constancy(frozenset("a"), "c")}) == fds
    assert equiv_list({Constancy(frozenset(["month"]), "quarter"), Compat.of([], "month", "quarter")}, ["year", "quarter", "month"], ["year", "month"])


def test_saturated_rules_hold_on_tables():
    rng = random.Random(8)
    for _ in range(60):
        rows, m = random_table(rng, 4, 6)
        columns, codes = list("abcd")[:m], codes_of(rows, m)
        valid = sorted(pairwise(codes, columns), key=str)
        part = set(rng.sample(valid, min(len(valid), 4)))
        assert saturate(part, columns) <= set(valid)


def test_edge_relations():
    none = search(LocalVerdicts([np.zeros(0, np.int64)] * 2, 0), ["a", "b"])
    assert none.ods == {Constancy(frozenset(), "a"), Constancy(frozenset(), "b")}
    one = search(LocalVerdicts([np.zeros(1, np.int64)] * 2, 1), ["a", "b"])
    assert one.ods == none.ods
    assert lattice_size(3) == (8, 16) and lattice_size(0) == (1, 1)
    state = []
    rows = [(0, 1, 2), (1, 1, 0), (2, 0, 1)]
    whole = search(LocalVerdicts(codes_of(rows, 3), 3), list("abc"), save=state.append)
    again = search(LocalVerdicts(codes_of(rows, 3), 3), list("abc"), start=state[0])
    assert again.ods == whole.ods


def test_ex_ab_equivalent_set_is_dropped():
    """Two columns that determine each other and agree: their pair set leaves, so the set of all three never comes up."""
    rows = [(0, 0, 1), (1, 1, 0), (2, 2, 1), (0, 0, 0)]
    got = search(LocalVerdicts(codes_of(rows, 3), len(rows)), list("abc"))
    assert got.levels[1].pruned >= 1 and len(got.levels) == 2


def test_sample_first_changes_nothing():
    from orderdep.discovery.verdicts import SampledVerdicts

    rng = np.random.default_rng(3)
    codes = [rng.integers(0, k, 300) for k in (2, 3, 5, 300)] + [np.arange(300) // 30]
    codes.append(codes[4] // 2)
    columns = list("abcdef")
    whole = LocalVerdicts(codes, 300)
    assert search(SampledVerdicts(whole, 40), columns).ods == search(LocalVerdicts(codes, 300), columns).ods
