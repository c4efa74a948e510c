"""The near-duplicate stage against all pairs by brute force."""

import random

import numpy as np
import pytest

from orderdep.llm import simhash

SCHEMA = "doc_id long, text string"


def similarity(a, b, size=5):
    one, two = ({" ".join(w[i : i + size]) for i in range(max(1, len(w) - size + 1))} for w in (a.lower().split(), b.lower().split()))
    return len(one & two) / len(one | two)


def brute(rows, least=0.8):
    """The ids that stay of (doc_id, text) rows with different ids."""
    root = {i: i for i, _ in rows}

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, (i, t) in enumerate(rows):
        for j, u in rows[:k]:
            if similarity(t, u) >= least:
                a, b = sorted((top(i), top(j)))
                root[b] = a
    return sorted({top(i) for i in root})


def stay(spark, rows):
    return sorted(r["doc_id"] for r in simhash.one_of_each(spark.createDataFrame(rows, SCHEMA).repartition(3)).select("doc_id").collect())


@pytest.mark.parametrize("kind", ["appended", "replaced", "changed words"])
def test_pairs_at_the_threshold_are_found(spark, kind):
    """Copies at 0.8 to 0.86, over words as unevenly spread as in prose."""
    rng = random.Random(kind)
    vocabulary, weights = [f"w{k}" for k in range(20_000)], [1 / (k + 1) for k in range(20_000)]
    words = lambda n: rng.choices(vocabulary, weights, k=n)
    rows = []
    for k in range(60):
        w = words(200)
        if kind == "appended":
            v = w + words(rng.randrange(35, 50))
        elif kind == "replaced":
            n = rng.randrange(15, 20)
            v = w[:90] + words(n) + w[90 + n :]
        else:
            v = list(w)
            for at in (20, 70, 120, 170):
                v[at] = "changed"
        rows += [(k, " ".join(w)), (1000 + k, " ".join(v))]
    assert all(similarity(rows[k][1], rows[k + 1][1]) >= 0.78 for k in range(0, len(rows), 2))
    assert stay(spark, rows) == brute(rows)


def test_same_words_in_another_order_both_stay(spark):
    rng = random.Random(1)
    words = [f"w{k}" for k in range(300)]
    rows = []
    for k in range(6):
        rng.shuffle(words)
        rows.append((k, " ".join(words)))
    rows += [(10, rows[0][1] + " w0 w1"), (11, rows[3][1].upper()), (12, rows[3][1].replace(" ", "\n"))]
    assert stay(spark, rows) == brute(rows) == list(range(6))


def test_links_that_fail_do_not_hide_true_ones(spark):
    """Texts of one template, most of them at 0.5 to 0.75, so that they meet without a link; a few are true copies."""
    rng = random.Random(2)
    template = [f"t{k}" for k in range(300)]
    rows = []
    for k in range(60):
        w = list(template)
        at = rng.randrange(0, 240)
        w[at : at + 25] = [f"own{k}_{n}" for n in range(25)]
        rows.append((rng.randrange(1 << 40), " ".join(w)))
        if k % 4 == 0:
            w[at + 30] = f"copy{k}"
            rows.append((rng.randrange(1 << 40), " ".join(w)))
    assert stay(spark, rows) == brute(rows)


def test_candidates_come_by_fingerprints(spark, monkeypatch):
    """Without the tables of least shingles the pairs within the fingerprints' radius are still found, and only these are tested."""
    rng = random.Random(4)
    rows = []
    for k in range(40):
        w = [f"v{rng.randrange(5000)}" for _ in range(400)]
        rows += [(k, " ".join(w)), (100 + k, " ".join([*w[:399], "last"]))]
    near = lambda a, b: ((simhash.fingerprint(a.encode(), 5) ^ simhash.fingerprint(b.encode(), 5)) & (1 << 64) - 1).bit_count() <= simhash.RADIUS
    linked = [100 + k for k in range(40) if near(rows[2 * k][1], rows[2 * k + 1][1])]
    assert len(linked) > 20
    monkeypatch.setattr(simhash, "meeting", lambda entries, f=simhash.meeting: f(entries.where(f"place = {simhash.TABLES}")))
    assert stay(spark, rows) == sorted({i for i, _ in rows} - set(linked))


def test_a_class_of_fingerprints_is_compared_whole(spark, monkeypatch):
    """Equal fingerprints are candidates, not links; a true link between two of a class is found behind failing ones."""
    monkeypatch.setattr(simhash, "first_table", lambda same: np.full(len(same), simhash.TABLES))
    rows = [(k, " ".join(f"{k % 6}a{n + k // 6}" for n in range(200))) for k in range(12)]
    nodes = spark.createDataFrame([(k, 7, k) for k in range(12)], "fp long, print long, row long")
    met = simhash.fingerprint_entries(nodes)
    assert met.select("entry").distinct().count() == 1 and met.count() == 12
    sets = simhash.shingle_sets(spark.createDataFrame([(k, t.encode()) for k, t in rows], "fp long, text binary"), 5)
    got = {(r["a"], r["b"]) for r in simhash.true_links(simhash.meeting(met), sets.cache(), 0.8).collect()}
    assert got == {(k, k + 6) for k in range(6)}
