"""Verdicts on canonical dependencies over bit masks: from a bounded relation in memory or by Spark plans."""

from __future__ import annotations

import math
import re
from collections.abc import Iterable, Sequence
from typing import Protocol

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Compat, bits
from ..operators import segscan
from ..operators.encode import order_codes
from ..operators.validate import PLAN_TASKS, ordered, verdict_plan
from ..storage import shuffles_dropped, stored

#: Different rows up to which a relation is small enough for one process; its size is counted before it is fetched.
LOCAL_ROWS = 800_000
LOCAL_CELLS = 8_000_000
#: Rows from which a relation in memory is asked through a sample first.
SAMPLED_ROWS = 10_000


#: Contexts of one aggregate by grouping sets: so many times are the rows read into partial aggregates at most.
GROUPING_SETS = 24
#: Different values from which a column has a sample of whole classes; classes that partial aggregates hold with ease.
MANY_VALUES, FEW_CLASSES = 1_000, 200_000
#: Cells of the crowded rows of one context that are fetched into memory, and of all such rows that are kept.
CROWDED_CELLS, KEPT_CELLS = 2_000_000, 16_000_000
#: Rows of a task that reads whole classes, and bounds of buckets at most.
TASK_ROWS, MOST_CUTS = 500_000, 255


class Verdicts(Protocol):
    def constant(self, tasks: Sequence[tuple[int, int]]) -> list[bool]: ...

    def compatible(self, tasks: Sequence[tuple[int, int, int]]) -> list[bool]: ...

    def key(self, mask: int) -> bool: ...


class LocalVerdicts:
    """Dense codes in arrays.  Class numbers of a set are refined from those of a subset; rows that are alone in their
    class can break nothing and are left out."""

    def __init__(self, codes: list[np.ndarray], rows: int, stripped: bool = True, keep: int = 4_000):
        self.codes, self.rows, self.stripped, self.most = codes, rows, stripped, keep
        self.known: dict[int, tuple[np.ndarray, np.ndarray, int]] = {}

    @staticmethod
    def of(df: DataFrame, columns: list[str], **options) -> LocalVerdicts:
        """The different rows of a relation whose size has been checked."""
        table = df.select(*columns).distinct().toArrow()
        return LocalVerdicts([dense(table.column(c)) for c in columns], table.num_rows, **options)

    def classes(self, mask: int) -> tuple[np.ndarray, np.ndarray, int]:
        """(rows, their class numbers, classes in all); without lone rows if stripped."""
        got = self.known.get(mask)
        if got is not None:
            return got
        if not mask:
            rows, ids, n = np.arange(self.rows, dtype=np.int32), np.zeros(self.rows, np.int32), int(self.rows > 0)
        else:
            base = next((mask ^ 1 << k for k in reversed(bits(mask)) if mask ^ 1 << k in self.known), mask ^ 1 << mask.bit_length() - 1)
            k = bits(mask ^ base)[0]
            rows, ids, n_base = self.classes(base)
            lone = n_base - (int(ids.max()) + 1 if len(ids) else 0) if self.stripped else 0
            code = self.codes[k][rows]
            ids, size = numbered(ids.astype(np.int64) * (int(code.max()) + 1 if len(code) else 1) + code)
            n = len(size) + lone
            if self.stripped and len(size):
                big = size > 1
                number = np.cumsum(big, dtype=np.int32) - 1
                stay = big[ids]
                rows, ids = rows[stay], number[ids[stay]]
        if len(self.known) >= self.most:
            self.known.clear()
        self.known[mask] = rows, ids, n
        return self.known[mask]

    def count(self, mask: int) -> int:
        return self.classes(mask)[2]

    def constant(self, tasks):
        return [self.count(context) == self.count(context | 1 << a) for context, a in tasks]

    def compatible(self, tasks):
        return [self._compatible(*t) for t in tasks]

    def _compatible(self, context: int, a: int, b: int) -> bool:
        rows, ids, _ = self.classes(context)
        x, y = self.codes[a][rows], self.codes[b][rows]
        n_x, n_y = (int(v.max(initial=0)) + 1 for v in (x, y))
        if (int(ids.max(initial=0)) + 1) * n_x * n_y < 1 << 62:  # one number a row sorts faster than three
            i, y = np.divmod(np.sort((ids.astype(np.int64) * n_x + x) * n_y + y), n_y)
            i, x = np.divmod(i, n_x)
        else:
            order = np.lexsort((y, x, ids))
            i, x, y = ids[order], x[order], y[order]
        return not ((i[1:] == i[:-1]) & (x[1:] != x[:-1]) & (y[1:] < y[:-1])).any()

    def key(self, mask: int) -> bool:
        return self.count(mask) == self.rows


def numbered(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(a number for each key from 0, equal for equal keys; how often each number comes)."""
    import pyarrow as pa

    ids = pa.array(keys).dictionary_encode().indices.to_numpy()
    return ids, np.bincount(ids)


class SampledVerdicts:
    """Asks samples of the rows first and the whole relation only about what they do not break: rows at random, and all rows
    of some values of each column with many, which hold the classes of every context with that column whole."""

    def __init__(self, whole: LocalVerdicts, sample_rows: int = 2_000):
        draw = np.random.Generator(np.random.PCG64(17))
        at = np.sort(draw.choice(whole.rows, sample_rows, replace=False))
        more = []
        for c in whole.codes:
            n = int(c.max()) + 1
            if MANY_VALUES <= n < whole.rows:
                chosen = draw.random(n) < sample_rows * 10 / whole.rows
                more.append(np.flatnonzero(chosen[c]))
        more.append(np.sort(draw.choice(whole.rows, min(whole.rows, sample_rows * 10), replace=False)))
        self.whole = whole
        self.samples = [LocalVerdicts([c[rows] for c in whole.codes], len(rows), whole.stripped, keep=256) for rows in (at, *more)]

    def _both(self, name: str, tasks):
        out = [True] * len(tasks)
        for v in (*self.samples, self.whole):
            left = [k for k, ok in enumerate(out) if ok]
            for k, ok in zip(left, getattr(v, name)([tasks[k] for k in left])):
                out[k] = ok
        return out

    def constant(self, tasks):
        return self._both("constant", tasks)

    def compatible(self, tasks):
        return self._both("compatible", tasks)

    def key(self, mask: int) -> bool:
        return all(v.key(mask) for v in (*self.samples, self.whole))


def dense(column) -> np.ndarray:
    """Dense ranks of an Arrow column: null first, then values, NaN last."""
    coded = column.combine_chunks().dictionary_encode(null_encoding="encode")
    return _ranks(coded.dictionary)[coded.indices.to_numpy()]


def _ranks(column) -> np.ndarray:
    import pyarrow as pa
    import pyarrow.compute as pc

    if pa.types.is_floating(column.type):
        v = np.asarray(column.fill_null(0).to_numpy(zero_copy_only=False), float) + 0.0
    elif pa.types.is_string(column.type) or pa.types.is_large_string(column.type) or pa.types.is_decimal(column.type):
        v = np.array(column.to_pylist(), object)
    elif pa.types.is_date32(column.type):
        v = column.cast(pa.int32()).cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False)
    else:
        v = column.cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False) if not pa.types.is_boolean(column.type) else column.fill_null(False).to_numpy(zero_copy_only=False).astype(np.int64)
    null = pc.is_null(column).to_numpy(zero_copy_only=False)
    out = np.zeros(len(v), np.int64)
    if (~null).any():
        out[~null] = np.unique(v[~null], return_inverse=True)[1] + 1
    return np.unique(out, return_inverse=True)[1] if len(out) else out


class SparkVerdicts:
    """Plans over a table of codes (stored unless they come row by row), behind samples: what a part of the rows breaks is broken.

    One sample takes rows at random; the others take all rows of some values of one column with many, so that the classes
    of every context with that column are there whole.  What they leave open is asked of all rows: contexts of few
    classes together, by one aggregate by grouping sets; a context of many classes by rows dealt out by its classes, which
    cross the network once for all contexts with a part in common and in no partial aggregate.  A context that a sample shows to have a class of many rows
    keeps partial aggregates, and buckets for compatibilities.

    A row that is alone in its class of a context is alone in every context above it.  So where the samples tell that few
    rows of a context share their class with others, those crowded rows are fetched once, if they are counted to be few, and
    answer for that context and all above it, and are one more sample for the others.
    """

    def __init__(self, df: DataFrame, columns: list[str], *, falsify: bool = True, sample_rows: int = 2_000, stripped: bool = True):
        self.columns, self.spark = columns, df.sparkSession
        self.safe = [f"c{k}" for k in range(len(columns))]
        with shuffles_dropped(self.spark):
            relation = once(df.select(*columns))
            codes, self.rows, self.distinct = order_codes(relation.toDF(*self.safe))
            self.codes = codes if row_by_row(codes) else stored(codes, "codes")
            drawn = self.codes.sample(min(1.0, sample_rows * 10 / max(1, self.rows)), 17).limit(sample_rows * 20).toArrow()
            #: Rows drawn at random, repeated ones too: the weights of classes and the spread of values are read off them.
            self.spread = np.array([c.to_numpy() for c in drawn.columns], np.int64).reshape(len(columns), -1)
            self.samples, self.whole_classes = [], {}
            if falsify and self.rows > sample_rows:
                rows = np.random.Generator(np.random.PCG64(17)).permutation(np.unique(self.spread, axis=1), axis=1)
                self.samples = [LocalVerdicts([np.unique(c, return_inverse=True)[1] for c in x], x.shape[1], stripped) for x in (rows[:, :sample_rows], rows)]
                for k, (c, n) in enumerate(zip(self.safe, self.distinct)):
                    if n >= MANY_VALUES:
                        share = F.pmod(F.xxhash64(c, F.lit(k)), F.lit(1 << 20)) < math.ceil((1 << 20) * min(1.0, sample_rows * 25 / self.rows))
                        self.whole_classes[k] = LocalVerdicts.of(self.codes.where(share).limit(sample_rows * 50), self.safe, stripped=stripped, keep=64)
                        self.samples.append(self.whole_classes[k])
        self.killed = self.sent = 0
        self.sets: dict[int, tuple[int, int]] = {}  # context -> masks of the columns asked of it and of those constant in it
        self.heavy: dict[int, bool] = {}
        self.stripped = stripped
        self.fetched: dict[int, LocalVerdicts] = {}  # context -> its crowded rows
        self.about: dict[int, float] = {}
        self.most_crowded = CROWDED_CELLS // max(1, len(columns)) if self.samples else 0
        self.cuts: dict[int, list[int]] = {}

    def _names(self, mask: int) -> list[str]:
        return [self.safe[k] for k in bits(mask)]

    def _alive(self, name: str, tasks: Sequence[tuple]) -> list[bool]:
        out = [True] * len(tasks)
        for s in (*self.samples, *self.fetched.values()):
            left = [k for k, ok in enumerate(out) if ok]
            for k, ok in zip(left, getattr(s, name)([tasks[k] for k in left])):
                out[k] = ok
        return out

    def _maybe_key(self, mask: int) -> bool:
        return all(s.key(mask) for s in (*self.samples, *self.fetched.values()))

    def _few(self, mask: int) -> bool:
        """Whether a context has few classes, so that partial aggregates are small."""
        return math.prod(max(1, self.distinct[k]) for k in bits(mask)) <= FEW_CLASSES

    def _heavy(self, mask: int) -> bool:
        """Whether the rows drawn at random show a class that is large for one task."""
        if not mask:
            return True
        if mask not in self.heavy:
            size = np.unique(self.spread[bits(mask)], axis=1, return_counts=True)[1]
            self.heavy[mask] = int(size.max(initial=0)) * 100 > self.spread.shape[1]
        return self.heavy[mask]

    def _dealt(self, mask: int, more: list[str]) -> DataFrame:
        """The columns of a context and some more, all rows of a class in one task unless a class is large."""
        keys = self._names(mask)
        some = self.codes.select(*keys, *more)
        return some if self._heavy(mask) else some.repartition(self._tasks(), *keys)

    def _tasks(self) -> int:
        return max(int(self.spark.conf.get("spark.sql.shuffle.partitions")), self.rows // TASK_ROWS)

    def _crowded(self, mask: int) -> float:
        """About how many rows share their class of a context with others, read off the samples."""
        if mask not in self.about:
            whole = [s for k, s in self.whole_classes.items() if mask >> k & 1 and s.rows]
            shares = []
            for s in whole or self.samples[1:2]:
                size = np.bincount(s.classes(mask)[1])
                if whole:
                    shares.append(size[size > 1].sum() / s.rows)
                else:  # pairs grow with the square; one more, as none drawn does not mean none
                    shares.append((size @ (size - 1) + 2) * self.rows / s.rows**2)
            self.about[mask] = max(shares) * self.rows
        return self.about[mask]

    def _above(self, mask: int) -> LocalVerdicts | None:
        """The crowded rows of a context below this one, or of itself; fetched first if the samples tell that they are few."""
        for c, v in self.fetched.items():
            if not c & ~mask:
                return v
        if not self.most_crowded or self._few(mask) or self._crowded(mask) > self.most_crowded:
            return None
        while True:  # the fewer columns, the more contexts above
            least = min((mask ^ 1 << k for k in bits(mask)), key=self._crowded)
            if self._crowded(least) > self.most_crowded * 0.8:
                break
            mask = least
        return self._fetch(mask)

    def _fetch(self, mask: int) -> LocalVerdicts | None:
        most = self.most_crowded
        hashed = self.codes.withColumn("h", F.xxhash64(*self._names(mask)))
        with shuffles_dropped(self.spark):
            # classes of one hash only bring rows that are alone
            shared = hashed.select("h").repartition(self._tasks(), "h").groupBy("h").agg(F.count("*").alias("n")).where("n > 1").select("h").limit(most + 1).toArrow()
            table = None
            if shared.num_rows <= most:
                table = hashed.join(F.broadcast(self.spark.createDataFrame(shared)), "h", "left_semi").select(*self.safe).distinct().limit(most * 2 + 1).toArrow()
        if table is None or table.num_rows > most * 2:
            self.most_crowded = 0  # the samples mislead: rows repeat, or are far apart
            return None
        v = LocalVerdicts([dense(c) for c in table.columns], table.num_rows, self.stripped, keep=64)
        self.fetched[mask] = v
        while sum(x.rows for x in self.fetched.values()) * len(self.columns) > KEPT_CELLS:
            self.fetched.pop(next(iter(self.fetched)))
        return v

    def _bases(self, contexts: Iterable[int]) -> dict[int, list[int]]:
        """The contexts by a part they share of which no class is large, so that one deal of the rows serves them all."""
        out: list[list] = []
        for c in sorted(contexts, key=lambda c: (c.bit_count(), c)):
            near = next((g for g in out if not self._heavy(g[0] & c)), None)
            if near:
                near[0] &= c
                near[1].append(c)
            else:
                out.append([c, [c]])
        return {base: own for base, own in out}

    def _apart(self, tasks: Sequence[tuple[int, ...]]) -> list[bool]:
        """Constancies (context, a) and compatibilities (context, a, b) of contexts without a large class: each task of a
        deal has whole classes and says what its rows break."""
        out = [True] * len(tasks)
        for base, own in self._bases({t[0] for t in tasks}).items():
            part = [k for k, t in enumerate(tasks) if t[0] in own]
            used = 0
            for k in part:
                used |= sum((1 << a for a in tasks[k][1:]), tasks[k][0])
            place = {k: i for i, k in enumerate(bits(used))}
            asked = [(number, sum(1 << place[k] for k in bits(tasks[number][0])), *[place[k] for k in tasks[number][1:]]) for number in part]
            rows = self.codes.select(*self._names(used)).repartition(self._tasks(), *self._names(base))
            for r in rows.mapInArrow(_breaker(asked), "task long").collect():
                out[r["task"]] = False
        return out

    def _broken(self, todo: dict[int, int]) -> dict[int, int]:
        """What rows fetched meanwhile leave open of some questions; what they break is noted."""
        open_ = {}
        for c, asked in todo.items():
            names = bits(asked)
            left = sum(1 << a for a, ok in zip(names, self._alive("constant", [(c, a) for a in names])) if ok)
            had, constant = self.sets.get(c, (c, c))
            self.sets[c] = had | asked & ~left, constant
            if left:
                open_[c] = left
        return open_

    def _settle(self, need: dict[int, int]) -> None:
        """Tells of each context which of the columns asked are constant in it."""
        everything = (1 << len(self.columns)) - 1
        todo = {c: a & ~c for c, a in need.items() if a & ~c & ~self.sets.get(c, (c, c))[0]}
        for c, asked in list(todo.items()):
            if (v := self._above(c)) is not None:
                had, constant = self.sets.get(c, (c, c))
                names = bits(asked)
                self.sets[c] = had | asked, constant | sum(1 << a for a, ok in zip(names, v.constant([(c, a) for a in names])) if ok)
                del todo[c]
        todo = self._broken(todo)
        few = sorted(c for c in todo if self._few(c))
        with shuffles_dropped(self.spark):
            for at in range(0, len(few), GROUPING_SETS):
                self._by_sets({c: todo[c] for c in few[at : at + GROUPING_SETS]})
            todo = {c: asked for c, asked in todo.items() if c not in self.sets or asked & ~self.sets[c][0]}
            dealt = [(c, a) for c, asked in todo.items() if not self._heavy(c) for a in bits(asked)]
            for (c, a), ok in zip(dealt, self._apart(dealt)):
                had, constant = self.sets.get(c, (c, c))
                self.sets[c] = had | 1 << a, constant | ok << a
            for c, asked in todo.items():
                if not self._heavy(c):
                    continue
                keys, whole = self._names(c), not self.rows
                if not whole and asked | c == everything and self._maybe_key(c):
                    whole = self._dealt(c, []).groupBy(*keys).agg(F.count("*").alias("n")).where("n > 1").limit(1).count() == 0
                if whole:  # no two rows share a class
                    self.sets[c] = everything, everything
                    continue
                groups = self._dealt(c, self._names(asked)).groupBy(*keys).agg(*self._ends(asked))
                self.sets[c] = self._read(c, asked, groups.agg(*self._spreads(asked)).first())

    @staticmethod
    def _ends(asked: int) -> list[Column]:
        return [f(f"c{k}").alias(f"{name}{k}") for k in bits(asked) for f, name in ((F.min, "lo"), (F.max, "hi"))]

    @staticmethod
    def _spreads(asked: int) -> list[Column]:
        return [F.max(F.col(f"lo{k}") != F.col(f"hi{k}")).alias(f"c{k}") for k in bits(asked)]

    def _read(self, context: int, asked: int, row) -> tuple[int, int]:
        had, constant = self.sets.get(context, (context, context))
        return had | asked, constant | sum(1 << k for k in bits(asked) if not row[f"c{k}"])

    def _by_sets(self, part: dict[int, int]) -> None:
        used = sorted({k for c in part for k in bits(c)})
        asked = 0
        for a in part.values():
            asked |= a
        number = {sum(1 << len(used) - 1 - i for i, k in enumerate(used) if not c >> k & 1): c for c in part}
        # an aggregate would read a column's grouped form, null outside its sets, so the ends are of copies
        codes = self.codes.select(*[F.col(f"c{k}").alias(f"g{k}") for k in used], *self._names(asked))
        if used:
            groups = codes.groupingSets([[f"g{k}" for k in bits(c)] for c in part], *[f"g{k}" for k in used]).agg(F.grouping_id().alias("set"), *self._ends(asked))
        else:
            groups = codes.agg(F.lit(0).alias("set"), *self._ends(asked))
        found = {number[r["set"]]: r for r in groups.groupBy("set").agg(*self._spreads(asked)).collect()}
        for c in part:
            self.sets[c] = self._read(c, asked, found[c]) if c in found else (-1, -1)  # no rows: no group

    def prepare(self, tasks: Sequence[tuple[int, int]]) -> None:
        """Answers for all contexts of some constancies that the samples leave open."""
        need: dict[int, int] = {}
        for (c, a), ok in zip(tasks, self._alive("constant", tasks)):
            if ok:
                need[c] = need.get(c, 0) | 1 << a
        for c in {c for c, _ in tasks}:
            if self._maybe_key(c):
                need[c] = (1 << len(self.columns)) - 1
        self._settle(need)

    def constant(self, tasks):
        first = self._alive("constant", tasks)
        need: dict[int, int] = {}
        for (c, a), ok in zip(tasks, first):
            if ok:
                need[c] = need.get(c, 0) | 1 << a
        self.killed += first.count(False)
        self.sent += first.count(True)
        self._settle(need)
        return [ok and bool(self.sets[c][1] >> a & 1) for (c, a), ok in zip(tasks, first)]

    def _cuts(self, k: int) -> list[int]:
        """Bounds of the buckets of a column: none for up to segscan.WIDTH values."""
        if k not in self.cuts:
            n = min(MOST_CUTS, self.distinct[k] // segscan.WIDTH)
            values = np.sort(self.spread[k]) if n else []
            self.cuts[k] = sorted({int(values[len(values) * i // (n + 1)]) for i in range(1, n + 1)}) if len(values) else []
        return self.cuts[k]

    def compatible(self, tasks):
        out = self._alive("compatible", tasks)
        left = [k for k, ok in enumerate(out) if ok]
        self.killed += len(tasks) - len(left)
        self.sent += len(left)
        together, alone, dealt = [], [], []
        with shuffles_dropped(self.spark):
            for k in left:
                if (v := self._above(tasks[k][0])) is not None:
                    out[k] = v._compatible(*tasks[k])
            left = [k for k in left if out[k] and self._above(tasks[k][0]) is None]
            for k, ok in zip(left, self._alive("compatible", [tasks[k] for k in left])):
                out[k] = ok
            for k in (k for k in left if out[k]):
                c, a, b = tasks[k]
                if self._few(c | 1 << min(a, b, key=self.distinct.__getitem__)):
                    together.append(k)
                elif self._heavy(c):
                    alone.append([k])
                else:
                    dealt.append(k)
            for k, ok in zip(dealt, self._apart([tasks[k] for k in dealt])):
                out[k] = ok
            for part in [*(together[at : at + PLAN_TASKS] for at in range(0, len(together), PLAN_TASKS)), *alone]:
                cuts = {self.safe[j]: self._cuts(j) for k in part for j in tasks[k][1:]}
                plan = verdict_plan(self.codes, [(k, Compat.of(self._names(tasks[k][0]), *[self.safe[j] for j in tasks[k][1:]])) for k in part], cuts, dict(zip(self.safe, self.distinct)))
                for r in plan.where("bad").collect():
                    out[r["task"]] = False
        return out

    def key(self, mask: int) -> bool:
        """Whether no two different rows share a class: all columns are constant in it."""
        if not self._maybe_key(mask):
            return False
        everything = (1 << len(self.columns)) - 1
        self._settle({mask: everything})
        return everything & ~(self.sets.get(mask, (mask, mask))[1] | mask) == 0


def _breaker(asked: list[tuple[int, ...]]):
    """For mapInArrow: the numbers of the questions (number, context, a or a and b) that the rows of a task break."""

    def run(batches):
        import pyarrow as pa

        if got := list(batches):
            table = pa.Table.from_batches(got)
            v = LocalVerdicts([dense(c) for c in table.columns], table.num_rows, keep=16)
            broken = [number for number, *t in asked if not (v.constant if len(t) == 2 else v.compatible)([t])[0]]
            yield pa.RecordBatch.from_pydict({"task": pa.array(broken, pa.int64())})

    return run


def once(df: DataFrame) -> DataFrame:
    """The relation itself if it only reads and computes; written down if it joins or groups, so that this happens once."""
    plan = df._jdf.queryExecution().optimizedPlan().toString().split("InMemoryRelation")[0]  # what is cached has been computed
    return stored(df, "relation") if re.search(r"^\W*(Join|Aggregate|Window|Sort|GlobalLimit)", plan, re.M) else df


def row_by_row(df: DataFrame) -> bool:
    """Whether every row of a file or of memory gives one row, always the same: then a copy saves little time and costs disk."""
    plan = df._jdf.queryExecution().optimizedPlan()
    nodes = re.findall(r"^\W*(\w+)", plan.toString(), re.M)
    return plan.deterministic() and set(nodes) <= {"Project", "Relation", "LocalRelation"}


def verdicts(df: DataFrame, columns: list[str], kind: str = "auto", **options) -> Verdicts:
    """kind: 'local', 'spark', or 'auto', which counts the rows and fetches a relation only below LOCAL_ROWS."""
    if kind == "auto":
        with shuffles_dropped(df.sparkSession):
            df = once(df.select(*columns))
        most = min(LOCAL_ROWS, LOCAL_CELLS // max(1, len(columns)))
        kind = "local" if df.select(*columns).limit(most + 1).count() <= most else "spark"
    if kind == "local":
        falsify = options.pop("falsify", True)
        whole = LocalVerdicts.of(df, columns, **options)
        return SampledVerdicts(whole) if falsify and whole.rows >= SAMPLED_ROWS else whole
    return SparkVerdicts(df, columns, **options)


__all__ = ["LocalVerdicts", "SparkVerdicts", "Verdicts", "dense", "ordered", "verdicts"]
