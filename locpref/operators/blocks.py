"""Many fits over the same cells at once: folds, repetitions and settings of a sweep, plain and private.

A row is a unit: the cells of some users, for one setting and repetition. A pass over all
units works on arrays and sums by item, run and method; the cells are never written once
for each run. User vectors are a matter of their own ratings and of the item vectors
before, so a pass makes them anew from these and keeps none. Masks and noise come from
the same keys as in ``experiment.repeat`` and ``private.fit_runs``. Where ``lanes`` can
be had, it makes the sums of a task in the JVM; the passes here do the same with arrays.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import lanes
from ..functions.draws import Keys, laplace
from ..sources.rounds import Rounds
from .private import PrivateConfig

#: Cells of a unit, about.
UNIT_CELLS = 16384
#: Up to so many times the cells there are, a unit is a matrix.
MOST_EMPTY = 10
#: Units in a batch that is read or goes to Python: one with its draws can be some MB.
BATCH_UNITS = 2
BATCHES = ("spark.sql.parquet.columnarReaderBatchSize", "spark.sql.execution.arrow.maxRecordsPerBatch")
#: Bytes of item vectors of a round that go to every task and the driver: those of all runs, or with ``lanes`` of as many as are fitted together.
MAX_VECTORS = 16 << 20
SUMS = "setting int, rep int, method int, sums binary"
COUNTS = ("tp", "fp", "tn", "fn", "right", "held")


@dataclass(frozen=True)
class Plan:
    """What all passes know: settings are (cells, unknown, eps), methods (name, config or None if plain, central)."""

    settings: tuple[tuple[int, float, float], ...]
    methods: tuple[tuple[str, PrivateConfig | None, bool], ...]
    first: tuple[int, ...]
    items: tuple[list[str], ...]
    folds: int
    runs: int
    d: int
    seed: int
    lam: float = 1e-4
    gamma: float = 0.5
    radius: float = 2.0

    def of_rep(self, rep: int) -> int:
        return min(self.folds, self.runs - rep * self.folds)

    def run(self, setting: int, rep: int, k: int) -> int:
        return setting * self.runs + rep * self.folds + k

    def noise(self, method: int, setting: int) -> tuple[float, float]:
        """Flip probability and Laplace scale."""
        cfg = self.methods[method][1]
        return replace(cfg, eps=self.settings[setting][2]).mechanism(1) if cfg else (0.0, 0.0)

    def drawn_by(self, method: int, setting: int) -> tuple[float, float]:
        """The same for what users draw: nothing where the server does."""
        return (0.0, 0.0) if self.methods[method][2] else self.noise(method, setting)

    def said(self) -> str | None:
        """What ``lanes`` needs of it as a text; none if that can't tell it."""
        if self.folds > 127 or any(c in name for names in self.items for name in names for c in "\x1e\x1f"):
            return None
        settings = [[kind, unknown, *(x for m in range(len(self.methods)) for x in self.drawn_by(m, n))] for n, (kind, unknown, _) in enumerate(self.settings)]
        return "\x1e".join("\x1f".join(map(str, x)) for x in ([self.seed, self.folds, self.runs, self.d, len(self.methods), len(settings)], *settings, *self.items))

    def fitted(self, method: int, setting: int) -> bool:
        """A plain fit has no eps: of settings that differ in it alone, the first is fitted."""
        return self.methods[method][1] is not None or self.first[setting] == setting

    def step(self, old: np.ndarray, gradient: np.ndarray) -> np.ndarray:
        new = old - self.gamma * (gradient + 2 * self.lam * old)
        size = np.sqrt((new * new).sum(axis=0))
        return new * np.minimum(1.0, self.radius / np.maximum(size, 1e-300))

    def groups(self) -> list[tuple[int, int, int, int]]:
        """Setting, repetition and its runs (from, to)."""
        return [(n, rep, 0, self.of_rep(rep)) for rep in range(-(-self.runs // self.folds)) for n in range(len(self.settings))]

    def together(self) -> list[list[tuple[int, int, int, int]]]:
        """Groups in lists whose item vectors, of all methods, are within ``MAX_VECTORS``; runs of a group that is not are told apart."""
        out, left = [], 0
        for n, rep, k, stop in self.groups():
            each = max(1, 8 * lanes.ROOM * len(self.items[self.settings[n][0]]) * sum(self.fitted(m, n) for m in range(len(self.methods))))
            while k < stop:
                if left < min(each * (stop - k), MAX_VECTORS):
                    out.append([])
                    left = MAX_VECTORS
                some = min(stop - k, max(1, left // each))
                out[-1].append((n, rep, k, k + some))
                left, k = left - some * each, k + some
                if k < stop:
                    left = 0
        return out

    def start(self, ids: list, prefix: str) -> np.ndarray:
        keys = Keys([str(x).encode() for x in ids])
        return np.stack([0.75 / math.sqrt(self.d) * (0.5 + keys.uniform([f"{self.seed}:init_{prefix}:".encode()], f":{k}".encode())[0]) for k in range(self.d)])


class Unit:
    """Cells of some users in all runs of a repetition."""

    def __init__(self, plan: Plan, setting: int, rep: int, users: np.ndarray, item: np.ndarray, rating: np.ndarray, truth: np.ndarray, drawn: memoryview | None = None):
        self.plan, self.setting, self.rep = plan, setting, rep
        self.item, self.rating, self.truth = item, rating, truth
        self.ids, self.at = np.unique(users, return_inverse=True)
        self.names = plan.items[plan.settings[setting][0]]
        self.n_items, self.of_rep, self.drawn_at = len(self.names), plan.of_rep(rep), 0
        self.told = drawn
        if drawn is not None:
            own = self.next(len(item), np.uint8)
            self.held = [own == k for k in range(self.of_rep)]
            self.first = self.next(plan.d * len(self.ids)).reshape(plan.d, -1)
        else:
            end = f":{rep}".encode()
            fold = Keys([str(u).encode() for u in self.ids.tolist()]).bits([f"{plan.seed}:fold:".encode()], end)[0] % np.uint64(plan.folds)
            masked = self.cells.uniform([f"{plan.seed}:mask:".encode()], end)[0] < plan.settings[setting][1]
            own = fold.astype(np.int64)[self.at]
            self.held = [(own == k) & masked for k in range(self.of_rep)]
            self.first = plan.start(self.ids.tolist(), "x")

        self.made: dict[tuple[str, str], np.ndarray] = {}
        self.kept: dict[int, np.ndarray] = {}
        self.dense = self.n_items * len(self.ids) <= MOST_EMPTY * len(item)
        self.place = self.at * self.n_items + item
        if self.dense:
            self.ratings = self.spread(rating)

    @cached_property
    def cells(self) -> Keys:
        heads, tails = [str(u).encode() + b":" for u in self.ids.tolist()], [x.encode() for x in self.names]
        return Keys([heads[u] + tails[i] for u, i in zip(self.at.tolist(), self.item.tolist(), strict=True)])

    def next(self, n: int, kind: type = np.float64) -> np.ndarray:
        """The next numbers of what ``lanes`` has drawn."""
        out = np.frombuffer(self.told, kind, n, self.drawn_at)
        self.drawn_at += out.nbytes
        return out

    def spread(self, w: np.ndarray) -> np.ndarray:
        """A matrix of users by items."""
        out = np.zeros(len(self.ids) * self.n_items)
        out[self.place] = w
        return out.reshape(len(self.ids), self.n_items)

    def known(self, k: int) -> np.ndarray:
        """1 for each known cell of a run and 0 for held ones, as a matrix or by cell."""
        if k not in self.kept:
            known = (~self.held[k]).astype(float)
            self.kept[k] = self.spread(known) if self.dense else known
        return self.kept[k]

    def by_item(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.item, w, self.n_items)

    def by_user(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.at, w, len(self.ids))

    def scores(self, X: np.ndarray, Z: np.ndarray) -> np.ndarray:
        """Products of the two vectors, as a matrix or by cell."""
        if self.dense:
            return X.T @ Z
        out = X[0][self.at] * Z[0][self.item]
        for x, z in zip(X[1:], Z[1:], strict=True):
            out += x[self.at] * z[self.item]
        return out

    def errors(self, X: np.ndarray, Z: np.ndarray, known: np.ndarray) -> np.ndarray:
        """-2 e, 0 where nothing is known."""
        e = self.scores(X, Z)
        e -= self.ratings if self.dense else self.rating
        e *= 2.0
        e *= known
        return e

    def users(self, k: int, past: list[np.ndarray], m: float) -> np.ndarray:
        """User vectors after the rounds whose item vectors are ``past``."""
        X, known = self.first, self.known(k) if past else None
        for Z in past:
            X = self.stepped(X, Z, self.errors(X, Z, known), m)
        return X

    def stepped(self, X: np.ndarray, Z: np.ndarray, e: np.ndarray, m: float) -> np.ndarray:
        return self.plan.step(X, (Z @ e.T if self.dense else np.stack([self.by_user(e * z[self.item]) for z in Z])) / m)

    def mean_part(self, k: int, X: np.ndarray) -> np.ndarray:
        """Sums of the vectors of users with a known rating."""
        return X[:, self.by_user((~self.held[k]).astype(float)) > 0].sum(axis=1)

    def gradients(self, k: int, X: np.ndarray, e: np.ndarray, cfg: PrivateConfig | None, weight: np.ndarray | None, noise: list[np.ndarray] | np.ndarray | None) -> np.ndarray:
        """Sums by item; ``e`` is overwritten. The noise is that of each cell, or its sums."""
        if cfg is not None:
            size = np.abs(X).sum(axis=0)
            size = np.abs(e) * (size[:, None] if self.dense else size[self.at])
            e *= np.minimum(1.0, cfg.clip / np.maximum(size, 1e-300))
        if weight is not None:
            e *= self.spread(weight) if self.dense else weight
        g = X @ e if self.dense else np.stack([self.by_item(e * x[self.at]) for x in X])
        if isinstance(noise, np.ndarray):
            g += noise
        elif noise is not None:
            share = (~self.held[k]).astype(float) if weight is None else np.where(self.held[k], 0.0, weight)
            g += np.stack([self.by_item(c * share) for c in noise])
        return g

    def uniforms(self, purpose: str, end: str) -> np.ndarray:
        """A draw for every run and cell; methods with the same key share it."""
        if (purpose, end) not in self.made:
            self.made[purpose, end] = self.cells.uniform(self.prefixes(purpose), end.encode())
        return self.made[purpose, end]

    def prefixes(self, purpose: str) -> list[bytes]:
        return [f"{self.plan.seed}:{purpose}:{self.plan.run(self.setting, self.rep, k)}:".encode() for k in range(self.of_rep)]

    def bits(self, t: int, p: float) -> np.ndarray:
        """Noisy bits of visits: 1, or a coin with chance ``p``. The draw that leaves fewer to the other comes first."""
        if ("bits", f"{t}") in self.made:
            return self.made["bits", f"{t}"]
        end, coin = f":{t}", p > 0.5
        open_ = self.uniforms("bit_coin", end) >= 0.5 if coin else self.uniforms("bit_flip", end) < p
        which, rows = np.nonzero(open_)
        other = self.cells.uniform_at(self.prefixes("bit_flip" if coin else "bit_coin"), end.encode(), which, rows)
        bits = np.ones(open_.shape)
        bits[which, rows] = other >= p if coin else other < 0.5
        self.made["bits", f"{t}"] = bits  # a setting has one p
        return bits

    def drawn(self, t: int, p: float, scale: float) -> tuple[list, list]:
        """Weights of the noisy bits and noise of the gradients in round ``t``, by run; none where nothing is drawn."""
        weight, noise = [None] * self.of_rep, [None] * self.of_rep
        if self.told is not None:
            for k in range(self.of_rep):
                if p > 0:
                    bits = np.unpackbits(self.next(-(-len(self.item) // 8), np.uint8), count=len(self.item), bitorder="little")
                    weight[k] = np.array([0 - p / 2, 1 - p / 2])[bits] / (1 - p)
                if scale > 0:
                    noise[k] = self.next(self.plan.d * self.n_items).reshape(self.plan.d, -1)
            return weight, noise
        if p > 0:
            weight = list((self.bits(t, p) - p / 2) / (1 - p))
        if scale > 0:
            each = [laplace(self.uniforms("lap", f":{t}:{c}"), scale) for c in range(self.plan.d)]
            noise = [[c[k] for c in each] for k in range(self.of_rep)]
        return weight, noise


def units_of(plan: Plan, batches: Iterable[pa.RecordBatch]) -> Iterator[Unit]:
    for batch in batches:
        for n in range(batch.num_rows):
            setting, rep = batch.column("setting")[n].as_py(), batch.column("rep")[n].as_py()
            arrays = (batch.column(c)[n].values.to_numpy(zero_copy_only=False) for c in ("users", "item", "rating", "truth"))
            drawn = batch.column("drawn")[n].as_buffer() if "drawn" in batch.schema.names else None
            yield Unit(plan, setting, rep, *arrays, drawn)


def _told(sums: dict, batch_type: pa.Schema) -> Iterator[pa.RecordBatch]:
    for key, v in sums.items():  # a batch each: a row can be large
        yield pa.RecordBatch.from_arrays([*(pa.array([x], pa.int32()) for x in key), pa.array([v.tobytes()], pa.binary())], schema=batch_type)


_SCHEMA = pa.schema([("setting", pa.int32()), ("rep", pa.int32()), ("method", pa.int32()), ("sums", pa.binary())])


def round_pass(plan: Plan, t: int, past: dict, sizes: dict, final: bool = False) -> Callable:
    """Sums over users for every run: item gradients of round ``t``, and in the first the ratings of items and the users; in a ``final`` one the user vectors after it."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple, np.ndarray] = {}

        def add(key, v):
            sums[key] = sums[key] + v if key in sums else v

        begun = [plan.start(names, "z") for names in plan.items]
        for unit in units_of(plan, batches):
            if t == 1:
                counts = []
                for held in unit.held:
                    known = (~held).astype(float)
                    counts.append(np.append(unit.by_item(known), (unit.by_user(known) > 0).sum()))
                add((unit.setting, unit.rep, -1), np.stack(counts))
            for method, (_, cfg, _) in enumerate(plan.methods):
                if not plan.fitted(method, unit.setting):
                    continue
                key = (unit.setting, unit.rep, method)
                weight, noise = unit.drawn(t, *plan.drawn_by(method, unit.setting))
                rows = []
                for k in range(unit.of_rep):
                    before = [begun[plan.settings[unit.setting][0]], *(Z[k] for Z in past.get(key, []))]
                    m = sizes[key[:2]][k][1] if t > 1 else 1.0
                    X = unit.users(k, before[:-1], m)
                    e = unit.errors(X, before[-1], unit.known(k))
                    after = [unit.mean_part(k, unit.stepped(X, before[-1], e, m))] if final else []
                    rows.append(np.concatenate([unit.gradients(k, X, e, cfg, weight[k], noise[k]).ravel(), *after]))
                add(key, np.stack(rows))
        yield from _told(sums, _SCHEMA)

    return work


def level(mean: np.ndarray, n: float, m: float, rated: np.ndarray, Z: np.ndarray) -> float:
    """The threshold of a run: the mean product, from the sums of its user vectors."""
    return ((mean / n) * Z[:, rated > 0].mean(axis=1)).sum() if n else math.nan


def last_pass(plan: Plan, past: dict, sizes: dict, mean: dict | None) -> Callable:
    """Sums of the last user vectors by run; or, with the ``mean`` ones, counts of decisions against the truth."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple, np.ndarray] = {}
        begun = [plan.start(names, "z") for names in plan.items]
        for unit in units_of(plan, batches):
            for method in range(len(plan.methods)):
                if not plan.fitted(method, unit.setting):
                    continue
                key, rows = (unit.setting, unit.rep, method), []
                for k in range(unit.of_rep):
                    Zs = [begun[plan.settings[unit.setting][0]], *(Z[k] for Z in past[key])]
                    X = unit.users(k, Zs[:-1], sizes[key[:2]][k][1])
                    if mean is None:
                        rows.append(unit.mean_part(k, X))
                        continue
                    there = unit.by_user((~unit.held[k]).astype(float)) > 0
                    known = sizes[key[:2]][k][2] > 0
                    score = unit.scores(X, Zs[-1])
                    yes = ((score.ravel()[unit.place] if unit.dense else score) > level(mean[key][k], *sizes[key[:2]][k], Zs[-1])) & there[unit.at] & known[unit.item]
                    true, held = unit.truth == 1, unit.held[k]
                    rows.append(np.array([(true & yes).sum(), (~true & yes).sum(), (~true & ~yes).sum(), (true & ~yes).sum(), ((true == yes) & held).sum(), held.sum()], float))
                v = np.stack(rows)
                sums[key] = sums[key] + v if key in sums else v
        yield from _told(sums, _SCHEMA)

    return work


def _add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of a key follow each other; one sum is held."""
    now, held = None, None
    for batch in batches:
        for n in range(batch.num_rows):
            key = tuple(batch.column(c)[n].as_py() for c in ("setting", "rep", "method"))
            v = np.frombuffer(batch.column("sums")[n].as_buffer(), np.float64)
            if key != now:
                if now is not None:
                    yield from _told({now: held}, _SCHEMA)
                now, held = key, v.copy()
            else:
                held += v
    if now is not None:
        yield from _told({now: held}, _SCHEMA)


def _summed(units: DataFrame, work: Callable) -> dict[tuple[int, int, int], np.ndarray]:
    """Sums by setting, repetition and method: as many numbers as a round has item vectors."""
    by = ("setting", "rep", "method")
    made = units.columns == [*by, "drawn"]  # by ``lanes``
    parts = units.withColumnRenamed("drawn", "sums") if made else units.mapInArrow(work, SUMS)
    rows = parts.repartition(*by).sortWithinPartitions(*by).mapInArrow(_add_up, SUMS)
    conf = units.sparkSession.conf
    was = {name: conf.get(name) for name in BATCHES}
    try:
        for name in BATCHES:
            conf.set(name, str(BATCH_UNITS))
        return {(r.setting, r.rep, r.method): np.frombuffer(r.sums, np.float64) for r in rows.collect()}
    finally:
        for name, value in was.items():
            conf.set(name, value)


def fits(cells: list[DataFrame], settings: list[int], runs: int, d: int, methods: int = 0) -> list[list[str]] | None:
    """Items of every table of cells, or none if vectors of all runs are too large to go to every task; with ``methods`` those of one run and setting."""
    left, items = MAX_VECTORS, []
    for n, c in enumerate(cells):
        each = 8 * lanes.ROOM * methods or 8 * d * runs * settings.count(n)
        names = sorted(r[0] for r in c.select("item_id").distinct().limit(left // each + 1).collect())
        if len(names) * each > left:
            return None
        left -= 0 if methods else len(names) * each
        items.append(names)
    return items


def _cut(kind: int, names: list[str]) -> Callable:
    """Arrays of some users' cells from rows that have the cells of a user together."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place, held, size = pa.array(names, pa.string()), [], 0

        def told(cells: pa.Table) -> pa.RecordBatch:
            columns = [cells["user_id"].cast(pa.int64()), pc.index_in(cells["item_id"], place), cells["rating"].cast(pa.float64()), cells["truth"].cast(pa.int32())]
            by = np.lexsort([columns[1].to_numpy(), columns[0].to_numpy()])
            lists = [pa.ListArray.from_arrays(pa.array([0, len(by)], pa.int32()), c.combine_chunks().take(pa.array(by))) for c in columns]
            return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), *lists], schema=_UNITS)

        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size < 2 * UNIT_CELLS:
                continue
            cells = pa.Table.from_batches(held)
            users = cells["user_id"].to_numpy()
            ends = np.append(np.nonzero(users[1:] != users[:-1])[0] + 1, 0)[:-1]  # the last user may go on
            start = 0
            while len(ends) and ends[-1] - start >= UNIT_CELLS:
                stop = int(ends[np.searchsorted(ends, start + UNIT_CELLS)])
                yield told(cells.slice(start, stop - start))
                start = stop
            held, size = cells.slice(start).to_batches(), size - start
        if size:
            yield told(pa.Table.from_batches(held))

    return work


_ARRAYS = {"users": "long", "item": "int", "rating": "double", "truth": "int"}
_UNITS = pa.schema([("cells", pa.int32()), *((c, pa.list_({"long": pa.int64(), "int": pa.int32(), "double": pa.float64()}[t])) for c, t in _ARRAYS.items())])


def units(scratch: Rounds, cells: Iterable[DataFrame], plan: Plan) -> tuple[DataFrame, DataFrame]:
    """``setting, rep, users, item, rating, truth``: arrays of the cells of some users, once for each setting and repetition; and what is stored, once for each table of ``cells``.

    The tables have all cells of a user in one task; none is shuffled.
    """
    spark, reps, out = scratch.spark, -(-plan.runs // plan.folds), None
    schema = "cells int, " + ", ".join(f"{c} array<{t}>" for c, t in _ARRAYS.items())
    for n, c in enumerate(cells):
        one = c.sortWithinPartitions("user_id").mapInArrow(_cut(n, plan.items[n]), schema)
        out = one if out is None else out.unionByName(one)
    stored = scratch.keep(out, "units")
    each = spark.createDataFrame([(s[0], n, rep) for n, s in enumerate(plan.settings) for rep in range(reps)], "cells int, setting int, rep int")
    return stored.join(F.broadcast(each), "cells").select("setting", "rep", *_ARRAYS), stored  # a row for each setting and repetition


class ItemNoise:
    """What the server adds to sums of items: its own noise, or that of all users without a rating as one normal draw, as in ``private``."""

    def __init__(self, plan: Plan, groups: list[tuple[int, int, int, int]]):
        self.plan, self.at, texts = plan, {}, []
        for setting, rep, start, stop in groups:
            self.at[setting, rep] = len(texts)
            texts += [f"{plan.run(setting, rep, k)}:{name}".encode() for k in range(start, stop) for name in plan.items[plan.settings[setting][0]]]
        self.keys = Keys(texts)

    def draw(self, t: int) -> None:
        plan, ends = self.plan, [f":{t}:{c}".encode() for c in range(self.plan.d)]
        kinds = {central for _, cfg, central in plan.methods if cfg is not None and "grads" in cfg.protect}
        self.own = {True: [self.keys.uniform([f"{plan.seed}:central:".encode()], end)[0] for end in ends] if True in kinds else [], False: [self.keys.gaussian(plan.seed, "synth", end) for end in ends] if False in kinds else []}

    def of(self, key: tuple[int, int, int], sizes: list[tuple]) -> list:
        """What is added to the sums of each run."""
        setting, rep, method = key
        (p, scale), central, out = self.plan.noise(method, setting), self.plan.methods[method][2], []
        q, wide, at = p / 2, len(self.plan.items[self.plan.settings[setting][0]]), self.at[setting, rep]
        for n, _, rated in sizes:
            if scale == 0 or (p == 0 and not central):
                out.append(0.0)
                continue
            own = np.stack([c[at : at + wide] for c in self.own[central]])
            out.append(laplace(own, scale) if central else own * (np.sqrt((n - rated) * q * (1 - q) * 2.0) / (1 - p) * scale))
            at += wide
        return out


def numbers(plan: Plan, groups: list, t: int, last: bool, sizes: dict, levels: dict | None) -> str:
    """What ``lanes`` needs for one pass besides the plan and item vectors, as a text."""
    out = [t, int(last), int(levels is not None), plan.lam, plan.gamma, plan.radius, *(-1 if cfg is None else cfg.clip for _, cfg, _ in plan.methods), len(groups)]
    for setting, rep, start, stop in groups:
        out += [setting, rep, start, stop, *(m for _, m, _ in sizes.get((setting, rep), [(0, 1.0, 0)] * (stop - start)))]
        for method in range(len(plan.methods)):
            out += [1, *(levels[setting, rep, method] if levels else [])] if plan.fitted(method, setting) else [0]
    return " ".join("NaN" if x != x else repr(float(x)) if isinstance(x, float) else str(x) for x in out)


def measure(data: DataFrame, plan: Plan, rounds: int, stored: DataFrame | None = None) -> DataFrame:
    """``method, run`` and counts of decisions against the truth (``right`` and ``held`` over held cells) after ``rounds`` rounds."""
    spark, rows = data.sparkSession, []
    jvm = rounds > 1 and lanes.known(stored, plan.said(), plan.d) is not None
    for groups in plan.together() if jvm else [plan.groups()]:
        known = lanes.known(stored, plan.said(), plan.d) if jvm else None
        rows += _measured(data, plan, rounds, groups, known)
        if known is not None:
            known.end()
    return spark.createDataFrame(rows, "method string, run int, " + ", ".join(f"{c} long" for c in COUNTS))  # a row for each run


def _measured(data: DataFrame, plan: Plan, rounds: int, groups: list[tuple[int, int, int, int]], known: lanes.Known | None) -> list[tuple]:
    """Rows of the runs of these groups, fitted together; all runs, if nothing is ``known`` to ``lanes``."""
    d, begun = plan.d, [plan.start(names, "z") for names in plan.items]
    past: dict[tuple, list[np.ndarray]] = {}
    sizes: dict[tuple, list[tuple]] = {}
    runs = {(setting, rep): range(start, stop) for setting, rep, start, stop in groups}
    fitted = [(setting, rep, m) for setting, rep in runs for m in range(len(plan.methods)) if plan.fitted(m, setting)]
    noise, mean, said = ItemNoise(plan, groups), {}, plan.said()
    if known is not None:
        known.more(begun)
    for t in range(1, rounds + 1):
        final = t == rounds > 1  # steps of users need the first round's sizes
        if known is not None:
            known.numbers = numbers(plan, groups, t, final, sizes, None)
        got = _summed(lanes.with_draws(data, said, t, known), round_pass(plan, t, past, sizes, final))
        for (setting, rep, method), v in got.items():
            if method == -1:  # users, items and ratings of each item, by run
                sizes[setting, rep] = [(row[-1], float((row[:-1] > 0).sum()), row[:-1]) for row in v.reshape(len(runs[setting, rep]), -1)]
        noise.draw(t)
        for key, v in got.items():
            setting, rep, method = key
            if method == -1:
                continue
            more, new = noise.of(key, sizes[setting, rep]), []
            v = v.reshape(len(runs[setting, rep]), -1)
            if final:
                v, mean[key] = v[:, :-d], v[:, -d:]
            for k, g in enumerate(v):
                n = sizes[setting, rep][k][0]
                g = g.reshape(d, -1) + more[k]
                new.append(plan.step(past[key][-1][k] if t > 1 else begun[plan.settings[setting][0]], g / n if n else g))
            past.setdefault(key, []).append(np.stack(new))
        if known is not None:
            if final:  # an item without a rating in a run is not decided
                known.more(np.where(sizes[key[:2]][k][2] > 0, z, math.nan) for key in fitted for k, z in enumerate(past[key][-1]))
                levels = {key: [level(mean[key][k], *sizes[key[:2]][k], z) for k, z in enumerate(past[key][-1])] for key in fitted}
                known.numbers = numbers(plan, groups, t, False, sizes, levels)
            else:
                known.more(z for key in fitted for z in past[key][-1])
    if not mean:
        mean = {key: v.reshape(-1, d) for key, v in _summed(lanes.with_draws(data, said, 0), last_pass(plan, past, sizes, None)).items()}
    counts = _summed(lanes.with_draws(data, said, 0, known), last_pass(plan, past, sizes, mean))
    return [(plan.methods[method][0], plan.run(setting, rep, k), *map(int, row)) for (setting, rep, method), v in counts.items() for k, row in zip(runs[setting, rep], v.reshape(-1, len(COUNTS)), strict=True)]
