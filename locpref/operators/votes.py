"""Neighbours and majorities for many runs at once, from the units of ``blocks``: no row is written for each run and cell.

Few items: a user's ratings are a vector, and sums for pairs of items are small. In a
run, the users of one fold have vectors without their held cells; all others have the
same as in every run, so similarities of these are made once for a repetition.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import baselines, blocks

#: Neighbours and common ratings, as in ``baselines``.
K, MIN_COMMON = 20, 2
#: Users whose neighbours are searched together, and users they are compared with at once.
ROWS, COLUMNS = 256, 2048
#: Bytes of all ratings as vectors, up to which they go to every task and the driver.
MAX_RATINGS = 32 << 20
NONE = np.iinfo(np.int64).max
METHODS = ("cf_user", "cf_item", "majority")


def _keys(s: np.ndarray, own: np.ndarray, first: int) -> np.ndarray:
    """Similarities as numbers to sort by: nine places, halves up, then the lesser id; ids are places of users or items."""
    order = np.where(np.isnan(s), 0.0, -np.sign(s) * np.floor(np.abs(s) * 1e9 + 0.5)).astype(np.int64)
    near = first + np.arange(s.shape[1])
    keys = (order << 32) + near
    keys[np.isnan(s) | (own[:, None] == near)] = NONE
    return keys


def _merged(best: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """The least keys of each row."""
    better = keys < best[:, -1:]
    most = better.sum(axis=1)
    widest = int(most.max(initial=0))
    if not widest:
        return best
    if widest > 4 * K:
        more = np.partition(keys, K - 1, axis=1)[:, :K]
    else:
        who, col = np.nonzero(better)
        more = np.full((len(keys), widest), NONE)
        more[who, np.arange(len(who)) - (np.cumsum(most) - most)[who]] = keys[who, col]
    return np.sort(np.hstack([best, more]), axis=1)[:, :K]


def _counted(yes: np.ndarray, there: np.ndarray, truth: np.ndarray, held: np.ndarray) -> np.ndarray:
    """Counts of decisions, in the order of ``blocks.COUNTS``."""
    yes, true = yes & there, (truth == 1) & there
    no, false, held = ~yes & there, (truth != 1) & there, held & there
    return np.array([(true & yes).sum(), (false & yes).sum(), (false & no).sum(), (true & no).sum(), ((true == yes) & held).sum(), held.sum()], float)


def _ratio(num: np.ndarray, den: np.ndarray) -> np.ndarray:
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.where(den == 0, np.nan, num / den)


def _vectors(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for n in range(batch.num_rows):
            users, item, rating, truth = (batch.column(c)[n].values.to_numpy(zero_copy_only=False) for c in ("users", "item", "rating", "truth"))
            ids, at = np.unique(users, return_inverse=True)
            v, t = np.full((len(ids), width), np.nan), np.zeros((len(ids), width), np.int8)
            v[at, item], t[at, item] = rating, truth
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in (ids.astype(np.int64), v, t)], names=["ids", "v", "t"])


def _people(units: DataFrame, setting: int, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Users by id, their ratings (NaN without one) and truths."""
    rows = units.where((F.col("setting") == setting) & (F.col("rep") == 0)).select("users", "item", "rating", "truth").mapInArrow(lambda b: _vectors(b, width), "ids binary, v binary, t binary").collect()  # within MAX_RATINGS
    ids, v, t = (np.concatenate([np.frombuffer(r[c], kind) for r in rows] or [np.empty(0, kind)]) for c, kind in (("ids", np.int64), ("v", np.float64), ("t", np.int8)))
    by = np.argsort(ids)
    return ids[by], v.reshape(-1, width)[by], t.reshape(-1, width)[by]


def search_pass(plan: blocks.Plan, people: dict) -> Callable:
    """Counts of the decisions by similar users, for the users from ``start`` to ``stop``."""

    def searched(unit: blocks.Unit, V, W, T, fold, held, lo: int, hi: int) -> np.ndarray:
        v, w, own, at = V[lo:hi], W[lo:hi], fold[lo:hi], np.arange(lo, hi)
        best = np.full((unit.of_rep, hi - lo, K), NONE)
        for c in range(0, len(V), COLUMNS):
            near, masked, f = V[c : c + COLUMNS], W[c : c + COLUMNS], fold[c : c + COLUMNS]
            whole, part = (_keys(baselines._best(v, x, "cosine", MIN_COMMON), at, c) for x in (near, masked))
            for k in range(unit.of_rep):
                rows, cols = own == k, f == k
                keys = whole.copy()
                keys[:, cols] = part[:, cols]
                if rows.any():
                    keys[rows] = _keys(baselines._best(w[rows], np.where(cols[:, None], masked, near), "cosine", MIN_COMMON), at[rows], c)
                best[k] = _merged(best[k], keys)
        out, exists = [], ~np.isnan(v)
        for k in range(unit.of_rep):
            there, who = best[k] != NONE, np.where(best[k] == NONE, 0, best[k] & 0xFFFFFFFF)
            b = np.where((fold[who] == k)[..., None], W[who], V[who])
            a = np.where((own == k)[:, None], w, v)[:, None, :]
            both, rated = ~np.isnan(a) & ~np.isnan(b), ~np.isnan(b) & there[..., None]
            x, y = np.where(both, a, 0.0), np.where(both, b, 0.0)
            s = _ratio((x * y).sum(axis=2), np.sqrt((x * x).sum(axis=2)) * np.sqrt((y * y).sum(axis=2)))
            num, den = np.zeros(v.shape), np.zeros(v.shape)
            for r in range(K):  # one after the other, as sums of equal numbers must be equal
                num += np.where(rated[:, r], s[:, r, None] * b[:, r], 0.0)
                den += np.where(rated[:, r], np.abs(s[:, r, None]), 0.0)
            out.append(_counted(_ratio(num, den) > 0.5, exists, T[lo:hi], held[k][lo:hi]))
        return np.stack(out)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for n in range(batch.num_rows):
                setting, rep, start, stop = (batch.column(c)[n].as_py() for c in ("setting", "rep", "start", "stop"))
                ids, V, T = people[plan.settings[setting][0]]
                at, item = np.nonzero(~np.isnan(V))
                unit = blocks.Unit(plan, setting, rep, ids[at], item, V[at, item], T[at, item])
                held, fold, W = np.zeros((unit.of_rep, *V.shape), bool), np.full(len(V), -1), V.copy()
                for k, cells in enumerate(unit.held):
                    held[k][at[cells], item[cells]] = True
                    W[held[k]] = np.nan
                    fold[at[cells]] = k
                counts = sum(searched(unit, V, W, T, fold, held, lo, min(stop, lo + ROWS)) for lo in range(start, stop, ROWS))
                yield from blocks._told({(setting, rep, METHODS.index("cf_user")): counts}, blocks._SCHEMA)

    return work


def _similar_items(sums: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Neighbours of every item by place, the nearest first, and their similarities (NaN without one)."""
    ab, aa, common = sums[: 3 * width * width].reshape(3, width, width)
    s = _ratio(ab, np.sqrt(aa) * np.sqrt(aa.T))
    s[common < MIN_COMMON] = np.nan
    keys = np.sort(_keys(s, np.arange(width), 0), axis=1)[:, :K]
    near = np.where(keys == NONE, 0, keys & 0xFFFFFFFF)
    return near, np.where(keys == NONE, np.nan, np.take_along_axis(s, near, axis=1))


def item_pass(plan: blocks.Plan, settings: list[int], methods: list[str], sums: dict | None) -> Callable:
    """Sums for items and pairs of them by run; or, with these ``sums``, counts of the decisions by similar items and by majorities."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: dict[tuple, np.ndarray] = {}
        for unit in blocks.units_of(plan, batches):
            if unit.setting not in settings:
                continue
            exists, rating, truth = (unit.spread(x) for x in (np.ones(len(unit.item)), unit.rating, unit.truth))
            rows: dict[int, list] = {}
            for k in range(unit.of_rep):
                held = unit.spread(unit.held[k].astype(float)) > 0
                known = exists * ~held
                r = rating * known
                if sums is None:
                    rows.setdefault(-1, []).append(np.concatenate([(r.T @ r).ravel(), ((r * r).T @ known).ravel(), (known.T @ known).ravel(), r.sum(axis=0)]))
                    continue
                mine = sums[unit.setting, unit.rep, -1].reshape(unit.of_rep, -1)[k]
                for m in methods:
                    if m == "cf_item":
                        near, s = _similar_items(mine, unit.n_items)
                        num, den = np.zeros(r.shape), np.zeros(r.shape)
                        for c in range(near.shape[1]):
                            w = np.where(np.isnan(s[:, c]), 0.0, s[:, c])
                            num += w * r[:, near[:, c]]
                            den += np.abs(w) * known[:, near[:, c]]
                        score = _ratio(num, den)
                    else:
                        n, total = np.diagonal(mine[2 * unit.n_items**2 : 3 * unit.n_items**2].reshape(unit.n_items, -1)), mine[3 * unit.n_items**2 :]
                        g = _ratio(total.sum(), n.sum())
                        u, i = _ratio(r.sum(axis=1), known.sum(axis=1)), _ratio(total, n)
                        score = np.where(np.isnan(u), g, u)[:, None] + np.where(np.isnan(i), g, i) - g
                    rows.setdefault(METHODS.index(m), []).append(_counted(score > 0.5, exists > 0, truth, held))
            for m, each in rows.items():
                key, v = (unit.setting, unit.rep, m), np.stack(each)
                out[key] = out[key] + v if key in out else v
        yield from blocks._told(out, blocks._SCHEMA)

    return work


def fits(cells: list[DataFrame], plan: blocks.Plan) -> bool:
    """Whether vectors of all users are small enough to go to every task."""
    width = max(map(len, plan.items))
    if not 0 < width <= baselines.MAX_DENSE:
        return False
    return sum(9 * len(names) * c.select("user_id").distinct().count() for c, names in zip(cells, plan.items, strict=True)) <= MAX_RATINGS


def measure(units: DataFrame, plan: blocks.Plan, methods: list[str]) -> DataFrame:
    """As ``blocks.measure``, for settings that differ in more than eps."""
    spark, reps = units.sparkSession, -(-plan.runs // plan.folds)
    settings = [n for n, first in enumerate(plan.first) if n == first]
    counts: dict[tuple, np.ndarray] = {}
    by_item = [m for m in methods if m != "cf_user"]
    if by_item:
        sums = blocks._summed(units, item_pass(plan, settings, by_item, None))
        counts |= blocks._summed(units, item_pass(plan, settings, by_item, sums))
    if "cf_user" in methods:
        people, rows = {}, []
        for n in settings:
            kind = plan.settings[n][0]
            if kind not in people:
                people[kind] = _people(units, n, len(plan.items[kind]))
            users = len(people[kind][0])
            each = ROWS * max(1, -(-users * reps * len(settings) // (ROWS * 4 * spark.sparkContext.defaultParallelism)))
            rows += [(n, rep, lo, min(users, lo + each)) for rep in range(reps) for lo in range(0, users, each)]
        parts = spark.createDataFrame(rows, "setting int, rep int, start int, stop int").repartition(max(1, len(rows)))
        counts |= blocks._summed(parts, search_pass(plan, people))
    out = [(METHODS[m], plan.run(setting, rep, k), *map(int, row)) for (setting, rep, m), v in counts.items() for k, row in enumerate(v.reshape(-1, len(blocks.COUNTS)))]
    return spark.createDataFrame(out, "method string, run int, " + ", ".join(f"{c} long" for c in blocks.COUNTS))  # a row for each run
