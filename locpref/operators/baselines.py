"""Methods to compare with: neighbours, constants, majorities, library factorisation, k-anonymity, coarsening."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform

#: Up to so many values of the other side, ratings of one id are a dense vector and pairs meet by products of matrices.
MAX_DENSE = 128
#: Vectors in a list, on either side of a product.
DENSE_ROWS = 1024


def similarities(triples: DataFrame, side: str, sim: str = "cosine", min_common: int = 2, keys: tuple[str, ...] = ()) -> DataFrame:
    """``keys, a, b, s`` for pairs of one side that rated something in common."""
    other = "item_id" if side == "user_id" else "user_id"
    base = triples.select(*keys, side, other, "rating")
    if sim == "pearson":
        mean = base.groupBy(*keys, side).agg(F.avg("rating").alias("m"))
        base = base.join(mean, [*keys, side]).select(*keys, side, other, (F.col("rating") - F.col("m")).alias("rating"))
    left = base.select(*keys, F.col(side).alias("a"), other, F.col("rating").alias("ra"))
    right = base.select(*keys, F.col(side).alias("b"), other, F.col("rating").alias("rb"))
    both = left.join(right, [*keys, other]).where("a <> b").groupBy(*keys, "a", "b").agg(F.count("*").alias("common"), F.sum(F.col("ra") * F.col("rb")).alias("ab"), F.sum(F.col("ra") * F.col("ra")).alias("aa"), F.sum(F.col("rb") * F.col("rb")).alias("bb"))
    if sim == "jaccard":
        s = F.expr("try_divide(ab, aa + bb - ab)")
    elif sim in ("cosine", "pearson"):
        s = F.expr("try_divide(ab, sqrt(aa) * sqrt(bb))")
    else:
        raise ValueError(f"unknown similarity {sim}")
    return both.where(F.col("common") >= min_common).select(*keys, "a", "b", s.alias("s")).where("s is not null")


def _best(rows: np.ndarray, others: np.ndarray, sim: str, min_common: int) -> np.ndarray:
    """Similarities of all rows of two matrices (a missing rating is NaN); NaN where there is none."""
    parts = []
    for v in (rows, others):
        there = ~np.isnan(v)
        if sim == "pearson":
            v = v - (np.where(there, v, 0.0).sum(axis=1) / there.sum(axis=1))[:, None]
        v = np.where(there, v, 0.0)
        parts.append((v, v * v, there.astype(np.float64)))
    (a, aa, ma), (b, bb, mb) = parts
    ab, aa, bb = a @ b.T, aa @ mb.T, ma @ bb.T
    with np.errstate(invalid="ignore", divide="ignore"):
        below = aa + bb - ab if sim == "jaccard" else np.sqrt(aa) * np.sqrt(bb)
        s = np.where(below == 0, np.nan, ab / below)
    s[ma @ mb.T < min_common] = np.nan
    return s


def dense_top(triples: DataFrame, side: str, values: list, k: int, sim: str, min_common: int, keys: tuple[str, ...]) -> DataFrame:
    """``keys, a, b, s``: the k most similar others of every id, from its ratings of the few ``values`` of the other side (one rating a cell).

    Ids with equal ratings are one class, compared once; of a class as neighbours the
    k + 1 least ids are enough, as all are equally near. A list of classes meets the
    lists of neighbours one after the other, so a task holds two lists and k + 1
    results for each class.
    """
    other = "item_id" if side == "user_id" else "user_id"
    at = F.col("_m")
    rated = triples.groupBy(*keys, F.col(side).alias("a")).agg(F.map_from_entries(F.collect_list(F.struct(other, F.col("rating").cast("double").alias("r")))).alias("_m"))
    rated = rated.select(*keys, "a", F.array(*(F.coalesce(F.try_element_at(at, F.lit(v)), F.lit(float("nan"))) for v in values)).alias("v"))
    same = Window.partitionBy(*keys, "v").orderBy("a")
    classes = rated.groupBy(*keys, "v").agg(F.min("a").alias("class"))
    lists = {}
    for name, rows, key in (("row", classes, "class"), ("near", rated.withColumn("_r", F.row_number().over(same)).where(F.col("_r") <= k + 1), "a")):
        n = rows.groupBy(*keys).agg(F.ceil(F.count("*") / DENSE_ROWS).alias("_n"))
        rows = rows.join(n, list(keys)) if keys else rows.crossJoin(n)
        lists[name] = rows.groupBy(*keys, F.pmod(F.xxhash64(key), F.col("_n")).alias("part")).agg(F.collect_list(F.col(key).cast("long")).alias("ids"), F.flatten(F.collect_list("v")).alias("vs"))
    rows, near = lists["row"].withColumn("kind", F.lit(0)), lists["near"].drop("part").withColumn("kind", F.lit(1))
    parts = rows.select(*keys, "part")
    near = near.join(parts, list(keys)) if keys else near.crossJoin(parts)
    both = rows.unionByName(near)
    # lists are rows of DENSE_ROWS vectors
    met = both.repartition(*keys, "part").sortWithinPartitions(*keys, "part", "kind")
    out = pa.schema([*((c, pa.int64()) for c in keys), ("class", pa.int64()), ("b", pa.int64()), ("s", pa.float64())])

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, v, best = None, None, None, None

        def told() -> Iterator[pa.RecordBatch]:
            if now is not None:
                who, nth = np.nonzero(best["order"] < np.inf)
                found = best[who, nth]
                yield pa.RecordBatch.from_arrays([*(pa.array(np.full(len(who), x, np.int64)) for x in now[:-1]), pa.array(ids[who]), pa.array(found["b"].copy()), pa.array(found["s"].copy())], schema=out)

        for batch in batches:
            for n in range(batch.num_rows):
                key = tuple(batch.column(c)[n].as_py() for c in (*keys, "part"))
                own = batch.column("ids")[n].values.to_numpy()
                vectors = batch.column("vs")[n].values.to_numpy(zero_copy_only=False).reshape(len(own), -1)
                if key != now:
                    yield from told()
                    now, ids, v = key, own.copy(), vectors.copy()
                    best = np.full((len(ids), k + 1), np.array((np.inf, 0, np.nan), [("order", "f8"), ("b", "i8"), ("s", "f8")]))
                    continue
                s = _best(v, vectors, sim, min_common)
                # nine places, halves up; least is best, unknown never
                order = np.where(np.isnan(s), np.inf, -np.sign(s) * np.floor(np.abs(s) * 1e9 + 0.5))
                who, col = np.nonzero((order <= best["order"][:, -1:]) & (order < np.inf))
                late = (order[who, col] == best["order"][who, -1]) & (own[col] > best["b"][who, -1])
                who, col = who[~late], col[~late]
                if not len(who):
                    continue
                more = np.empty(len(who), best.dtype)
                more["order"], more["b"], more["s"] = order[who, col], own[col], s[who, col]
                hit = np.unique(who)
                all_who, every = np.concatenate([np.repeat(hit, k + 1), who]), np.concatenate([best[hit].ravel(), more])
                by = np.lexsort((every["b"], every["order"], all_who))
                all_who, every = all_who[by], every[by]
                rank = np.arange(len(by)) - np.searchsorted(all_who, all_who)
                good = rank <= k
                best[all_who[good], rank[good]] = every[good]
        yield from told()

    types = dict(triples.dtypes)
    top = met.mapInArrow(search, ", ".join([*(f"{c} long" for c in keys), "class long", "b long", "s double"]))
    top = top.select(*(F.col(c).cast(types[c]).alias(c) for c in keys), "class", F.col("b").cast(types[side]).alias("b"), "s")
    of_class = rated.select(*keys, "a", F.min("a").over(Window.partitionBy(*keys, "v")).cast("long").alias("class"))
    nearest = Window.partitionBy(*keys, "a").orderBy(F.desc(F.round("s", 9)), "b")
    return of_class.join(top, [*keys, "class"]).where("a <> b").withColumn("r", F.row_number().over(nearest)).where(F.col("r") <= k).select(*keys, "a", "b", "s")


def _top(triples: DataFrame, side: str, k: int, sim: str, min_common: int, keys: tuple[str, ...]) -> DataFrame:
    other, types = "item_id" if side == "user_id" else "user_id", dict(triples.dtypes)
    if all(types[c] in ("int", "bigint") for c in (side, *keys)):
        values = sorted(r[0] for r in triples.select(other).where(F.col(other).isNotNull()).distinct().limit(MAX_DENSE + 1).collect())
        if 0 < len(values) <= MAX_DENSE:
            return dense_top(triples, side, values, k, sim, min_common, keys)
    near = Window.partitionBy(*keys, "a").orderBy(F.desc(F.round("s", 9)), "b")
    return similarities(triples, side, sim, min_common, keys).withColumn("r", F.row_number().over(near)).where(F.col("r") <= k).select(*keys, "a", "b", "s")


def _neighbours(cells: DataFrame, triples: DataFrame, side: str, k: int, sim: str, min_common: int, keys: tuple[str, ...]) -> DataFrame:
    other = "item_id" if side == "user_id" else "user_id"
    top = _top(triples, side, k, sim, min_common, keys)
    votes = cells.select(*keys, "user_id", "item_id").join(top.withColumnRenamed("a", side), [*keys, side]).join(triples.select(*keys, F.col(side).alias("b"), other, F.col("rating").alias("vote")), [*keys, "b", other])
    found = votes.groupBy(*keys, "user_id", "item_id").agg(F.expr("try_divide(sum(s * vote), sum(abs(s)))").alias("score"))
    return cells.join(found, [*keys, "user_id", "item_id"], "left")


def cf_user(cells: DataFrame, triples: DataFrame, k: int = 20, sim: str = "cosine", min_common: int = 2, keys: tuple[str, ...] = ()) -> DataFrame:
    """Mean rating of the k most similar users, weighted by similarity; null without neighbours."""
    return _neighbours(cells, triples, "user_id", k, sim, min_common, keys)


def cf_item(cells: DataFrame, triples: DataFrame, k: int = 20, sim: str = "cosine", min_common: int = 2, keys: tuple[str, ...] = ()) -> DataFrame:
    return _neighbours(cells, triples, "item_id", k, sim, min_common, keys)


def constant(cells: DataFrame, decision: int) -> DataFrame:
    return cells.withColumn("score", F.lit(float(decision))).withColumn("decision", F.lit(int(decision)))


def majority(cells: DataFrame, triples: DataFrame, by: str = "global", keys: tuple[str, ...] = ()) -> DataFrame:
    """Share of positive ratings: global, by item, by user, or user and item bias together."""
    overall = triples.groupBy(*keys).agg(F.avg("rating").alias("g"))
    item = triples.groupBy(*keys, "item_id").agg(F.avg("rating").alias("i"))
    user = triples.groupBy(*keys, "user_id").agg(F.avg("rating").alias("u"))
    joined = cells.join(F.broadcast(overall), list(keys), "left") if keys else cells.crossJoin(F.broadcast(overall))  # a row for each run
    if by == "global":
        return joined.withColumn("score", F.col("g")).drop("g")
    if by in ("item", "bias"):
        joined = joined.join(item, [*keys, "item_id"], "left")
    if by in ("user", "bias"):
        joined = joined.join(user, [*keys, "user_id"], "left")
    i, u = (F.coalesce(c, "g") for c in ("i", "u")) if by == "bias" else (None, None)
    score: Column = u + i - F.col("g") if by == "bias" else F.coalesce({"item": "i", "user": "u"}[by], "g")
    return joined.withColumn("score", score).drop("g", "i", "u")


def coin(cells: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    return cells.withColumn("decision", (uniform(seed, "coin", F.col("user_id"), F.col("item_id")) < rate).cast("int")).withColumn("score", F.col("decision").cast("double"))


def als(triples: DataFrame, cells: DataFrame, rank: int = 4, rounds: int = 8, reg: float = 0.05, nonnegative: bool = False, seed: int = 42) -> DataFrame:
    """The library's alternating least squares; ids must fit an int."""
    from pyspark.ml.recommendation import ALS

    ids = [F.col(c).cast("int").alias(c) for c in ("user_id", "item_id")]
    model = ALS(rank=rank, maxIter=rounds, regParam=reg, userCol="user_id", itemCol="item_id", ratingCol="rating", nonnegative=nonnegative, seed=seed).fit(triples.select(*ids, "rating"))
    return model.transform(cells.withColumns({c: F.col(c).cast("int") for c in ("user_id", "item_id")})).withColumnRenamed("prediction", "score")


def k_anonymous(visits: DataFrame, k: int, item: str = "item") -> DataFrame:
    """Visits to items that k users or more visited."""
    known = visits.groupBy(item).agg(F.countDistinct("user_id").alias("n")).where(F.col("n") >= k).select(item)
    return visits.join(known, item, "left_semi")


def coarsen(visits: DataFrame, levels: DataFrame, ladder: tuple[str, ...] = ("place", "area", "region")) -> DataFrame:
    """``shown``: the location on the level that each user's application may see (``levels``: user_id, level)."""
    shown = F.lit(None).cast("string")
    for n, c in enumerate(ladder):
        shown = F.when(F.col("level") == n, F.col(c).cast("string")).otherwise(shown)
    return visits.join(levels, "user_id").withColumn("shown", shown)
