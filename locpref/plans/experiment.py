"""Folds, masks, repetitions, sweeps and the choice of parameters.

Folds and repetitions are a ``run`` column in one plan: a round of all fits is one set
of jobs, not one for each fit.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import granularity as g
from ..functions import lanes
from ..functions.hashing import hash_bits, uniform
from ..operators import baselines, blocks, dataset, factorization, metrics, predict, preferences, private, votes
from ..sources.rounds import Rounds

#: What the private methods protect; ``central`` adds its noise to exact sums instead.
PROTECT = {"private": ("bits", "grads"), "both": ("bits", "grads"), "bits": ("bits",), "grads": ("grads",), "none": (), "central": ("bits", "grads")}
#: What tells the rows of a sweep apart, besides the run.
SETTING = ("method", "width", "eps", "unknown", "place")

#: Up to so many runs are fitted by joins; more of them by blocks, if item vectors of all runs fit in a task.
FEW_RUNS = 4


def user_folds(users: DataFrame, folds: int = 10, seed: int = 42, exact: bool = False) -> DataFrame:
    """``fold`` by hash of the user, or of equal sizes by order of the hash (one task)."""
    bits = hash_bits(seed, "fold", F.col("user_id"))
    if exact:
        return users.select("user_id").distinct().withColumn("fold", F.ntile(folds).over(Window.orderBy(bits, "user_id")) - 1)
    return users.select("user_id").distinct().withColumn("fold", F.pmod(bits, F.lit(folds)).cast("int"))


def mask_unknown(triples: DataFrame, test_users: DataFrame, share: float, seed: int = 42, exact: bool = False, item: str = "item_id") -> DataFrame:
    """``held`` 1 for the share of test users' cells that counts as unknown."""
    draw = uniform(seed, "mask", F.col("user_id"), F.col(item))
    marked = triples.join(test_users.select("user_id", F.lit(1).alias("_test")), "user_id", "left")
    if exact:
        per_user = Window.partitionBy("user_id").orderBy(draw, item)
        hidden = F.percent_rank().over(per_user) < share
    else:
        hidden = draw < share
    return marked.withColumn("held", (hidden & F.col("_test").isNotNull()).cast("int")).drop("_test")


def repeat(triples: DataFrame, folds: int, repeats: int, share: float, seed: int = 42) -> DataFrame:
    """Every cell once for each run (fold and repetition), with ``held``. A repetition has draws of its own; its folds share them."""
    reps = triples.sparkSession.range(repeats).select(F.col("id").alias("_rep"))
    cells = triples.crossJoin(F.broadcast(reps))  # a row for each repetition
    cells = cells.withColumn("_fold", F.pmod(hash_bits(seed, "fold", F.col("user_id"), F.col("_rep")), F.lit(folds)).cast("int"))
    cells = cells.withColumn("_masked", uniform(seed, "mask", F.col("user_id"), F.col("item_id"), F.col("_rep")) < share)
    each = cells.select("*", F.explode(F.sequence(F.lit(0), F.lit(folds - 1))).alias("_k"))
    return each.withColumn("run", (F.col("_rep") * folds + F.col("_k")).cast("int")).withColumn("held", ((F.col("_fold") == F.col("_k")) & F.col("_masked")).cast("int")).drop("_rep", "_fold", "_masked", "_k")


def spread(spark: SparkSession) -> int:
    """Tasks for rows that take long for their bytes: no fewer than run at once."""
    return max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))


def event_cells(visits: DataFrame, width: int, places: int | None = None, hourly: bool = True, seed: int = 42, place: str = "category", unit: str = "hours") -> DataFrame:
    """Planted ``user_id, item_id, rating, truth`` at a slot width; ``places`` adds a coarse place to the item.

    ``place`` is a kind of location key. ``unit`` "months" is for carriers that have
    dates only; their truth has no hours.
    """
    loc = g.location_key(place) if places is None else F.concat_ws(":", "category", F.pmod("place", F.lit(places)).cast("string"))
    slot = g.time_slot(F.col("ts"), width) if unit == "hours" else g.month_slot(F.col("ts"), width)
    if hourly and unit == "hours":
        cells = preferences.build(dataset.planted_hourly(visits, loc, seed=seed), loc, slot).withColumn("truth", F.col("rating").cast("int"))
    else:
        made = preferences.build(visits, loc, slot).select("user_id", "item")
        cells = dataset.planted(made.repartition(spread(made.sparkSession)), seed=seed)  # few bytes, but many draws for each
    return cells.select("user_id", F.col("item").alias("item_id"), "rating", "truth")


class Cells:
    """What ``event_cells`` gives for visits that lie by user: planted vectors are drawn once for each user and item, hourly truths once for all widths, and no cell is shuffled."""

    def __init__(self, scratch: Rounds, visits: DataFrame, hourly: bool, seed: int, unit: str, places: int | None = None):
        self.scratch, self.hourly, self.seed, self.unit, self.places = scratch, hourly and unit == "hours", seed, unit, places
        self.visits = scratch.keep(visits.drop("event_id"), "visits", ["user_id"])  # read and joined once for all settings
        self.people = scratch.keep(dataset.planted_vectors(self.visits, "user_id", "x", seed=seed), "people", ["user_id"])
        self.labelled: dict[str, DataFrame] = {}

    def of(self, width: int, place: str) -> tuple[DataFrame, DataFrame]:
        """Items, and cells with these."""
        loc = g.location_key(place) if self.places is None else F.concat_ws(":", "category", F.pmod("place", F.lit(self.places)).cast("string"))
        slot = g.time_slot(F.col("ts"), width) if self.unit == "hours" else g.month_slot(F.col("ts"), width)
        visits, n = self.visits.where(loc.isNotNull()), len(self.scratch.made)
        items = visits.where(slot.isNotNull() & F.col("label").isNotNull() & F.col("user_id").isNotNull()).select(preferences.item_key(loc, slot).alias("item"))
        if self.hourly:
            if place not in self.labelled:
                keyed = visits.withColumn("item", loc)
                vectors = self.scratch.keep(dataset.planted_vectors(keyed, "item", "z", seed=self.seed), f"planted-{n}")
                drawn = dataset.planted_hourly(keyed.join(self.people, "user_id").join(vectors, "item"), F.col("item"), seed=self.seed, drawn=True)
                self.labelled[place] = self.scratch.keep(drawn.select(*self.visits.columns, "truth"), f"labelled-{n}", ["user_id"])
            cells = preferences.build(self.labelled[place], loc, slot).withColumn("truth", F.col("rating").cast("int"))
            items = self.scratch.keep(items.distinct(), f"items-{n}")
        else:
            vectors = self.scratch.keep(dataset.planted_vectors(items, "item", "z", seed=self.seed), f"items-{n}")
            made = preferences.build(visits, loc, slot).select("user_id", "item")
            cells, items = dataset.planted(made.join(self.people, "user_id").join(vectors, "item"), seed=self.seed, drawn=True), vectors.select("item")
        return items.withColumnRenamed("item", "item_id"), cells.select("user_id", F.col("item").alias("item_id"), "rating", "truth")


def evaluate(cells: DataFrame, scored: DataFrame, method: str) -> DataFrame:
    """FPR and recall over all known cells, reconstruction over the held ones, by run."""
    both = cells.select("run", "user_id", "item_id", "truth", "held").join(scored.select("run", "user_id", "item_id", "decision"), ["run", "user_id", "item_id"], "left").withColumn("decision", F.coalesce("decision", F.lit(0)))
    whole = metrics.rates(metrics.confusion(both, ("run",)), "fpr", "recall").select("run", "fpr", "recall")
    held = metrics.rates(metrics.confusion(both.where("held = 1"), ("run",)), "reconstruction").select("run", "reconstruction")
    return whole.join(held, "run", "left").select(F.lit(method).alias("method"), "run", "fpr", "recall", "reconstruction")


def measures(counts: DataFrame) -> DataFrame:
    """The same from counts by method and run."""
    rates = metrics.rates(counts, "fpr", "recall")
    return rates.select("method", "run", "fpr", "recall", F.expr("try_divide(right, cast(held AS double))").alias("reconstruction"))


def for_all(rows: DataFrame, copies: DataFrame, runs: int) -> DataFrame:
    """Rows of the settings that were fitted, once for each setting alike (``copies``: _first, _no)."""
    no = F.floor(F.col("run") / runs).cast("int")
    return rows.join(F.broadcast(copies), no == F.col("_first")).withColumn("run", (F.col("_no") * runs + F.col("run") % runs).cast("int")).drop("_first", "_no")  # a row for each setting


def sweep(visits: DataFrame, grid: list[dict], folds: int = 10, runs: int = 1, rounds: int = 8, d: int = 3, methods: tuple[str, ...] = ("plain", "private"), seed: int = 42, places: int | None = None, hourly: bool = False, unit: str = "hours") -> DataFrame:
    """A row for every method, setting and run; settings are ``width``, ``eps``, ``unknown`` and ``place`` (a kind of location key).

    All settings and runs of a method are one fit; the methods see the same masks.
    What adds no noise doesn't depend on ``eps``: of settings that differ in it alone, one
    is fitted and measured for all.
    """
    spark = visits.sparkSession
    scratch = Rounds(spark, "sweep")
    eps_of, named, made, alike, of = [], [], {}, {}, []
    source = Cells(scratch, visits, hourly, seed, unit, places)
    for g_no, s in enumerate(grid):
        place = s.get("place", "category")
        key = (s["width"], place)
        alike.setdefault((*key, s["unknown"]), []).append(g_no)
        if key not in made:
            made[key] = source.of(*key)
        of.append(key)
        for r in range(runs):
            eps_of.append((g_no * runs + r, s["eps"]))
            named.append((g_no * runs + r, int(s["width"]), float(s["eps"]), float(s["unknown"]), place))
    no = F.floor(F.col("run") / runs).cast("int")
    copies = spark.createDataFrame([(same[0], k) for same in alike.values() for k in same], "_first int, _no int")
    settings = spark.createDataFrame(named, "run int, width int, eps double, unknown double, place string")
    out, done = None, ()
    fits = tuple(m for m in methods if m == "plain" or m in PROTECT)
    lists, tables = zip(*made.values(), strict=True)
    kinds = [list(made).index(key) for key in of]
    if len(grid) * runs > FEW_RUNS and all(dict(t.dtypes)["user_id"] in ("int", "bigint") for t in tables):
        items = blocks.fits(lists, kinds, runs, d)
        split = items is None and lanes.function(spark) and d <= lanes.ROOM and rounds > 1
        if split:
            items = blocks.fits(lists, kinds, runs, d, len(fits))
        if items is not None:
            first = {k: same[0] for same in alike.values() for k in same}
            plan = blocks.Plan(tuple((k, s["unknown"], s["eps"]) for k, s in zip(kinds, grid, strict=True)), tuple((m, None if m == "plain" else private.PrivateConfig(d=d, rounds=rounds, seed=seed, protect=PROTECT[m]), m == "central") for m in fits), tuple(first[k] for k in range(len(grid))), tuple(items), folds, runs, d, seed)
            asked = [m for m in methods if m in votes.METHODS and votes.fits(tables, plan)]
            if (fits or asked) and not (split and plan.said() is None):
                units, stored = blocks.units(scratch, tables, plan)
                if set(methods) <= {*fits, *asked}:
                    scratch.only("units")
                counts = [blocks.measure(units, plan, rounds, stored)] * bool(fits) + [votes.measure(units, plan, asked)] * bool(asked)
                out, done = measures(counts[0] if len(counts) == 1 else counts[0].unionByName(counts[1])), (*fits, *asked)
                if len(alike) < len(grid):
                    private_ = F.col("method").isin(*PROTECT)
                    out = out.where(private_).unionByName(for_all(out.where(~private_), copies, runs))
    rest, all_cells = [m for m in methods if m not in done], None
    if rest:
        tables = [scratch.keep(t, f"cells-{k}") for k, t in enumerate(tables)]
        for g_no, s in enumerate(grid):
            one = repeat(tables[kinds[g_no]], folds, -(-runs // folds), s["unknown"], seed).where(F.col("run") < runs).withColumn("run", F.col("run") + g_no * runs)
            all_cells = one if all_cells is None else all_cells.unionByName(one)
        all_cells = scratch.keep(all_cells.withColumn("run", F.col("run").cast("int")), "cells")
    for m in rest:
        once = m not in PROTECT and len(alike) < len(grid)
        cells = all_cells.where(no.isin([same[0] for same in alike.values()])) if once else all_cells
        known, asked = cells.where("held = 0"), cells.select("run", "user_id", "item_id")
        if m == "plain" or m in PROTECT:
            if m == "plain":
                model = factorization.fit_plain(known, factorization.FitConfig(d=d, rounds=rounds, max_norm=2.0, seed=seed), ("run",))
            else:
                model = private.fit_runs(known, eps_of, private.PrivateConfig(d=d, rounds=rounds, seed=seed, protect=PROTECT[m]), m == "central")
            scored = predict.decide(predict.score(asked, model.X, model.Z, d, ("run",)), predict.mean_threshold(model.X, model.Z, d, ("run",)))
        else:
            rated, keys = known.select("run", "user_id", "item_id", "rating"), ("run",)
            one = {"cf_user": lambda: baselines.cf_user(asked, rated, keys=keys), "cf_item": lambda: baselines.cf_item(asked, rated, keys=keys), "majority": lambda: baselines.majority(asked, rated, "bias", keys)}[m]()
            scored = one.select("run", "user_id", "item_id", (F.coalesce("score", F.lit(0.0)) > 0.5).cast("int").alias("decision"))
        rows = evaluate(cells, scored, m)
        if once:
            rows = for_all(rows, copies, runs)
        out = rows if out is None else out.unionByName(rows)
    out = out.join(F.broadcast(settings), "run").select(*SETTING, "run", "fpr", "recall", "reconstruction")  # a row for each run
    out = scratch.keep(out, "rows")
    scratch.only("rows")
    return out


def averaged(rows: DataFrame) -> DataFrame:
    """Mean, spread and interval of every method and setting over all its runs."""
    return metrics.summarise(rows, SETTING, ("fpr", "recall", "reconstruction"))


def best_width(rows: DataFrame, by: str = "reconstruction") -> DataFrame:
    return rows.groupBy("method", "width").agg(F.avg(by).alias("u")).groupBy("method").agg(F.max_by("width", F.struct("u", -F.col("width"))).alias("best_width"))


def smallest_eps(rows: DataFrame, tol: float, by: str = "reconstruction") -> DataFrame:
    """The least eps whose utility is within ``tol`` of the best."""
    mean = rows.groupBy("method", "eps").agg(F.avg(by).alias("u"))
    top = mean.groupBy("method").agg(F.max("u").alias("top"))
    return mean.join(top, "method").where(F.col("u") >= F.col("top") - tol).groupBy("method").agg(F.min("eps").alias("smallest_eps"))


def needed_known_share(rows: DataFrame, target: float, by: str = "reconstruction") -> DataFrame:
    """The least share of ratings a user must give to reach the target."""
    return rows.groupBy("method", "unknown").agg(F.avg(by).alias("u")).where(F.col("u") >= target).groupBy("method").agg(F.round(1 - F.max("unknown"), 6).alias("known_share"))


def utility_slope(rows: DataFrame, by: str = "reconstruction") -> DataFrame:
    """Change of utility per step of eps between neighbouring values."""
    mean = rows.groupBy("method", "eps").agg(F.avg(by).alias("u"))
    w = Window.partitionBy("method").orderBy("eps")
    return mean.withColumn("slope", F.expr("try_divide(u - lag(u) OVER (PARTITION BY method ORDER BY eps), eps - lag(eps) OVER (PARTITION BY method ORDER BY eps))")).withColumn("step", F.row_number().over(w))


def choice(widths: DataFrame, levels: DataFrame, shares: DataFrame, tol: float, target: float, by: str = "reconstruction_mean") -> DataFrame:
    """Width, eps and known share by method, each from the sweep that varies it; null where no share reaches the target."""
    return best_width(widths, by).join(smallest_eps(levels, tol, by), "method", "left").join(needed_known_share(shares, target, by), "method", "left")
