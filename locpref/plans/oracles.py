"""The same results in SQL for the registered queries, draws included."""

from __future__ import annotations

import math
from dataclasses import replace

from ..functions.granularity import DAY_PARTS
from ..functions.privacy import flip_probability
from ..operators.private import PrivateConfig
from ..sources.tables import event_visits
from .experiment import PROTECT
from .queries import FOLDS, PRIVATE, REPEATS, REPEATS_LARGE, SEED, SWEEP_ROUNDS, SWEEPS, TARGET, TOLERANCE

EV = "SELECT user_id, event_id, ts, event_type AS category, CAST(json_extract_string(props, '$.k') AS INT) AS place, (value >= 35)::INT AS label FROM events"
ORD = """SELECT o_custkey AS user_id, l_orderkey * 10 + l_linenumber AS event_id, o_orderdate AS ts, p_type AS category, l_suppkey AS place, n_name AS area, r_name AS region, (l_returnflag <> 'R')::INT AS label
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey"""

#: Levels that customers can afford.
LEVELS = "SELECT floor(abs(c_acctbal) / 10) / 100 AS eps, count(*) AS users FROM customer WHERE c_acctbal IS NOT NULL GROUP BY 1"


def bits(purpose: str, *parts: str) -> str:
    return f"('0x' || substr(md5(concat_ws(':', '{SEED}:{purpose}'{''.join(', ' + p for p in parts)})), 1, 13))::BIGINT"


def u(purpose: str, *parts: str) -> str:
    return f"({bits(purpose, *parts)} / {float(2**52)!r}::DOUBLE)"


def gauss(purpose: str, *parts: str) -> str:
    return f"(sqrt(-2.0::DOUBLE * ln(1.0::DOUBLE - {u(purpose + '_r', *parts)})) * cos({2.0 * math.pi!r}::DOUBLE * {u(purpose + '_a', *parts)}))"


def lap(draw: str, scale: float | str) -> str:
    scale = scale if isinstance(scale, str) else f"{scale!r}::DOUBLE"
    v = f"(greatest({2.0**-53!r}::DOUBLE, least({1 - 2.0**-53!r}::DOUBLE, {draw})) - 0.5::DOUBLE)"
    return f"(-{scale} * sign({v}) * ln(1.0::DOUBLE - 2.0::DOUBLE * abs({v})))"


def r(x: str, name: str | None = None) -> str:
    return f"round({x}, 6) AS {name or x}"


def item(loc: str = "category", slot: str = "hour(ts) // 6") -> str:
    return f"{loc} || '@' || ({slot})::VARCHAR"


def cells(rating: str = "(avg(label) > 0.5)::INT::DOUBLE", key: str | None = None, source: str = EV) -> str:
    return f"SELECT user_id, {key or item()} AS item, {rating} AS rating, count(*) AS visits FROM ({source}) GROUP BY 1, 2"


STATS = "count(DISTINCT user_id) AS users, count(DISTINCT item) AS items, count(*) AS ratings, round(count(*) / (count(DISTINCT user_id)::DOUBLE * count(DISTINCT item)), 6) AS density, round(avg(rating), 6) AS positive"
T = f"t AS MATERIALIZED (SELECT user_id, item AS item_id, rating FROM ({cells()}))"


def init(side: str, p: str, d: int = 2) -> str:
    s = 0.75 / math.sqrt(d)
    return f"{p}_0 AS MATERIALIZED (SELECT {side}, {', '.join(f'{s!r}::DOUBLE * (0.5::DOUBLE + {u(f'init_{p}', side, str(k))}) AS {p}{k}' for k in range(d))} FROM (SELECT DISTINCT {side} FROM t))"


START = f"WITH {T}, {init('user_id', 'x')}, {init('item_id', 'z')}"
RES = "SELECT t.*, x.x0, x.x1, z.z0, z.z1, rating - (x0 * z0 + x1 * z1) AS e FROM t JOIN x_{a} x USING (user_id) JOIN z_{b} z USING (item_id)"


def stepped(p: str, side: str, t: int, grad: str, gamma: float, lam: float, radius: float | None) -> str:
    raw = [f"{p}.{p}{k} - {gamma!r}::DOUBLE * (coalesce(g.g{k}, 0) + {2 * lam!r}::DOUBLE * {p}.{p}{k})" for k in range(2)]
    shrink = "" if radius is None else f" * least(1.0::DOUBLE, {radius!r}::DOUBLE / greatest(sqrt({p}0 * {p}0 + {p}1 * {p}1), 1e-300::DOUBLE))"
    return f"{p}_{t} AS MATERIALIZED (SELECT {side}, {', '.join(f'{p}{k}{shrink} AS {p}{k}' for k in range(2))} FROM (SELECT {p}.{side}, {', '.join(f'{x} AS {p}{k}' for k, x in enumerate(raw))} FROM {p}_{t - 1} {p} LEFT JOIN ({grad}) g USING ({side})))"


def plain(rounds: int, norm: str = "ratings", order: str = "joint", gammas: list[float] | None = None, radius: float | None = None) -> str:
    w = {"ratings": ("(SELECT count(*) FROM t)",) * 2, "users": ("(SELECT count(DISTINCT item_id) FROM t)", "(SELECT count(DISTINCT user_id) FROM t)")}[norm]
    out = [START]
    for t in range(1, rounds + 1):
        gamma = (gammas or [0.5] * rounds)[t - 1]
        a = t if order == "alternate" else t - 1
        gx = f"SELECT user_id, sum(-2.0 * (1.0::DOUBLE / {w[0]}) * e * z0) AS g0, sum(-2.0 * (1.0::DOUBLE / {w[0]}) * e * z1) AS g1 FROM ({RES.format(a=t - 1, b=t - 1)}) GROUP BY 1"
        gz = f"SELECT item_id, sum(-2.0 * (1.0::DOUBLE / {w[1]}) * e * x0) AS g0, sum(-2.0 * (1.0::DOUBLE / {w[1]}) * e * x1) AS g1 FROM ({RES.format(a=a, b=t - 1)}) GROUP BY 1"
        out += [stepped("x", "user_id", t, gx, gamma, 1e-4, radius), stepped("z", "item_id", t, gz, gamma, 1e-4, radius)]
    return ",\n".join(out)


def z_of(t: int) -> str:
    return f"\nSELECT item_id, {r('z0')}, {r('z1')} FROM z_{t}"


def clipped(bound: float, kind: str = "l1") -> list[str]:
    raw = ["(-2.0 * e * x0)", "(-2.0 * e * x1)"]
    if kind == "coordinate":
        return [f"greatest({-bound!r}::DOUBLE, least({bound!r}::DOUBLE, {x}))" for x in raw]
    n = f"(abs({raw[0]}) + abs({raw[1]}))" if kind == "l1" else f"sqrt({raw[0]} * {raw[0]} + {raw[1]} * {raw[1]})"
    return [f"{x} * least(1.0::DOUBLE, {bound!r}::DOUBLE / greatest({n}, 1e-300::DOUBLE))" for x in raw]


def ring(t: int, sample: int) -> str:
    """Exactly ``sample`` items of each user: those after a drawn place among items in order of their hashes."""
    m = "(SELECT count(*) FROM z_0)"
    place = f"SELECT item_id, row_number() OVER (ORDER BY {bits('ring', 'item_id', str(t))}, item_id) - 1 AS place FROM z_0"
    return f"SELECT user_id, item_id FROM (SELECT user_id, (floor({u('sample', 'user_id', str(t))} * {m})::BIGINT + unnest(range(least({sample}, {m})))) % {m} AS place FROM x_0) JOIN ({place}) USING (place)"


def reports(t: int, p: float | str, scale: float | str, product: bool = False, sample: int | None = None, levels: str | None = None) -> str:
    """All users' reports of round t from the factors before it; ``levels`` (user_id, p, scale) for levels of their own."""
    own = f"SELECT user_id, item_id, {clipped(1.0)[0]} AS g0, {clipped(1.0)[1]} AS g1 FROM ({RES.format(a=t - 1, b=t - 1)})"
    key = ("c.user_id", "c.item_id", str(t))
    p, scale = ("l.p", "l.scale") if levels else (f"{p!r}::DOUBLE", f"{scale!r}::DOUBLE")
    bit = f"CASE WHEN {u('bit_flip', *key)} < {p} THEN ({u('bit_coin', *key)} < 0.5)::INT ELSE (g0 IS NOT NULL)::INT END"
    noisy = [f"coalesce(g{k}, 0) + {lap(u('lap', *key, str(k)), scale)} AS g{k}" for k in range(2)]
    cells_ = f"SELECT user_id, item_id FROM x_{t - 1}, z_{t - 1}" if sample is None else ring(t, sample)
    more = f" JOIN ({levels}) l ON l.user_id = c.user_id" if levels else ""
    weight = f", ({bit} - l.p / 2) / (1 - l.p) AS w" if levels else ""
    q = f"SELECT c.user_id, c.item_id, {bit} AS ybit, {', '.join(noisy)}{weight} FROM ({cells_}) c LEFT JOIN ({own}) o ON o.user_id = c.user_id AND o.item_id = c.item_id{more}"
    return f"SELECT user_id, item_id, ybit * g0 AS g0, ybit * g1 AS g1 FROM ({q})" if product else q


def mean_report(q: str, p: float, product: bool = False) -> str:
    parts = [f"avg(g{k}) / {1 - p / 2!r}::DOUBLE" if product else f"avg((ybit - {p / 2!r}::DOUBLE) / {1 - p!r}::DOUBLE * g{k})" for k in range(2)]
    return f"SELECT item_id, {parts[0]} AS g0, {parts[1]} AS g1 FROM ({q}) GROUP BY 1"


def private(rounds: int, product: bool = False, server: bool = False, sample: int | None = None, user_step: bool = True) -> str:
    cfg = replace(PRIVATE, user_side="server" if server else "client")
    p, scale = cfg.mechanism(1)
    out = [START]
    for t in range(1, rounds + 1):
        m = "(SELECT count(DISTINCT item_id) FROM t)"
        gx = f"SELECT user_id, sum(-2.0 * (1.0::DOUBLE / {m}) * e * z0) AS g0, sum(-2.0 * (1.0::DOUBLE / {m}) * e * z1) AS g1 FROM ({RES.format(a=t - 1, b=t - 1)}) GROUP BY 1"
        if server:
            gx = f"SELECT user_id, {', '.join(f'g{k} * least(1.0::DOUBLE, 1.0::DOUBLE / greatest(abs(g0) + abs(g1), 1e-300::DOUBLE)) + {lap(u('lap_user', 'user_id', str(t), str(k)), cfg.user_scale(1))} AS g{k}' for k in range(2))} FROM ({gx})"
        gz = mean_report(reports(t, p, scale, product, sample), p, product)
        out += [stepped("z", "item_id", t, gz, 0.5, 1e-4, 2.0), stepped("x", "user_id", t, gx, 0.5, 1e-4, 2.0)]
    return ",\n".join(out)


PLANTED = f"""p0 AS MATERIALIZED (
  SELECT user_id, item_id, (({' + '.join(f"{gauss('planted_x', 'user_id', str(k))} * {gauss('planted_z', 'item_id', str(k))}" for k in range(3))}) + 0.3 > 0)::INT AS truth FROM t
), planted AS MATERIALIZED (SELECT *, (CASE WHEN {u('flip', 'user_id', 'item_id')} < 0.05 THEN 1 - truth ELSE truth END)::DOUBLE AS rating FROM p0)"""
TEST = f"(({bits('fold', 'user_id')}) % 10) = 0"
SCORED = f"""WITH {T}, {PLANTED}, s AS (
  SELECT p.*, round(avg(rating) OVER (PARTITION BY item_id), 9) AS score, ({TEST} AND {u('mask', 'user_id', 'item_id')} < 0.3)::INT AS held FROM planted p
), scored AS (SELECT *, (score > 0.6)::INT AS decision FROM s)"""
COUNTS = "count(*) FILTER (truth = 1 AND decision = 1) AS tp, count(*) FILTER (truth = 0 AND decision = 1) AS fp, count(*) FILTER (truth = 0 AND decision = 0) AS tn, count(*) FILTER (truth = 1 AND decision = 0) AS fn"
SURVEY = f"""kinds AS (SELECT category, row_number() OVER (ORDER BY category) - 1 AS k FROM (SELECT DISTINCT category FROM ({EV}))),
survey AS MATERIALIZED (
  SELECT respondent, slot, answer, kinds.category FROM (
    SELECT source AS respondent, lang, (doc_id % 4)::INT AS slot, quality::INT AS answer, ({bits('category', 'lang')}) % (SELECT count(*) FROM kinds) AS k FROM labels JOIN documents USING (doc_id)
  ) JOIN kinds USING (k)
), visits AS (SELECT *, (hour(ts) // 6)::INT AS slot FROM ({EV})),
rated AS (
  SELECT v.*, ({u('transfer', 'event_id')} < coalesce(r2, r1, (SELECT avg(answer) FROM survey)))::INT AS by_rate FROM visits v
  LEFT JOIN (SELECT category, slot, avg(answer) AS r2 FROM survey GROUP BY 1, 2) USING (category, slot) LEFT JOIN (SELECT category, avg(answer) AS r1 FROM survey GROUP BY 1) USING (category)
), people AS (SELECT respondent, row_number() OVER (ORDER BY respondent) - 1 AS n FROM (SELECT DISTINCT respondent FROM survey)),
both_ AS (
  SELECT r.*, a.label AS own FROM (SELECT *, ({bits('archetype', 'user_id')}) % (SELECT count(*) FROM people) AS n FROM rated) r JOIN people USING (n)
  LEFT JOIN (SELECT respondent, category, slot, (avg(answer) > 0.5)::INT AS label FROM survey GROUP BY 1, 2, 3) a USING (respondent, category, slot)
)"""


def runs_of(name: str) -> str:
    """Cells of a registered sweep, once for each run, as ``cells``; known ones as ``known``."""
    carrier, grid, how = SWEEPS[name]
    reps = REPEATS if carrier is event_visits else REPEATS_LARGE
    source = EV if carrier is event_visits else ORD
    forms = {"category": "category", "area": "area", "category_area": "category || ':' || area", "place": "place::VARCHAR"}
    out, made, parts = [], {}, []
    for n, s in enumerate(grid):
        place, width = s.get("place", "category"), s["width"]
        loc = forms[place]
        slot = f"hour(ts) // {width}" if how.get("unit", "hours") == "hours" else f"(month(ts) - 1) // {width}"
        if (place, width) not in made:
            made[place, width] = f"c_{len(made)}"
            if how.get("hourly"):
                angle = f"{2 * math.pi!r}::DOUBLE * hour(ts) / 24"
                wave = [f"cos({angle})", f"sin({angle})", None]
                score = " + ".join(f"{gauss('planted_x', 'user_id', str(k))} * ({gauss('planted_z', loc, str(k))}" + (f" + 1.5::DOUBLE * {wave[k]})" if wave[k] else ")") for k in range(3))
                true = f"SELECT user_id, {item(loc, slot)} AS item_id, (({score}) + 0.3 > 0)::INT AS y, {u('flip_hour', 'user_id', loc, 'hour(ts)')} AS f FROM ({source})"
                q = f"SELECT user_id, item_id, (avg(CASE WHEN f < 0.05 THEN 1 - y ELSE y END) > 0.5)::INT::DOUBLE AS rating, (avg(CASE WHEN f < 0.05 THEN 1 - y ELSE y END) > 0.5)::INT AS truth FROM ({true}) GROUP BY 1, 2"
            else:
                score = " + ".join(f"{gauss('planted_x', 'user_id', str(k))} * {gauss('planted_z', 'item_id', str(k))}" for k in range(3))
                q = f"SELECT user_id, item_id, (CASE WHEN {u('flip', 'user_id', 'item_id')} < 0.05 THEN 1 - truth ELSE truth END)::DOUBLE AS rating, truth FROM (SELECT *, (({score}) + 0.3 > 0)::INT AS truth FROM (SELECT DISTINCT user_id, {item(loc, slot)} AS item_id FROM ({source})))"
            out.append(f"{made[place, width]} AS MATERIALIZED ({q})")
        drawn = f"SELECT *, ({bits('fold', 'user_id', 'rep')}) % {FOLDS} AS fold, {u('mask', 'user_id', 'item_id', 'rep')} < {s['unknown']!r}::DOUBLE AS masked FROM {made[place, width]}, (SELECT unnest(range({reps})) AS rep)"
        parts.append(f"SELECT ({n * reps * FOLDS} + rep * {FOLDS} + k)::INT AS run, user_id, item_id, rating, truth, (fold = k AND masked)::INT AS held FROM ({drawn}), (SELECT unnest(range({FOLDS})) AS k)")
    out.append(f"cells AS MATERIALIZED ({' UNION ALL '.join(parts)})")
    out.append("known AS MATERIALIZED (SELECT run, user_id, item_id, rating FROM cells WHERE held = 0)")
    return ",\n".join(out)


def fit_of(tag: str, known: str, rounds: int, d: int, levels: str | None = None, central: bool = False, lam: float = 1e-4) -> str:
    """Factors of many runs after ``rounds`` rounds, as ``{tag}x_n`` and ``{tag}z_n``.

    ``levels`` (run, p, scale) makes the fit private: noise of rated cells one by one,
    of the others as a normal draw; or, ``central``, noise on exact sums.
    """
    first = lambda side, p: f"{tag}{p}_0 AS MATERIALIZED (SELECT run, {side}, {', '.join(f'{0.75 / math.sqrt(d)!r}::DOUBLE * (0.5::DOUBLE + {u(f'init_{p}', side, str(k))}) AS {p}{k}' for k in range(d))} FROM (SELECT DISTINCT run, {side} FROM {known}))"
    out = [f"{tag}n AS MATERIALIZED (SELECT run, count(DISTINCT user_id)::DOUBLE AS n, count(DISTINCT item_id)::DOUBLE AS m FROM {known} GROUP BY 1)", first("user_id", "x"), first("item_id", "z")]
    if levels:
        out.append(f"{tag}l AS MATERIALIZED ({levels})")
    xs, zs = [f"x{k}" for k in range(d)], [f"z{k}" for k in range(d)]
    for t in range(1, rounds + 1):
        res = f"SELECT t.run, t.user_id, t.item_id, {', '.join(xs + zs)}, rating - ({' + '.join(f'{a} * {b}' for a, b in zip(xs, zs, strict=True))}) AS e, n, m FROM {known} t JOIN {tag}x_{t - 1} USING (run, user_id) JOIN {tag}z_{t - 1} USING (run, item_id) JOIN {tag}n USING (run)"
        out.append(f"{tag}r_{t} AS MATERIALIZED ({res})")
        gx = f"SELECT run, user_id, {', '.join(f'sum(-2.0 * (1.0::DOUBLE / m) * e * z{k}) AS g{k}' for k in range(d))} FROM {tag}r_{t} GROUP BY 1, 2"
        if not levels:
            gz = f"SELECT run, item_id, {', '.join(f'sum(-2.0 * (1.0::DOUBLE / n) * e * x{k}) AS g{k}' for k in range(d))} FROM {tag}r_{t} GROUP BY 1, 2"
        else:
            norm = " + ".join(f"abs(-2.0 * e * x{k})" for k in range(d))
            clip = f"least(1.0::DOUBLE, 1.0::DOUBLE / greatest({norm}, 1e-300::DOUBLE))"
            key = ("run", "user_id", "item_id", str(t))
            if central:
                sums = f"SELECT run, item_id, any_value(n) AS n, {', '.join(f'sum(-2.0 * e * x{k} * {clip}) AS g{k}' for k in range(d))} FROM {tag}r_{t} GROUP BY 1, 2"
                gz = f"SELECT run, item_id, {', '.join(f'(g{k} + {lap(u('central', 'run', 'item_id', str(t), str(k)), 'scale')}) / n AS g{k}' for k in range(d))} FROM ({sums}) JOIN {tag}l USING (run)"
            else:
                bit = f"CASE WHEN {u('bit_flip', *key)} < p THEN ({u('bit_coin', *key)} < 0.5)::INT ELSE 1 END"
                noisy = f"SELECT run, item_id, n, p, scale, ({bit} - p / 2) / (1 - p) AS w, {', '.join(f'-2.0 * e * x{k} * {clip} + {lap(u('lap', *key, str(k)), 'scale')} AS g{k}' for k in range(d))} FROM {tag}r_{t} JOIN {tag}l USING (run)"
                spread = "sqrt((n - c) * (p / 2) * (1 - p / 2) * 2.0) / (1 - p) * scale"
                gz = f"SELECT run, item_id, {', '.join(f'(s{k} + {gauss('synth', 'run', 'item_id', str(t), str(k))} * {spread}) / n AS g{k}' for k in range(d))} FROM (SELECT run, item_id, any_value(n) AS n, any_value(p) AS p, any_value(scale) AS scale, count(*) AS c, {', '.join(f'sum(w * g{k}) AS s{k}' for k in range(d))} FROM ({noisy}) GROUP BY 1, 2)"
        for side, p, g in (("user_id", "x", gx), ("item_id", "z", gz)):
            raw = ", ".join(f"f.{p}{k} - 0.5::DOUBLE * (coalesce(g.g{k}, 0) + {2 * lam!r}::DOUBLE * f.{p}{k}) AS {p}{k}" for k in range(d))
            shrink = f"least(1.0::DOUBLE, 2.0::DOUBLE / greatest(sqrt({' + '.join(f'{p}{k} * {p}{k}' for k in range(d))}), 1e-300::DOUBLE))"
            out.append(f"{tag}{p}_{t} AS MATERIALIZED (SELECT run, {side}, {', '.join(f'{p}{k} * {shrink} AS {p}{k}' for k in range(d))} FROM (SELECT f.run, f.{side}, {raw} FROM {tag}{p}_{t - 1} f LEFT JOIN ({g}) g USING (run, {side})))")
    return ",\n".join(out)


def swept(name: str, d: int = 3) -> str:
    """A registered sweep's averages as a statement's body after WITH: the last table is ``averages``."""
    carrier, grid, how = SWEEPS[name]
    each = FOLDS * (REPEATS if carrier is event_visits else REPEATS_LARGE)
    out, decided = [runs_of(name)], []
    for m in how.get("methods", ("plain", "private")):
        if m == "plain" or m in PROTECT:
            levels = None
            if m != "plain":
                cfg = PrivateConfig(d=d, rounds=SWEEP_ROUNDS, protect=PROTECT[m])
                rows = ", ".join(f"({n}, {0.0 if m == 'central' else p!r}::DOUBLE, {scale!r}::DOUBLE)" for n, s in enumerate(grid) for p, scale in [replace(cfg, eps=s["eps"]).mechanism(1)])
                levels = f"SELECT (n * {each} + i)::INT AS run, p, scale FROM (VALUES {rows}) v(n, p, scale), (SELECT unnest(range({each})) AS i)"
            out.append(fit_of(f"{m}_", "known", SWEEP_ROUNDS, d, levels, m == "central"))
            x, z = f"{m}_x_{SWEEP_ROUNDS}", f"{m}_z_{SWEEP_ROUNDS}"
            mean = f"SELECT run, {' + '.join(f'a{k} * b{k}' for k in range(d))} AS h FROM (SELECT run, {', '.join(f'avg(x{k}) AS a{k}' for k in range(d))} FROM {x} GROUP BY 1) JOIN (SELECT run, {', '.join(f'avg(z{k}) AS b{k}' for k in range(d))} FROM {z} GROUP BY 1) USING (run)"
            score = " + ".join(f"x{k} * z{k}" for k in range(d))
            got = f"SELECT run, user_id, item_id, ({score} > h)::INT AS decision FROM cells JOIN {x} USING (run, user_id) JOIN {z} USING (run, item_id) JOIN ({mean}) USING (run)"
        elif m == "majority":
            got = "SELECT c.run, c.user_id, c.item_id, (coalesce(coalesce(u, g) + coalesce(i, g) - g, 0) > 0.5)::INT AS decision FROM cells c LEFT JOIN (SELECT run, avg(rating) AS g FROM known GROUP BY 1) USING (run) LEFT JOIN (SELECT run, item_id, avg(rating) AS i FROM known GROUP BY 1, 2) USING (run, item_id) LEFT JOIN (SELECT run, user_id, avg(rating) AS u FROM known GROUP BY 1, 2) USING (run, user_id)"
        else:
            side, other = ("user_id", "item_id") if m == "cf_user" else ("item_id", "user_id")
            sims = f"SELECT run, a, b, ab / nullif(sqrt(aa) * sqrt(bb), 0) AS s FROM (SELECT run, l.{side} AS a, r.{side} AS b, count(*) AS c, sum(l.rating * r.rating) AS ab, sum(l.rating * l.rating) AS aa, sum(r.rating * r.rating) AS bb FROM known l JOIN known r USING (run, {other}) WHERE l.{side} <> r.{side} GROUP BY 1, 2, 3) WHERE c >= 2"
            out.append(f"{m}_top AS MATERIALIZED (SELECT * FROM ({sims}) WHERE s IS NOT NULL QUALIFY row_number() OVER (PARTITION BY run, a ORDER BY round(s, 9) DESC, b) <= 20)")
            votes = f"SELECT c.run, c.user_id, c.item_id, sum(s * v.rating) / nullif(sum(abs(s)), 0) AS score FROM cells c JOIN {m}_top p ON p.run = c.run AND p.a = c.{side} JOIN known v ON v.run = c.run AND v.{side} = p.b AND v.{other} = c.{other} GROUP BY 1, 2, 3"
            got = f"SELECT run, user_id, item_id, (coalesce(score, 0) > 0.5)::INT AS decision FROM cells LEFT JOIN ({votes}) USING (run, user_id, item_id)"
        whole = f"SELECT run, truth, held, coalesce(decision, 0) AS decision FROM cells LEFT JOIN ({got}) USING (run, user_id, item_id)"
        decided.append(f"SELECT '{m}' AS method, run, count(*) FILTER (truth = 0 AND decision = 1) / nullif(count(*) FILTER (truth = 0), 0)::DOUBLE AS fpr, count(*) FILTER (truth = 1 AND decision = 1) / nullif(count(*) FILTER (truth = 1), 0)::DOUBLE AS recall, count(*) FILTER (held = 1 AND truth = decision) / nullif(count(*) FILTER (held = 1), 0)::DOUBLE AS reconstruction FROM ({whole}) GROUP BY run")
    named = ", ".join(f"({n}, {s['width']}, {s['eps']!r}::DOUBLE, {s['unknown']!r}::DOUBLE, '{s.get('place', 'category')}')" for n, s in enumerate(grid))
    measures = ", ".join(f"round(avg({x}), 6) AS {x}_mean, round(stddev_samp({x}), 6) AS {x}_sd, round(1.96 * stddev_samp({x}) / sqrt(count({x})), 6) AS {x}_half" for x in ("fpr", "recall", "reconstruction"))
    out.append(f"averages AS MATERIALIZED (SELECT method, width, eps, unknown, place, count(*) AS n, {measures} FROM ({' UNION ALL '.join(decided)}) JOIN (VALUES {named}) g(no, width, eps, unknown, place) ON run // {each} = no GROUP BY 1, 2, 3, 4, 5)")
    return ",\n".join(out)


def averages_of(name: str) -> str:
    """The averages as a table expression of its own."""
    return f"(WITH {swept(name)} SELECT * FROM averages)"


def bold(rounds: int, first: float) -> str:
    """Rounds whose step follows the loss: up 5 % after a better one, halved after a worse one."""
    out = [START]
    for t in range(1, rounds + 1):
        gamma = f"{first!r}::DOUBLE" if t <= 2 else f"(SELECT gamma FROM s_{t - 1}) * (CASE WHEN (SELECT loss FROM s_{t - 1}) <= (SELECT loss FROM s_{t - 2}) THEN 1.05 ELSE 0.5 END)"
        if t == 2:
            gamma = "(SELECT gamma FROM s_1)" if first is None else f"{first!r}::DOUBLE"
        out.append(f"k_{t} AS MATERIALIZED (SELECT {gamma} AS gamma)")
        for p, side, other, w in (("x", "user_id", "z", "(SELECT count(DISTINCT item_id) FROM t)"), ("z", "item_id", "x", "(SELECT count(DISTINCT user_id) FROM t)")):
            g = f"SELECT {side}, sum(-2.0 * (1.0::DOUBLE / {w}) * e * {other}0) AS g0, sum(-2.0 * (1.0::DOUBLE / {w}) * e * {other}1) AS g1 FROM ({RES.format(a=t - 1, b=t - 1)}) GROUP BY 1"
            new = ", ".join(f"f.{p}{k} - (SELECT gamma FROM k_{t}) * (coalesce(g.g{k}, 0) + {2e-4!r}::DOUBLE * f.{p}{k}) AS {p}{k}" for k in range(2))
            out.append(f"{p}_{t} AS MATERIALIZED (SELECT f.{side}, {new} FROM {p}_{t - 1} f LEFT JOIN ({g}) g USING ({side}))")
        loss = f"(SELECT avg(e * e) FROM ({RES.format(a=t, b=t)})) + 1e-4 * (SELECT sum(x0 * x0 + x1 * x1) FROM x_{t}) + 1e-4 * (SELECT sum(z0 * z0 + z1 * z1) FROM z_{t})"
        out.append(f"s_{t} AS MATERIALIZED (SELECT {t} AS round, {loss} AS loss, gamma FROM k_{t})")
    return ",\n".join(out) + " " + " UNION ALL ".join(f"SELECT round::INT AS round, round(loss, 6) AS loss, round(gamma, 6) AS gamma FROM s_{t}" for t in range(1, rounds + 1))


def blocks(rounds: int, n: int) -> str:
    """Stratified rounds: one diagonal of user and item blocks after the other, a step after each."""
    out, k = [START], 0
    wu, wz = "(SELECT count(DISTINCT item_id) FROM t)", "(SELECT count(DISTINCT user_id) FROM t)"
    for _ in range(rounds):
        for b in range(n):
            part = f"SELECT * FROM ({RES.format(a=k, b=k)}) WHERE ({bits('block', 'user_id')}) % {n} = (({bits('block', 'item_id')}) + {b}) % {n}"
            gx = f"SELECT user_id, sum(-2.0 * (1.0::DOUBLE / {wu}) * e * z0) AS g0, sum(-2.0 * (1.0::DOUBLE / {wu}) * e * z1) AS g1 FROM ({part}) GROUP BY 1"
            gz = f"SELECT item_id, sum(-2.0 * (1.0::DOUBLE / {wz}) * e * x0) AS g0, sum(-2.0 * (1.0::DOUBLE / {wz}) * e * x1) AS g1 FROM ({part}) GROUP BY 1"
            k += 1
            out += [stepped("x", "user_id", k, gx, 0.5, 1e-4, None), stepped("z", "item_id", k, gz, 0.5, 1e-4, None)]
    return ",\n".join(out) + z_of(k)


def folded(z: str, lam: float) -> str:
    """Ridge solutions of the two by two systems by determinants."""
    sums = f"SELECT user_id, sum(z0 * z0) + {lam!r}::DOUBLE * count(*) AS a, sum(z0 * z1) AS b, sum(z1 * z1) + {lam!r}::DOUBLE * count(*) AS c, sum(rating * z0) AS p, sum(rating * z1) AS q FROM t JOIN {z} USING (item_id) GROUP BY 1"
    return f"SELECT user_id, round((c * p - b * q) / (a * c - b * b), 6) AS x0, round((a * q - b * p) / (a * c - b * b), 6) AS x1 FROM ({sums})"


def descended(z: str, lam: float, gamma: float, rounds: int) -> str:
    q = f"SELECT user_id, count(*)::DOUBLE AS n, sum(z0 * z0) AS a, sum(z0 * z1) AS b, sum(z1 * z1) AS c, sum(rating * z0) AS p, sum(rating * z1) AS q, 0.0::DOUBLE AS x0, 0.0::DOUBLE AS x1 FROM t JOIN {z} USING (item_id) GROUP BY 1"
    for _ in range(rounds):
        q = f"SELECT user_id, n, a, b, c, p, q, x0 - {gamma!r}::DOUBLE * (-2 * (p - a * x0 - b * x1) / n + {2 * lam!r}::DOUBLE * x0) AS x0, x1 - {gamma!r}::DOUBLE * (-2 * (q - b * x0 - c * x1) / n + {2 * lam!r}::DOUBLE * x1) AS x1 FROM ({q})"
    return f"SELECT user_id, {r('x0')}, {r('x1')} FROM ({q})"


def shares(rounds: int = 12, lam: float = 0.1) -> str:
    """New users who give a share of their ratings: a plain fit of the others, then three by three systems."""
    known = f"rest AS MATERIALIZED (SELECT 0 AS run, user_id, item_id, rating FROM planted WHERE NOT {TEST}), new AS MATERIALIZED (SELECT *, {u('mask', 'user_id', 'item_id')} AS draw FROM planted WHERE {TEST})"
    fit = fit_of("s_", "rest", rounds, 3).replace("least(1.0::DOUBLE, 2.0::DOUBLE / greatest(", "least(1.0::DOUBLE, 1e300::DOUBLE / greatest(")
    out = []
    for share in (0.1, 0.3, 0.5, 0.7, 0.9):
        pair = lambda i, j: f"sum(z{i} * z{j})" + (f" + {lam!r}::DOUBLE * count(*)" if i == j else "")
        sums = f"SELECT user_id, {', '.join(f'{pair(i, j)} AS a{i}{j}' for i in range(3) for j in range(3))}, {', '.join(f'sum(rating * z{i}) AS b{i}' for i in range(3))} FROM new JOIN s_z_{rounds} USING (item_id) WHERE NOT (draw < {1 - share!r}::DOUBLE) GROUP BY 1"
        det = lambda m: f"({m[0][0]} * ({m[1][1]} * {m[2][2]} - {m[1][2]} * {m[2][1]}) - {m[0][1]} * ({m[1][0]} * {m[2][2]} - {m[1][2]} * {m[2][0]}) + {m[0][2]} * ({m[1][0]} * {m[2][1]} - {m[1][1]} * {m[2][0]}))"
        a = [[f"a{i}{j}" for j in range(3)] for i in range(3)]
        swapped = [[[f"b{i}" if j == k else a[i][j] for j in range(3)] for i in range(3)] for k in range(3)]
        x = f"SELECT user_id, {', '.join(f'{det(swapped[k])} / {det(a)} AS x{k}' for k in range(3))} FROM ({sums})"
        out.append(f"SELECT {share!r}::DOUBLE AS known_share, round(avg((coalesce((x0 * z0 + x1 * z1 + x2 * z2 > 0.5)::INT, 0) = truth)::INT), 6) AS reconstruction FROM new LEFT JOIN ({x}) USING (user_id) LEFT JOIN s_z_{rounds} USING (item_id) WHERE draw < {1 - share!r}::DOUBLE")
    return f"WITH {T}, {PLANTED}, {known}, {fit} " + " UNION ALL ".join(out)


def smoothed() -> str:
    """Nations' scores drawn to their regions, and the measures."""
    key = item("area", "(month(ts) - 1) // 12")
    score = " + ".join(f"{gauss('planted_x', 'user_id', str(k))} * {gauss('planted_z', 'item_id', str(k))}" for k in range(3))
    planted = f"SELECT user_id, area, item_id, truth, (CASE WHEN {u('flip', 'user_id', 'item_id')} < 0.05 THEN 1 - truth ELSE truth END)::DOUBLE AS rating, ({TEST} AND {u('mask', 'user_id', 'item_id')} < 0.3)::INT AS held FROM (SELECT *, (({score}) + 0.3 > 0)::INT AS truth FROM (SELECT DISTINCT user_id, area, {key} AS item_id FROM ({ORD})))"
    near = "SELECT a.n_name AS loc, b.n_name AS near FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_name <> b.n_name"
    own = "SELECT user_id, area AS loc, truth, held, CASE WHEN held = 0 THEN rating ELSE coalesce(avg(rating) FILTER (held = 0) OVER (PARTITION BY user_id), 0.5) END AS score FROM p"
    others = "SELECT o.user_id, n.loc, avg(o.score) AS other FROM o JOIN n ON n.near = o.loc GROUP BY 1, 2"
    shown = "SELECT alpha, truth, held, (round((1 - alpha) * score + alpha * coalesce(other, score), 9) > 0.5)::INT AS decision FROM o LEFT JOIN r USING (user_id, loc), (SELECT unnest([0.0, 0.3, 0.6]::DOUBLE[]) AS alpha)"
    return f"WITH p AS MATERIALIZED ({planted}), n AS ({near}), o AS MATERIALIZED ({own}), r AS ({others}), s AS ({shown}) SELECT alpha, round(count(*) FILTER (truth = 0 AND decision = 1) / count(*) FILTER (truth = 0), 6) AS fpr, round(count(*) FILTER (truth = 1 AND decision = 1) / count(*) FILTER (truth = 1), 6) AS recall, round(count(*) FILTER (held = 1 AND truth = decision) / count(*) FILTER (held = 1), 6) AS reconstruction FROM s GROUP BY 1"


def leaked(slots: int = 4, steps: int = 6, eps: float = 0.5) -> str:
    """Leakage by all subsets of columns for all pairs of rows of the transition matrix."""
    m = f"SELECT a.i, a.j, coalesce(p, 0) AS p FROM (SELECT i, j FROM (SELECT unnest(range({slots})) AS i), (SELECT unnest(range({slots})) AS j)) a LEFT JOIN (SELECT slot AS i, next_slot AS j, count(*) / sum(count(*)) OVER (PARTITION BY slot) AS p FROM (SELECT (hour(ts) // {24 // slots})::INT AS slot, lead((hour(ts) // {24 // slots})::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_slot FROM events) WHERE next_slot IS NOT NULL GROUP BY 1, 2) b ON a.i = b.i AND a.j = b.j"
    sets = f"SELECT x.i AS a, y.i AS b, s, sum(x.p) AS q, sum(y.p) AS d FROM m x JOIN m y ON x.j = y.j, (SELECT unnest(range({2**slots})) AS s) WHERE (s >> x.j) & 1 = 1 GROUP BY 1, 2, 3"
    out = [f"WITH m AS MATERIALIZED ({m})", f"sets AS MATERIALIZED ({sets})", f"l_1 AS MATERIALIZED (SELECT {eps!r}::DOUBLE AS v)"]
    for t in range(2, steps + 1):
        e = f"(exp((SELECT v FROM l_{t - 1})) - 1)"
        out.append(f"l_{t} AS MATERIALIZED (SELECT {eps!r}::DOUBLE + greatest(0, max(ln((q * {e} + 1) / (d * {e} + 1)))) AS v FROM sets)")
    return ",\n".join(out) + " " + " UNION ALL ".join(f"SELECT {t}::INT AS step, round(v, 6) AS leakage, {eps * t!r}::DOUBLE AS worst FROM l_{t}" for t in range(1, steps + 1))


def similar(side: str, sim: str) -> str:
    other = "item_id" if side == "user_id" else "user_id"
    base = f"SELECT {side}, {other}, rating FROM t" if sim != "pearson" else f"SELECT {side}, {other}, rating - avg(rating) OVER (PARTITION BY {side}) AS rating FROM t"
    s = "ab / nullif(aa + bb - ab, 0)" if sim == "jaccard" else "ab / nullif(sqrt(aa) * sqrt(bb), 0)"
    return f"""WITH {T}, base AS MATERIALIZED ({base}), sims AS (
  SELECT a, b, {s} AS s FROM (SELECT l.{side} AS a, r.{side} AS b, count(*) AS c, sum(l.rating * r.rating) AS ab, sum(l.rating * l.rating) AS aa, sum(r.rating * r.rating) AS bb FROM base l JOIN base r USING ({other}) WHERE l.{side} <> r.{side} GROUP BY 1, 2) WHERE c >= 2
), top AS (SELECT * FROM sims WHERE s IS NOT NULL QUALIFY row_number() OVER (PARTITION BY a ORDER BY round(s, 9) DESC, b) <= 5),
votes AS (SELECT c.user_id, c.item_id, sum(s * v.rating) / nullif(sum(abs(s)), 0) AS score FROM t c JOIN top ON top.a = c.{side} JOIN t v ON v.{side} = top.b AND v.{other} = c.{other} GROUP BY 1, 2)
SELECT user_id, item_id, round(score, 6) AS score FROM (SELECT user_id, item_id FROM t) LEFT JOIN votes USING (user_id, item_id)"""


def oracle_sql() -> dict[str, str]:
    part = "[" + ", ".join(f"'{x}'" for x in DAY_PARTS) + "][((hour(ts) + 18) % 24) // 4 + 1]"
    kind = "CASE WHEN isodow(ts) < 6 THEN 'Weekday' ELSE 'Weekend' END"
    loc = {"category": ("category", EV), "category_place": ("category || ':' || place", EV), "area": ("area", ORD), "category_area": ("category || ':' || area", ORD), "place": ("place::VARCHAR", ORD)}
    rules = {"majority": "(avg(label) > 0.5)::INT::DOUBLE", "most_private": "min(label)::DOUBLE", "most_open": "max(label)::DOUBLE", "latest": "arg_max(label, strftime(ts, '%Y%m%d%H%M%S%f') || lpad(event_id::VARCHAR, 12, '0'))::DOUBLE"}
    p1 = flip_probability(1.0)
    y = f"SELECT a.user_id, b.item_id, (t.rating IS NOT NULL)::INT AS y FROM (SELECT DISTINCT user_id FROM t) a CROSS JOIN (SELECT DISTINCT item_id FROM t) b LEFT JOIN t ON t.user_id = a.user_id AND t.item_id = b.item_id"
    bit = lambda p, *key: f"CASE WHEN {u('bit_flip', *key)} < {p} THEN ({u('bit_coin', *key)} < 0.5)::INT ELSE y END"
    pr, scale = PRIVATE.mechanism(1)
    out = {f"slots_w{w}": f"SELECT {STATS} FROM ({cells(key=item(slot=f'hour(ts) // {w}'))})" for w in (2, 3, 4, 6, 8, 12)}
    out |= {
        "day_part_counts": f"SELECT {part} AS part, count(*) AS n FROM events GROUP BY 1",
        "day_kind_counts": f"SELECT {kind} AS kind, dayname(ts) AS name, count(*) AS n FROM events GROUP BY 1, 2",
        "composite_time_keys": f"SELECT concat_ws(':', month(ts), {kind}, {part}) AS key, count(*) AS n FROM events GROUP BY 1",
        "calendar_slots": "SELECT strftime(time_bucket(INTERVAL 6 HOURS, ts), '%Y-%m-%d %H:%M') AS slot_start, count(*) AS n FROM events GROUP BY 1",
        "month_slots": "SELECT ((month(o_orderdate) - 1) // 3)::INT AS slot, count(*) AS n, count(DISTINCT o_custkey) AS users FROM orders GROUP BY 1",
        "location_ladder": f"SELECT region, area, grouping(region, area)::BIGINT AS level, count(*) AS visits, sum(label)::BIGINT AS open FROM ({ORD}) GROUP BY ROLLUP (region, area)",
        "prefs_supported": f"SELECT * FROM ({cells()}) WHERE visits >= 3",
        "matrix_stats_events": f"SELECT {STATS} FROM ({cells(key=item('category || chr(58) || place'))})",
        "matrix_stats_lineitem": f"SELECT {STATS} FROM ({cells(key=item('area', '(month(ts) - 1) // 6'), source=ORD)})",
        "degree_quantiles": f"WITH {T} SELECT quantile_cont(d, 0.1) AS q10, quantile_cont(d, 0.5) AS q50, quantile_cont(d, 0.9) AS q90 FROM (SELECT count(*)::DOUBLE AS d FROM t GROUP BY user_id)",
        "survey_rates": f"WITH {SURVEY} SELECT category, slot, round(avg(answer), 6) AS rate, count(*) AS answers FROM survey GROUP BY 1, 2",
        "archetypes_cosine": f"""WITH {SURVEY}, own AS (SELECT user_id, category, count(*)::DOUBLE AS n FROM visits GROUP BY 1, 2), theirs AS (SELECT respondent, category, count(*)::DOUBLE AS m FROM survey GROUP BY 1, 2),
d AS (SELECT user_id, respondent, sum(n * m) AS dot FROM own JOIN theirs USING (category) GROUP BY 1, 2), l AS (SELECT respondent, sqrt(sum(m * m)) AS l FROM theirs GROUP BY 1),
best AS (SELECT user_id, respondent FROM d JOIN l USING (respondent) QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY round(dot / l, 9) DESC, respondent DESC) = 1)
SELECT respondent, count(*) AS users FROM best GROUP BY 1""",
        "user_folds": f"SELECT user_id, (({bits('fold', 'user_id')}) % 10)::INT AS fold FROM (SELECT DISTINCT user_id FROM events)",
        "user_folds_exact": f"SELECT fold, count(*) AS users FROM (SELECT (ntile(10) OVER (ORDER BY {bits('fold', 'user_id')}, user_id) - 1)::INT AS fold FROM (SELECT DISTINCT user_id FROM events)) GROUP BY 1",
        "init_factors": f"{START} SELECT user_id, {r('x0')}, {r('x1')} FROM x_0",
        "score_cells": f"{START} SELECT user_id, item_id, rating, round(rating - e, 6) AS score FROM ({RES.format(a=0, b=0)})",
        "loss_initial": f"{START} SELECT round((SELECT avg(e * e) FROM ({RES.format(a=0, b=0)})) + 1e-4 * (SELECT sum(x0 * x0 + x1 * x1) FROM x_0) + 1e-4 * (SELECT sum(z0 * z0 + z1 * z1) FROM z_0), 6) AS loss",
        "loss_dense": f"{START} SELECT round(sum(y * (coalesce(rating, 0) - s) * (coalesce(rating, 0) - s)) / sum(y), 6) AS dense, (SELECT round(avg(e * e), 6) FROM ({RES.format(a=0, b=0)})) AS sparse FROM (SELECT g.*, t.rating, (t.rating IS NOT NULL)::INT AS y FROM (SELECT user_id, item_id, x0 * z0 + x1 * z1 AS s FROM x_0, z_0) g LEFT JOIN t USING (user_id, item_id))",
        "user_gradient": f"{START} SELECT user_id, round(sum(-2.0 * e * z0), 6) AS g0, round(sum(-2.0 * e * z1), 6) AS g1 FROM ({RES.format(a=0, b=0)}) GROUP BY 1",
        "item_gradient": f"{START} SELECT item_id, round(sum(-2.0 * e * x0), 6) AS g0, round(sum(-2.0 * e * x1), 6) AS g1 FROM ({RES.format(a=0, b=0)}) GROUP BY 1",
        "fit_plain_k1": plain(1) + z_of(1),
        "fit_plain_k3": plain(3) + z_of(3),
        "fit_plain_alternate": plain(3, order="alternate") + z_of(3),
        "fit_plain_by_users": plain(3, "users") + z_of(3),
        "fit_plain_inverse_step": plain(3, gammas=[0.5, 0.25, 0.5 / 3]) + z_of(3),
        "fit_plain_projected": plain(3, radius=0.5) + z_of(3),
        "protocol_round": plain(1) + z_of(1),
        "mean_threshold": f"{START} SELECT round((SELECT avg(x0) FROM x_0) * (SELECT avg(z0) FROM z_0) + (SELECT avg(x1) FROM x_0) * (SELECT avg(z1) FROM z_0), 6) AS threshold",
        "mean_threshold_observed": f"{START} SELECT round(avg(rating - e), 6) AS threshold FROM ({RES.format(a=0, b=0)})",
        "mean_threshold_per_user": f"{START} SELECT user_id, round(x0 * (SELECT avg(z0) FROM z_0) + x1 * (SELECT avg(z1) FROM z_0), 6) AS threshold FROM x_0",
        "mean_threshold_grid": f"{START} SELECT round(avg(x0 * z0 + x1 * z1), 6) AS threshold FROM x_0, z_0",
        "unknown_cells": f"WITH {T} SELECT user_id, item_id FROM ({y}) WHERE y = 0",
        "recommend": plain(3) + f", g AS (SELECT c.user_id, c.item_id, x0 * z0 + x1 * z1 AS s FROM ({y}) c JOIN x_3 USING (user_id) JOIN z_3 USING (item_id) WHERE y = 0) SELECT user_id, item_id, round(s, 6) AS score, (s > (SELECT avg(x0 * z0 + x1 * z1) FROM x_3, z_3))::INT AS decision FROM g",
        "top_k": plain(3) + f" SELECT user_id, item_id, row_number() OVER (PARTITION BY user_id ORDER BY score DESC, item_id)::INT AS rank, score FROM (SELECT c.user_id, c.item_id, round(x0 * z0 + x1 * z1, 6) AS score FROM ({y}) c JOIN x_3 USING (user_id) JOIN z_3 USING (item_id) WHERE y = 0) QUALIFY rank <= 3",
        "flip_probability_grid": f"SELECT eps, round(2.0 / (1.0 + exp(eps)), 9) AS p, users FROM ({LEVELS})",
        "noisy_bits_fresh": f"WITH {T} SELECT user_id, item_id, y, {bit(repr(p1), 'user_id', 'item_id', '1')} AS ybit FROM ({y})",
        "noisy_bits_permanent": f"WITH {T} SELECT user_id, item_id, y, {bit(repr(p1), 'user_id', 'item_id')} AS ybit FROM ({y})",
        "visit_estimates": f"WITH {T} SELECT item_id, round(avg((b - {p1 / 2!r}::DOUBLE) / {1 - p1!r}::DOUBLE), 6) AS estimate, round(avg(y), 6) AS truth FROM (SELECT *, {bit(repr(p1), 'user_id', 'item_id', '1')} AS b FROM ({y})) GROUP BY 1",
        "bits_by_user": f"WITH {T}, c AS (SELECT y.*, 2.0::DOUBLE / (1.0 + exp(1.0::DOUBLE + length(c_mktsegment) / 10::DOUBLE)) AS p FROM ({y}) y JOIN customer ON c_custkey = user_id) SELECT item_id, round(avg(({bit('p', 'user_id', 'item_id', '1')} - p / 2) / (1 - p)), 6) AS estimate, count(*) AS n FROM c GROUP BY 1",
        "laplace_noise": f"SELECT event_id, round({lap(u('lap', 'event_id'), 2.0)}, 6) AS noise FROM events",
        "client_reports": f"{START} SELECT user_id, item_id, ybit, {r('g0')}, {r('g1')} FROM ({reports(1, pr, scale)})",
        "aggregated_gradient_affine": f"{START} SELECT item_id, {r('g0')}, {r('g1')} FROM ({mean_report(reports(1, pr, scale), pr)})",
        "aggregated_gradient_product": f"{START} SELECT item_id, {r('g0')}, {r('g1')} FROM ({mean_report(reports(1, pr, scale, True), pr, True)})",
        "fit_private_k1": private(1) + z_of(1),
        "fit_private_k2": private(2) + z_of(2),
        "fit_private_product": private(2, True) + z_of(2),
        "fit_private_server_side": private(1, server=True) + z_of(1),
        "fit_private_sampled": private(1, sample=5) + z_of(1),
        "budget_ledger": "SELECT c_custkey AS user_id, round_ AS round, mechanism, 0.125::DOUBLE AS eps_spent, 0.125::DOUBLE * (2 * (round_ - 1) + k) AS eps_total FROM customer, (SELECT unnest(range(1, 5))::INT AS round_), (VALUES ('bit', 1), ('gradient', 2)) m(mechanism, k)",
        "privacy_audit": f"SELECT eps, round(max((2 - p) / p / exp(eps)), 6) AS bit_ratio, round(max(exp((abs(o + 1) - abs(o - 1)) / (2 / eps)) / exp(eps)), 6) AS laplace_ratio FROM (SELECT eps, 2.0::DOUBLE / (1.0 + exp(eps)) AS p FROM ({LEVELS}) WHERE eps > 0), (SELECT unnest(range(-40, 41)) / 10 AS o) GROUP BY 1",
        "cf_user": similar("user_id", "cosine"), "cf_item": similar("item_id", "cosine"), "cf_user_pearson": similar("user_id", "pearson"), "cf_item_jaccard": similar("item_id", "jaccard"),
        "majority_global": f"WITH {T} SELECT user_id, item_id, round(avg(rating) OVER (), 6) AS score FROM t",
        "majority_item": f"WITH {T} SELECT user_id, item_id, round(avg(rating) OVER (PARTITION BY item_id), 6) AS score FROM t",
        "majority_user": f"WITH {T} SELECT user_id, item_id, round(avg(rating) OVER (PARTITION BY user_id), 6) AS score FROM t",
        "majority_bias": f"WITH {T} SELECT user_id, item_id, round(avg(rating) OVER (PARTITION BY user_id) + avg(rating) OVER (PARTITION BY item_id) - avg(rating) OVER (), 6) AS score FROM t",
        "constant_hide": f"WITH {T}, {PLANTED} SELECT 0::BIGINT AS tp, 0::BIGINT AS fp, count(*) FILTER (truth = 0) AS tn, count(*) FILTER (truth = 1) AS fn, 0.0::DOUBLE AS fpr, 0.0::DOUBLE AS recall FROM planted",
        "constant_publish": f"WITH {T}, {PLANTED} SELECT count(*) FILTER (truth = 1) AS tp, count(*) FILTER (truth = 0) AS fp, 0::BIGINT AS tn, 0::BIGINT AS fn, 1.0::DOUBLE AS fpr, 1.0::DOUBLE AS recall FROM planted",
        "coin": f"WITH {T}, {PLANTED} SELECT {COUNTS} FROM (SELECT *, ({u('coin', 'user_id', 'item_id')} < 0.5)::INT AS decision FROM planted)",
        "k_anonymous": f"SELECT {item('place')} AS item, count(*) AS n, count(DISTINCT user_id) AS users FROM ({EV}) GROUP BY 1 HAVING count(DISTINCT user_id) >= 20",
        "coarsened": f"SELECT level, count(*) AS n, count(DISTINCT CASE level WHEN 0 THEN place::VARCHAR WHEN 1 THEN area ELSE region END) AS shown FROM (SELECT o.*, CASE c_mktsegment WHEN 'BUILDING' THEN 0 WHEN 'MACHINERY' THEN 1 ELSE 2 END AS level FROM ({ORD}) o JOIN customer ON c_custkey = user_id) GROUP BY 1",
        "planted_triples": f"WITH {T}, {PLANTED} SELECT * FROM planted",
        "confusion": f"{SCORED} SELECT {COUNTS} FROM scored",
        "fpr_recall": f"{SCORED}, c AS (SELECT {COUNTS} FROM scored) SELECT *, round(fp / (fp + tn), 6) AS fpr, round(tp / (tp + fn), 6) AS recall, round((tp + tn) / (tp + fp + tn + fn), 6) AS reconstruction, round(tp / (tp + fp), 6) AS precision, round(2 * tp / (2 * tp + fp + fn), 6) AS f1, round((tp / (tp + fn) + tn / (tn + fp)) / 2, 6) AS balanced FROM c",
        "reconstruction": f"{SCORED}, c AS (SELECT {COUNTS} FROM scored WHERE held = 1) SELECT *, round((tp + tn) / (tp + fp + tn + fn), 6) AS reconstruction FROM c",
        "rmse": f"{SCORED} SELECT round(sqrt(avg((rating - score) * (rating - score))), 6) AS rmse, round(avg(abs(rating - score)), 6) AS mae FROM scored",
        "metrics_cube": f"{SCORED}, k AS (SELECT *, split_part(item_id, '@', 2) AS slot FROM scored) SELECT slot, held, grouping(slot, held)::BIGINT AS level, count(*) AS n, count(*) FILTER (decision = truth) AS right FROM k GROUP BY CUBE (slot, held)",
        "traffic": f"WITH {T}, s AS (SELECT count(DISTINCT user_id)::BIGINT AS n, count(DISTINCT item_id)::BIGINT AS m, count(*)::BIGINT AS k FROM t) SELECT protocol, down AS bytes_down, up AS bytes_up, (down + up) * 50 AS bytes_total FROM s, LATERAL (VALUES ('plain', 64 * (n + m), 80 * k), ('private', 64 * m * n, 65 * n * m), ('sampled_10', 64 * m * n, 65 * n * least(10, m))) x(protocol, down, up)",
        "asof_preference": f"WITH v AS ({EV}), a AS (SELECT event_id, last_value(CASE WHEN event_id % 2 = 0 THEN label END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS stated FROM v) SELECT * FROM a WHERE event_id % 2 = 1",
        "colocation_interval": f"WITH v AS (SELECT user_id, place, floor(epoch(ts)) AS t FROM ({EV})) SELECT a.user_id, count(*) AS met FROM v a JOIN v b ON a.place = b.place AND a.user_id <> b.user_id AND abs(a.t - b.t) <= 7200 GROUP BY 1",
        "visit_gaps": "SELECT user_id, max(g)::BIGINT AS longest, min(g)::BIGINT AS shortest FROM (SELECT user_id, floor(epoch(ts)) - floor(epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))) AS g FROM events) GROUP BY 1",
        "rolling_24h": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, floor(epoch(ts))::BIGINT AS t FROM events)",
        "range_bracket": "SELECT bracket, eps, count(*) AS users FROM customer JOIN (VALUES ('low', -1e9, 0.0, 10.0::DOUBLE), ('mid', 0.0, 5000.0, 1.0::DOUBLE), ('high', 5000.0, 1e9, 0.1::DOUBLE)) b(bracket, lo, hi, eps) ON c_acctbal >= lo AND c_acctbal < hi GROUP BY 1, 2",
        "host_places": r"SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, count(*) AS n, count(DISTINCT page_id) AS pages FROM pages GROUP BY 1",
        "role_slot_matrix": "SELECT role, (turn % 4)::INT AS slot, count(*) AS n, count(DISTINCT conv_id) AS users FROM conversations GROUP BY 1, 2",
        "sensitive_bit_estimate": f"SELECT round(avg((b - {flip_probability(2.0) / 2!r}::DOUBLE) / {1 - flip_probability(2.0)!r}::DOUBLE), 6) AS estimate, round(avg(toxic), 6) AS truth FROM (SELECT toxic, CASE WHEN {u('rr_a', 'doc_id')} < {flip_probability(2.0)!r}::DOUBLE THEN ({u('rr_b', 'doc_id')} < 0.5)::INT ELSE toxic END AS b FROM labels)",
        "embedding_topk": "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank, vec_id, score FROM (SELECT q.vec_id AS query_id, v.vec_id, round(list_inner_product(q.embedding::DOUBLE[], v.embedding::DOUBLE[]), 6) AS score FROM embeddings q JOIN embeddings v ON q.vec_id <> v.vec_id WHERE q.vec_id % 50 = 0) QUALIFY rank <= 5",
        "embedding_class_means": "SELECT label, k::INT AS k, round(avg(x), 6) AS mean FROM (SELECT label, unnest(range(len(embedding))) AS k, unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY 1, 2",
        "neighbour_smoothing": f"WITH s AS (SELECT user_id, area AS loc, avg(label) AS score FROM ({ORD}) GROUP BY 1, 2), n AS (SELECT a.n_name AS loc, b.n_name AS near FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_name <> b.n_name), o AS (SELECT s.user_id, n.loc, avg(score) AS other FROM s JOIN n ON n.near = s.loc GROUP BY 1, 2) SELECT loc, round(avg(0.7 * score + 0.3 * coalesce(other, score)), 6) AS score, count(*) AS n FROM s LEFT JOIN o USING (user_id, loc) GROUP BY 1",
        "slot_transitions": "WITH e AS (SELECT (hour(ts) // 6)::INT AS slot, lead((hour(ts) // 6)::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_slot FROM events) SELECT slot, next_slot, round(count(*) / sum(count(*)) OVER (PARTITION BY slot), 6) AS p FROM e WHERE next_slot IS NOT NULL GROUP BY 1, 2",
        "stream_slot_counts": "SELECT strftime(time_bucket(INTERVAL 6 HOURS, ts), '%Y-%m-%d %H:%M') AS slot_start, event_type, count(*) AS n FROM events GROUP BY 1, 2, time_bucket(INTERVAL 6 HOURS, ts) HAVING time_bucket(INTERVAL 6 HOURS, ts) + INTERVAL 6 HOURS <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)",
        "stream_gate": plain(3) + f", g AS (SELECT c.user_id, c.item_id, (x0 * z0 + x1 * z1 > (SELECT avg(x0 * z0 + x1 * z1) FROM x_3, z_3))::INT AS decision FROM ({y}) c JOIN x_3 USING (user_id) JOIN z_3 USING (item_id) WHERE y = 0 UNION ALL SELECT user_id, item_id, rating::INT FROM t) SELECT event_type, count(*) FILTER (coalesce(decision, 0) = 1) AS released, count(*) FILTER (coalesce(decision, 0) <> 1) AS hidden FROM events LEFT JOIN g ON g.user_id = events.user_id AND g.item_id = event_type || '@' || (hour(ts) // 6)::VARCHAR GROUP BY 1",
        "stream_sessions": """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 24 HOURS THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e), w AS (SELECT user_id, k, count(*) AS n, max(ts) + INTERVAL 24 HOURS AS e FROM s GROUP BY 1, 2)
SELECT user_id, count(*) AS sessions, sum(n)::BIGINT AS events FROM w WHERE e <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY 1""",
    }
    draw20 = f"CASE WHEN {u('bit_flip', 'user_id', 'item_id', 'r')} < {p1!r}::DOUBLE THEN ({u('bit_coin', 'user_id', 'item_id', 'r')} < 0.5)::INT ELSE y END"
    out |= {
        "masked_exact": f"WITH {T} SELECT *, ({TEST} AND percent_rank() OVER (PARTITION BY user_id ORDER BY {u('mask', 'user_id', 'item_id')}, item_id) < 0.3)::INT AS held FROM t",
        "estimator_errors": f"WITH {T}, e AS (SELECT item_id, r, avg(({draw20} - {p1 / 2!r}::DOUBLE) / {1 - p1!r}::DOUBLE) AS estimate, avg(y) AS truth FROM ({y}), (SELECT unnest(range(1, 21)) AS r) GROUP BY 1, 2) SELECT item_id, round(avg(estimate) - avg(truth), 6) AS bias, round(var_samp(estimate), 6) AS variance, count(*) AS n FROM e GROUP BY 1",
        "survey_of_users": f"SELECT CASE WHEN {u('survey', 'user_id')} < 0.13 THEN 'survey' ELSE 'trajectory' END AS kind, count(DISTINCT user_id) AS users, count(*) AS records, count(DISTINCT place) AS places FROM ({EV}) GROUP BY 1",
        "compare_models": plain(3) + f" SELECT item_id, {r('a.z0', 'a0')}, {r('a.z1', 'a1')}, {r('b.z0', 'z0')}, {r('b.z1', 'z1')} FROM z_1 a FULL JOIN z_3 b USING (item_id)",
        "silent_customers": "SELECT c_mktsegment, count(*) AS n FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT') GROUP BY 1",
        "folds_and_rest": f"WITH {T} SELECT * FROM (VALUES ('common', 0::BIGINT), ('missing', 0::BIGINT)) v(part, n) UNION ALL SELECT 'all', count(*) FROM t",
        "measures_long": f"{SCORED}, c AS (SELECT {COUNTS} FROM scored), w AS (SELECT round(fp / (fp + tn), 6) AS fpr, round(tp / (tp + fn), 6) AS recall, round((tp + tn) / (tp + fp + tn + fn), 6) AS reconstruction FROM c) UNPIVOT w ON fpr, recall, reconstruction INTO NAME measure VALUE value",
        "grouped_sets": f"{SCORED}, k AS (SELECT *, split_part(item_id, '@', 2) AS slot FROM scored) SELECT slot, held, count(*) AS n, round(avg(decision), 6) AS share FROM k GROUP BY GROUPING SETS ((slot), (held), ())",
        "lateral_top": f"SELECT user_id, place, count(*) AS n FROM ({EV}) GROUP BY 1, 2 QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, place) <= 2",
        "mean_vector_udaf": "SELECT label, k::INT AS k, round(avg(x), 6) AS mean FROM (SELECT label, unnest(range(len(embedding))) AS k, unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY 1, 2",
        "time_ladder": "SELECT w::INT AS width, (hour(ts) // w)::INT AS slot, count(*) AS n FROM events, (SELECT unnest([1, 2, 3, 4, 6, 8, 12, 24]) AS w) GROUP BY 1, 2",
        "observed_loss": f"{START} SELECT round(avg(e * e), 6) AS data, count(*) AS rows FROM ({RES.format(a=0, b=0)})",
        "budgeted_stream": "SELECT user_id, least(10, count(*))::BIGINT AS accepted, (count(*) - least(10, count(*)))::BIGINT AS refused FROM events GROUP BY 1",
    }
    seg = f"SELECT c_custkey AS user_id, 2.0::DOUBLE / (1.0 + exp((1.0::DOUBLE + length(c_mktsegment) / 10::DOUBLE) * {PRIVATE.bit_share!r}::DOUBLE)) AS p, {2 * PRIVATE.clip!r}::DOUBLE / ((1.0::DOUBLE + length(c_mktsegment) / 10::DOUBLE) * {1 - PRIVATE.bit_share!r}::DOUBLE) AS scale FROM customer"
    size = lambda f, p, side: f"SELECT '{side}' AS side, round(min(v), 6) AS least, round(avg(v), 6) AS mean, round(max(v), 6) AS most, count(*) AS n FROM (SELECT sqrt({p}0 * {p}0 + {p}1 * {p}1) AS v FROM {f})"
    one = f"one AS MATERIALIZED (SELECT 0 AS run, user_id, item_id, rating FROM t)"
    mech = f"SELECT 0 AS run, {pr!r}::DOUBLE AS p, {scale!r}::DOUBLE AS scale"
    spent = "SELECT policy, permanent, share AS user_share, 1.0::DOUBLE AS eps_total, (CASE WHEN share > 0 THEN 3 ELSE 2 END)::BIGINT AS releases, (SELECT count(DISTINCT c_custkey) FROM customer) AS users FROM (VALUES ('per_item'), ('per_user')) a(policy), (VALUES (false), (true)) b(permanent), (VALUES (0.0::DOUBLE), (0.25::DOUBLE)) c(share)"
    slide = "SELECT s AS st FROM (SELECT DISTINCT time_bucket(INTERVAL 3 HOURS, ts) - INTERVAL 3 HOURS * k AS s FROM events, (SELECT unnest([0, 1]) AS k))"
    out |= {
        "budget_ledger_server": "SELECT c_custkey AS user_id, round_ AS round, mechanism, x AS eps_spent, round(0.25::DOUBLE * (round_ - 1) + y, 6) AS eps_total FROM customer, (SELECT unnest(range(1, 5))::INT AS round_), (VALUES ('bit', 0.09375::DOUBLE, 0.09375::DOUBLE), ('gradient', 0.09375::DOUBLE, 0.1875::DOUBLE), ('user_gradient', 0.0625::DOUBLE, 0.25::DOUBLE)) m(mechanism, x, y)".replace("x AS eps_spent", "round(x, 6) AS eps_spent"),
        "ledger_totals": spent,
        "private_round": START + f", g AS ({mean_report(reports(1, pr, scale), pr)}) SELECT item_id, {', '.join(f'round(n{k} * least(1.0::DOUBLE, 2.0::DOUBLE / greatest(sqrt(n0 * n0 + n1 * n1), 1e-300::DOUBLE)), 6) AS z{k}' for k in range(2))} FROM (SELECT item_id, {', '.join(f'z{k} - 0.5::DOUBLE * (g{k} + 0.0002::DOUBLE * z{k}) AS n{k}' for k in range(2))} FROM z_0 JOIN g USING (item_id))",
        "sampled_reports": f"WITH {T} SELECT user_id, least(5, (SELECT count(DISTINCT item_id) FROM t))::BIGINT AS reports, least(5, (SELECT count(DISTINCT item_id) FROM t))::BIGINT AS items FROM (SELECT DISTINCT user_id FROM t)",
        "aggregated_by_levels": f"{START} SELECT item_id, round(avg(w * g0), 6) AS g0, round(avg(w * g1), 6) AS g1 FROM ({reports(1, 0.0, 0.0, levels=seg)}) GROUP BY 1",
        "observed_traffic": f"WITH {T}, s AS (SELECT count(DISTINCT user_id) AS n, count(DISTINCT item_id) AS m FROM t) SELECT kind, n * m AS reports, n AS users, m AS items, n * m * w AS bytes_up FROM s, (VALUES ('pair', 17), ('product', 16)) v(kind, w)",
        "factor_norms": plain(3) + f" {size('x_3', 'x', 'user')} UNION ALL {size('z_3', 'z', 'item')}",
        "fold_in": plain(3) + " " + folded("z_3", 0.01),
        "fold_in_descent": plain(3) + " " + descended("z_3", 0.01, 0.5, 2),
        "fold_in_shares": shares(),
        "fit_trace": bold(4, 0.5),
        "fit_plain_blocks": blocks(3, 2),
        "fit_private_fast": f"WITH {T}, {one}, {fit_of('f_', 'one', 2, 2, mech)} SELECT item_id, {r('z0')}, {r('z1')} FROM f_z_2",
        "fit_central": f"WITH {T}, {one}, {fit_of('f_', 'one', 2, 2, mech, True)} SELECT item_id, {r('z0')}, {r('z1')} FROM f_z_2",
        "synthesized_noise": f"WITH {T}, i AS (SELECT item_id, count(*) AS c, (SELECT count(DISTINCT user_id) FROM t) AS n FROM t GROUP BY 1) SELECT item_id, {', '.join(f'round({gauss('synth', 'item_id', '1', str(k))} * (sqrt((n - c) * {pr / 2!r}::DOUBLE * (1 - {pr / 2!r}::DOUBLE) * 2.0) / (1 - {pr!r}::DOUBLE) * {scale!r}::DOUBLE), 6) AS s{k}' for k in range(2))} FROM i",
        "leakage": leaked(),
        "neighbour_measures": smoothed(),
        "stream_sliding": f"SELECT strftime(st, '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM ({slide}) JOIN events ON ts >= st AND ts < st + INTERVAL 6 HOURS WHERE st + INTERVAL 6 HOURS <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY 1",
        "stream_dedup": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
        "stream_totals": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
        "stream_matched": "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events v ON a.user_id = v.user_id AND v.ts <= a.ts AND v.ts >= a.ts - INTERVAL 6 HOURS WHERE a.event_id % 2 = 0 AND v.event_id % 2 = 1 GROUP BY 1",
        "stream_refit": "SELECT event_type, count(*) AS users, sum(label)::BIGINT AS open FROM (SELECT user_id, event_type, arg_max((value >= 35)::INT, strftime(ts, '%Y%m%d%H%M%S%f') || lpad(event_id::VARCHAR, 12, '0')) AS label FROM events GROUP BY 1, 2) GROUP BY 1",
    }
    out |= {name: f"WITH {swept(name)} SELECT * FROM averages" for name in SWEEPS}
    u_, by = "reconstruction_mean", "GROUP BY 1, 2"
    out |= {
        "gap_pivot": f"WITH w AS (SELECT unknown, avg({u_}) FILTER (method = 'private') AS a, avg({u_}) FILTER (method = 'plain') AS b FROM {averages_of('sweep_unknown')} GROUP BY 1) SELECT unknown, round(a, 6) AS private, round(b, 6) AS plain, round(a - b, 6) AS gap FROM w",
        "utility_slope": f"WITH e AS (SELECT method, eps, avg({u_}) AS v FROM {averages_of('sweep_eps')} {by}) SELECT method, eps, round(v, 6) AS u, round((v - lag(v) OVER w) / (eps - lag(eps) OVER w), 6) AS slope FROM e WINDOW w AS (PARTITION BY method ORDER BY eps)",
        "choose_parameters": f"""WITH w AS (SELECT method, width, avg({u_}) AS v FROM {averages_of('sweep_width')} {by}), e AS MATERIALIZED (SELECT method, eps, avg({u_}) AS v FROM {averages_of('sweep_eps')} {by}), h AS (SELECT method, unknown, avg({u_}) AS v FROM {averages_of('sweep_unknown')} {by})
SELECT method, best_width, smallest_eps, known_share FROM (SELECT method, width AS best_width FROM w QUALIFY row_number() OVER (PARTITION BY method ORDER BY v DESC, width) = 1)
LEFT JOIN (SELECT method, min(eps) AS smallest_eps FROM e JOIN (SELECT method, max(v) AS m FROM e GROUP BY 1) USING (method) WHERE v >= m - {TOLERANCE} GROUP BY 1) USING (method)
LEFT JOIN (SELECT method, round(1 - max(unknown), 6) AS known_share FROM h WHERE v >= {TARGET} GROUP BY 1) USING (method)""",
    }
    out |= {f"location_keys_{k}": f"SELECT {x} AS loc, count(*) AS n, count(DISTINCT user_id) AS users FROM ({src}) GROUP BY 1" for k, (x, src) in loc.items()}
    out |= {f"prefs_{k}": cells(x) for k, x in rules.items()}
    out |= {f"dense_ids_{k}": f"WITH {T} SELECT item_id, row_number() OVER (ORDER BY item_id) - 1 AS id FROM (SELECT DISTINCT item_id FROM t)" for k in ("rank", "range")}
    own = {"rate": "by_rate", "archetype": "own", "hybrid": "coalesce(own, by_rate)"}
    out |= {f"transfer_{k}": f"WITH {SURVEY} SELECT category, slot, count(*) AS n, count({x}) AS labelled, sum({x})::BIGINT AS open FROM both_ GROUP BY 1, 2" for k, x in own.items()}
    out |= {f"described_{k}": f"SELECT count(DISTINCT user_id) AS users, count(*) AS records, count(DISTINCT place) AS places, strftime(min(ts), '%Y-%m-%d') AS first_ts, strftime(max(ts), '%Y-%m-%d') AS last_ts FROM ({x})" for k, x in (("events", EV), ("orders", ORD))}
    out |= {f"masked_cells_h{h}": f"WITH {T} SELECT *, ({TEST} AND {u('mask', 'user_id', 'item_id')} < {h / 10!r}::DOUBLE)::INT AS held FROM t" for h in range(1, 10)}
    out |= {f"clipped_gradients_{k}": f"{START} SELECT user_id, item_id, round({clipped(0.2, k)[0]}, 6) AS g0, round({clipped(0.2, k)[1]}, 6) AS g1 FROM ({RES.format(a=0, b=0)})" for k in ("l1", "l2", "coordinate")}
    return out
