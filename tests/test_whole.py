"""Queries whose SQL can't show a cut, against the whole of their input."""

from collections import Counter

from locpref.plans import queries
from locpref.sources.tables import event_visits, table
from locpref.streaming import checkins


def test_lateral_top_has_every_user(spark, small):
    seen = {}
    for r in event_visits(spark, small).select("user_id", "place").collect():
        seen.setdefault(r.user_id, Counter())[r.place] += 1
    assert any(u >= 10 for u in seen)
    want = {(u, p, n) for u, c in seen.items() for p, n in sorted(c.items(), key=lambda x: (-x[1], x[0]))[:2]}
    assert sorted(map(tuple, queries.lateral_top(spark, small).collect())) == sorted(want)


def test_stream_gate_has_every_user_s_decisions(spark, small):
    rating = {(r.user_id, r.item_id): r.rating for r in queries.triples(spark, small).collect()}
    want = {}
    for r in event_visits(spark, small).select("user_id", "category", queries.slot().alias("slot")).collect():
        n = want.setdefault(r.category, [0, 0])
        n[rating[r.user_id, f"{r.category}@{r.slot}"] != 1] += 1
    assert {r.event_type: [r.released, r.hidden] for r in queries.stream_gate(spark, small).collect()} == want


def test_gate_takes_recommendations_and_hides_the_rest(spark, small):
    rating = {(r.user_id, r.item_id): int(r.rating) for r in queries.triples(spark, small).collect()}
    advice = {(r.user_id, r.item_id): r.decision for r in queries.recommend(spark, small).collect()}
    cells = queries.gate_cells(spark, small)
    assert sorted((r.user_id, r.item, r.decision) for r in cells.collect()) == sorted((*k, v) for k, v in (rating | advice).items())
    asked = [next(k for k, v in known.items() if v == d) for known in (rating, advice) for d in (1, 0)]
    new = -1, asked[0][1]  # a user without any cell
    seen = spark.createDataFrame([*asked, new], "user_id long, item string")
    assert {(r.user_id, r.item): r.released for r in checkins.gate(seen, cells).collect()} == dict(zip([*asked, new], [True, False, True, False, False]))


def test_ledger_has_every_customer(spark, small):
    users = {r.c_custkey for r in table(spark, small, "customer").select("c_custkey").collect()}
    rows = queries.budget_ledger(spark, small).collect()
    assert {r.user_id for r in rows} == users and len(rows) == 8 * len(users)


def test_models_side_by_side(spark, small):
    items = {r.item_id for r in queries.triples(spark, small).collect()}
    assert {r.item_id for r in queries.compare_models(spark, small).collect() if r.a0 is not None and r.z0 is not None} == items
    one = spark.createDataFrame([("a", 1.0, 2.0), ("b", 3.0, 4.0)], "item_id string, z0 double, z1 double")
    two = spark.createDataFrame([("b", 5.0, 6.0), ("c", 7.0, 8.0)], "item_id string, z0 double, z1 double")
    assert sorted(map(tuple, queries.side_by_side(one, two).collect())) == [("a", 1.0, 2.0, None, None), ("b", 3.0, 4.0, 5.0, 6.0), ("c", None, None, 7.0, 8.0)]
