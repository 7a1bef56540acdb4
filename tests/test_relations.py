"""Worked examples, Allen's cases, invariants."""

import datetime as dt

import pytest

from caregraph.operators import baseline, events, inference, relations, timeline

DAY0 = dt.datetime(2012, 1, 1)
FULL = "event_id string, patient_id bigint, kind string, begin_ts timestamp_ntz, end_ts timestamp_ntz"


def ev(spark, *spans, patient=1):
    """Events a, b, c … of (begin day, end day)."""
    rows = [("abcdefghij"[k], patient, "x", DAY0 + dt.timedelta(b), DAY0 + dt.timedelta(e)) for k, (b, e) in enumerate(spans)]
    return timeline.classify(spark.createDataFrame(rows, FULL))


def edges(df, *names):
    return {(r["src"], r["dst"], r["relation"]) for r in df.collect() if not names or r["relation"] in names}


def test_diagnosis_before_drug(spark):
    assert edges(relations.build(ev(spark, (1, 1), (2, 7)))) == {("a", "b", "Before"), ("b", "a", "After")}


def test_points_of_one_time_are_concurrent(spark):
    assert edges(relations.build(ev(spark, (3, 3), (3, 3)))) == {("a", "b", "Concurrent")}


@pytest.mark.parametrize(
    "spans, want",
    [
        (((3, 5), (1, 9)), {("a", "b", "During")}),
        (((3, 12), (1, 9)), {("a", "b", "Overlap")}),
        (((1, 10), (10, 10)), {("b", "a", "During")}),
        (((1, 10), (4, 10)), set()),
        (((1, 5), (1, 9)), {("a", "b", "During")}),
        (((1, 5), (5, 9)), {("b", "a", "Overlap")}),
        (((1, 5), (1, 5)), {("a", "b", "Concurrent")}),
        (((1, 1), (1, 5)), {("a", "b", "During")}),
    ],
)
def test_span_cases(spark, spans, want):
    assert edges(relations.build(ev(spark, *spans), inverse=False)) == want


def test_equal_ends_can_count_as_during(spark):
    assert edges(relations.build(ev(spark, (1, 10), (4, 10)), equal_end="during")) == {("b", "a", "During")}


def test_only_neighbours_are_linked(spark):
    e = ev(spark, (1, 1), (2, 2), (3, 3))
    reduced = relations.build(e)
    assert edges(reduced, "Before") == {("a", "b", "Before"), ("b", "c", "Before")}
    assert len(edges(reduced, "After")) == 2
    assert relations.build(e, density="full").count() == 6
    closed = {(r["src"], r["dst"]) for r in inference.closure(reduced).collect()}
    assert closed == {("a", "b"), ("b", "c"), ("a", "c")}


def test_patients_are_not_comparable(spark):
    e = ev(spark, (1, 1), (3, 3)).unionByName(ev(spark, (2, 2), (4, 4), patient=2).withColumn("event_id", __import__("pyspark").sql.functions.concat("event_id", "event_id")))
    assert edges(relations.build(e, inverse=False)) == {("a", "b", "Before"), ("aa", "bb", "Before")}
    assert relations.assert_same_patient(relations.build(e), e).count() == 0


def test_ties_and_chain(spark):
    e = ev(spark, (1, 1), (1, 1), (2, 2), (2, 2))
    r = relations.build(e, inverse=False)
    assert len(edges(r, "Before")) == 4 and len(edges(r, "Concurrent")) == 2
    c = relations.build(e, density="chain", inverse=False)
    assert edges(c) == {("a", "c", "Before"), ("a", "b", "Concurrent"), ("c", "d", "Concurrent")}


def test_scope_per_step(spark):
    e = ev(spark, (1, 1), (2, 3), (4, 4))
    assert relations.before(e).count() == 2
    assert relations.before(e, scope="per_step").count() == 3


def test_antichain(spark):
    e = ev(spark, (1, 4), (2, 5), (3, 6), (7, 9), (7, 10), (8, 9))
    assert relations.before(e).count() == 9


def test_long_ranges_cross_chunks(spark, monkeypatch):
    monkeypatch.setattr(relations, "CHUNK", 3)
    e = ev(spark, (0, 20), *((k, k) for k in range(1, 9)))
    assert len(edges(relations.build(e, inverse=False), "During")) == 8


def test_reduction_against_bruteforce(spark, sf):
    e = events.extract(spark, sf)
    fast = {(r["src"], r["dst"]) for r in relations.before(e).collect()}
    slow = {(r["src"], r["dst"]) for r in baseline.reduce_bruteforce(e).collect()}
    assert fast == slow and len(fast) == 9557


def test_invariants(spark, sf):
    e = events.extract(spark, sf).cache()
    key = ["patient_id", "src", "dst"]
    glob, per, full = (relations.before(e, **o).select(*key) for o in ({}, {"scope": "per_step"}, {"density": "full"}))
    assert glob.subtract(per).count() == 0 and per.subtract(full).count() == 0
    every = relations.build(e, density="full", equal_end="during", inverse=False).select(*key)
    n = e.groupBy("patient_id").count().selectExpr("sum(count * (count - 1) / 2) AS n").first()["n"]
    assert every.count() == n  # one relation for each pair
    red = relations.redundancy(e).selectExpr("sum(full_edges) f", "sum(reduced_edges) r").first()
    assert (red["f"], red["r"]) == (177768, 9557)


def test_counts_follow_the_published_shape(spark, sf):
    """Before and After are mutual, and the total is the sum of the parts."""
    from caregraph.operators import profile

    c = {r["relation"]: r["edges"] for r in profile.relations(relations.build(events.extract(spark, sf))).collect()}
    assert c["Before"] == c["After"] and c["total"] == sum(v for k, v in c.items() if k != "total")
    assert (c["Concurrent"], c["During"], c["Overlap"]) == (26, 26440, 2912)


def test_empty(spark, sf):
    e = events.extract(spark, sf).limit(0)
    assert relations.build(e).count() == 0
