"""Similarities, calibration, terminology."""

import pytest
from pyspark.sql import functions as F

from caregraph.functions import similarity as sim
from caregraph.operators import calibrate, linking, vocab
from caregraph.sources import records


def one(spark, col, a, b):
    return spark.createDataFrame([(a, b)], "a string, b string").select(col(F.col("a"), F.col("b")).alias("x")).first()["x"]


def test_unit_values(spark):
    assert one(spark, sim.jaccard_sim, "small ring", "red plate") == pytest.approx(4 / 13)
    assert one(spark, sim.lcs_length, "small ring", "smll rnig") == 8
    assert one(spark, sim.lev_sim, "abc", "abd") == pytest.approx(2 / 3)
    for f in (sim.lev_sim, sim.jaccard_sim, sim.lcs_sim):
        assert one(spark, f, "心力衰竭", "心力衰竭") == 1 and one(spark, f, "", "ab") == 0 and one(spark, f, "", "") == 1
    assert one(spark, sim.lcs_sim, "éa", "ea") == 0.5


def test_lcs_native_equals_arrow(spark):
    pairs = [("kitten", "sitting"), ("a" * 40, "ab" * 20), ("xyz", "abc"), ("心力衰竭", "力竭")]
    rows = spark.createDataFrame(pairs, "a string, b string").select(sim.lcs_length(F.col("a"), F.col("b")).alias("n"), sim.lcs_length_arrow(F.col("a"), F.col("b")).alias("m")).collect()
    assert all(r["n"] == r["m"] for r in rows)


def test_ties_go_to_the_lesser_term(spark):
    p = spark.createDataFrame([("k", "ab", "ad"), ("k", "ab", "ac")], "kind string, mention string, label string")
    assert linking.best(linking.scored(p)).first()["term"] == "ac"


def test_pruning_is_exact_above_its_threshold(spark, sf):
    m, t = records.mentions(spark, sf), vocab.terms(spark, sf)
    full = linking.best(linking.scored(linking.candidates(m, t))).where("score > 0.6")
    cut = linking.best(linking.scored(linking.candidates(m, t, "length", 0.6), prune=0.6)).where("score > 0.6")
    assert full.exceptAll(cut).count() == 0 and cut.exceptAll(full).count() == 0


def test_votes(spark):
    v = spark.createDataFrame([([True] * 3 + [False] * 3,), ([True] * 4 + [False] * 2,), ([False] * 6,)], "v array<boolean>").select(calibrate.majority(F.col("v")).alias("m"), calibrate.agreement(F.col("v")).alias("a")).collect()
    assert [r["m"] for r in v] == [False, True, False] and v[1]["a"] == pytest.approx(4 / 6)


def test_calibration_matches_the_survey(spark):
    from caregraph.queries.link import QUERIES

    got = {r["kind"]: (r["threshold"], round(r["auc"], 3)) for r in QUERIES["cal_best_threshold"](spark, "/root/testdata/sf0.01").collect()}
    assert got == {"diagnosis": (0.55, 0.768), "drug": (0.65, 0.739), "assay": (0.6, 0.804)}


def test_sampling_methods(spark, sf):
    links = linking.best(linking.scored(linking.candidates(records.mentions(spark, sf), vocab.terms(spark, sf)))).cache()
    n = links.count()
    assert calibrate.sample(links).count() == pytest.approx(n / 10, abs=3)
    assert calibrate.sample(links, method="stratified").count() >= n / 10
    assert 0 <= calibrate.sample(links, method="random").count() < n / 2


def test_perfect_auc(spark):
    df = spark.createDataFrame([(0.1, 0), (0.2, 0), (0.9, 1)], "s double, l int")
    assert calibrate.roc_auc(df, "s", "l").first()["auc"] == 1.0


def test_lines_meet_items_at_any_place(spark, sf):
    import re

    from caregraph.queries import link

    lines = [r["mention"] for r in spark.read.parquet(f"{sf}/documents.parquet").selectExpr("explode(split(text, '\\n')) AS mention").distinct().collect()]
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()] + [(-1, "of the"), (-2, "...")]
    words = lambda t: [w for w in re.split(r"[\W_]+", t.lower()) if w]
    runs = lambda w, n: {tuple(w[k : k + n]) for k in range(len(w) - n + 1)}
    want = set()
    for i, t in items:
        n = min(3, len(words(t)))
        own = runs(words(t), n) if n else set()
        want |= {(m, i) for m in lines if own & runs(words(m), n)} if n else set()
    got = link.text_pairs(spark.createDataFrame([(m,) for m in lines], "mention string"), spark.createDataFrame(items, "item_id long, label string"))
    got = [(r["mention"], r["item_id"]) for r in got.collect()]
    assert set(got) == want and len(got) == len(want)
    assert {(m, i) for i, t in items for m in lines if i >= 0 and t in m} <= want
    assert link.text_matches(spark, sf).count() == len({p for p in want if p[1] >= 0})
