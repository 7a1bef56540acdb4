"""The stored graph, inference, costs, streams with bounded state, SQL surface."""

import datetime as dt
import random

import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from caregraph import session, store
from caregraph.functions import udf
from caregraph.operators import calibrate, costs, events, inference, linking, relations, timeline, vocab, workloads
from caregraph.plans import mapping, pattern
from caregraph.queries import work
from caregraph.sources import io, ntriples, records
from caregraph.streaming import streams

DAY0 = dt.datetime(2012, 1, 1)


def random_events(spark, seed, n=40, days=14, patients=2):
    r = random.Random(seed)
    rows = []
    for k in range(n):
        b = r.randint(0, days)
        rows.append((f"e{k:02d}", k % patients, "x", DAY0 + dt.timedelta(b), DAY0 + dt.timedelta(b + r.choice([0, 0, 1, 2, 5]))))
    return timeline.classify(spark.createDataFrame(rows, "event_id string, patient_id bigint, kind string, begin_ts timestamp_ntz, end_ts timestamp_ntz"))


def pairs(df, relation):
    return {(r["src"], r["dst"]) for r in df.where(F.col("relation") == relation).collect()}


def test_stored_tables_equal_fresh_ones(spark, sf):
    assert store.events(spark, sf).exceptAll(events.extract(spark, sf)).count() == 0 == events.extract(spark, sf).exceptAll(store.events(spark, sf)).count()
    fresh = relations.build(store.events(spark, sf))
    assert store.relations(spark, sf).exceptAll(fresh).count() == 0 and store.relations(spark, sf).count() == fresh.count()
    t = mapping.clinical(spark, sf, store.events(spark, sf), store.entities(spark, sf))
    assert store.triples(spark, sf).count() == t.count()


def test_stored_events_need_no_shuffle_by_patient(spark, sf):
    plan = relations.placed(store.events(spark, sf))._jdf.queryExecution().executedPlan().toString()
    assert "Window" in plan and "Exchange" not in plan
    p = pattern.exec_wide(workloads.W3, workloads.labelled(spark, sf), records.patients(spark, sf))
    assert costs.measure(p)["shuffled_bytes"] < 10_000


def test_stored_tables_follow_their_sources(spark, sf, tmp_path):
    import shutil

    for t in store.SOURCES:
        shutil.copy(f"{sf}/{t}.parquet", tmp_path)
    d = str(tmp_path)
    n = store.events(spark, d).count()
    (tmp_path / "orders.parquet").chmod(0o644)
    pq.write_table(pq.read_table(f"{sf}/orders.parquet").slice(0, 10), f"{d}/orders.parquet")
    assert store.events(spark, d).count() < n
    assert store.events(spark, sf).count() == n


def test_no_machine_local_folder_on_a_cluster(spark, monkeypatch):
    class Context:
        master = "spark://host:7077"

    class Session:
        sparkContext = Context()
        conf = spark.conf

    if spark.conf.get("spark.checkpoint.dir", None) is None:
        with pytest.raises(ValueError):
            store.shared_folder(Session())


def test_fixpoint_of_the_sparsest_form_is_all_of_it(spark):
    for seed in (1, 2):
        e = random_events(spark, seed)
        got = inference.fixpoint(relations.build(e, density="chain"))
        full = relations.build(e, density="full")
        for r in ("Before", "After", "During", "Overlap", "Concurrent"):
            assert pairs(got, r) == pairs(full, r), r


def test_wanted_relations_are_made_alone(spark):
    e = random_events(spark, 5)
    every = relations.build(e)
    for wanted in (("Before",), ("After",), ("During", "Overlap"), ("Concurrent",), ("Overlap", "Concurrent", "After")):
        got = relations.build(e, wanted=wanted)
        assert {r["relation"] for r in got.select("relation").distinct().collect()} <= set(wanted)
        assert all(pairs(got, w) == pairs(every, w) for w in wanted)


def test_costs_are_read_from_the_plan_that_ran(spark, sf):
    got = {r["executor"]: r for r in work.costs_compared(spark, sf).where("question = 'W3'").collect()}
    assert got["stars"]["joins"] < got["relational"]["joins"] < got["triples"]["joins"]
    assert got["stars"]["shuffled_bytes"] < got["relational"]["shuffled_bytes"]


def test_ranks_in_slices(spark):
    r = random.Random(4)
    rows = [(r.choice("ab"), f"m{k:03d}", r.choice([0.0, 0.5, 1.0, round(r.random(), 3)])) for k in range(300)]
    df = spark.createDataFrame(rows, "kind string, mention string, score double")
    for falling in (False, True):
        want = {}
        for kind in "ab":
            for pos, x in enumerate(sorted((x for x in rows if x[0] == kind), key=lambda x: (-x[2] if falling else x[2], x[1])), 1):
                want[x[1]] = pos
        assert {x["mention"]: x["pos"] for x in calibrate.ranked(df, "kind", "score", "mention", falling=falling).collect()} == want


def test_pairs_in_blocks_and_pruned(spark, sf, monkeypatch):
    m, t = records.mentions(spark, sf), vocab.terms(spark, sf)
    want = {tuple(r) for r in linking.candidates(m, t).collect()}
    slow = {tuple(r) for r in linking.best(linking.scored(linking.candidates(m, t))).collect()}
    monkeypatch.setattr(linking, "BROADCAST_BYTES", 2000)
    assert {tuple(r) for r in linking.candidates(m, t).collect()} == want
    assert {tuple(r) for r in linking.best_pruned(linking.candidates(m, t)).collect()} == slow


def test_minhash_recall(spark):
    from caregraph.queries import link

    assert all(r["recall"] >= 0.9 for r in link.minhash_recall(spark, "/root/testdata/sf0.01").collect())


def test_hierarchies_are_not_cut(spark):
    rows = [(f"t{k}", "broader", f"t{k + 1}") for k in range(16)] + [("it's", "broader", "t0")]
    edge = spark.createDataFrame(rows, "src string, rel string, dst string")
    got = vocab.narrower(edge, "t16")
    assert got.count() == 17 and got.agg(F.max("steps")).first()[0] == 17
    assert vocab.narrower(edge, "it's").count() == 0 and not [t for t in spark.catalog.listTables() if t.name.startswith("cg_edges")]


def test_views_and_functions(spark, sf):
    udf.register(spark)
    udf.register_graph(spark, {"event": store.events(spark, sf), "triple": store.triples(spark, sf)})
    assert spark.sql("SELECT count(*) AS n FROM event").first()["n"] == 7500
    assert spark.sql("SELECT count(*) AS n FROM ego_triples('cg:event/O-1')").first()["n"] > 3
    r = spark.sql("SELECT lcs_sim('abcd', 'acd') AS l, lcs_sim('', '') AS e, lcs_sim('a', '') AS z, vote_majority(array(true, false)) AS v, normalize_qualitative('（＋）') AS q").first()
    assert (r["l"], r["e"], r["z"], r["v"], r["q"]) == (0.75, 1.0, 0.0, False, "positive")
    session.register_views({"shared_event": store.events(spark, sf).limit(3)}, shared=True)
    assert spark.sql("SELECT count(*) AS n FROM global_temp.shared_event").first()["n"] == 3


def test_triple_lines_both_ways(spark):
    rows = [("cg:a", "cg:p", 'x "y"\n\t\\n', "literal", "xsd:string", None), ("_:b1", "cg:p", "cg:c", "iri", None, None), ("cg:a", "rdf:type", "_:b1", "bnode", None, None), ("cg:a", "cg:l", "né", "literal", None, "fr")]
    t = spark.createDataFrame(rows, "s string, p string, o string, o_kind string, datatype string, lang string")
    text = [r["value"] for r in ntriples.lines(t).collect()]
    assert sorted(map(str, (ntriples.parse_line(x) for x in text))) == sorted(map(str, rows))
    assert ntriples.parse_line("# comment") is None


def test_triple_source_reads_each_line_once(spark, tmp_path):
    for k in range(3):
        (tmp_path / f"f{k}.nt").write_text("".join(f"<urn:caregraph:e{k}-{i}> <urn:caregraph:p> <urn:caregraph:o{i}> .\n" for i in range(50)))
    spark.dataSource.register(io.TripleSource)
    for size in (37, 100, 10**6):
        got = [r["s"] for r in spark.read.format("cg_triples").option("path", str(tmp_path)).option("bytes", str(size)).load().collect()]
        assert sorted(got) == sorted(f"cg:e{k}-{i}" for k in range(3) for i in range(50))


def test_bounded_stream_state(spark, sf, tmp_path):
    """In order, a stream with a delay gives the batch's edges; rows behind the watermark are dropped and counted."""
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("day", F.to_date("ts"))
    days = [r["day"] for r in e.select("day").distinct().orderBy("day").collect()]
    cut = days[len(days) // 2]
    out = f"{tmp_path}/s.parquet"
    e.where(F.col("day") < F.lit(cut)).drop("day").coalesce(1).write.parquet(out)
    import time

    time.sleep(1.1)
    e.where(F.col("day") >= F.lit(cut)).drop("day").coalesce(1).write.mode("append").parquet(out)
    want = {(r["src"], r["dst"]) for r in relations.before(events.extract(spark, sf, "clicks").where("kind <> 'drug'")).collect()}

    def net(df):
        return {(r["src"], r["dst"]) for r in df.groupBy("src", "dst").agg(F.sum("op").alias("n")).where("n > 0").collect()}

    got = net(streams.run(streams.relations(streams.source(spark, out), "2 days"), "cg_bounded"))
    assert got == want and streams.LATE["cg_bounded"] == 0
    time.sleep(1.1)
    e.where(F.col("day") < F.lit(days[2])).drop("day").coalesce(1).write.mode("append").parquet(out)
    streams.run(streams.dedup(streams.source(spark, out), "1 day"), "cg_too_late")
    assert streams.LATE["cg_too_late"] > 0


def test_long_periods_keep_their_views(spark, sf):
    path = f"{sf}/events.parquet"
    a, b = ({tuple(r) for r in streams.run(streams.during(streams.source(spark, path), streams.source(spark, path), piece=p), "cg_pieces").collect()} for p in ("60 days", "6 hours"))
    assert a == b and a


def test_forgotten_tables_are_made_again(spark, sf):
    n = store.events(spark, sf).count()
    store.forget(spark)
    assert store.events(spark, sf).count() == n


def test_ego_graph_grows_by_steps(spark):
    rows = [("a", "p", "b", "iri"), ("b", "p", "c", "iri"), ("c", "p", "d", "iri"), ("x", "p", "a", "iri"), ("b", "n", "1", "literal"), ("y", "p", "z", "iri")]
    t = spark.createDataFrame(rows, "s string, p string, o string, o_kind string")
    for hops, want in ((1, "ab xa"), (2, "ab xa bc b1"), (3, "ab xa bc b1 cd")):
        assert {r["s"] + r["o"] for r in mapping.ego(t, "a", hops).collect()} == set(want.split())


def test_stored_relations_are_made_and_read_where_a_patient_is(spark, sf):
    was = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        with store.dealt_by_patient(spark):
            plan = relations.build(store.events(spark, sf))._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", was)
    assert "SortMergeJoin" in plan and "Exchange" not in plan
    plan = store.relations(spark, sf).groupBy("patient_id").count()._jdf.queryExecution().executedPlan().toString()
    assert "HashAggregate" in plan and "Exchange" not in plan


def test_edges_are_not_shuffled_to_find_ends_of_other_patients(spark, sf):
    rel, e = store.relations(spark, sf), store.events(spark, sf)
    assert costs.measure(relations.assert_same_patient(rel, e))["shuffled_bytes"] < 10_000
    moved = rel.withColumn("patient_id", F.when(F.col("src") == rel.first()["src"], -1).otherwise(F.col("patient_id")))
    assert relations.assert_same_patient(moved, e).count() == moved.where("patient_id = -1").count() > 0


def test_measured_plans_leave_no_shuffles(spark):
    held = lambda: spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses().size()
    df = spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count()
    n = held()
    assert costs.measure(df)["exchanges"] == 1 and held() <= n


def test_reach_of_any_graph_in_blocks():
    r = random.Random(3)
    for n, m in ((1, 1), (12, 14), (30, 25), (40, 90)):
        edges = {(r.randrange(n), r.randrange(n)) for _ in range(m)}
        want, more = set(edges), True
        while more:
            new = want | {(a, d) for a, b in want for c, d in edges if b == c}
            want, more = new, new != want
        for block in (3, 8, 64):
            got = [(x, int(y)) for x, found in inference.reach(n, edges, None, block) for y in found]
            assert len(got) == len(set(got)) and set(got) == want
        some = list(range(0, n, 3))
        assert {(x, int(y)) for x, found in inference.reach(n, edges, some, 2) for y in found} == {p for p in want if p[1] in some}


def test_closure_writes_no_rounds_and_keeps_to_chosen_events(spark):
    import os

    e = random_events(spark, 5)
    rel = relations.build(e)
    folder = store.shared_folder(spark).removeprefix("file:")
    n = len(os.listdir(folder)) if os.path.isdir(folder) else 0
    got = inference.closure(rel)
    want = {(r["src"], r["dst"]) for r in relations.full_before(e).collect()}
    assert {(r["src"], r["dst"]) for r in got.collect()} == want and got.count() == len(want)
    assert pairs(got.withColumnRenamed("origin", "relation"), "asserted") == pairs(rel, "Before")
    some = {r["event_id"] for r in e.collect()[::3]}
    few = inference.closure(rel, e.where(F.col("event_id").isin(*some)).select("patient_id", "event_id"))
    assert {(r["src"], r["dst"]) for r in few.collect()} == {(a, b) for a, b in want if a in some and b in some}
    inference.fixpoint(rel).count()
    assert (len(os.listdir(folder)) if os.path.isdir(folder) else 0) == n


def test_superclasses_reach_from_a_table_s_labels_to_thing(spark, sf):
    part = {(r["p_name"], r["p_type"]) for r in records.table(spark, sf, "part").collect()}
    got = {tuple(r) for r in work.QUERIES["ont_superclasses"](spark, sf).collect()}
    name, kind = min(part)
    assert {(name, kind, 1), (name, "Object", 2), (name, "Actor", 3), (name, "Thing", 4), (kind, "Thing", 3), ("Drug", "Object", 1)} <= got
    assert {(a, b) for a, b, n in got if n == 1 and (a, b) in part} == part
