"""Mapping, cleaning, patterns, text queries, streams, and the entry module."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from caregraph.operators import clean
from caregraph.operators.ontology import Ontology
from caregraph.plans import mapping, pattern
from caregraph.plans.sparql import Executor, Parser, QueryError
from caregraph.sources import io, ntriples
from caregraph.operators import workloads


def test_direct_mapping_counts(spark, sf):
    for name, (pk, fks) in mapping.KEYS.items():
        df = spark.read.parquet(f"{sf}/{name}.parquet")
        assert mapping.direct(df, name, pk, fks).count() == df.count() * (1 + len(df.columns) + len(fks))


def test_nulls_emit_nothing(spark):
    df = spark.createDataFrame([(1, None), (2, "x")], "k int, v string")
    tm = mapping.TriplesMap("t", mapping.Template("cg:t/{k}"), ("cg:T",), (("cg:v", mapping.Literal("v")),))
    assert mapping.apply(tm, {"t": df}).count() == 3


def test_ntriples_round_trip(spark):
    rows = [("cg:a b", "cg:p", 'quo"te\\n \\ and\nline\ttab', "literal", "xsd:string", None), ("cg:a", "cg:p", "心力", "literal", None, "zh"), ("_:b1", "rdf:type", "cg:T", "iri", None, None)]
    t = spark.createDataFrame(rows, "s string, p string, o string, o_kind string, datatype string, lang string")
    back = ntriples.parse(ntriples.lines(t))
    assert {tuple(r) for r in back.collect()} == set(rows)


def test_ontology_extends_and_validates(spark):
    o = Ontology()
    o.register_property("causes", "DiagnosisEvent", "DrugEvent")
    with pytest.raises(ValueError):
        o.register_class("X", "Unknown")
    t = spark.createDataFrame([("e", "rdf:type", "cg:DrugEvent", "iri"), ("p", "rdf:type", "cg:Patient", "iri"), ("e", "cg:hasActor", "p", "iri"), ("p", "cg:hasActor", "e", "iri"), ("e", "cg:causes", "e", "iri")], "s string, p string, o string, o_kind string")
    faults = {(r["s"], r["p"], r["fault"]) for r in o.validate(spark, t).collect()}
    assert faults == {("p", "cg:hasActor", "domain"), ("p", "cg:hasActor", "range"), ("e", "cg:causes", "domain")}


def test_qualitative_spellings(spark):
    said = ["negative (-)", "positive (+)", "(+)", "(-)", "（＋）", " POS ", "-", None, "unclear"]
    got = [r["x"] for r in spark.createDataFrame([(x,) for x in said], "v string").select(clean.normalize_qualitative(F.col("v")).alias("x")).collect()]
    assert got == ["negative", "positive", "positive", "negative", "positive", "positive", "negative", None, None]


def test_units_split_and_intervals(spark):
    u = clean.convert_units(spark.createDataFrame([(1.5, "g/dL"), (15.0, "g/L"), (3.0, "mg")], "v double, u string"), "v", "u").collect()
    assert [(r["value_std"], r["unit_known"]) for r in u] == [(15.0, True), (15.0, True), (3.0, False)]
    s = clean.split_cell(spark.createDataFrame([("a, b；c  d;;",)], "x string"), "x")
    assert [r["item"] for r in s.orderBy("pos").collect()] == ["a", "b", "c", "d"]
    d = spark.sql("SELECT timestamp_ntz'2012-01-05' AS b, timestamp_ntz'2012-01-01' AS e")
    for policy, n in (("clamp", 0), ("swap", 4), ("null", None)):
        assert clean.repair_interval(d, "b", "e", policy).select(F.datediff("e", "b").alias("n")).first()["n"] == n
    assert clean.repair_interval(d, "b", "e", "drop").count() == 0


def test_classes_of_questions():
    assert [pattern.classify(w) for w in (workloads.W1, workloads.W2, workloads.W3)] == ["SE", "ME", "CME"]


def test_edges_mode_agrees_with_timestamps(spark, sf):
    from caregraph.operators import events, relations
    from caregraph.queries.work import triples

    t = triples(spark, sf).cache()
    p = pattern.Pattern().event("dx", "diagnosis", type="PROMO").event("stay", "stay").rel("dx", "During", "stay")
    rel = relations.build(events.extract(spark, sf), density="full")
    a = {r[0] for r in pattern.exec_triples(p, t).collect()}
    assert a == {r[0] for r in pattern.exec_triples(p, t, "edges", rel).collect()} and a


def test_patterns_with_a_value_are_joined_first(spark, sf):
    """the filter on a label or type stood behind joins of all events, the patients' category behind all of them."""
    t = entry.queries()["triples_clinical"](spark, sf).withColumn("s_kind", F.lit(None)).withColumn("class", F.lit(None))
    for p, n in ((workloads.W1, 5), (workloads.W2, 18), (workloads.W3, 21), (workloads.W3B, 30)):
        plan = pattern.exec_triples(p, t)._jdf.queryExecution().analyzed().toString()
        values = ["= red plate"] if p is workloads.W1 else [f"= {p.category}", "= PROMO"]
        assert plan.count("Join Inner") == n
        assert all(plan.index(v) < plan.index("= rdf:type") for v in values)


def test_text_queries(spark):
    t = spark.createDataFrame([("cg:a", "cg:next", "cg:b"), ("cg:b", "cg:next", "cg:c"), ("cg:a", "cg:n", "3"), ("cg:b", "cg:n", "5")], "s string, p string, o string")
    x = Executor(t)
    assert {r["y"] for r in x.query("SELECT ?y WHERE { cg:a cg:next+ ?y }").collect()} == {"cg:b", "cg:c"}
    assert {r["y"] for r in x.query("SELECT ?y WHERE { cg:a cg:next* ?y }").collect()} == {"cg:a", "cg:b", "cg:c"}
    assert x.query("SELECT (SUM(?v) AS ?t) WHERE { ?s cg:n ?v }").first()["t"] == 8
    assert [r["s"] for r in x.query("SELECT ?s WHERE { ?s cg:n ?v } ORDER BY DESC(?v) LIMIT 1").collect()] == ["cg:b"]
    assert x.query("SELECT ?s ?w WHERE { ?s cg:next ?o OPTIONAL { ?o cg:n ?w } FILTER (!bound(?w)) }").count() == 1
    assert x.query("ASK { cg:a cg:next cg:z }").first()["answer"] is False
    with pytest.raises(QueryError):
        x.query("SELECT ?a WHERE { ?a cg:n ?b . ?c cg:n ?d }")
    with pytest.raises(QueryError):
        Parser("SELECT ?a WHERE { ?a cg:n ?b ").query()


def test_sources(spark, tmp_path, sf):
    df = spark.read.parquet(f"{sf}/nation.parquet")
    for fmt in ("parquet", "orc", "json", "csv"):
        io.write(df, f"{tmp_path}/{fmt}", fmt)
        assert {tuple(r) for r in io.read(spark, f"{tmp_path}/{fmt}", fmt, df.schema).select(*df.columns).collect()} == {tuple(r) for r in df.collect()}
    assert io.jdbc(spark, "jdbc:x:y", "t", "k", 0, 100, 4) is not None


def test_streamed_relations_survive_late_events(spark, sf, tmp_path):
    """Two files in wrong order give the batch's edges."""
    from caregraph.streaming import streams

    e = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts")
    e.where(F.col("event_id") % 2 == 1).coalesce(1).write.parquet(f"{tmp_path}/s/a.parquet")
    e.where(F.col("event_id") % 2 == 0).coalesce(1).write.mode("append").parquet(f"{tmp_path}/s/a.parquet")
    s = streams.run(streams.relations(streams.source(spark, f"{tmp_path}/s/a.parquet")), "cg_late")
    net = {(r["src"], r["dst"]) for r in s.groupBy("src", "dst").agg(F.sum("op").alias("n")).where("n > 0").collect()}
    from caregraph.operators import events, relations

    want = {(r["src"], r["dst"]) for r in relations.before(events.extract(spark, sf, "clicks").where("kind <> 'drug'")).collect()}
    assert net == want


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["relation", "step", "edges"] and df.count() > 0


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())
