"""Queries on workloads, mapping and cleaning."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph import store
from caregraph.operators import baseline, clean, costs, events, inference, linking, profile, relations, vocab, workloads
from caregraph.operators.ontology import Ontology
from caregraph.plans import mapping, pattern
from caregraph.queries.base import ENTITIES, EVENTS, LINES, RELATIONS, sql
from caregraph.queries.link import ACCEPTED, MENTIONS, accepted
from caregraph.sources import ntriples, records

TRIPLE = ("s", "p", "o", "o_kind", "datatype", "lang")


def triples(spark: SparkSession, d: str) -> DataFrame:
    return store.triples(spark, d)


def wide(p: pattern.Pattern):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return pattern.exec_wide(p, workloads.labelled(spark, d), records.patients(spark, d))

    return run


def by_triples(p: pattern.Pattern):
    return lambda spark, d: pattern.exec_triples(p, triples(spark, d))


def counted(run):
    return lambda spark, d: run(spark, d).agg(F.count("*").alias("patients"))


def stage_counts(spark: SparkSession, d: str) -> DataFrame:
    """Rows after every step of the construction."""
    n = lambda df, name: df.agg(F.lit(name).alias("stage"), F.count("*").alias("rows"))
    dirty = records.dirty_lines(spark, d)
    out = n(dirty.where(clean.normalize_qualitative(F.col("prompt_raw")).isNotNull()), "cleaned")
    out = out.unionByName(n(store.events(spark, d), "events")).unionByName(n(store.triples(spark, d), "triples")).unionByName(n(store.relations(spark, d), "relations"))
    return out.unionByName(n(accepted(spark, d).where("accepted"), "links"))


def statistics(spark: SparkSession, d: str) -> DataFrame:
    """The dataset's description, one figure a row."""
    ev = store.events(spark, d)
    e = profile.events(ev).select(F.concat(F.lit("events "), "kind").alias("measure"), F.col("events").alias("n"))
    o = profile.entities(ev).select(F.concat(F.lit("entities "), "kind").alias("measure"), F.col("entities").alias("n"))
    r = profile.relations(store.relations(spark, d)).select(F.concat(F.lit("relations "), "relation").alias("measure"), F.col("edges").alias("n"))
    return e.unionByName(o).unionByName(r)


def all_triples(spark: SparkSession, d: str) -> DataFrame:
    """Triples of all four classes by predicate."""
    t = triples(spark, d).unionByName(mapping.temporal(store.relations(spark, d)))
    link = linking.link_triples(accepted(spark, d)).select("*", F.lit("iri").alias("s_kind"), F.lit("link").alias("class"))
    return profile.triples(t.unionByName(link))


def rebuilt(table: str):
    """Makes a stored table anew and counts its rows: what a build costs."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        ev = store.events(spark, d)
        df = {"event": lambda: events.extract(spark, d), "triple": lambda: mapping.clinical(spark, d, ev, store.entities(spark, d)), "relation": lambda: relations.build(ev)}[table]()
        return df.agg(F.lit(table).alias("table"), F.count("*").alias("rows"))

    return run


def costs_compared(spark: SparkSession, d: str) -> DataFrame:
    """What each question costs by stars over stored events, by stored triples, and by joins of the source tables. Numbers of operators are those of the plans that ran."""
    r = baseline.Relational(spark, d)
    ways = {
        "W1": (workloads.W1, r.w1()),
        "W2": (workloads.W2, r.w2()),
        "W3": (workloads.W3, r.w3()),
        "W3b": (workloads.W3B, r.w3(strict=True)),
    }
    each = {q: {"stars": wide(p)(spark, d), "triples": by_triples(p)(spark, d), "relational": rel} for q, (p, rel) in ways.items()}
    return spark.createDataFrame(costs.compared(each), "question string, executor string, joins int, scans int, exchanges int, shuffled_bytes long, rows_read long, seconds double")


def by_edges(p: pattern.Pattern, how: str):
    """A question with time by relation edges instead of times: stored ones, and for Before and After what they imply.

    all: from the events' times, without iteration. closure: by following the
    stored edges until no more come, for the patients that have all that the question names.
    Only edges between events that the question names go on to its joins.
    """
    named = {v for a, r, b in p.temporal if r in ("Before", "After") for v in (a, b)}

    def run(spark: SparkSession, d: str) -> DataFrame:
        ev = workloads.labelled(spark, d)
        who = pattern.having_all(p, ev, records.patients(spark, d))
        among = pattern.any_of([s for s in p.stars if s.name in named], ev).join(who, "patient_id", "left_semi")
        held = store.relations(spark, d).join(who, "patient_id", "left_semi").select("patient_id", "src", "dst", "relation")
        if how == "all":
            far = relations.full_before(among).select("patient_id", "src", "dst")
        else:
            far = inference.closure(held, among).select("patient_id", "src", "dst")
        far = relations.with_inverse(far.withColumn("relation", F.lit("Before")))
        return pattern.exec_triples(p, triples(spark, d), "edges", held.where("relation not in ('Before', 'After')").unionByName(far))

    return run


def direct(name: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        pk, fks = mapping.KEYS[name]
        return mapping.direct(records.table(spark, d, name), name, pk, fks).groupBy("p", "o_kind").agg(F.count("*").alias("triples"), F.countDistinct("s").alias("subjects"))

    return run


def direct_sql(name: str, columns: list[str]) -> str:
    _, fks = mapping.KEYS[name]
    rows = [f"SELECT 'rdf:type' AS p, 'iri' AS o_kind, count(*) AS triples, count(*) AS subjects FROM {name}"]
    rows += [f"SELECT 'cg:{name}#{c}', 'literal', count({c}), count({c}) FROM {name}" for c in columns]
    rows += [f"SELECT 'cg:{name}#ref-{c}', 'iri', count({c}), count({c}) FROM {name}" for c in fks]
    return " UNION ALL ".join(rows)


COLUMNS = {
    "region": ["r_regionkey", "r_name"],
    "nation": ["n_nationkey", "n_name", "n_regionkey"],
    "customer": ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"],
    "supplier": ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"],
    "part": ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"],
    "orders": ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"],
    "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"],
    "events": ["event_id", "ts", "user_id", "event_type", "value", "props"],
}


def wide_again(spark: SparkSession, d: str) -> DataFrame:
    """Diagnosis events back from their triples."""
    t = triples(spark, d).where("class = 'event'")
    got = mapping.to_wide(t, ["rdf:type", "cg:hasBegin", "cg:situation"]).where(F.col("rdf:type") == "cg:DiagnosisEvent")
    return got.select(F.substring("s", 10, 200).alias("event_id"), F.col("cg:hasBegin").alias("begin"), F.col("cg:situation").alias("situation"))


def referenced(spark: SparkSession, d: str) -> DataFrame:
    """References through a parent's non-key column: nations point to regions by name."""
    region = mapping.TriplesMap("region", mapping.Template("cg:region/{r_name}"), (), ())
    tm = mapping.TriplesMap("nation", mapping.Template("cg:nation/{n_nationkey}"), (), (("cg:within", mapping.Ref(region, (("n_regionkey", "r_regionkey"),))),))
    return mapping.apply(tm, {"nation": records.table(spark, d, "nation"), "region": records.table(spark, d, "region")}).select("s", "p", "o")


def page_triples(spark: SparkSession, d: str) -> DataFrame:
    tm = mapping.TriplesMap("pages", mapping.Template("cg:page/{page_id}"), (), (("cg:url", mapping.Literal("url")), ("cg:html", mapping.Literal("html"))))
    return mapping.apply(tm, {"pages": records.table(spark, d, "pages")})


def page_round_trip(spark: SparkSession, d: str) -> DataFrame:
    """URLs and pages through N-Triples text and back."""
    back = ntriples.parse(ntriples.lines(page_triples(spark, d)))
    return back.where("p = 'cg:html'").select(F.substring("s", 9, 40).cast("long").alias("page_id"), F.md5("o").alias("html_md5"))


def violations(spark: SparkSession, d: str) -> DataFrame:
    return Ontology().validate(spark, triples(spark, d)).agg(F.count("*").alias("violations"))


def planted_violations(spark: SparkSession, d: str) -> DataFrame:
    """Triples whose ends are turned round for every fifth patient, and begins that are nodes for every seventh order: each must be found, and nothing else."""
    t = triples(spark, d)
    actor = t.where("p = 'cg:hasActor' and o like 'cg:patient/%'").where("cast(substring(o, 12) as bigint) % 5 = 0").select("o", "p", "s").toDF("s", "p", "o").withColumn("o_kind", F.lit("iri"))
    begin = t.where("p = 'cg:hasBegin' and s like 'cg:event/O-%'").where("cast(substring(s, 12) as bigint) % 7 = 0").select("s", "p", "o", F.lit("iri").alias("o_kind"))
    own = t.select("s", "p", "o", "o_kind")
    return Ontology().validate(spark, own.unionByName(actor).unionByName(begin)).groupBy("p", "fault").agg(F.countDistinct("s", "o").alias("n"))


def qualitative(spark: SparkSession, d: str) -> DataFrame:
    df = records.dirty_lines(spark, d)
    return df.groupBy("prompt_raw", clean.normalize_qualitative(F.col("prompt_raw")).alias("prompt"), "l_linestatus").agg(F.count("*").alias("n"))


def units(spark: SparkSession, d: str) -> DataFrame:
    df = clean.convert_units(records.dirty_lines(spark, d), "value_raw", "unit_raw")
    return df.groupBy("unit_raw", "unit_std", "unit_known").agg(F.count("*").alias("n"), F.round(F.sum("value_std"), 2).alias("total"))


def missing(spark: SparkSession, d: str) -> DataFrame:
    df = clean.missing(records.dirty_lines(spark, d), {"quantity_raw": "null"})
    return df.groupBy(F.col("quantity_raw").cast("int").alias("quantity")).agg(F.count("*").alias("n"))


def intervals(spark: SparkSession, d: str) -> DataFrame:
    li, o = records.table(spark, d, "lineitem", "l_orderkey", "l_shipdate"), records.table(spark, d, "orders", "o_orderkey", "o_orderdate")
    df = clean.repair_interval(li.join(o, F.col("l_orderkey") == F.col("o_orderkey")), "o_orderdate", "l_shipdate")
    return df.groupBy("repaired").agg(F.count("*").alias("n"), F.min(F.datediff("l_shipdate", "o_orderdate")).alias("least_days"))


def spellings(spark: SparkSession, d: str) -> DataFrame:
    return clean.cluster_spellings(records.mentions(spark, d), "mention").select("key", "canonical", "spellings", F.col("rows").alias("n"))


def report(spark: SparkSession, d: str) -> DataFrame:
    df = records.dirty_lines(spark, d)
    rules = {"quantity missing": clean.null_missing(F.col("quantity_raw")).isNull(), "prompt not standard": ~F.col("prompt_raw").isin("positive", "negative"), "unit not standard": F.col("unit_raw") != "g/L"}
    return clean.report(df, rules)


def merged(spark: SparkSession, d: str) -> DataFrame:
    """Cells taken apart and put together again."""
    items = clean.split_cell(records.packed_cells(spark, d), "labels_raw")
    return clean.merge_values(items.select("l_orderkey", "item"), "l_orderkey", "item")


def superclasses(spark: SparkSession, d: str) -> DataFrame:
    """The ontology's classes with the labels and types of ``part`` below Object."""
    part = records.table(spark, d, "part", "p_name", "p_type").distinct()
    more = part.select(F.inline(F.array(F.struct(F.col("p_name").alias("cls"), F.col("p_type").alias("parent")), F.struct(F.col("p_type").alias("cls"), F.lit("Object").alias("parent"))))).distinct()
    return Ontology().superclasses(spark, more=more)


def ego(spark: SparkSession, d: str) -> DataFrame:
    return mapping.ego(triples(spark, d), "cg:event/O-1").select(*TRIPLE)


QUERIES = {
    "w1_single_event": wide(workloads.W1),
    "w2_multi_event": wide(workloads.W2),
    "w3_temporal": counted(wide(workloads.W3)),
    "w3b_temporal_strict": counted(wide(workloads.W3B)),
    "w1_single_event_triples": by_triples(workloads.W1),
    "w2_multi_event_triples": by_triples(workloads.W2),
    "w3_temporal_triples": counted(by_triples(workloads.W3)),
    "w3b_temporal_strict_triples": counted(by_triples(workloads.W3B)),
    "w1_single_event_relational": lambda s, d: baseline.Relational(s, d).w1(),
    "w2_multi_event_relational": lambda s, d: baseline.Relational(s, d).w2(),
    "w3_temporal_relational": lambda s, d: baseline.Relational(s, d).w3(),
    "w3b_temporal_strict_relational": lambda s, d: baseline.Relational(s, d).w3(strict=True),
    "w4_cooccurrence": lambda s, d: workloads.cooccurrence(workloads.labelled(s, d)),
    "w5_effectiveness": lambda s, d: workloads.effectiveness(workloads.labelled(s, d)),
    "w6_side_effects": lambda s, d: workloads.side_effects(workloads.labelled(s, d)),
    "w7_timeline": lambda s, d: workloads.status(store.events(s, d)),
    "w8_features": lambda s, d: workloads.features(store.events(s, d)),
    "w9_category_type": lambda s, d: workloads.on_drug(workloads.labelled(s, d), "type", "PROMO"),
    "w9_category_brand": lambda s, d: workloads.on_drug(workloads.labelled(s, d), "brand", "Brand#2"),
    "w9_category_expanded": lambda s, d: pattern.exec_wide(pattern.Pattern().event("rx", "drug", names=vocab.expand(vocab.edges(s, d), "Brand#2")), workloads.labelled(s, d), records.patients(s, d)),
    "w9_region": workloads.by_region,
    "w3_temporal_edges": counted(by_edges(workloads.W3, "all")),
    "w3_temporal_closure": counted(by_edges(workloads.W3, "closure")),
    "a11_costs": costs_compared,
    "w10_stage_counts": stage_counts,
    **{f"build_{t}": rebuilt(t) for t in ("event", "triple", "relation")},
    "w12_statistics": statistics,
    "a1_triples": all_triples,
    "triples_clinical": lambda s, d: triples(s, d).select(*TRIPLE),
    "triples_by_predicate": lambda s, d: triples(s, d).groupBy("class", "p").agg(F.count("*").alias("triples")),
    "triples_to_wide": wide_again,
    "ref_object_map": referenced,
    "ntriples_text": lambda s, d: ntriples.lines(triples(s, d).where("class = 'event' and p = 'cg:hasActor'")),
    "ntriples_round_trip": page_round_trip,
    "ego_triples_one_event": ego,
    "ont_superclasses": superclasses,
    "violations_domain_range": violations,
    "violations_domain_range_planted": planted_violations,
    "clean_missing": missing,
    "clean_qualitative": qualitative,
    "clean_units": units,
    "clean_split_cell": lambda s, d: clean.split_cell(records.packed_cells(s, d), "labels_raw").select("l_orderkey", F.col("pos").cast("long").alias("pos"), "item"),
    "clean_split_document_lines": lambda s, d: clean.split_cell(records.table(s, d, "documents", "doc_id", "text"), "text", "\n").groupBy("doc_id").agg(F.count("*").alias("n")),
    "clean_merge_values": merged,
    "clean_spelling_clusters": spellings,
    "clean_interval_repair": intervals,
    "clean_report": report,
    **{f"direct_{t}": direct(t) for t in COLUMNS},
}

_LAB = "lb AS (SELECT ev.*, ent.label, ent.brand, ent.type FROM ev LEFT JOIN ent ON ev.entity_id = ent.entity_id)"
GRAPH = (EVENTS, ENTITIES, _LAB)
_W1 = sql(*GRAPH, body="SELECT DISTINCT patient_id FROM lb WHERE kind = 'diagnosis' AND label = 'red plate'")
_W2 = sql(
    *GRAPH,
    body="""SELECT c_custkey AS patient_id FROM customer WHERE c_mktsegment = 'BUILDING' AND c_custkey IN (SELECT patient_id FROM lb WHERE kind = 'diagnosis' AND type = 'PROMO')
    AND c_custkey IN (SELECT patient_id FROM lb WHERE kind = 'drug' AND label = 'hot ring') AND c_custkey IN (SELECT patient_id FROM lb WHERE kind = 'drug' AND label = 'red bolt')""",
)


def _w3(strict: str = "") -> str:
    return sql(
        *GRAPH,
        body=f"""SELECT count(DISTINCT dx.patient_id) AS patients FROM lb dx JOIN lb st ON st.patient_id = dx.patient_id AND st.kind = 'stay' AND st.begin_ts < st.end_ts AND dx.begin_ts BETWEEN st.begin_ts AND st.end_ts
        JOIN lb rx ON rx.patient_id = dx.patient_id AND rx.kind = 'drug' AND rx.type = 'ECONOMY' AND rx.begin_ts > dx.end_ts
        JOIN lb la ON la.patient_id = dx.patient_id AND la.kind = 'assay' AND la.prompt = 'F' AND la.begin_ts BETWEEN rx.begin_ts AND rx.end_ts
        WHERE dx.kind = 'diagnosis' AND dx.type = 'PROMO' AND dx.patient_id IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'MACHINERY') {strict}""",
    )


_W3 = _w3()
_W3B = _w3("AND EXISTS (SELECT 1 FROM lb bad WHERE bad.patient_id = la.patient_id AND bad.kind = 'assay' AND bad.prompt = 'O' AND bad.type = la.type AND bad.end_ts < la.begin_ts)")
_ISO = "strftime({}, '%Y-%m-%dT%H:%M:%S')"


def _event_triples() -> str:
    cls = "CASE kind WHEN 'stay' THEN 'StayEvent' WHEN 'diagnosis' THEN 'DiagnosisEvent' WHEN 'drug' THEN 'DrugEvent' WHEN 'assay' THEN 'AssayEvent' ELSE 'SurgeryEvent' END"
    e = "'cg:event/' || event_id"
    rows = [
        ("event", e, "rdf:type", f"'cg:' || {cls}", "iri", None, "ev"),
        ("event", e, "cg:hasBegin", _ISO.format("begin_ts"), "literal", "xsd:dateTime", "ev"),
        ("event", e, "cg:hasEnd", _ISO.format("end_ts"), "literal", "xsd:dateTime", "ev"),
        ("event", e, "cg:hasActor", "'cg:patient/' || patient_id", "iri", None, "ev"),
        ("event", e, "cg:hasActor", "'cg:entity/' || entity_id", "iri", None, "ev WHERE entity_id IS NOT NULL"),
        ("event", e, "cg:situation", "situation", "literal", "xsd:string", "ev WHERE situation IS NOT NULL"),
        ("event", e, "cg:assayPrompt", "prompt", "literal", "xsd:string", "ev WHERE prompt IS NOT NULL"),
        ("event", e, "cg:assayResult", "CAST(result AS VARCHAR)", "literal", "xsd:double", "ev WHERE result IS NOT NULL"),
        ("entity", "'cg:patient/' || c_custkey", "rdf:type", "'cg:Patient'", "iri", None, "customer"),
        ("entity", "'cg:patient/' || c_custkey", "cg:label", "c_name", "literal", "xsd:string", "customer"),
        ("entity", "'cg:patient/' || c_custkey", "cg:category", "c_mktsegment", "literal", "xsd:string", "customer"),
        ("entity", "'cg:entity/' || entity_id", "rdf:type", "'cg:' || CASE kind WHEN 'diagnosis' THEN 'Disease' WHEN 'drug' THEN 'Drug' WHEN 'assay' THEN 'Assay' ELSE 'Surgery' END", "iri", None, "ent"),
        ("entity", "'cg:entity/' || entity_id", "cg:label", "label", "literal", "xsd:string", "ent"),
        ("entity", "'cg:entity/' || entity_id", "cg:broaderBrand", "brand", "literal", "xsd:string", "ent"),
        ("entity", "'cg:entity/' || entity_id", "cg:broaderType", "type", "literal", "xsd:string", "ent"),
    ]
    return "tr AS (" + " UNION ALL ".join(f"SELECT '{c}' AS class, {s} AS s, '{p}' AS p, {o} AS o, '{k}' AS o_kind, {'NULL' if t is None else repr(t)} AS datatype, CAST(NULL AS VARCHAR) AS lang FROM {f}" for c, s, p, o, k, t, f in rows) + ")"


TRIPLES = (EVENTS, ENTITIES, _event_triples())
_ACCEPTED_LINKS = f"WITH {ACCEPTED} SELECT count(*) AS n FROM ac WHERE accepted"
_DIRTY = """dl AS (SELECT *, CASE WHEN l_linestatus = 'F' THEN 'negative' ELSE 'positive' END AS w, CASE WHEN l_linestatus = 'F' THEN '-' ELSE '+' END AS sg FROM lineitem),
dd AS (SELECT *, CASE l_linenumber % 4 WHEN 0 THEN w WHEN 1 THEN w || ' (' || sg || ')' WHEN 2 THEN '(' || sg || ')' ELSE sg END AS prompt_raw, CASE WHEN l_suppkey % 2 = 0 THEN 'g/dL' ELSE 'g/L' END AS unit_raw FROM dl)"""
_CELL = "ce AS (SELECT l_orderkey, list(replace(p_name, ' ', '_') ORDER BY replace(p_name, ' ', '_')) AS names FROM li JOIN part ON p_partkey = l_partkey WHERE kind = 'diagnosis' GROUP BY 1)"

SQL = {
    "w1_single_event": _W1,
    "w2_multi_event": _W2,
    "w3_temporal": _W3,
    "w3b_temporal_strict": _W3B,
    **{f"{k}_{v}": q for k, q in (("w1_single_event", _W1), ("w2_multi_event", _W2), ("w3_temporal", _W3), ("w3b_temporal_strict", _W3B)) for v in ("triples", "relational")},
    "w3_temporal_edges": _W3,
    "w3_temporal_closure": _W3,
    "build_event": sql(EVENTS, body="SELECT 'event' AS \"table\", count(*) AS rows FROM ev"),
    "build_triple": sql(*TRIPLES, body="SELECT 'triple' AS \"table\", count(*) AS rows FROM tr"),
    "build_relation": sql(EVENTS, RELATIONS, body="SELECT 'relation' AS \"table\", count(*) AS rows FROM rel"),
    "w10_stage_counts": sql(*TRIPLES, RELATIONS, body=f"SELECT 'cleaned' AS stage, count(*) AS rows FROM lineitem UNION ALL SELECT 'events', count(*) FROM ev UNION ALL SELECT 'triples', count(*) FROM tr UNION ALL SELECT 'relations', count(*) FROM rel UNION ALL SELECT 'links', n FROM ({_ACCEPTED_LINKS})"),
    "w4_cooccurrence": sql(
        *GRAPH,
        "f AS (SELECT patient_id, type AS assay_type, min(begin_ts) AS since FROM lb WHERE kind = 'assay' AND prompt = 'O' GROUP BY 1, 2)",
        "dx AS (SELECT patient_id, label, max(begin_ts) AS last FROM lb WHERE kind = 'diagnosis' GROUP BY 1, 2)",
        "m AS (SELECT assay_type, label, count(*) AS patients FROM f JOIN dx USING (patient_id) WHERE last > since GROUP BY 1, 2)",
        body="""SELECT * FROM (SELECT assay_type, m.label, patients, round((patients / s.n) / (b.n / (SELECT count(DISTINCT patient_id) FROM ev)), 6) AS lift, row_number() OVER (PARTITION BY assay_type ORDER BY patients DESC, m.label) AS rank
          FROM m JOIN (SELECT assay_type, count(*) AS n FROM f GROUP BY 1) s USING (assay_type) JOIN (SELECT label, count(*) AS n FROM dx GROUP BY 1) b ON b.label = m.label) WHERE rank <= 5""",
    ),
    "w5_effectiveness": sql(
        *GRAPH,
        "x AS (SELECT patient_id, kind, type, last_value(prompt IGNORE NULLS) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS was, first_value(prompt IGNORE NULLS) OVER (w ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS nxt FROM lb WHERE kind IN ('assay', 'drug') WINDOW w AS (PARTITION BY patient_id ORDER BY begin_ts, kind = 'assay', event_id))",
        body="SELECT type, count(DISTINCT patient_id) AS abnormal, count(DISTINCT patient_id) FILTER (WHERE nxt = 'F') AS turned, round(count(DISTINCT patient_id) FILTER (WHERE nxt = 'F') / count(DISTINCT patient_id), 6) AS share FROM x WHERE kind = 'drug' AND was = 'O' GROUP BY 1",
    ),
    "w6_side_effects": sql(*GRAPH, "f AS (SELECT patient_id, kind, type, min(begin_ts) AS t FROM lb GROUP BY 1, 2, 3)", body="SELECT a.type AS drug_type, b.type AS diagnosis_type, count(*) AS patients FROM f a JOIN f b USING (patient_id) WHERE a.kind = 'drug' AND b.kind = 'diagnosis' AND b.t >= a.t GROUP BY 1, 2"),
    "w7_timeline": sql(EVENTS, body="SELECT patient_id, event_id, row_number() OVER w AS pos, datediff('day', lag(begin_ts) OVER w, begin_ts) AS gap_days, count(*) OVER (PARTITION BY patient_id, kind ORDER BY begin_ts, event_id) AS so_far FROM ev WINDOW w AS (PARTITION BY patient_id ORDER BY begin_ts, event_id)"),
    "w8_features": sql(
        EVENTS,
        body="""SELECT patient_id, count(*) FILTER (WHERE kind = 'stay') AS n_stay, count(*) FILTER (WHERE kind = 'diagnosis') AS n_diagnosis, count(*) FILTER (WHERE kind = 'drug') AS n_drug, count(*) FILTER (WHERE kind = 'assay') AS n_assay,
        count(*) FILTER (WHERE kind = 'surgery') AS n_surgery, round(count(*) FILTER (WHERE kind = 'assay' AND prompt = 'O') / nullif(count(*) FILTER (WHERE kind = 'assay'), 0), 6) AS abnormal_rate,
        round(avg(CASE WHEN kind = 'stay' THEN datediff('day', begin_ts, end_ts) END), 6) AS mean_stay_days, datediff('day', max(begin_ts), (SELECT max(begin_ts) FROM ev)) AS days_since_last FROM ev GROUP BY 1""",
    ),
    "w9_category_type": sql(*GRAPH, body="SELECT DISTINCT patient_id FROM lb WHERE kind = 'drug' AND type = 'PROMO'"),
    "w9_category_brand": sql(*GRAPH, body="SELECT DISTINCT patient_id FROM lb WHERE kind = 'drug' AND brand = 'Brand#2'"),
    "w9_category_expanded": sql(*GRAPH, body="SELECT DISTINCT patient_id FROM lb WHERE kind = 'drug' AND label IN (SELECT p_name FROM part WHERE p_brand = 'Brand#2')"),
    "w9_region": "SELECT r_name AS region, count(*) AS patients FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
    "w12_statistics": sql(
        EVENTS,
        RELATIONS,
        body="SELECT 'events ' || kind AS measure, count(*) AS n FROM ev GROUP BY kind UNION ALL SELECT 'entities ' || coalesce(kind, 'all'), count(DISTINCT entity_id) FROM ev WHERE entity_id IS NOT NULL GROUP BY ROLLUP (kind) UNION ALL SELECT 'relations ' || coalesce(relation, 'total'), count(*) FROM rel GROUP BY ROLLUP (relation)",
    ),
    "a1_triples": sql(*TRIPLES, RELATIONS, body="SELECT class, p, count(*) AS triples FROM tr GROUP BY ALL UNION ALL SELECT 'temporal', 'cg:' || relation, count(*) FROM rel GROUP BY relation UNION ALL SELECT 'link', 'cg:linkedTo', n FROM (" + _ACCEPTED_LINKS + ")"),
    "triples_by_predicate": sql(*TRIPLES, body="SELECT class, p, count(*) AS triples FROM tr GROUP BY ALL"),
    "triples_clinical": sql(*TRIPLES, body="SELECT s, p, o, o_kind, datatype, lang FROM tr"),
    "triples_to_wide": sql(EVENTS, body="SELECT event_id, " + _ISO.format("begin_ts") + " AS begin, situation FROM ev WHERE kind = 'diagnosis'"),
    "ref_object_map": "SELECT 'cg:nation/' || n_nationkey AS s, 'cg:within' AS p, 'cg:region/' || replace(r_name, ' ', '%20') AS o FROM nation JOIN region ON n_regionkey = r_regionkey",
    "ntriples_text": sql(*TRIPLES, body="SELECT '<urn:caregraph:' || s[4:] || '> <urn:caregraph:hasActor> <urn:caregraph:' || o[4:] || '> .' AS value FROM tr WHERE class = 'event' AND p = 'cg:hasActor'"),
    "ntriples_round_trip": "SELECT page_id, md5(html) AS html_md5 FROM pages WHERE html IS NOT NULL",
    "ego_triples_one_event": sql(*TRIPLES, body="SELECT s, p, o, o_kind, datatype, lang FROM tr WHERE s = 'cg:event/O-1' OR o = 'cg:event/O-1'"),
    "violations_domain_range": "SELECT CAST(0 AS BIGINT) AS violations",
    "ont_superclasses": "WITH RECURSIVE c(cls, parent) AS (VALUES ('Actor', 'Thing'), ('Object', 'Actor'), ('Event', 'Thing'), ('Patient', 'Actor'), ('Disease', 'Object'), ('Drug', 'Object'), ('Assay', 'Object'), ('Surgery', 'Object'), ('StayEvent', 'Event'), ('DiagnosisEvent', 'Event'), ('DrugEvent', 'Event'), ('AssayEvent', 'Event'), ('SurgeryEvent', 'Event') UNION SELECT p_name, p_type FROM part UNION SELECT p_type, 'Object' FROM part), up AS (SELECT cls, parent AS super, 1 AS steps FROM c UNION ALL SELECT up.cls, c.parent, steps + 1 FROM up JOIN c ON c.cls = up.super) SELECT DISTINCT * FROM up",
    "violations_domain_range_planted": sql(EVENTS, body="SELECT 'cg:hasActor' AS p, fault, count(*) AS n FROM ev CROSS JOIN (SELECT unnest(['domain', 'range']) AS fault) WHERE patient_id % 5 = 0 GROUP BY 2 UNION ALL SELECT 'cg:hasBegin', 'range', count(*) FROM orders WHERE o_orderkey % 7 = 0"),
    "clean_spelling_clusters": f"""WITH {MENTIONS}, f AS (SELECT mention, array_to_string(list_sort(list_distinct(list_filter(regexp_split_to_array(regexp_replace(lower(mention), '[^a-z0-9 ]', '', 'g'), ' +'), lambda w: w <> ''))), ' ') AS key FROM men),
      g AS (SELECT key, mention AS v, count(*) AS n FROM f GROUP BY 1, 2) SELECT key, arg_min(v, (-n, v)) AS canonical, count(*) AS spellings, CAST(sum(n) AS BIGINT) AS n FROM g GROUP BY 1""",
    "clean_missing": "SELECT CASE WHEN l_orderkey % 50 > 3 THEN CAST(l_quantity AS INTEGER) END AS quantity, count(*) AS n FROM lineitem GROUP BY 1",
    "clean_qualitative": f"WITH {_DIRTY} SELECT prompt_raw, w AS prompt, l_linestatus, count(*) AS n FROM dd GROUP BY ALL",
    "clean_units": f"WITH {_DIRTY} SELECT unit_raw, 'g/L' AS unit_std, TRUE AS unit_known, count(*) AS n, round(sum(l_extendedprice * 10), 2) AS total FROM dd GROUP BY unit_raw",
    "clean_split_cell": sql(LINES, _CELL, body="SELECT l_orderkey, unnest(range(len(names))) AS pos, unnest(names) AS item FROM ce"),
    "clean_split_document_lines": "SELECT doc_id, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents) WHERE trim(l) <> '' GROUP BY 1",
    "clean_merge_values": sql(LINES, _CELL, body="SELECT l_orderkey, array_to_string(names, ';') AS item FROM ce"),
    "clean_interval_repair": "SELECT l_shipdate < o_orderdate AS repaired, count(*) AS n, CAST(min(greatest(datediff('day', o_orderdate, l_shipdate), 0)) AS INTEGER) AS least_days FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
    "clean_report": "SELECT 'quantity missing' AS rule, count(*) FILTER (WHERE l_orderkey % 50 < 4) AS violations, count(*) AS rows FROM lineitem UNION ALL SELECT 'prompt not standard', count(*) FILTER (WHERE l_linenumber % 4 <> 0), count(*) FROM lineitem UNION ALL SELECT 'unit not standard', count(*) FILTER (WHERE l_suppkey % 2 = 0), count(*) FROM lineitem",
    **{f"direct_{t}": direct_sql(t, c) for t, c in COLUMNS.items()},
}
