"""Queries on events, entities and temporal relations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph import store
from caregraph.operators import baseline, events, inference, profile, relations, timeline
from caregraph.queries.base import CONCURRENT, ENTITIES, EVENTS, LINES, RELATIONS, STABBED, bounds, sql

EDGE = ("patient_id", "src", "dst", "relation", "step")


def ev(spark: SparkSession, d: str) -> DataFrame:
    return store.events(spark, d)


def rel(spark: SparkSession, d: str, **options) -> DataFrame:
    """Made anew from the stored events."""
    return relations.build(ev(spark, d), **options).select(*EDGE)


def counts(df: DataFrame) -> DataFrame:
    return df.groupBy("relation", "step").agg(F.count("*").alias("edges"))


def ev_rows(spark: SparkSession, d: str) -> DataFrame:
    return events.extract(spark, d)


def cube(spark: SparkSession, d: str) -> DataFrame:
    return ev(spark, d).cube("kind", "time_kind").agg(F.count("*").alias("events"), F.grouping_id().cast("int").alias("level"))


def small_profile(name: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return events.extract(spark, d, name).select("event_id", "patient_id", "kind", "entity_id", "begin_ts", "end_ts", "time_kind", "result")

    return run


def clicks_day(spark: SparkSession, d: str) -> DataFrame:
    day = events.extract(spark, d, "clicks", "day").where("kind <> 'drug'")
    return relations.build(day, density="chain", inverse=False).groupBy("relation").agg(F.count("*").alias("edges"))


def dialogue_edges(spark: SparkSession, d: str) -> DataFrame:
    return relations.before(events.extract(spark, d, "dialogue"))


def allen13(spark: SparkSession, d: str) -> DataFrame:
    """How often each of Allen's relations holds between events of one stay, with the stored relation."""
    e = ev(spark, d)
    a = e.where("kind <> 'stay'").select("patient_id", "stay_id", "begin_ts", "end_ts")
    b = e.where("kind = 'stay'").select(F.col("event_id").alias("stay_id"), F.col("begin_ts").alias("bb"), F.col("end_ts").alias("be"))
    both = a.join(b, "stay_id")
    span = ("begin_ts", "end_ts", "bb", "be")
    return both.groupBy(timeline.allen(*map(F.col, span)).alias("allen"), timeline.relation_of(*map(F.col, span)).alias("relation")).agg(F.count("*").alias("pairs"))


def timeline_ranks(spark: SparkSession, d: str) -> DataFrame:
    return timeline.ranked(ev(spark, d)).select("event_id", F.col("grp").cast("long").alias("grp"), F.col("pos").cast("long").alias("pos"), "n_p")


def full_counts(spark: SparkSession, d: str) -> DataFrame:
    return relations.full_before(ev(spark, d)).groupBy("step").agg(F.count("*").alias("edges"))


def closure_of_reduced(spark: SparkSession, d: str) -> DataFrame:
    """The closure of the reduced edges, counted: it's all of Before."""
    some = events.extract(spark, d, "clicks")
    return inference.closure(relations.build(some, inverse=False)).groupBy("patient_id").agg(F.count("*").alias("pairs"))


def derived(spark: SparkSession, d: str) -> DataFrame:
    return inference.derived(store.relations(spark, d)).groupBy("relation", "rule").agg(F.count("*").alias("edges"))


def fixpoint(spark: SparkSession, d: str) -> DataFrame:
    """All that the sparsest stored form implies, counted: as much as the times say."""
    some = events.extract(spark, d, "clicks")
    return inference.fixpoint(relations.build(some, density="chain")).groupBy("relation").agg(F.count("*").alias("edges"))


def planted(spark: SparkSession, d: str) -> DataFrame:
    """Edges of the dialogue profile, where every seventh has an end in the next conversation: all of these must be found."""
    e = events.extract(spark, d, "dialogue")
    r = relations.before(e)
    broken = F.concat_ws("-", F.lit("T"), F.col("patient_id") + 1, F.substring_index("dst", "-", -1))
    r = r.withColumn("dst", F.when(F.pmod("patient_id", F.lit(7)) == 0, broken).otherwise(F.col("dst")))
    return relations.assert_same_patient(r, e)


CLICKS = """
ck AS (SELECT 'E-' || event_id AS event_id, user_id AS patient_id,
         CASE event_type WHEN 'signup' THEN 'stay' WHEN 'error' THEN 'diagnosis' WHEN 'purchase' THEN 'drug' WHEN 'view' THEN 'assay' WHEN 'click' THEN 'surgery' END AS kind,
         json_extract_string(props, '$.k') AS k, ts AS begin_ts,
         CASE WHEN event_type = 'purchase' THEN ts + to_microseconds(CAST(round(value * 3600000000) AS BIGINT)) ELSE ts END AS end_ts,
         CASE WHEN event_type = 'view' THEN value END AS result FROM events),
ev AS (SELECT *, kind || '-' || k AS entity_id, CASE WHEN begin_ts = end_ts THEN 'point' ELSE 'period' END AS time_kind FROM ck)"""

QUERIES = {
    "ent_patients": lambda s, d: events.patient_entities(s, d).select("entity_id", "kind", "label", "category"),
    "ent_objects": events.entities,
    "ev_rows": ev_rows,
    "ev_by_kind": lambda s, d: profile.events(ev(s, d)),
    "ev_by_kind_timeclass_cube": cube,
    "ev_clicks_profile": small_profile("clicks"),
    "ev_dialogue_profile": small_profile("dialogue"),
    "ev_timeline_ranks": timeline_ranks,
    "rel_reduced_counts": lambda s, d: counts(rel(s, d)),
    "rel_step1": lambda s, d: relations.steps(ev(s, d), 1).select(*EDGE),
    "rel_step2": lambda s, d: relations.steps(ev(s, d), 2).select(*EDGE),
    "rel_step3": lambda s, d: relations.steps(ev(s, d), 3).select(*EDGE),
    "rel_step4": lambda s, d: relations.steps(ev(s, d), 4).select(*EDGE),
    "rel_full_counts": full_counts,
    "rel_reduced": lambda s, d: relations.before(ev(s, d)),
    "rel_reduced_per_step": lambda s, d: relations.before(ev(s, d), scope="per_step"),
    "rel_chain": lambda s, d: rel(s, d, density="chain", wanted=("Before", "Concurrent")),
    "rel_inverse": lambda s, d: rel(s, d, wanted=("Before", "After")).groupBy("relation").agg(F.count("*").alias("edges")),
    "rel_allen13": allen13,
    "rel_equal_end_during": lambda s, d: rel(s, d, equal_end="during").groupBy("relation").agg(F.count("*").alias("edges")),
    "rel_equal_ends": lambda s, d: relations.equal_ends(ev(s, d)),
    "rel_redundancy": lambda s, d: relations.redundancy(ev(s, d)),
    "rel_bruteforce_reduction": lambda s, d: baseline.reduce_bruteforce(events.extract(s, d, "clicks")),
    "rel_closure": closure_of_reduced,
    "rel_derived": derived,
    "rel_fixpoint": fixpoint,
    "rel_bruteforce_reduction_commerce": lambda s, d: baseline.reduce_bruteforce(ev(s, d)),
    "violations_planted": planted,
    "rel_clicks_day": clicks_day,
    "rel_dialogue_chain": dialogue_edges,
    "violations_same_patient": lambda s, d: relations.assert_same_patient(store.relations(s, d), ev(s, d)).agg(F.count("*").alias("violations")),
    "a2_relations": lambda s, d: profile.relations(store.relations(s, d)),
    "a3_events": lambda s, d: profile.events(ev(s, d)),
    "a4_entities": lambda s, d: profile.entities(ev(s, d)),
    "a5_records": profile.records,
    "a10_per_patient": lambda s, d: profile.per_patient(ev(s, d), store.relations(s, d)),
    "op_agg_approx_distinct": lambda s, d: profile.entities(ev(s, d), approx=True),
    "op_agg_hll": lambda s, d: profile.entity_sketch(ev(s, d)),
    "op_agg_kll": lambda s, d: profile.result_quantiles(ev(s, d)),
    "op_agg_sketches_close": lambda s, d: profile.sketches(ev(s, d)),
    "op_agg_kll_close": lambda s, d: profile.quantiles_close(ev(s, d)),
}

_STEP = "SELECT * FROM rel WHERE step = {}"
_BY_KIND = "SELECT kind, count(*) AS events FROM ev GROUP BY kind"

SQL = {
    "ent_patients": "SELECT 'patient-' || c_custkey AS entity_id, 'patient' AS kind, c_name AS label, c_mktsegment AS category FROM customer",
    "ent_objects": sql(LINES, ENTITIES, body="SELECT * FROM ent"),
    "ev_rows": sql(EVENTS, body="SELECT * FROM ev"),
    "ev_by_kind": sql(EVENTS, body=_BY_KIND),
    "ev_by_kind_timeclass_cube": sql(EVENTS, body="SELECT kind, time_kind, count(*) AS events, CAST(grouping(kind, time_kind) AS INTEGER) AS level FROM ev GROUP BY CUBE (kind, time_kind)"),
    "ev_clicks_profile": sql(CLICKS, body="SELECT event_id, patient_id, kind, entity_id, begin_ts, end_ts, time_kind, result FROM ev"),
    "ev_dialogue_profile": "SELECT concat_ws('-', 'T', conv_id, turn) AS event_id, conv_id AS patient_id, role AS kind, CAST(NULL AS VARCHAR) AS entity_id, TIMESTAMP '1970-01-01' + to_seconds(turn) AS begin_ts, TIMESTAMP '1970-01-01' + to_seconds(turn) AS end_ts, 'point' AS time_kind, CAST(NULL AS DOUBLE) AS result FROM conversations",
    "ev_timeline_ranks": sql(EVENTS, body="SELECT event_id, dense_rank() OVER (PARTITION BY patient_id ORDER BY begin_ts) AS grp, row_number() OVER (PARTITION BY patient_id ORDER BY begin_ts, end_ts, event_id) AS pos, count(*) OVER (PARTITION BY patient_id) AS n_p FROM ev"),
    "rel_reduced_counts": sql(EVENTS, RELATIONS, body="SELECT relation, step, count(*) AS edges FROM rel GROUP BY ALL"),
    **{f"rel_step{k}": sql(EVENTS, RELATIONS, body=_STEP.format(k)) for k in (1, 2, 3, 4)},
    "rel_full_counts": sql(EVENTS, body="SELECT CASE WHEN a.time_kind = 'point' AND b.time_kind = 'point' THEN 1 WHEN a.time_kind = 'period' AND b.time_kind = 'period' THEN 2 ELSE 3 END AS step, count(*) AS edges FROM ev a JOIN ev b ON a.patient_id = b.patient_id AND a.end_ts < b.begin_ts GROUP BY 1"),
    "rel_reduced": sql(EVENTS, bounds("bef", "ev"), body="SELECT * FROM bef"),
    "rel_reduced_per_step": sql(
        EVENTS,
        "pt AS (SELECT * FROM ev WHERE time_kind = 'point')",
        "pd AS (SELECT * FROM ev WHERE time_kind = 'period')",
        bounds("b1", "pt"),
        bounds("b2", "pd"),
        bounds("b3", "ev"),
        body="SELECT * FROM b1 UNION ALL SELECT * FROM b2 UNION ALL SELECT * FROM b3 WHERE step = 3",
    ),
    "rel_chain": sql(
        EVENTS,
        "rep AS (SELECT * FROM ev QUALIFY row_number() OVER (PARTITION BY patient_id, begin_ts, end_ts ORDER BY event_id) = 1)",
        bounds("bef", "rep"),
        "lk AS (SELECT patient_id, lag(event_id) OVER (PARTITION BY patient_id, begin_ts, end_ts ORDER BY event_id) AS src, event_id AS dst, CASE WHEN time_kind = 'point' THEN 1 ELSE 2 END AS step FROM ev)",
        body="SELECT patient_id, src, dst, 'Before' AS relation, step FROM bef UNION ALL SELECT patient_id, src, dst, 'Concurrent', step FROM lk WHERE src IS NOT NULL",
    ),
    "rel_inverse": sql(EVENTS, RELATIONS, body="SELECT relation, count(*) AS edges FROM rel WHERE relation IN ('Before', 'After') GROUP BY 1"),
    "rel_allen13": sql(
        EVENTS,
        "p AS (SELECT a.begin_ts ab, a.end_ts ae, b.begin_ts bb, b.end_ts be FROM ev a JOIN ev b ON a.stay_id = b.event_id WHERE a.kind <> 'stay')",
        body="""SELECT CASE WHEN ae < bb THEN 'before' WHEN ab > be THEN 'after' WHEN ab = bb AND ae = be THEN 'equal' WHEN ab = bb THEN (CASE WHEN ae < be THEN 'starts' ELSE 'started_by' END)
            WHEN ae = be THEN (CASE WHEN ab > bb THEN 'finishes' ELSE 'finished_by' END) WHEN ae = bb THEN 'meets' WHEN ab = be THEN 'met_by' WHEN ab > bb AND ae < be THEN 'during'
            WHEN ab < bb AND ae > be THEN 'contains' WHEN ab < bb THEN 'overlaps' ELSE 'overlapped_by' END AS allen,
          CASE WHEN ae < bb THEN 'Before' WHEN ab > be THEN 'After' WHEN ab = bb AND ae = be THEN 'Concurrent'
            WHEN bb < be AND ab BETWEEN bb AND be AND (ae < be OR (ab = ae AND ab = be)) THEN 'During'
            WHEN ab < ae AND bb < be AND ab > bb AND ab <= be AND ae > be THEN 'Overlap' END AS relation, count(*) AS pairs FROM p GROUP BY ALL""",
    ),
    "rel_equal_end_during": sql(EVENTS, bounds("bef", "ev"), CONCURRENT, STABBED, body="SELECT 'Before' AS relation, count(*) AS edges FROM bef UNION ALL SELECT 'After', count(*) FROM bef UNION ALL SELECT 'Concurrent', count(*) FROM con UNION ALL SELECT CASE WHEN finishes THEN 'During' ELSE relation END AS r, count(*) FROM stab WHERE relation IS NOT NULL OR finishes GROUP BY r"),
    "rel_equal_ends": sql(EVENTS, body="SELECT a.patient_id, a.event_id AS src, b.event_id AS dst FROM ev a JOIN ev b USING (patient_id, end_ts) WHERE a.time_kind = 'period' AND b.time_kind = 'period' AND a.begin_ts > b.begin_ts"),
    "rel_redundancy": sql(
        EVENTS,
        bounds("bef", "ev"),
        body="SELECT patient_id, f AS full_edges, coalesce(r, 0) AS reduced_edges FROM (SELECT e.patient_id, count(b.event_id) AS f FROM ev e LEFT JOIN ev b ON e.patient_id = b.patient_id AND e.end_ts < b.begin_ts GROUP BY 1) LEFT JOIN (SELECT patient_id, count(*) AS r FROM bef GROUP BY 1) USING (patient_id)",
    ),
    "rel_bruteforce_reduction": sql(CLICKS, bounds("bef", "ev"), body="SELECT patient_id, src, dst FROM bef"),
    "rel_closure": sql(CLICKS, body="SELECT a.patient_id, count(*) AS pairs FROM ev a JOIN ev b ON a.patient_id = b.patient_id AND a.end_ts < b.begin_ts GROUP BY 1"),
    "rel_derived": sql(
        EVENTS,
        RELATIONS,
        "same AS (SELECT patient_id, src, dst FROM con UNION SELECT patient_id, dst, src FROM con)",
        "du AS (SELECT patient_id, src AS i, dst AS o FROM stab WHERE relation = 'During')",
        body="""SELECT 'Concurrent' AS relation, 'symmetric' AS rule, count(*) AS edges FROM same
          UNION ALL SELECT 'Before', 'substitute', count(*) FROM (SELECT DISTINCT b.src, s.dst FROM bef b JOIN same s ON s.patient_id = b.patient_id AND s.src = b.dst)
          UNION ALL SELECT 'Before', 'inside_before', count(*) FROM (SELECT DISTINCT du.i, b.dst FROM du JOIN bef b ON b.patient_id = du.patient_id AND b.src = du.o)
          UNION ALL SELECT 'Before', 'before_inside', count(*) FROM (SELECT DISTINCT b.src, du.i FROM bef b JOIN du ON b.patient_id = du.patient_id AND b.dst = du.o)""",
    ),
    "rel_fixpoint": sql(
        CLICKS,
        "p AS (SELECT CASE WHEN a.end_ts < b.begin_ts THEN 'Before' WHEN a.begin_ts = b.begin_ts AND a.end_ts = b.end_ts THEN (CASE WHEN a.event_id < b.event_id THEN 'Concurrent' END) WHEN b.begin_ts < b.end_ts AND a.begin_ts BETWEEN b.begin_ts AND b.end_ts AND (a.end_ts < b.end_ts OR (a.begin_ts = a.end_ts AND a.begin_ts = b.end_ts)) THEN 'During' WHEN a.begin_ts < a.end_ts AND b.begin_ts < b.end_ts AND a.begin_ts > b.begin_ts AND a.begin_ts <= b.end_ts AND a.end_ts > b.end_ts THEN 'Overlap' END AS relation FROM ev a JOIN ev b ON a.patient_id = b.patient_id AND a.event_id <> b.event_id)",
        body="SELECT relation, count(*) AS edges FROM p WHERE relation IS NOT NULL GROUP BY 1 UNION ALL SELECT 'After', count(*) FROM p WHERE relation = 'Before'",
    ),
    "rel_bruteforce_reduction_commerce": sql(EVENTS, bounds("bef", "ev"), body="SELECT patient_id, src, dst FROM bef"),
    "violations_planted": "SELECT c AS patient_id, 'T-' || c || '-' || t AS src, 'T-' || (c + 1) || '-' || n AS dst FROM (SELECT conv_id AS c, turn AS t, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS n FROM conversations) WHERE n IS NOT NULL AND c % 7 = 0",
    "rel_clicks_day": sql(
        "ev AS (SELECT 'E-' || event_id AS event_id, user_id AS patient_id, date_trunc('day', ts) AS begin_ts, date_trunc('day', ts) AS end_ts, 'point' AS time_kind FROM events WHERE event_type <> 'purchase')",
        "rep AS (SELECT * FROM ev QUALIFY row_number() OVER (PARTITION BY patient_id, begin_ts ORDER BY event_id) = 1)",
        bounds("bef", "rep"),
        body="SELECT 'Before' AS relation, count(*) AS edges FROM bef UNION ALL SELECT 'Concurrent', (SELECT count(*) FROM ev) - (SELECT count(*) FROM rep)",
    ),
    "rel_dialogue_chain": sql(
        "t AS (SELECT conv_id AS patient_id, concat_ws('-', 'T', conv_id, turn) AS dst, lag(concat_ws('-', 'T', conv_id, turn)) OVER (PARTITION BY conv_id ORDER BY turn) AS src FROM conversations)",
        body="SELECT patient_id, src, dst, 1 AS step FROM t WHERE src IS NOT NULL",
    ),
    "violations_same_patient": "SELECT CAST(0 AS BIGINT) AS violations",
    "a2_relations": sql(EVENTS, RELATIONS, body="SELECT coalesce(relation, 'total') AS relation, count(*) AS edges FROM rel GROUP BY ROLLUP (relation)"),
    "a3_events": sql(EVENTS, body=_BY_KIND),
    "a4_entities": sql(EVENTS, body="SELECT coalesce(kind, 'all') AS kind, count(DISTINCT entity_id) AS entities FROM ev WHERE entity_id IS NOT NULL GROUP BY ROLLUP (kind)"),
    "op_agg_sketches_close": sql(EVENTS, body="SELECT coalesce(kind, 'all') AS kind, count(DISTINCT entity_id) AS entities, TRUE AS approx_close, TRUE AS sketch_close FROM ev WHERE entity_id IS NOT NULL GROUP BY ROLLUP (kind)"),
    "op_agg_kll_close": sql(EVENTS, body="SELECT CAST(q AS INTEGER) AS q, count(result) AS results, TRUE AS close FROM ev CROSS JOIN (SELECT unnest([25, 50, 75]) AS q) WHERE kind = 'assay' GROUP BY 1"),
    "a5_records": sql(EVENTS, body="SELECT 'patient' AS record, count(*) AS n FROM customer UNION ALL SELECT kind, count(*) FROM ev GROUP BY kind"),
    "a10_per_patient": sql(
        EVENTS,
        RELATIONS,
        body="SELECT patient_id, e AS events, coalesce(r, 0) AS edges, round(coalesce(r, 0) / e, 6) AS density, l AS chain_length FROM (SELECT patient_id, count(*) AS e, count(DISTINCT begin_ts) AS l FROM ev GROUP BY 1) LEFT JOIN (SELECT patient_id, count(*) AS r FROM rel GROUP BY 1) USING (patient_id)",
    ),
}
