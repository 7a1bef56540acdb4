"""Queries of the text language, of streams, sources and user functions."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph import store
from caregraph.functions import udf
from caregraph.operators import events
from caregraph.plans.sparql import Executor
from caregraph.queries.base import RELATIONS, sql
from caregraph.queries.link import _LCS, ACCEPTED, marks
from caregraph.queries.work import TRIPLES, referenced, triples
from caregraph.sources import io, ntriples, records
from caregraph.streaming import streams

TEXTS = {
    "sparql_select_distinct": 'SELECT DISTINCT ?p WHERE { ?e a cg:DiagnosisEvent ; cg:hasActor ?p , ?d . ?d cg:label "red plate" . ?p a cg:Patient }',
    "sparql_count": 'SELECT (COUNT(DISTINCT ?p) AS ?n) WHERE { ?p a cg:Patient ; cg:category "BUILDING" . ?e cg:hasActor ?p ; a cg:SurgeryEvent }',
    "sparql_filter": "SELECT ?e ?r WHERE { ?e cg:assayResult ?r . FILTER (?r > 90000 && ?r <= 95000) }",
    "sparql_optional": "SELECT ?e ?r WHERE { ?e cg:hasActor cg:patient/1 . OPTIONAL { ?e cg:assayResult ?r } }",
    "sparql_union": 'SELECT ?d WHERE { { ?d cg:broaderType "PROMO" } UNION { ?d cg:broaderBrand "Brand#2" } }',
    "sparql_group_having": "SELECT ?c (COUNT(?p) AS ?n) WHERE { ?p cg:category ?c } GROUP BY ?c HAVING (COUNT(?p) > 290)",
    "sparql_order_limit": "SELECT ?e ?b WHERE { ?e a cg:SurgeryEvent ; cg:hasBegin ?b } ORDER BY DESC(?b) ?e LIMIT 10 OFFSET 5",
    "sparql_ask": 'ASK { ?d cg:label "red plate" }',
    "sparql_construct": "CONSTRUCT { ?p cg:operatedOn ?b } WHERE { ?e a cg:SurgeryEvent ; cg:hasActor ?p ; cg:hasBegin ?b . ?p a cg:Patient }",
    "sparql_path_sequence": "SELECT ?e ?l WHERE { ?e a cg:SurgeryEvent . ?e cg:hasActor/cg:label ?l }",
    "sparql_path_inverse": "SELECT DISTINCT ?d WHERE { cg:patient/1 ^cg:hasActor/cg:hasActor ?d . ?d a cg:Drug }",
    "sparql_path_alternative": "SELECT ?d ?x WHERE { ?d a cg:Surgery ; (cg:broaderBrand|cg:broaderType) ?x }",
}
TEXT_SQL = {
    "sparql_select_distinct": "SELECT DISTINCT 'cg:patient/' || patient_id AS p FROM ev JOIN ent USING (entity_id) WHERE ev.kind = 'diagnosis' AND label = 'red plate'",
    "sparql_count": "SELECT count(DISTINCT patient_id) AS n FROM ev JOIN customer ON c_custkey = patient_id WHERE kind = 'surgery' AND c_mktsegment = 'BUILDING'",
    "sparql_filter": "SELECT 'cg:event/' || event_id AS e, CAST(result AS VARCHAR) AS r FROM ev WHERE result > 90000 AND result <= 95000",
    "sparql_optional": "SELECT 'cg:event/' || event_id AS e, CAST(result AS VARCHAR) AS r FROM ev WHERE patient_id = 1",
    "sparql_union": "SELECT 'cg:entity/' || entity_id AS d FROM ent WHERE type = 'PROMO' UNION ALL SELECT 'cg:entity/' || entity_id FROM ent WHERE brand = 'Brand#2'",
    "sparql_group_having": "SELECT c_mktsegment AS c, count(*) AS n FROM customer GROUP BY 1 HAVING count(*) > 290",
    "sparql_order_limit": "SELECT 'cg:event/' || event_id AS e, strftime(begin_ts, '%Y-%m-%dT%H:%M:%S') AS b FROM ev WHERE kind = 'surgery' ORDER BY b DESC, e LIMIT 10 OFFSET 5",
    "sparql_ask": "SELECT count(*) > 0 AS answer FROM ent WHERE label = 'red plate'",
    "sparql_construct": "SELECT DISTINCT 'cg:patient/' || patient_id AS s, 'cg:operatedOn' AS p, strftime(begin_ts, '%Y-%m-%dT%H:%M:%S') AS o FROM ev WHERE kind = 'surgery'",
    "sparql_path_sequence": "SELECT 'cg:event/' || event_id AS e, c_name AS l FROM ev JOIN customer ON c_custkey = patient_id WHERE kind = 'surgery' UNION ALL SELECT 'cg:event/' || event_id, label FROM ev JOIN ent USING (entity_id) WHERE ev.kind = 'surgery'",
    "sparql_path_inverse": "SELECT DISTINCT 'cg:entity/' || entity_id AS d FROM ev WHERE patient_id = 1 AND kind = 'drug'",
    "sparql_path_alternative": "SELECT 'cg:entity/' || entity_id AS d, unnest([brand, type]) AS x FROM ent WHERE kind = 'surgery'",
}


def text(q: str):
    return lambda spark, d: Executor(triples(spark, d)).query(q)


def path_closure(spark: SparkSession, d: str) -> DataFrame:
    """One or more steps up: nation, region, world."""
    n, r = records.table(spark, d, "nation"), records.table(spark, d, "region")
    t = n.join(r, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("s"), F.lit("cg:broader").alias("p"), F.col("r_name").alias("o"))
    t = t.unionByName(r.select(F.col("r_name").alias("s"), F.lit("cg:broader").alias("p"), F.lit("WORLD").alias("o")))
    return Executor(t).query("SELECT ?a ?b WHERE { ?a cg:broader+ ?b }")


def stream(name: str, build, mode: str = "append"):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return streams.run(build(streams.source(spark, f"{d}/events.parquet")), name, mode)

    return run


def net_relations(spark: SparkSession, d: str) -> DataFrame:
    s = streams.run(streams.relations(streams.source(spark, f"{d}/events.parquet")), "cg_stream_relations")
    return s.groupBy("patient_id", "src", "dst").agg(F.sum("op").alias("n")).where("n > 0").select("patient_id", "src", "dst")


def during(spark: SparkSession, d: str) -> DataFrame:
    path = f"{d}/events.parquet"
    return streams.run(streams.during(streams.source(spark, path), streams.source(spark, path)), "cg_stream_during")


def annotated(spark: SparkSession, d: str) -> DataFrame:
    keys = records.table(spark, d, "part", "p_partkey", "p_name").where("p_partkey < 100")
    links = keys.select(F.concat(F.lit("drug-"), "p_partkey").alias("key"), F.col("p_name").alias("term"))
    out = streams.run(streams.annotate(streams.source(spark, f"{d}/events.parquet"), links), "cg_stream_annotate")
    return out.where("term is not null").groupBy("term").agg(F.count("*").alias("n"))


def udtf_split(spark: SparkSession, d: str) -> DataFrame:
    udf.register(spark)
    records.packed_cells(spark, d).createOrReplaceTempView("__cg_cells")
    return spark.sql("SELECT l_orderkey, s.pos, s.item FROM __cg_cells, LATERAL split_cell(labels_raw, ',; ') s")


def udtf_edges(spark: SparkSession, d: str) -> DataFrame:
    """Neighbours of each conversation's turns, by a table function over sorted ids."""
    udf.register(spark)
    e = events.extract(spark, d, "dialogue")
    e.groupBy("patient_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("begin_ts", "event_id"))), lambda x: x["event_id"]).alias("ids")).createOrReplaceTempView("__cg_turns")
    return spark.sql("SELECT patient_id, e.src, e.dst FROM __cg_turns, LATERAL timeline_edges(ids) e")


def udaf(spark: SparkSession, d: str) -> DataFrame:
    udf.register(spark)
    records.table(spark, d, "documents", "doc_id", "n_chars").join(records.table(spark, d, "labels", "doc_id", "quality"), "doc_id").createOrReplaceTempView("__cg_marked")
    return spark.sql("SELECT round(auc_udaf(n_chars, quality), 6) AS auc FROM __cg_marked")


def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    udf.register(spark)
    records.table(spark, d, "part", "p_partkey", "p_name").createOrReplaceTempView("__cg_part")
    return spark.sql("SELECT p_partkey, round(lev_sim(p_name, 'red plate'), 6) AS lev, round(jaccard_sim(p_name, 'red plate'), 6) AS jac, round(lcs_sim(p_name, 'red plate'), 6) AS lcs, round(matchability(p_name, 'red plate'), 6) AS mean FROM __cg_part")


def marked_votes(spark: SparkSession, d: str) -> DataFrame:
    """The other functions for SQL users, on the stored graph's views: Allen's relation of diagnoses to their stays, raw prompts, votes, and one patient's triples."""
    udf.register(spark)
    udf.register_graph(spark, {"event": store.events(spark, d), "triple": store.triples(spark, d), "relation": store.relations(spark, d), "dirty": records.dirty_lines(spark, d), "marked": marks(spark, d)})
    return spark.sql("""
        SELECT 'allen ' || allen_relation(a.begin_ts, a.end_ts, b.begin_ts, b.end_ts) AS what, count(*) AS n FROM event a JOIN event b ON a.stay_id = b.event_id WHERE a.kind = 'diagnosis' GROUP BY 1
        UNION ALL SELECT 'prompt ' || normalize_qualitative(prompt_raw), count(*) FROM dirty GROUP BY 1
        UNION ALL SELECT 'majority ' || vote_majority(votes), count(*) FROM marked GROUP BY 1
        UNION ALL SELECT 'ego ' || p, count(*) FROM ego_triples('cg:patient/1') GROUP BY 1
        UNION ALL SELECT 'relation ' || relation, count(*) FROM relation GROUP BY 1""")


def written_triples(spark: SparkSession, d: str) -> str:
    """A folder of N-Triples files of the reference map."""
    path = f"{store.shared_folder(spark)}/graph-nt-{uuid.uuid4().hex}"
    t = referenced(spark, d).select("*", F.lit("iri").alias("o_kind"), F.lit(None).cast("string").alias("datatype"), F.lit(None).cast("string").alias("lang"))
    ntriples.write(t, path)
    spark.dataSource.register(io.TripleSource)
    return path


def triple_source(spark: SparkSession, d: str) -> DataFrame:
    """Triples through N-Triples files and the data source, in ranges of 500 bytes."""
    return spark.read.format("cg_triples").option("path", written_triples(spark, d)).option("bytes", "500").load().select("s", "p", "o")


def triple_stream(spark: SparkSession, d: str) -> DataFrame:
    path = written_triples(spark, d)
    return streams.run(spark.readStream.format("cg_triples").option("path", path).load(), "cg_stream_triple_files").select("s", "p", "o")


def round_trip(fmt: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        df = records.table(spark, d, "supplier")
        path = f"{store.shared_folder(spark)}/graph-{fmt}-{uuid.uuid4().hex}"
        io.write(df, path, fmt, ("s_nationkey",))
        return io.read(spark, path, fmt, df.schema).select(df.columns)

    return run


QUERIES = {
    **{k: text(q) for k, q in TEXTS.items()},
    "sparql_path_closure": path_closure,
    "stream_triples": stream("cg_stream_triples", streams.triples),
    "stream_dedup": stream("cg_stream_dedup", lambda s: streams.dedup(s).select("event_id", "user_id", "event_type")),
    "stream_window_tumbling": stream("cg_stream_tumbling", lambda s: streams.window_counts(s).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n"), "complete"),
    "stream_window_sliding": stream("cg_stream_sliding", lambda s: streams.window_counts(s, "sliding").select(F.date_format("start", "yyyy-MM-dd HH").alias("hour"), "event_type", "n"), "complete"),
    "stream_window_session": stream("cg_stream_session", lambda s: streams.window_counts(s, "session", "6 hours").select("user_id", F.col("n"), F.date_format("start", "yyyy-MM-dd HH:mm:ss.SSSSSS").alias("start")), "complete"),
    "stream_relations_net": net_relations,
    "stream_during": during,
    "stream_annotate": annotated,
    "udtf_split_cell": udtf_split,
    "udtf_timeline_edges": udtf_edges,
    "udaf_auc": udaf,
    "fn_sql_similarities": sql_functions,
    "fn_sql_graph": marked_votes,
    "io_triple_source": triple_source,
    "io_triple_stream": triple_stream,
    **{f"io_round_trip_{f}": round_trip(f) for f in ("parquet", "orc", "json", "csv")},
}
_PATH = "e AS (SELECT n_name AS s, r_name AS o FROM nation JOIN region ON n_regionkey = r_regionkey UNION ALL SELECT r_name, 'WORLD' FROM region)"
SQL = {
    **{k: sql(*TRIPLES[:2], body=q) for k, q in TEXT_SQL.items()},
    "sparql_path_closure": sql(_PATH, "r AS (SELECT s, o FROM e UNION SELECT r.s, e.o FROM r JOIN e ON e.s = r.o)", body="SELECT s AS a, o AS b FROM r", recursive=True),
    "stream_triples": "SELECT 'cg:event/E-' || event_id AS s, unnest(['cg:kind', 'cg:hasBegin', 'cg:hasActor']) AS p, unnest([CASE event_type WHEN 'signup' THEN 'stay' WHEN 'error' THEN 'diagnosis' WHEN 'purchase' THEN 'drug' WHEN 'view' THEN 'assay' ELSE 'surgery' END, strftime(ts, '%Y-%m-%dT%H:%M:%S'), 'cg:patient/' || user_id]) AS o FROM events",
    "stream_dedup": "SELECT event_id, user_id, event_type FROM events",
    "stream_window_tumbling": "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY ALL",
    "stream_window_sliding": "SELECT strftime(h, '%Y-%m-%d %H') AS hour, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 12 HOURS, ts), time_bucket(INTERVAL 12 HOURS, ts) - INTERVAL 12 HOURS]) AS h FROM events) GROUP BY ALL",
    "stream_window_session": "WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOURS THEN 1 ELSE 0 END AS cut FROM events), s AS (SELECT user_id, ts, sum(cut) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, count(*) AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f') AS start FROM s GROUP BY user_id, k",
    "stream_relations_net": "WITH t AS (SELECT user_id AS patient_id, 'E-' || event_id AS src, lead('E-' || event_id) OVER (PARTITION BY user_id ORDER BY ts) AS dst FROM events WHERE event_type <> 'purchase') SELECT patient_id, src, dst FROM t WHERE dst IS NOT NULL",
    "stream_during": "SELECT a.user_id, 'E-' || a.event_id AS src, 'E-' || b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND a.ts >= b.ts AND a.ts <= b.ts + to_microseconds(CAST(round(b.value * 3600000000) AS BIGINT)) AND a.ts <= b.ts + INTERVAL 60 DAYS",
    "stream_annotate": "SELECT p_name AS term, count(*) AS n FROM events JOIN part ON 'drug-' || p_partkey = (CASE WHEN event_type = 'purchase' THEN 'drug-' || json_extract_string(props, '$.k') END) AND p_partkey < 100 GROUP BY 1",
    "udtf_split_cell": "WITH li AS (SELECT l_orderkey, replace(p_name, ' ', '_') AS n FROM lineitem JOIN part ON p_partkey = l_partkey WHERE l_returnflag = 'R' AND l_quantity < 50), c AS (SELECT l_orderkey, list(n ORDER BY n) AS ns FROM li GROUP BY 1) SELECT l_orderkey, unnest(range(len(ns))) AS pos, unnest(ns) AS item FROM c",
    "udtf_timeline_edges": "SELECT patient_id, src, dst FROM (SELECT conv_id AS patient_id, lag(concat_ws('-', 'T', conv_id, turn)) OVER (PARTITION BY conv_id ORDER BY turn) AS src, concat_ws('-', 'T', conv_id, turn) AS dst FROM conversations) WHERE src IS NOT NULL",
    "udaf_auc": "WITH d AS (SELECT n_chars AS s, sum(quality) AS p, sum(1 - quality) AS q FROM documents JOIN labels USING (doc_id) GROUP BY 1), w AS (SELECT p, q, p * (coalesce(sum(q) OVER (ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + q / 2) AS w FROM d) SELECT round(sum(w) / (sum(p) * sum(q)), 6) AS auc FROM w",
    "fn_sql_graph": sql(
        *TRIPLES,
        RELATIONS,
        body=f"""SELECT 'allen ' || CASE WHEN a.begin_ts < b.begin_ts THEN 'before' WHEN a.begin_ts > b.end_ts THEN 'after' WHEN b.begin_ts = b.end_ts THEN 'equal' WHEN a.begin_ts = b.begin_ts THEN 'starts' WHEN a.begin_ts = b.end_ts THEN 'finishes' ELSE 'during' END AS what, count(*) AS n
          FROM ev a JOIN ev b ON a.stay_id = b.event_id WHERE a.kind = 'diagnosis' GROUP BY 1
        UNION ALL SELECT 'prompt ' || CASE WHEN l_linestatus = 'F' THEN 'negative' ELSE 'positive' END, count(*) FROM lineitem GROUP BY 1
        UNION ALL SELECT 'majority ' || v, n FROM (WITH {ACCEPTED} SELECT len(list_filter(votes, lambda v: v)) > 3 AS v, count(*) AS n FROM vote GROUP BY 1)
        UNION ALL SELECT 'ego ' || p, count(*) FROM tr WHERE s = 'cg:patient/1' OR o = 'cg:patient/1' GROUP BY p
        UNION ALL SELECT 'relation ' || relation, count(*) FROM rel GROUP BY 1""",
    ),
    **{k: "SELECT 'cg:nation/' || n_nationkey AS s, 'cg:within' AS p, 'cg:region/' || replace(r_name, ' ', '%20') AS o FROM nation JOIN region ON n_regionkey = r_regionkey" for k in ("io_triple_source", "io_triple_stream")},
    **{f"io_round_trip_{f}": "SELECT * FROM supplier" for f in ("parquet", "orc", "json", "csv")},
    "fn_sql_similarities": "SELECT p_partkey, round(1 - levenshtein(p_name, 'red plate') / greatest(length(p_name), 9), 6) AS lev, round(jaccard(p_name, 'red plate'), 6) AS jac, round(lcs, 6) AS lcs, round((1 - levenshtein(p_name, 'red plate') / greatest(length(p_name), 9) + jaccard(p_name, 'red plate') + lcs) / 3, 6) AS mean FROM (SELECT *, " + _LCS.replace("mention", "p_name").replace("label", "'red plate'") + " / greatest(length(p_name), 9) AS lcs FROM part)",
}
