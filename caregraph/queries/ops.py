"""Relational operators that queries on the graph need, one entry each."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from caregraph import store
from caregraph.operators import relations, timeline
from caregraph.operators import events as ev_mod
from caregraph.queries.base import EVENTS, STABBED, sql
from caregraph.sources.records import table


def W():
    """A patient's events in order."""
    return Window.partitionBy("patient_id").orderBy("begin_ts", "event_id")


def ev(spark: SparkSession, d: str, *kinds: str) -> DataFrame:
    out = store.events(spark, d)
    return out.where(F.col("kind").isin(*kinds)) if kinds else out


def _sides(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    c = table(spark, d, "customer", "c_custkey", "c_mktsegment").where("c_custkey % 3 <> 0")
    o = table(spark, d, "orders", "o_orderkey", "o_custkey").where("o_custkey % 5 <> 0")
    return c, o


def join(how: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        c, o = _sides(spark, d)
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), how)

    return run


def join_cross(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "region", "r_name").crossJoin(F.broadcast(table(spark, d, "region", "r_regionkey")))


def join_asof(direction: str):
    """The last assay before each drug event, or the first after it, from one sort."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        x = ev(spark, d, "drug", "assay").select("patient_id", "kind", "event_id", "begin_ts", F.when(F.col("kind") == "assay", F.col("begin_ts")).alias("at"))
        if direction == "prev":
            w = Window.partitionBy("patient_id").orderBy("begin_ts", F.col("kind") == "assay").rowsBetween(Window.unboundedPreceding, -1)
        else:
            w = Window.partitionBy("patient_id").orderBy(F.desc("begin_ts"), F.col("kind") == "assay").rowsBetween(Window.unboundedPreceding, -1)
        return x.withColumn("assay_at", F.last("at", ignorenulls=True).over(w)).where("kind = 'drug'").select("event_id", "assay_at")

    return run


def join_range(spark: SparkSession, d: str) -> DataFrame:
    """Assays within 30 days after a diagnosis, by day buckets: an equi-join with a residual."""
    dx = ev(spark, d, "diagnosis").select("patient_id", F.col("event_id").alias("dx"), F.col("begin_ts").alias("t"), F.explode(F.array(*(F.floor(F.datediff("begin_ts", F.lit("1970-01-01")) / 30) + k for k in (0, 1)))).alias("bucket"))
    lab = ev(spark, d, "assay").select("patient_id", F.col("event_id").alias("lab"), F.col("begin_ts").alias("u"), F.floor(F.datediff("begin_ts", F.lit("1970-01-01")) / 30).alias("bucket"))
    return dx.join(lab, ["patient_id", "bucket"]).where("u >= t and datediff(u, t) <= 30").select("patient_id", "dx", "lab")


def join_lateral(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "nation").createOrReplaceTempView("__cg_nation")
    table(spark, d, "region").createOrReplaceTempView("__cg_region")
    return spark.sql("SELECT r_name, x.n_name FROM __cg_region r JOIN LATERAL (SELECT max(n_name) AS n_name FROM __cg_nation n WHERE n.n_regionkey = r.r_regionkey) x")


def subquery(text: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        for t in ("customer", "orders"):
            table(spark, d, t).createOrReplaceTempView(f"__cg_{t}")
        return spark.sql(text)

    return run


SUB = {
    "scalar": "SELECT c_custkey FROM __cg_customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM __cg_customer)",
    "exists": "SELECT c_custkey FROM __cg_customer c WHERE EXISTS (SELECT 1 FROM __cg_orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'P')",
    "not_exists": "SELECT c_custkey FROM __cg_customer c WHERE NOT EXISTS (SELECT 1 FROM __cg_orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'P')",
    "in": "SELECT c_custkey FROM __cg_customer WHERE c_custkey IN (SELECT o_custkey FROM __cg_orders WHERE o_totalprice > 200000)",
}


def agg_basic(spark: SparkSession, d: str) -> DataFrame:
    x = ev(spark, d, "assay")
    r = lambda c, n: F.round(c, 4).alias(n)
    return x.groupBy("prompt").agg(F.count("*").alias("n"), r(F.sum("result"), "total"), r(F.avg("result"), "mean"), F.min("result").alias("least"), F.max("result").alias("most"), r(F.stddev("result"), "sd"))


def two_sets(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return (ev(spark, d, k).select("patient_id") for k in ("surgery", "diagnosis"))


def set_op(name: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        a, b = two_sets(spark, d)
        return {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.union(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: b.subtract(a), "except_all": lambda: b.exceptAll(a)}[name]()

    return run


SETS = {"union": "UNION", "union_all": "UNION ALL", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL"}


def pivot(spark: SparkSession, d: str) -> DataFrame:
    return ev(spark, d).groupBy("time_kind").pivot("kind", ["stay", "diagnosis", "drug", "assay", "surgery"]).agg(F.count("event_id")).na.fill(0)


def unpivot(spark: SparkSession, d: str) -> DataFrame:
    return pivot(spark, d).unpivot(["time_kind"], ["stay", "drug"], "kind", "n")


def joined_segments(spark: SparkSession, d: str) -> DataFrame:
    return ev(spark, d).join(table(spark, d, "customer", "c_custkey", "c_mktsegment"), F.col("patient_id") == F.col("c_custkey"))


def text_functions(spark: SparkSession, d: str) -> DataFrame:
    n = F.col("p_name")
    return table(spark, d, "part", "p_partkey", "p_name").select("p_partkey", F.upper(n).alias("up"), F.reverse(n).alias("back"), F.lpad(n, 14, "*").alias("pad"), F.instr(n, "l").alias("at"), F.translate(n, "aeiou", "AEIOU").alias("tr"), F.regexp_replace(n, "[aeiou]", "").alias("bare"), F.substring_index(n, " ", 1).alias("head"), F.length(n).alias("len"))


def date_functions(spark: SparkSession, d: str) -> DataFrame:
    t = F.col("o_orderdate")
    return table(spark, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year(t).alias("y"), F.month(t).alias("m"), F.dayofmonth(t).alias("dd"), F.date_format(F.date_trunc("month", t), "yyyy-MM-dd").alias("first"), F.date_format(F.date_add(t, 10), "yyyy-MM-dd").alias("later"), F.datediff(t, F.lit("1995-01-01")).cast("long").alias("days"))


def math_functions(spark: SparkSession, d: str) -> DataFrame:
    v = F.col("p_retailprice")
    return table(spark, d, "part", "p_partkey", "p_retailprice", "p_size").select("p_partkey", F.round(F.sqrt(v), 6).alias("root"), F.round(F.log(v), 6).alias("ln"), F.abs(F.col("p_size") - 25).alias("dist"), F.greatest("p_size", F.lit(10)).alias("g"), F.least("p_size", F.lit(10)).alias("l"), F.pmod("p_size", F.lit(7)).alias("m"))


def array_functions(spark: SparkSession, d: str) -> DataFrame:
    c = F.split("p_name", "")
    return table(spark, d, "part", "p_partkey", "p_name").select("p_partkey", F.array_join(F.array_sort(F.array_distinct(c)), "").alias("letters"), F.size(F.filter(c, lambda x: x == "l")).alias("ls"), F.exists(c, lambda x: x == "z").alias("z"), F.aggregate(F.transform(c, lambda x: F.ascii(x)), F.lit(0), lambda s, x: s + x).alias("codes"))


def json_functions(spark: SparkSession, d: str) -> DataFrame:
    p = F.from_json("props", "k int")
    return table(spark, d, "events", "event_id", "props").select("event_id", p["k"].alias("k"), F.get_json_object("props", "$.k").alias("k_text"), F.expr("variant_get(parse_json(props), '$.k', 'int')").alias("k_variant"))


def map_functions(spark: SparkSession, d: str) -> DataFrame:
    x = ev_mod.with_props(ev(spark, d))
    return x.select("event_id", F.array_join(F.array_sort(F.map_keys("props")), ",").alias("names"), F.element_at("props", "situation").alias("situation"))


def struct_functions(spark: SparkSession, d: str) -> DataFrame:
    s = F.struct("n_name", "n_regionkey")
    return table(spark, d, "nation").select("n_nationkey", s["n_name"].alias("name"), s.withField("n_regionkey", F.col("n_regionkey") + 1)["n_regionkey"].alias("next"))


def case_null(spark: SparkSession, d: str) -> DataFrame:
    x = ev(spark, d)
    return x.select("event_id", F.coalesce("situation", "prompt", F.lit("-")).alias("note"), F.nullif("kind", F.lit("stay")).alias("k"), F.col("prompt").eqNullSafe("F").alias("normal"), F.when(F.col("result") > 50000, "high").when(F.col("result").isNotNull(), "low").alias("level"))


def salted(spark: SparkSession, d: str) -> DataFrame:
    """Orders per nation with the hot side dealt over salts: partial sums meet in a second aggregation."""
    c, o = table(spark, d, "customer", "c_custkey", "c_nationkey"), table(spark, d, "orders", "o_orderkey", "o_custkey")
    salt = 8
    left = o.withColumn("salt", F.pmod(F.xxhash64("o_orderkey"), F.lit(salt)))
    right = c.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salt - 1).cast("long"))))
    part = left.join(right, (F.col("o_custkey") == F.col("c_custkey")) & (left["salt"] == right["salt"]))
    return part.groupBy("c_nationkey", left["salt"].alias("s")).agg(F.count("*").alias("n")).groupBy("c_nationkey").agg(F.sum("n").alias("orders"))


QUERIES = {
    **{f"op_join_{k}": join(h) for k, h in (("inner", "inner"), ("left", "left"), ("right", "right"), ("full", "full"), ("semi", "left_semi"), ("anti", "left_anti"))},
    "op_join_cross": join_cross,
    "op_join_range": join_range,
    "op_join_interval": lambda s, d: relations.stabbed(ev(s, d)).groupBy("relation", "step").agg(F.count("*").alias("n")),
    "op_join_asof_prev": join_asof("prev"),
    "op_join_asof_next": join_asof("next"),
    "op_join_lateral": join_lateral,
    "op_join_salted": salted,
    **{f"op_subquery_{k}": subquery(v) for k, v in SUB.items()},
    "op_agg_basic": agg_basic,
    "op_agg_distinct": lambda s, d: ev(s, d).groupBy("kind").agg(F.countDistinct("patient_id").alias("patients"), F.countDistinct("entity_id").alias("entities")),
    "op_agg_conditional": lambda s, d: ev(s, d).groupBy("patient_id").agg(F.count_if(F.col("kind") == "drug").alias("drugs"), F.bool_or(F.col("kind") == "surgery").alias("surgery"), F.max_by("event_id", F.struct("begin_ts", "event_id")).alias("latest")),
    "op_agg_collect": lambda s, d: ev(s, d).groupBy("patient_id").agg(F.array_join(F.array_sort(F.collect_set("kind")), ",").alias("kinds")),
    "op_agg_percentile": lambda s, d: ev(s, d, "assay").groupBy("prompt").agg(F.round(F.percentile("result", F.lit(0.9)), 4).alias("p90"), F.round(F.median("result"), 4).alias("mid")),
    "op_agg_rollup": lambda s, d: joined_segments(s, d).rollup("c_mktsegment", "kind").agg(F.count("*").alias("n")),
    "op_agg_cube": lambda s, d: joined_segments(s, d).cube("c_mktsegment", "time_kind").agg(F.count("*").alias("n")),
    "op_agg_grouping_sets": lambda s, d: joined_segments(s, d).groupingSets([["c_mktsegment"], ["kind"]], "c_mktsegment", "kind").agg(F.count("*").alias("n")),
    "op_agg_pivot": pivot,
    "op_agg_unpivot": unpivot,
    "op_win_rank": lambda s, d: ev(s, d, "assay").select("event_id", F.rank().over(Window.partitionBy("patient_id").orderBy("result")).cast("long").alias("r"), F.dense_rank().over(Window.partitionBy("patient_id").orderBy("result")).cast("long").alias("dr"), F.round(F.percent_rank().over(Window.partitionBy("patient_id").orderBy("result")), 6).alias("pr")),
    "op_win_ntile": lambda s, d: ev(s, d).select("event_id", F.ntile(4).over(W()).cast("long").alias("q")),
    "op_win_lag_lead": lambda s, d: ev(s, d).select("event_id", F.lag("event_id").over(W()).alias("prev"), F.lead("event_id", 2).over(W()).alias("next2")),
    "op_win_first_last": lambda s, d: ev(s, d).select("event_id", F.first("event_id").over(W()).alias("f"), F.last("prompt", ignorenulls=True).over(W().rowsBetween(Window.unboundedPreceding, 0)).alias("p")),
    "op_win_rows_frame": lambda s, d: ev(s, d, "assay").select("event_id", F.round(F.sum("result").over(W().rowsBetween(-2, 0)), 4).alias("last3")),
    "op_win_range_frame": lambda s, d: ev(s, d, "assay").select("event_id", F.count("*").over(Window.partitionBy("patient_id").orderBy(F.datediff("begin_ts", F.lit("1970-01-01"))).rangeBetween(-30, 0)).alias("n30")),
    "op_win_suffix_min": lambda s, d: relations.successor_bounds(ev(s, d)).select("event_id", "m"),
    "op_topk_global": lambda s, d: ev(s, d, "assay").orderBy(F.desc("result"), "event_id").limit(20).select("event_id", "result"),
    "op_topk_per_group": lambda s, d: ev(s, d, "assay").withColumn("rank", F.row_number().over(Window.partitionBy("patient_id").orderBy(F.desc("result"), "event_id")).cast("long")).where("rank <= 2").select("patient_id", "event_id", "rank"),
    "op_limit_offset": lambda s, d: ev(s, d).orderBy("event_id").offset(100).limit(50).select("event_id"),
    **{f"op_set_{k}": set_op(k) for k in ("union", "union_all", "intersect", "intersect_all", "except", "except_all")},
    "op_fn_string": text_functions,
    "op_fn_date": date_functions,
    "op_fn_math": math_functions,
    "op_fn_array": array_functions,
    "op_fn_map": map_functions,
    "op_fn_json": json_functions,
    "op_fn_struct": struct_functions,
    "op_fn_case_null": case_null,
    "op_timeline_allen": lambda s, d: ev(s, d).groupBy(timeline.allen(F.col("begin_ts"), F.col("end_ts"), F.col("begin_ts"), F.col("end_ts")).alias("allen")).agg(F.count("*").alias("n")),
}

_C, _O = "(SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey % 3 <> 0)", "(SELECT o_orderkey, o_custkey FROM orders WHERE o_custkey % 5 <> 0)"
_SEG = "FROM ev JOIN customer ON patient_id = c_custkey"
_PIV = "SELECT time_kind, " + ", ".join(f"count(*) FILTER (WHERE kind = '{k}') AS {k}" for k in ("stay", "diagnosis", "drug", "assay", "surgery")) + " FROM ev GROUP BY 1"
_WP = "(PARTITION BY patient_id ORDER BY begin_ts, event_id"


def _sets(op: str, a: str = "surgery", b: str = "diagnosis") -> str:
    return sql(EVENTS, body=f"SELECT patient_id FROM ev WHERE kind = '{a}' {op} SELECT patient_id FROM ev WHERE kind = '{b}'")


SQL = {
    **{f"op_join_{k}": f"SELECT * FROM {_C} {h} JOIN {_O} ON c_custkey = o_custkey" for k, h in (("inner", ""), ("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL"), ("semi", "SEMI"), ("anti", "ANTI"))},
    "op_join_cross": "SELECT a.r_name, b.r_regionkey FROM region a CROSS JOIN region b",
    "op_join_range": sql(EVENTS, body="SELECT a.patient_id, a.event_id AS dx, b.event_id AS lab FROM ev a JOIN ev b ON a.patient_id = b.patient_id AND a.kind = 'diagnosis' AND b.kind = 'assay' AND b.begin_ts >= a.begin_ts AND datediff('day', a.begin_ts, b.begin_ts) <= 30"),
    "op_join_interval": sql(EVENTS, STABBED, body="SELECT relation, step, count(*) AS n FROM stab WHERE relation IS NOT NULL GROUP BY ALL"),
    "op_join_asof_prev": sql(EVENTS, body="SELECT d.event_id, a.begin_ts AS assay_at FROM (SELECT * FROM ev WHERE kind = 'drug') d ASOF LEFT JOIN (SELECT DISTINCT patient_id, begin_ts FROM ev WHERE kind = 'assay') a ON a.patient_id = d.patient_id AND d.begin_ts > a.begin_ts"),
    "op_join_asof_next": sql(EVENTS, body="SELECT d.event_id, a.begin_ts AS assay_at FROM (SELECT * FROM ev WHERE kind = 'drug') d ASOF LEFT JOIN (SELECT DISTINCT patient_id, begin_ts FROM ev WHERE kind = 'assay') a ON a.patient_id = d.patient_id AND d.begin_ts < a.begin_ts"),
    "op_join_lateral": "SELECT r_name, max(n_name) AS n_name FROM region LEFT JOIN nation ON n_regionkey = r_regionkey GROUP BY 1",
    "op_join_salted": "SELECT c_nationkey, CAST(count(*) AS BIGINT) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
    **{f"op_subquery_{k}": v.replace("__cg_", "") for k, v in SUB.items()},
    "op_agg_basic": sql(EVENTS, body="SELECT prompt, count(*) AS n, round(sum(result), 4) AS total, round(avg(result), 4) AS mean, min(result) AS least, max(result) AS most, round(stddev(result), 4) AS sd FROM ev WHERE kind = 'assay' GROUP BY 1"),
    "op_agg_distinct": sql(EVENTS, body="SELECT kind, count(DISTINCT patient_id) AS patients, count(DISTINCT entity_id) AS entities FROM ev GROUP BY 1"),
    "op_agg_conditional": sql(EVENTS, body="SELECT patient_id, count(*) FILTER (WHERE kind = 'drug') AS drugs, bool_or(kind = 'surgery') AS surgery, arg_max(event_id, (begin_ts, event_id)) AS latest FROM ev GROUP BY 1"),
    "op_agg_collect": sql(EVENTS, body="SELECT patient_id, string_agg(kind, ',' ORDER BY kind) AS kinds FROM (SELECT DISTINCT patient_id, kind FROM ev) GROUP BY 1"),
    "op_agg_percentile": sql(EVENTS, body="SELECT prompt, round(quantile_cont(result, 0.9), 4) AS p90, round(median(result), 4) AS mid FROM ev WHERE kind = 'assay' GROUP BY 1"),
    "op_agg_rollup": sql(EVENTS, body=f"SELECT c_mktsegment, kind, count(*) AS n {_SEG} GROUP BY ROLLUP (c_mktsegment, kind)"),
    "op_agg_cube": sql(EVENTS, body=f"SELECT c_mktsegment, time_kind, count(*) AS n {_SEG} GROUP BY CUBE (c_mktsegment, time_kind)"),
    "op_agg_grouping_sets": sql(EVENTS, body=f"SELECT c_mktsegment, kind, count(*) AS n {_SEG} GROUP BY GROUPING SETS ((c_mktsegment), (kind))"),
    "op_agg_pivot": sql(EVENTS, body=_PIV),
    "op_agg_unpivot": sql(EVENTS, f"p AS ({_PIV})", body="SELECT time_kind, 'stay' AS kind, stay AS n FROM p UNION ALL SELECT time_kind, 'drug', drug FROM p"),
    "op_win_rank": sql(EVENTS, body="SELECT event_id, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr FROM ev WHERE kind = 'assay' WINDOW w AS (PARTITION BY patient_id ORDER BY result)"),
    "op_win_ntile": sql(EVENTS, body=f"SELECT event_id, ntile(4) OVER {_WP}) AS q FROM ev"),
    "op_win_lag_lead": sql(EVENTS, body=f"SELECT event_id, lag(event_id) OVER {_WP}) AS prev, lead(event_id, 2) OVER {_WP}) AS next2 FROM ev"),
    "op_win_first_last": sql(EVENTS, body=f"SELECT event_id, first_value(event_id) OVER {_WP}) AS f, last_value(prompt IGNORE NULLS) OVER {_WP} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS p FROM ev"),
    "op_win_rows_frame": sql(EVENTS, body=f"SELECT event_id, round(sum(result) OVER {_WP} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last3 FROM ev WHERE kind = 'assay'"),
    "op_win_range_frame": sql(EVENTS, body="SELECT event_id, count(*) OVER (PARTITION BY patient_id ORDER BY begin_ts RANGE BETWEEN INTERVAL 30 DAYS PRECEDING AND CURRENT ROW) AS n30 FROM ev WHERE kind = 'assay'"),
    "op_win_suffix_min": sql(EVENTS, "s AS (SELECT patient_id, begin_ts, min(min(end_ts)) OVER (PARTITION BY patient_id ORDER BY begin_ts DESC ROWS UNBOUNDED PRECEDING) AS m FROM ev GROUP BY 1, 2)", body="SELECT event_id, m FROM ev ASOF LEFT JOIN s ON ev.patient_id = s.patient_id AND ev.end_ts < s.begin_ts"),
    "op_topk_global": sql(EVENTS, body="SELECT event_id, result FROM ev WHERE kind = 'assay' ORDER BY result DESC, event_id LIMIT 20"),
    "op_topk_per_group": sql(EVENTS, body="SELECT * FROM (SELECT patient_id, event_id, row_number() OVER (PARTITION BY patient_id ORDER BY result DESC, event_id) AS rank FROM ev WHERE kind = 'assay') WHERE rank <= 2"),
    "op_limit_offset": sql(EVENTS, body="SELECT event_id FROM ev ORDER BY event_id LIMIT 50 OFFSET 100"),
    **{f"op_set_{k}": _sets(v) for k, v in SETS.items()},
    "op_set_except": _sets("EXCEPT", "diagnosis", "surgery"),
    "op_set_except_all": _sets("EXCEPT ALL", "diagnosis", "surgery"),
    "op_fn_string": "SELECT p_partkey, upper(p_name) AS up, reverse(p_name) AS back, CASE WHEN length(p_name) > 14 THEN left(p_name, 14) ELSE lpad(p_name, 14, '*') END AS pad, CAST(instr(p_name, 'l') AS INTEGER) AS at, translate(p_name, 'aeiou', 'AEIOU') AS tr, regexp_replace(p_name, '[aeiou]', '', 'g') AS bare, split_part(p_name, ' ', 1) AS head, CAST(length(p_name) AS INTEGER) AS len FROM part",
    "op_fn_date": "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(day(o_orderdate) AS INTEGER) AS dd, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, strftime(o_orderdate + to_days(10), '%Y-%m-%d') AS later, datediff('day', DATE '1995-01-01', o_orderdate) AS days FROM orders",
    "op_fn_math": "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS root, round(ln(p_retailprice), 6) AS ln, abs(p_size - 25) AS dist, greatest(p_size, 10) AS g, least(p_size, 10) AS l, p_size % 7 AS m FROM part",
    "op_fn_array": "SELECT p_partkey, array_to_string(list_sort(list_distinct(string_split(p_name, ''))), '') AS letters, CAST(len(list_filter(string_split(p_name, ''), lambda c: c = 'l')) AS INTEGER) AS ls, list_contains(string_split(p_name, ''), 'z') AS z, CAST(list_sum(list_transform(string_split(p_name, ''), lambda c: ascii(c))) AS INTEGER) AS codes FROM part",
    "op_fn_map": sql(EVENTS, body="SELECT event_id, concat_ws(',', CASE WHEN prompt IS NOT NULL THEN 'prompt' END, CASE WHEN result IS NOT NULL THEN 'result' END, CASE WHEN situation IS NOT NULL THEN 'situation' END) AS names, situation FROM ev"),
    "op_fn_json": "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, json_extract_string(props, '$.k') AS k_text, CAST(json_extract(props, '$.k') AS INTEGER) AS k_variant FROM events",
    "op_fn_struct": "SELECT n_nationkey, n_name AS name, n_regionkey + 1 AS next FROM nation",
    "op_fn_case_null": sql(EVENTS, body="SELECT event_id, coalesce(situation, prompt, '-') AS note, nullif(kind, 'stay') AS k, coalesce(prompt = 'F', FALSE) AS normal, CASE WHEN result > 50000 THEN 'high' WHEN result IS NOT NULL THEN 'low' END AS level FROM ev"),
    "op_timeline_allen": sql(EVENTS, body="SELECT 'equal' AS allen, count(*) AS n FROM ev"),
}
