"""Events and entities of the graph, and the graph around one event."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.sources import records


def time_kind(begin: Column, end: Column) -> Column:
    """A point begins and ends at once, whatever its kind."""
    return F.when(begin == end, "point").otherwise("period")


def _event(df: DataFrame, **cols: Column) -> DataFrame:
    null = F.lit(None)
    full = {"entity_id": null.cast("string"), "stay_id": null.cast("string"), "situation": null.cast("string"), "result": null.cast("double"), "prompt": null.cast("string")} | cols
    names = ("event_id", "patient_id", "kind", "entity_id", "begin_ts", "end_ts")
    return df.select(*(full[k].alias(k) for k in names), time_kind(full["begin_ts"], full["end_ts"]).alias("time_kind"), *(full[k].alias(k) for k in ("stay_id", "situation", "result", "prompt")))


def extract(spark: SparkSession, sf_dir: str, profile: str = "commerce", granularity: str | None = None) -> DataFrame:
    """All events of a profile, in the EVENT schema; ``granularity`` truncates times."""
    out = {"commerce": _commerce, "clicks": _clicks, "dialogue": _dialogue}[profile](spark, sf_dir)
    if granularity:
        out = out.withColumn("begin_ts", F.date_trunc(granularity, "begin_ts").cast("timestamp_ntz")).withColumn("end_ts", F.date_trunc(granularity, "end_ts").cast("timestamp_ntz"))
        out = out.withColumn("time_kind", time_kind(F.col("begin_ts"), F.col("end_ts")))
    return out


def _commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = records.stays(spark, sf_dir)
    stays = _event(s, event_id=F.col("event_id"), patient_id=F.col("patient_id"), kind=F.lit("stay"), begin_ts=F.col("begin_ts"), end_ts=F.col("end_ts"), situation=F.col("situation"))
    li = records.lines(spark, sf_dir).where("kind is not null")
    kind = F.col("kind")
    # Days of supply make a drug event a period.
    end = F.when(kind == "drug", F.expr("l_shipdate + make_dt_interval(cast(l_quantity as int))")).otherwise(F.col("l_shipdate"))
    rest = _event(
        li,
        event_id=F.col("event_id"),
        patient_id=F.col("o_custkey"),
        kind=kind,
        entity_id=F.concat_ws("-", kind, F.col("l_partkey")),
        begin_ts=F.col("l_shipdate"),
        end_ts=end,
        stay_id=F.concat(F.lit("O-"), F.col("l_orderkey")),
        situation=F.when(kind == "diagnosis", F.col("l_linestatus")),
        result=F.when(kind == "assay", F.col("l_extendedprice")),
        prompt=F.when(kind == "assay", F.col("l_linestatus")),
    )
    return stays.unionByName(rest)


CLICK_KINDS = {"signup": "stay", "error": "diagnosis", "purchase": "drug", "view": "assay", "click": "surgery"}


def click_events(e: DataFrame) -> DataFrame:
    """EVENT rows of ``events`` rows, batch or stream; a purchase lasts its value in hours."""
    kind = F.lit(None).cast("string")
    for a, b in CLICK_KINDS.items():
        kind = F.when(F.col("event_type") == a, b).otherwise(kind)
    end = F.when(F.col("event_type") == "purchase", F.expr("ts + make_dt_interval(0, 0, 0, cast(round(value * 3600000000) as decimal(18, 0)) / 1000000)")).otherwise(F.col("ts"))
    return _event(
        e,
        event_id=F.concat(F.lit("E-"), F.col("event_id")),
        patient_id=F.col("user_id"),
        kind=kind,
        entity_id=F.concat_ws("-", kind, F.get_json_object("props", "$.k")),
        begin_ts=F.col("ts"),
        end_ts=end,
        result=F.when(F.col("event_type") == "view", F.col("value")),
    )


def _clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return click_events(records.table(spark, sf_dir, "events"))


def _dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = records.table(spark, sf_dir, "conversations", "conv_id", "turn", "role")
    at = F.expr("timestamp_ntz'1970-01-01 00:00:00' + make_dt_interval(0, 0, 0, turn)")
    return _event(c, event_id=F.concat_ws("-", F.lit("T"), "conv_id", "turn"), patient_id=F.col("conv_id"), kind=F.col("role"), begin_ts=at, end_ts=at)


def entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Object entities: each (kind, part) that an event uses, with its label and broader terms."""
    used = records.lines(spark, sf_dir).where("kind is not null").select("kind", "l_partkey").distinct()
    part = records.table(spark, sf_dir, "part", "p_partkey", "p_name", "p_brand", "p_type")
    both = used.join(part, F.col("l_partkey") == F.col("p_partkey"))
    return both.select(F.concat_ws("-", "kind", "l_partkey").alias("entity_id"), "kind", F.col("p_name").alias("label"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"))


def patient_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = records.patients(spark, sf_dir)
    return p.select(F.concat(F.lit("patient-"), F.col("patient_id")).alias("entity_id"), F.lit("patient").alias("kind"), F.col("name").alias("label"), F.col("category"), "birthday")


def with_labels(ev: DataFrame, ent: DataFrame) -> DataFrame:
    """Events with label, brand and type of their object; ids hold the kind, so one key joins."""
    return ev.join(ent.select("entity_id", "label", "brand", "type"), "entity_id", "left")


def with_props(ev: DataFrame) -> DataFrame:
    """The extra properties as one map, absent ones left out."""
    bag = F.create_map(F.lit("situation"), F.col("situation"), F.lit("result"), F.col("result").cast("string"), F.lit("prompt"), F.col("prompt"))
    return ev.withColumn("props", F.map_filter(bag, lambda k, v: v.isNotNull()))
