"""The questions asked of the graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from caregraph import store
from caregraph.plans.pattern import Pattern
from caregraph.sources import records

W1 = Pattern().event("dx", "diagnosis", label="red plate")
W2 = Pattern().patient("BUILDING").event("dx", "diagnosis", type="PROMO").event("rx1", "drug", label="hot ring").event("rx2", "drug", label="red bolt")
W3 = (
    Pattern().patient("MACHINERY").event("dx", "diagnosis", type="PROMO").event("stay", "stay").event("rx", "drug", type="ECONOMY").event("lab", "assay", prompt="F")
    .rel("dx", "During", "stay").rel("rx", "After", "dx").rel("lab", "During", "rx")
)
W3B = W3.event("bad", "assay", prompt="O").rel("bad", "Before", "lab").share("bad", "type", "lab")


def labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with their objects' label, brand and type."""
    return store.labelled(spark, sf_dir)


def cooccurrence(ev: DataFrame, k: int = 5) -> DataFrame:
    """Auxiliary diagnosis: for each type of assay, the k labels diagnosed in most patients after their first abnormal assay of it, with lift."""
    first = ev.where("kind = 'assay' and prompt = 'O'").groupBy("patient_id", F.col("type").alias("assay_type")).agg(F.min("begin_ts").alias("at"))
    dx = ev.where("kind = 'diagnosis'").groupBy("patient_id", "label").agg(F.max("begin_ts").alias("last"))
    base = dx.groupBy("label").agg(F.count("*").alias("all_n"))
    people = ev.agg(F.countDistinct("patient_id").alias("people"))
    sick = first.groupBy("assay_type").agg(F.count("*").alias("sick"))
    met = first.join(dx, "patient_id").where("last > at").groupBy("assay_type", "label").agg(F.count("*").alias("patients"))
    met = met.join(base, "label").join(F.broadcast(sick), "assay_type").join(F.broadcast(people), F.lit(True))
    w = Window.partitionBy("assay_type").orderBy(F.desc("patients"), "label")
    lift = F.round((F.col("patients") / F.col("sick")) / (F.col("all_n") / F.col("people")), 6)
    return met.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("assay_type", "label", "patients", lift.alias("lift"), F.col("rank").cast("long").alias("rank"))


def effectiveness(ev: DataFrame) -> DataFrame:
    """Therapeutic effectiveness: per drug type, patients whose last assay before a drug event was abnormal, and of them those whose next was normal.

    Both neighbours come from one sort of each patient's assays and drugs.
    """
    x = ev.where("kind in ('assay', 'drug')").select("patient_id", "kind", "type", "prompt", "begin_ts", "event_id")
    w = Window.partitionBy("patient_id").orderBy("begin_ts", F.col("kind") == "assay", "event_id")
    before = F.last("prompt", ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, -1))
    after = F.first("prompt", ignorenulls=True).over(w.rowsBetween(1, Window.unboundedFollowing))
    d = x.select("patient_id", "kind", "type", before.alias("was"), after.alias("then")).where("kind = 'drug' and was = 'O'")
    turned = F.countDistinct(F.when(F.col("then") == "F", F.col("patient_id")))
    return d.groupBy("type").agg(F.countDistinct("patient_id").alias("abnormal"), turned.alias("turned")).withColumn("share", F.round(F.col("turned") / F.col("abnormal"), 6))


def side_effects(ev: DataFrame) -> DataFrame:
    """Patients whose first diagnosis of a type comes at or after their first drug of a type."""
    first = lambda kind, name, at: ev.where(F.col("kind") == kind).groupBy("patient_id", F.col("type").alias(name)).agg(F.min("begin_ts").alias(at))
    met = first("drug", "drug_type", "d").join(first("diagnosis", "diagnosis_type", "x"), "patient_id").where("x >= d")
    return met.groupBy("drug_type", "diagnosis_type").agg(F.count("*").alias("patients"))


def status(ev: DataFrame) -> DataFrame:
    """A patient's timeline: position, days since the last begin, how many of the kind so far."""
    w = Window.partitionBy("patient_id").orderBy("begin_ts", "event_id")
    return ev.select("patient_id", "event_id", F.row_number().over(w).cast("long").alias("pos"), F.datediff(F.col("begin_ts"), F.lag("begin_ts").over(w)).cast("long").alias("gap_days"), F.count("*").over(Window.partitionBy("patient_id", "kind").orderBy("begin_ts", "event_id")).alias("so_far"))


def features(ev: DataFrame) -> DataFrame:
    """A row of features for each patient."""
    end = ev.agg(F.max("begin_ts").alias("now"))
    n = lambda k: F.count_if(F.col("kind") == k).alias("n_" + k)
    bad = F.count_if((F.col("kind") == "assay") & (F.col("prompt") == "O")) / F.nullif(F.count_if(F.col("kind") == "assay"), F.lit(0))
    stay = F.avg(F.when(F.col("kind") == "stay", F.datediff("end_ts", "begin_ts")))
    f = ev.groupBy("patient_id").agg(*map(n, ("stay", "diagnosis", "drug", "assay", "surgery")), F.round(bad, 6).alias("abnormal_rate"), F.round(stay, 6).alias("mean_stay_days"), F.max("begin_ts").alias("last"))
    return f.join(F.broadcast(end), F.lit(True)).withColumn("days_since_last", F.datediff("now", "last").cast("long")).drop("now", "last")


def on_drug(ev: DataFrame, column: str, value: str) -> DataFrame:
    return ev.where((F.col("kind") == "drug") & (F.col(column) == value)).select("patient_id").distinct()


def by_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Patients by region: two steps up the place hierarchy."""
    c, n, r = (records.table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy(F.col("r_name").alias("region")).agg(F.count("*").alias("patients"))
