"""What the graph is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.sources.records import table


def reduce_bruteforce(ev: DataFrame) -> DataFrame:
    """(patient_id, src, dst): Before pairs that no third event lies between, by an anti-join over all pairs."""
    cols = ("event_id", "begin_ts", "end_ts")
    a = ev.select("patient_id", *(F.col(c).alias("a_" + c) for c in cols))
    b = ev.select("patient_id", *(F.col(c).alias("b_" + c) for c in cols))
    c = ev.select("patient_id", *(F.col(x).alias("c_" + x) for x in cols))
    pairs = a.join(b, "patient_id").where("a_end_ts < b_begin_ts")
    between = (pairs["patient_id"] == c["patient_id"]) & (F.col("c_begin_ts") > F.col("a_end_ts")) & (F.col("c_end_ts") < F.col("b_begin_ts"))
    return pairs.join(c, between, "left_anti").select("patient_id", F.col("a_event_id").alias("src"), F.col("b_event_id").alias("dst"))


class Relational:
    """The source tables, for answering the questions by joins without the graph."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.customer = table(spark, sf_dir, "customer", "c_custkey", "c_mktsegment")
        self.orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
        self.line = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_returnflag", "l_linestatus", "l_shipdate")
        self.part = table(spark, sf_dir, "part", "p_partkey", "p_name", "p_type")

    def of(self, flag: str, **kept: str) -> DataFrame:
        """Lines of one flag with their patient and part, as (patient, kept columns)."""
        li = self.line.where(F.col("l_returnflag") == flag)
        if flag == "R":
            li = li.where("l_quantity < 50")
        j = li.join(self.orders, F.col("l_orderkey") == F.col("o_orderkey")).join(self.part, F.col("l_partkey") == F.col("p_partkey"))
        return j.select(F.col("o_custkey").alias("patient"), *(F.col(v).alias(k) for k, v in kept.items()))

    def spans(self) -> DataFrame:
        last = self.line.groupBy("l_orderkey").agg(F.max("l_shipdate").alias("last"))
        return self.orders.join(last, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("patient"), F.col("o_orderdate").alias("sb"), F.greatest("o_orderdate", "last").alias("se"))

    def w1(self, label: str = "red plate") -> DataFrame:
        return self.of("R", label="p_name").where(F.col("label") == label).select(F.col("patient").alias("patient_id")).distinct()

    def w2(self, category: str = "BUILDING", group: str = "PROMO", drugs: tuple[str, str] = ("hot ring", "red bolt")) -> DataFrame:
        who = self.customer.where(F.col("c_mktsegment") == category).select(F.col("c_custkey").alias("patient"))
        out = who.join(self.of("R", type="p_type").where(F.col("type") == group), "patient", "left_semi")
        for drug in drugs:
            out = out.join(self.of("N", label="p_name").where(F.col("label") == drug), "patient", "left_semi")
        return out.select(F.col("patient").alias("patient_id"))

    def w3(self, category: str = "MACHINERY", group: str = "PROMO", drug: str = "ECONOMY", strict: bool = False) -> DataFrame:
        who = self.customer.where(F.col("c_mktsegment") == category).select(F.col("c_custkey").alias("patient"))
        dx = self.of("R", type="p_type", at="l_shipdate").where(F.col("type") == group).select("patient", "at")
        s = self.spans().where("sb < se")
        dx = dx.join(s, "patient").where("at between sb and se").groupBy("patient").agg(F.min("at").alias("at"))
        rx = self.of("N", type="p_type", db="l_shipdate", days="l_quantity").where(F.col("type") == drug).select("patient", "db", F.expr("db + make_dt_interval(cast(days as int))").alias("de"))
        lab = self.of("A", ap="l_shipdate", status="l_linestatus", atype="p_type")
        ok = lab.where("status = 'F'").select("patient", "ap", "atype")
        if strict:
            bad = lab.where("status = 'O'").groupBy("patient", "atype").agg(F.min("ap").alias("worst"))
            ok = ok.join(bad, ["patient", "atype"]).where("worst < ap")
        hit = who.join(dx, "patient").join(rx, "patient").where("db > at").join(ok, "patient").where("ap between db and de")
        return hit.agg(F.countDistinct("patient").alias("patients"))
