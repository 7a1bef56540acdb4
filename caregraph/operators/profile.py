"""Counts that describe a graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.operators import events as ev_mod
from caregraph.sources.records import table


def triples(t: DataFrame) -> DataFrame:
    """Triples by class (entity, event, temporal, link) and predicate."""
    return t.groupBy("class", "p").agg(F.count("*").alias("triples"))


def relations(rel: DataFrame) -> DataFrame:
    """Edges by relation, and their total, which is the sum of the parts."""
    return rel.rollup("relation").agg(F.count("*").alias("edges")).select(F.coalesce("relation", F.lit("total")).alias("relation"), "edges")


def events(ev: DataFrame) -> DataFrame:
    return ev.groupBy("kind").agg(F.count("*").alias("events"))


def entities(ev: DataFrame, approx: bool = False) -> DataFrame:
    """Different object entities, by kind and over all; ``approx`` counts by a sketch of fixed size."""
    n = F.approx_count_distinct("entity_id") if approx else F.countDistinct("entity_id")
    return ev.where("entity_id is not null").rollup("kind").agg(n.alias("entities")).select(F.coalesce("kind", F.lit("all")).alias("kind"), "entities")


def entity_sketch(ev: DataFrame) -> DataFrame:
    """One mergeable sketch per kind, merged for the total."""
    per = ev.where("entity_id is not null").groupBy("kind").agg(F.hll_sketch_agg("entity_id").alias("s"))
    return per.select("kind", F.hll_sketch_estimate("s").alias("entities")).unionByName(per.agg(F.lit("all").alias("kind"), F.hll_sketch_estimate(F.hll_union_agg("s")).alias("entities")))


def result_quantiles(ev: DataFrame) -> DataFrame:
    """Quartiles of assay results by a KLL sketch."""
    s = ev.where("kind = 'assay'").agg(F.expr("kll_sketch_agg_double(result)").alias("s"))
    return s.select(*(F.expr(f"kll_sketch_get_quantile_double(s, {q})").alias(f"q{int(q * 100)}") for q in (0.25, 0.5, 0.75)))


def sketches(ev: DataFrame, most: float = 0.15) -> DataFrame:
    """(kind, entities, approx_close, sketch_close): exact counts, and whether both approximations lie within ``most`` of them, three standard errors of the coarser one."""
    exact = entities(ev)
    a = entities(ev, approx=True).select("kind", F.col("entities").alias("a"))
    s = entity_sketch(ev).select("kind", F.col("entities").alias("s"))
    near = lambda c: F.abs(F.col(c) - F.col("entities")) <= F.greatest(F.col("entities") * most, F.lit(1.0))
    return exact.join(a, "kind").join(s, "kind").select("kind", "entities", near("a").alias("approx_close"), near("s").alias("sketch_close"))


def quantiles_close(ev: DataFrame, most: float = 0.02) -> DataFrame:
    """(q, below, close): for each quartile, how many results lie at or below its sketched value, as a share of all, and whether that is within ``most`` of it."""
    q = result_quantiles(ev)
    each = q.select(F.explode(F.array(*(F.struct(F.lit(int(c[1:])).alias("q"), F.col(c).alias("v")) for c in q.columns))).alias("x")).select("x.*")
    some = ev.where("kind = 'assay'").select("result").join(F.broadcast(each), F.lit(True))
    got = some.groupBy("q").agg((F.count_if(F.col("result") <= F.col("v")) / F.count("result")).alias("share"), F.count("result").alias("results"))
    return got.select("q", "results", (F.abs(F.col("share") - F.col("q") / 100) <= most).alias("close"))


def records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Source records by kind."""
    ev = ev_mod.extract(spark, sf_dir).groupBy(F.col("kind").alias("record")).agg(F.count("*").alias("n"))
    return table(spark, sf_dir, "customer", "c_custkey").agg(F.lit("patient").alias("record"), F.count("*").alias("n")).unionByName(ev)


def per_patient(ev: DataFrame, rel: DataFrame) -> DataFrame:
    """Events, edges, edges an event, and the number of different begins, of every patient with events."""
    e = ev.groupBy("patient_id").agg(F.count("*").alias("events"), F.countDistinct("begin_ts").alias("chain_length"))
    r = rel.groupBy("patient_id").agg(F.count("*").alias("r"))
    n = F.coalesce("r", F.lit(0))
    return e.join(r, "patient_id", "left").select("patient_id", "events", n.alias("edges"), F.round(n / F.col("events"), 6).alias("density"), "chain_length")


def link_rate(ev: DataFrame, links: DataFrame, over: str = "events") -> DataFrame:
    """(kind, linked, total, rate): over occurrences, or over different mentions.

    ``ev`` (kind, mention, …) has a row an event or carries their number in n.
    """
    n = F.col("n") if "n" in ev.columns else F.lit(1)
    base = ev.groupBy("kind", "mention").agg((F.sum(n) if over == "events" else F.lit(1)).cast("long").alias("n"))
    held = base.join(links.where("accepted").select("kind", "mention", F.lit(1).alias("hit")), ["kind", "mention"], "left")
    out = held.groupBy("kind").agg(F.sum(F.when(F.col("hit") == 1, F.col("n")).otherwise(0)).alias("linked"), F.sum("n").alias("total"))
    return out.withColumn("rate", F.round(F.col("linked") / F.col("total"), 6))
