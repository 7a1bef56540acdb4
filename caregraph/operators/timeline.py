"""Time classes, patient timelines, and Allen's thirteen relations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from caregraph.operators.events import time_kind


def classify(ev: DataFrame) -> DataFrame:
    return ev.withColumn("time_kind", time_kind(F.col("begin_ts"), F.col("end_ts")))


def ranked(ev: DataFrame) -> DataFrame:
    """Adds grp (dense rank of the begin), pos and n_p within the patient."""
    w = Window.partitionBy("patient_id")
    o = w.orderBy("begin_ts")
    return ev.withColumn("grp", F.dense_rank().over(o)).withColumn("pos", F.row_number().over(w.orderBy("begin_ts", "end_ts", "event_id"))).withColumn("n_p", F.count("*").over(w))


def allen(ab: Column, ae: Column, bb: Column, be: Column) -> Column:
    """Name of the one of thirteen relations that spans A and B are in.

    Points are spans of no length; where two readings fit then (a point at a
    period's end meets it and finishes it), shared ends go before touching.
    """
    return (
        F.when(ae < bb, "before")
        .when(ab > be, "after")
        .when((ab == bb) & (ae == be), "equal")
        .when((ab == bb) & (ae < be), "starts")
        .when((ab == bb) & (ae > be), "started_by")
        .when((ae == be) & (ab > bb), "finishes")
        .when((ae == be) & (ab < bb), "finished_by")
        .when(ae == bb, "meets")
        .when(ab == be, "met_by")
        .when((ab > bb) & (ae < be), "during")
        .when((ab < bb) & (ae > be), "contains")
        .when((ab < bb) & (ae > bb), "overlaps")
        .otherwise("overlapped_by")
    )


def relation_of(ab: Column, ae: Column, bb: Column, be: Column, equal_end: str = "none") -> Column:
    """The stored relation that holds from A to B, or null (its inverse, or none).

    A closed end holds a point: a point at a period's end is during it.
    ``equal_end`` decides whether a period that ends with another, but begins
    later, is during it.
    """
    period_a, period_b = ab < ae, bb < be
    inside = period_b & (ab >= bb) & (ab <= be) & ((ae < be) | (~period_a & (ab == be)))
    if equal_end == "during":
        inside = inside | (period_a & period_b & (ab > bb) & (ae == be))
    return (
        F.when(ae < bb, "Before")
        .when(ab > be, "After")
        .when((ab == bb) & (ae == be), "Concurrent")
        .when(inside, "During")
        .when(period_a & period_b & (ab > bb) & (ab <= be) & (ae > be), "Overlap")
    )
