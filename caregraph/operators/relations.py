"""Temporal relations between events of one patient.

Before is stored for neighbours only: B is an immediate successor of A unless
some C lies between them, that is, unless C begins after A ends and ends before
B begins. With m(A) the least end among the events that begin after A ends, B
follows immediately iff A.end < B.begin <= m(A). So one sort per patient gives
the bounds, bounds become ranges of places among the patient's begins, and ranges become an equi-join;
no pair of events is made that isn't an edge. During, Overlap and Concurrent are found the
same way: what begins inside a period has a place in the period's range.
"""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from caregraph.operators.timeline import relation_of
from caregraph.store import saved

CORE = ("patient_id", "event_id", "begin_ts", "end_ts", "time_kind")
CHUNK = 256
"""Places of a range are exploded in blocks of so many, so a very long period is never one row's array."""


def step_of(a: Column, b: Column) -> Column:
    """Pass that builds a Before, After or Concurrent edge: points 1, periods 2, mixed 3."""
    return F.when((a == "point") & (b == "point"), 1).when((a == "period") & (b == "period"), 2).otherwise(3)


def successor_bounds(ev: DataFrame) -> DataFrame:
    """Each event with m: the least end of those that begin after it ends (null without any).

    Ends probe begins in one sort: going back in time, an end sees the begins
    passed so far, and comes first where times tie.
    """
    probe = ev.select(*CORE, F.col("end_ts").alias("t"), F.lit(0).alias("build"))
    build = ev.select(*CORE, F.col("begin_ts").alias("t"), F.lit(1).alias("build"))
    w = Window.partitionBy("patient_id").orderBy(F.desc("t"), "build").rowsBetween(Window.unboundedPreceding, -1)
    both = probe.unionByName(build).withColumn("m", F.min(F.when(F.col("build") == 1, F.col("end_ts"))).over(w))
    return both.where("build = 0").select(*CORE, "m")


def placed(ev: DataFrame) -> DataFrame:
    """Events with their place among the patient's begins: idx (own, ties in id order), first (of those that begin with it), upto (the last that begins by its end), hi.

    The events that follow it immediately have the places upto + 1 .. hi; hi is null where
    nothing follows. What begins inside a period has the places first .. upto.
    With m as in the module's text, hi is the number of begins by m; as that number grows with
    the end, it's the least ``upto`` of all later events. Both steps sort a patient's
    events once, and nothing but the patient is a key, so EVENT rows that are already dealt by patient aren't shuffled.
    """
    ends = F.array(F.struct(F.col("begin_ts").alias("t"), F.lit(0).alias("is_end")), F.struct(F.col("end_ts").alias("t"), F.lit(1).alias("is_end")))
    both = ev.select(*CORE, F.explode(ends).alias("x")).select(*CORE, "x.t", "x.is_end")
    order = Window.partitionBy("patient_id").orderBy("t", "is_end", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    both = both.withColumn("n", F.sum(1 - F.col("is_end")).over(order))
    both = both.withColumn("lead_n", F.min(F.when(F.col("is_end") == 0, F.col("n"))).over(Window.partitionBy("patient_id", "t")))
    at = lambda c, end: F.max(F.when(F.col("is_end") == end, F.col(c)))
    one = both.groupBy(*CORE).agg(at("n", 0).alias("idx"), at("lead_n", 0).alias("first"), at("n", 1).alias("upto"))
    keys = F.array(F.struct(F.col("idx").alias("k"), F.lit(0).alias("probe")), F.struct((F.col("upto") + 1).alias("k"), F.lit(1).alias("probe")))
    each = one.select("*", F.explode(keys).alias("x")).select(*one.columns, "x.k", "x.probe")
    later = Window.partitionBy("patient_id").orderBy(F.desc("k"), "probe").rowsBetween(Window.unboundedPreceding, 0)
    return each.withColumn("hi", F.min(F.when(F.col("probe") == 0, F.col("upto"))).over(later)).where("probe = 1").drop("k", "probe")


def _meet(ranges: DataFrame, events: DataFrame) -> DataFrame:
    """Joins every row's range of places [lo, hi] to the events that stand there, whose columns end in _b."""
    blocks = ranges.where("lo <= hi").withColumn("at", F.explode(F.sequence("lo", "hi", F.lit(CHUNK))))
    each = blocks.withColumn("idx", F.explode(F.sequence("at", F.least(F.col("hi"), F.col("at") + (CHUNK - 1))))).drop("at", "lo", "hi")
    other = events.select("patient_id", "idx", *(F.col(c).alias(c + "_b") for c in CORE if c != "patient_id"))
    return each.join(other, ["patient_id", "idx"]).drop("idx")


def _edges(ev: DataFrame, wanted: set[str], equal_end: str = "none", inverse: bool = False) -> DataFrame:
    """(patient_id, src, dst, relation, step) of the ``wanted`` relations, from one range join: what begins inside an event, and what follows it immediately, stand side by side."""
    at = placed(ev)
    inside = wanted & {"During", "Overlap", "Concurrent"}
    periods_only = bool(inside) and "Concurrent" not in inside
    lo = F.col("first") if inside and not periods_only else F.when(F.col("time_kind") == "period", F.col("first")).otherwise(F.col("upto") + 1) if inside else F.col("upto") + 1
    hi = F.coalesce("hi", "upto") if "Before" in wanted else F.col("upto")
    ranges = at.select(*CORE, lo.alias("lo"), hi.alias("hi"))
    met = _meet(ranges, at).where("event_id <> event_id_b")
    # The event whose begin lies in the range is the later one, or the inner one.
    after = F.col("begin_ts_b") > F.col("end_ts")
    held = relation_of(F.col("begin_ts_b"), F.col("end_ts_b"), F.col("begin_ts"), F.col("end_ts"), equal_end)
    edge = lambda src, dst, relation, step: F.struct(F.col(src).alias("src"), F.col(dst).alias("dst"), relation.alias("relation"), step.alias("step"))
    step = step_of(F.col("time_kind"), F.col("time_kind_b"))
    names = [k for k in ("During", "Overlap") if k in wanted]
    cases = F.when(after, F.array(edge("event_id", "event_id_b", F.lit("Before"), step), *([edge("event_id_b", "event_id", F.lit("After"), step)] if inverse else [])) if "Before" in wanted else F.array())
    if "Concurrent" in wanted:
        cases = cases.when((held == "Concurrent") & (F.col("event_id") < F.col("event_id_b")), F.array(edge("event_id", "event_id_b", F.lit("Concurrent"), step)))
    if names:
        cases = cases.when(held.isin(*names), F.array(edge("event_id_b", "event_id", held, F.when(F.col("time_kind_b") == "point", 3).otherwise(4))))
    return met.select("patient_id", F.inline(cases))


def immediate_before(ev: DataFrame) -> DataFrame:
    """(patient_id, src, dst, step): the transitive reduction of Before."""
    return _edges(ev, {"Before"}).drop("relation")


def full_before(ev: DataFrame) -> DataFrame:
    """(patient_id, src, dst, step): every Before pair; as many as the square of a patient's events. The baseline that reduction avoids."""
    a = ev.select(*CORE)
    b = ev.select("patient_id", *(F.col(c).alias(c + "_b") for c in CORE if c != "patient_id"))
    met = a.join(b, "patient_id").where(F.col("end_ts") < F.col("begin_ts_b"))
    return met.select("patient_id", F.col("event_id").alias("src"), F.col("event_id_b").alias("dst"), step_of(F.col("time_kind"), F.col("time_kind_b")).alias("step"))


def concurrent(ev: DataFrame, density: str = "reduced") -> DataFrame:
    """(patient_id, src, dst, step): events with equal spans. Pairs with src < dst, or for density chain the links of each group in id order."""
    keys = ["patient_id", "begin_ts", "end_ts"]
    if density == "chain":
        w = Window.partitionBy(*keys).orderBy("event_id")
        out = ev.select(*CORE).withColumn("dst", F.col("event_id")).withColumn("src", F.lag("event_id").over(w)).where("src is not null")
    else:
        b = ev.select(*keys, F.col("event_id").alias("dst"))
        out = ev.select(*CORE).withColumnRenamed("event_id", "src").join(b, keys).where("src < dst")
    return out.select("patient_id", "src", "dst", step_of(F.col("time_kind"), F.col("time_kind")).alias("step"))


def stabbed(ev: DataFrame, equal_end: str = "none") -> DataFrame:
    """(patient_id, src, dst, relation, step): During and Overlap, from a range join of periods with what begins inside them."""
    return _edges(ev, {"During", "Overlap"}, equal_end)


def equal_ends(ev: DataFrame) -> DataFrame:
    """Pairs of periods with one end where the first begins later: in no relation by default."""
    p = ev.where("time_kind = 'period'").select(*CORE)
    b = p.select("patient_id", "end_ts", F.col("event_id").alias("dst"), F.col("begin_ts").alias("bb"))
    return p.join(b, ["patient_id", "end_ts"]).where("begin_ts > bb").select("patient_id", F.col("event_id").alias("src"), "dst")


def representatives(ev: DataFrame) -> DataFrame:
    """The first event of each group with equal spans."""
    w = Window.partitionBy("patient_id", "begin_ts", "end_ts").orderBy("event_id")
    return ev.withColumn("__rn", F.row_number().over(w)).where("__rn = 1").drop("__rn")


def before(ev: DataFrame, density: str = "reduced", scope: str = "global") -> DataFrame:
    """Before edges. density: full, reduced or chain; scope per_step reduces points and periods each by their own kind only."""
    if density == "full":
        return full_before(ev)
    base = representatives(ev) if density == "chain" else ev
    if scope == "global":
        return immediate_before(base)
    points, periods = (base.where(F.col("time_kind") == k) for k in ("point", "period"))
    return immediate_before(points).unionByName(immediate_before(periods)).unionByName(immediate_before(base).where("step = 3"))


def with_inverse(rel: DataFrame) -> DataFrame:
    """Adds After for every Before, in one pass."""
    own = F.struct("src", "dst", "relation")
    back = F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit("After").alias("relation"))
    both = F.when(F.col("relation") == "Before", F.array(own, back)).otherwise(F.array(own))
    return rel.select("patient_id", F.inline(both), *(c for c in rel.columns if c not in ("patient_id", "src", "dst", "relation"))).select(rel.columns)


RELATIONS = ("Before", "After", "Concurrent", "During", "Overlap")


def build(ev: DataFrame, density: str = "reduced", scope: str = "global", equal_end: str = "none", inverse: bool = True, wanted: Iterable[str] = RELATIONS) -> DataFrame:
    """The ``wanted`` relations of the four passes, in the RELATION schema; ``inverse`` False leaves After out.

    Reduced relations come from one range join; only Before of another density or scope is made by itself.
    """
    origin = F.lit("asserted").alias("origin")
    wanted, columns = set(wanted), ("patient_id", "src", "dst", "relation", "step")
    if not inverse:
        wanted -= {"After"}
    if wanted & {"Before", "After"} and (density, scope) == ("reduced", "global"):
        out = _edges(ev, wanted | {"Before"}, equal_end, "After" in wanted)
        return (out if "Before" in wanted else out.where("relation <> 'Before'")).select(*columns, origin)
    parts = []
    if wanted & {"Before", "After"}:
        b = before(ev, density, scope).select("patient_id", "src", "dst", F.lit("Before").alias("relation"), "step")
        b = with_inverse(b) if "After" in wanted else b
        parts.append(b if "Before" in wanted else b.where("relation = 'After'"))
    if "Concurrent" in wanted and density == "chain":
        parts.append(concurrent(ev, density).select("patient_id", "src", "dst", F.lit("Concurrent").alias("relation"), "step"))
    rest = wanted & ({"During", "Overlap"} if density == "chain" else {"Concurrent", "During", "Overlap"})
    if rest:
        parts.append(_edges(ev, rest, equal_end))
    return reduce(DataFrame.unionByName, [p.select(*columns) for p in parts]).select(*columns, origin)


def steps(ev: DataFrame, step: int, density: str = "reduced", scope: str = "global", equal_end: str = "none") -> DataFrame:
    """One of the four passes; it makes only the relations that the pass can give, from events that can have them."""
    wanted = {1: ("Before", "After", "Concurrent"), 2: ("Before", "After", "Concurrent"), 3: RELATIONS, 4: ("During", "Overlap")}[step]
    some = ev.where("time_kind = 'period'") if step == 4 else ev
    return build(some, density, scope, equal_end, wanted=wanted).where(F.col("step") == step)


def redundancy(ev: DataFrame) -> DataFrame:
    """(patient_id, full_edges, reduced_edges): Before edges that reduction saves.

    The full count needs no pairs: an end sees how many begins come after it.
    """
    probe = ev.select("patient_id", F.col("end_ts").alias("t"), F.lit(0).alias("build"))
    begins = ev.select("patient_id", F.col("begin_ts").alias("t"), F.lit(1).alias("build"))
    w = Window.partitionBy("patient_id").orderBy(F.desc("t"), "build").rowsBetween(Window.unboundedPreceding, -1)
    full = probe.unionByName(begins).withColumn("later", F.coalesce(F.sum("build").over(w), F.lit(0))).where("build = 0").groupBy("patient_id").agg(F.sum("later").alias("full_edges"))
    less = immediate_before(ev).groupBy("patient_id").agg(F.count("*").alias("reduced_edges"))
    return full.join(less, "patient_id", "left").select("patient_id", "full_edges", F.coalesce("reduced_edges", F.lit(0)).alias("reduced_edges"))


def assert_same_patient(rel: DataFrame, ev: DataFrame) -> DataFrame:
    """Edges whose ends aren't both events of the edge's patient; must be empty."""
    # Different ends first: each event is an end of many edges. Edges are looked up again only for ends that aren't events.
    own = ev.where("patient_id is not null and event_id is not null").select("patient_id", F.col("event_id").alias("e"), F.lit(0).alias("unknown"))
    ends = rel.select("patient_id", F.explode(F.array("src", "dst")).alias("e"), F.lit(1).alias("unknown"))
    bad = ends.unionByName(own).groupBy("patient_id", "e").agg(F.min("unknown").alias("unknown")).where("unknown = 1").select(F.col("patient_id").alias("p"), "e")
    bad = saved(bad)
    if bad.isEmpty():
        return rel.select("patient_id", "src", "dst").limit(0)
    edges = rel.select("patient_id", "src", "dst")
    held = [edges.join(bad, edges["patient_id"].eqNullSafe(bad["p"]) & edges[end].eqNullSafe(bad["e"]), "left_semi") for end in ("src", "dst")]
    return held[0].unionByName(held[1]).distinct()
