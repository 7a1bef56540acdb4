"""Graph patterns, and two ways to run them.

A pattern has event variables of one patient, each a star: its kind, object,
properties. Between variables stand temporal predicates. The star executor scans
EVENT once a variable and joins on the patient, with times compared in the join;
the triple executor joins once for every triple pattern. Both give the patients
that match.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from caregraph.operators.ontology import EVENT_CLASS


@dataclass(frozen=True)
class Star:
    """An event variable and what it must have."""

    name: str
    kind: str
    label: str | None = None
    type: str | None = None
    brand: str | None = None
    prompt: str | None = None
    names: DataFrame | None = None
    """(name): labels that are allowed, from an expansion of the terminology graph."""


@dataclass(frozen=True)
class Pattern:
    stars: tuple[Star, ...] = ()
    temporal: tuple[tuple[str, str, str], ...] = ()
    same: tuple[tuple[str, str, str], ...] = ()
    category: str | None = None
    extra: dict = field(default_factory=dict)

    def event(self, name: str, kind: str, **has) -> "Pattern":
        return replace(self, stars=(*self.stars, Star(name, kind, **has)))

    def rel(self, a: str, relation: str, b: str) -> "Pattern":
        return replace(self, temporal=(*self.temporal, (a, relation, b)))

    def share(self, a: str, column: str, b: str) -> "Pattern":
        """Two variables whose objects agree in a column."""
        return replace(self, same=(*self.same, (a, column, b)))

    def patient(self, category: str) -> "Pattern":
        return replace(self, category=category)


def classify(p: Pattern) -> str:
    """SE: one event. ME: several. CME: several, in time."""
    return "CME" if p.temporal else "ME" if len(p.stars) > 1 else "SE"


def holds(rel: str, a: str, b: str) -> Column:
    """Whether a relation of the closure holds, from times alone."""
    ab, ae, bb, be = (F.col(f"{v}_{c}") for v in (a, b) for c in ("b", "e"))
    return {
        "Before": ae < bb,
        "After": ab > be,
        "Concurrent": (ab == bb) & (ae == be),
        "During": (bb < be) & (ab >= bb) & (ab <= be) & ((ae < be) | ((ab == ae) & (ab == be))),
        "Overlap": (ab < ae) & (bb < be) & (ab > bb) & (ab <= be) & (ae > be),
    }[rel]


def _has(star: Star) -> Column:
    """What an event of this variable has in its own columns."""
    held = F.col("kind") == star.kind
    for c in ("label", "type", "brand", "prompt"):
        if (v := getattr(star, c)) is not None:
            held &= F.col(c) == v
    return held


def any_of(stars: list[Star], ev: DataFrame) -> DataFrame:
    """Events that some of the variables could be; allowed names aren't looked at."""
    return ev.where(reduce(Column.__or__, map(_has, stars), F.lit(False)))


def _scan(star: Star, ev: DataFrame, keep: set[str]) -> DataFrame:
    df = ev.where(_has(star))
    if star.names is not None:
        df = df.join(star.names.select(F.col("name").alias("label")), "label", "left_semi")
    n = star.name
    return df.select("patient_id", F.col("event_id").alias(f"{n}_id"), F.col("begin_ts").alias(f"{n}_b"), F.col("end_ts").alias(f"{n}_e"), *(F.col(c).alias(f"{n}_{c}") for c in sorted(keep)))


def exec_wide(p: Pattern, ev: DataFrame, patients: DataFrame) -> DataFrame:
    """(patient_id) by stars over EVENT with labels. Variables without a temporal predicate only have to exist: they become semi-joins."""
    out = patients.where(F.col("category") == p.category).select("patient_id") if p.category else None
    timed = {v for a, _, b in (*p.temporal, *p.same) for v in (a, b)}
    loose = [s for s in p.stars if s.name not in timed]
    for s in loose:
        scan = _scan(s, ev, set()).select("patient_id")
        out = scan.distinct() if out is None else out.join(scan, "patient_id", "left_semi")
    seen: set[str] = set()
    for s in (s for s in p.stars if s.name in timed):
        keep = {c for a, c, b in p.same if s.name in (a, b)}
        scan = _scan(s, ev, keep)
        out = scan if out is None else out.join(scan, "patient_id")
        seen.add(s.name)
        for a, r, b in p.temporal:
            if {a, b} <= seen and s.name in (a, b):
                out = out.where(holds(r, a, b))
        for a, c, b in p.same:
            if {a, b} <= seen and s.name in (a, b):
                out = out.where(F.col(f"{a}_{c}") == F.col(f"{b}_{c}"))
        # Columns of variables that no later predicate needs go, and so do repeats.
        later = {v for a, _, b in (*p.temporal, *p.same) if not {a, b} <= seen for v in (a, b)} & seen
        keepers = [c for c in out.columns if c == "patient_id" or any(c.startswith(v + "_") and not c.endswith("_id") for v in later)]
        out = out.select(*keepers).distinct()
    return out.select("patient_id").distinct()


def having_all(p: Pattern, ev: DataFrame, patients: DataFrame) -> DataFrame:
    """(patient_id) of those who have an event for each variable, whatever the times: what a question with time can be about."""
    return exec_wide(replace(p, temporal=(), same=()), ev, patients)


def exec_triples(p: Pattern, triples: DataFrame, mode: str = "timestamps", closure: DataFrame | None = None) -> DataFrame:
    """(patient_id) by self-joins of triples: one for each triple pattern.

    ``mode`` timestamps compares begin and end literals; edges and closure join
    the given relation rows (src, dst, relation) instead.
    """

    def of(pred: str, s: str, o: str) -> DataFrame:
        return triples.where(F.col("p") == pred).select(F.col("s").alias(s), F.col("o").alias(o))

    # Patterns with a value come first, so that what is joined with them is small from then on.
    out = of("cg:category", "patient", "cat").where(F.col("cat") == p.category) if p.category else None
    for s in p.stars:
        n = s.name
        shared = {c for a, c, b in p.same if n in (a, b)}
        own = [(v, c, of(pred, f"{n}_ent", f"{n}_{c}")) for v, c, pred in ((s.label, "label", "cg:label"), (s.type, "type", "cg:broaderType"), (s.brand, "brand", "cg:broaderBrand")) if v or c in shared]
        steps = [(f"{n}_ent", at.where(F.col(f"{n}_{c}") == v)) for v, c, at in own if v]
        if own:
            steps.append((f"{n}_ent", of("cg:hasActor", f"{n}_id", f"{n}_ent").where(F.startswith(f"{n}_ent", F.lit("cg:entity/")))))
            steps += [(f"{n}_ent", at) for v, _, at in own if not v]
        if s.prompt:
            steps.append((f"{n}_id", of("cg:assayPrompt", f"{n}_id", f"{n}_p").where(F.col(f"{n}_p") == s.prompt)))
        steps.append((f"{n}_id", triples.where((F.col("p") == "rdf:type") & (F.col("o") == "cg:" + EVENT_CLASS[s.kind])).select(F.col("s").alias(f"{n}_id"))))
        steps.append((f"{n}_id", of("cg:hasActor", f"{n}_id", "patient").where(F.startswith("patient", F.lit("cg:patient/")))))
        steps += [(f"{n}_id", of(pred, f"{n}_id", f"{n}_{c}")) for c, pred in (("b", "cg:hasBegin"), ("e", "cg:hasEnd"))]
        star = reduce(lambda x, step: x.join(step[1], step[0]), steps[1:], steps[0][1])
        out = star if out is None else out.join(star, "patient")
        for a, r, b in p.temporal:
            names = {x.name for x in p.stars[: p.stars.index(s) + 1]}
            if {a, b} <= names and n in (a, b):
                if mode == "timestamps":
                    out = out.where(holds(r, a, b))
                else:
                    edge = closure.where(F.col("relation") == r).select(F.concat(F.lit("cg:event/"), "src").alias(f"{a}_id"), F.concat(F.lit("cg:event/"), "dst").alias(f"{b}_id"))
                    out = out.join(edge, [f"{a}_id", f"{b}_id"], "left_semi")
        for a, c, b in p.same:
            names = {x.name for x in p.stars[: p.stars.index(s) + 1]}
            if {a, b} <= names and n in (a, b):
                out = out.where(F.col(f"{a}_{c}") == F.col(f"{b}_{c}"))
    return out.select(F.substring("patient", len("cg:patient/") + 1, 32).cast("long").alias("patient_id")).distinct()
