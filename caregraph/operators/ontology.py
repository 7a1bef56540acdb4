"""Ontology as data: classes, their superclasses, and what properties link."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Class, superclass.
CLASSES = [
    ("Actor", "Thing"), ("Object", "Actor"), ("Event", "Thing"), ("Patient", "Actor"),
    ("Disease", "Object"), ("Drug", "Object"), ("Assay", "Object"), ("Surgery", "Object"),
    ("StayEvent", "Event"), ("DiagnosisEvent", "Event"), ("DrugEvent", "Event"), ("AssayEvent", "Event"), ("SurgeryEvent", "Event"),
]
#: Property, domain, range.
PROPERTIES = [
    ("hasActor", "Event", "Actor"), ("hasBegin", "Event", "literal"), ("hasEnd", "Event", "literal"), ("situation", "Event", "literal"),
    ("assayResult", "AssayEvent", "literal"), ("assayPrompt", "AssayEvent", "literal"), ("category", "Patient", "literal"), ("birthday", "Patient", "literal"),
    ("label", "Thing", "literal"), ("broaderBrand", "Object", "literal"), ("broaderType", "Object", "literal"),
    ("Before", "Event", "Event"), ("After", "Event", "Event"), ("Concurrent", "Event", "Event"), ("During", "Event", "Event"), ("Overlap", "Event", "Event"),
]
EVENT_CLASS = {"stay": "StayEvent", "diagnosis": "DiagnosisEvent", "drug": "DrugEvent", "assay": "AssayEvent", "surgery": "SurgeryEvent"}
OBJECT_CLASS = {"diagnosis": "Disease", "drug": "Drug", "assay": "Assay", "surgery": "Surgery"}


@dataclass
class Ontology:
    """Classes and properties; both can be added to without code."""

    classes: list[tuple[str, str]] = field(default_factory=lambda: list(CLASSES))
    properties: list[tuple[str, str, str]] = field(default_factory=lambda: list(PROPERTIES))

    def register_class(self, name: str, parent: str) -> None:
        if parent != "Thing" and parent not in {c for c, _ in self.classes}:
            raise ValueError(f"unknown superclass {parent}")
        self.classes.append((name, parent))

    def register_property(self, name: str, domain: str, range_: str) -> None:
        self.properties.append((name, domain, range_))

    def frame(self, spark: SparkSession) -> DataFrame:
        """(sub, pred, super): the class tree, and domain and range of properties."""
        rows = [(a, "subClassOf", b) for a, b in self.classes]
        rows += [(p, "domain", d) for p, d, _ in self.properties] + [(p, "range", r) for p, _, r in self.properties]
        return values(spark, rows, ("sub", "pred", "super"))

    def superclasses(self, spark: SparkSession, cls: str | None = None, more: DataFrame | None = None) -> DataFrame:
        """(cls, super, steps): all superclasses, by a recursive query. ``more`` (cls, parent): classes that come from data; each pair of steps counts once."""
        own = values(spark, self.classes, ("cls", "parent"))
        (own.unionByName(more) if more is not None else own).createOrReplaceTempView("__cg_classes")
        out = spark.sql("""
            WITH RECURSIVE up(cls, super, steps) AS (
              SELECT cls, parent, 1 FROM __cg_classes
              UNION ALL SELECT u.cls, c.parent, u.steps + 1 FROM up u JOIN __cg_classes c ON c.cls = u.super)
            SELECT DISTINCT * FROM up""")
        return out.where(F.col("cls") == cls) if cls else out

    def validate(self, spark: SparkSession, triples: DataFrame) -> DataFrame:
        """(s, p, o, fault): triples whose ends aren't of the property's domain or range. Types come from the triples themselves."""
        up = self.superclasses(spark).select("cls", "super").unionByName(values(spark, [(c, c) for c, _ in self.classes], ("cls", "super"))).unionByName(values(spark, [(c, "Thing") for c, _ in self.classes], ("cls", "super"))).distinct()
        props = values(spark, self.properties, ("p", "domain", "range"))
        types = triples.where("p = 'rdf:type'").select(F.col("s").alias("node"), F.regexp_replace("o", "^cg:", "").alias("cls")).join(F.broadcast(up), "cls").select("node", "super").distinct()
        used = triples.where("p <> 'rdf:type'").withColumn("q", F.regexp_replace("p", "^cg:", "")).join(F.broadcast(props), F.col("q") == props["p"]).select(triples["s"], triples["p"], "o", "o_kind", "domain", "range")
        wrong = used.join(types, (used["s"] == types["node"]) & (used["domain"] == types["super"]), "left_anti").select("s", "p", "o", F.lit("domain").alias("fault"))
        literal = used.where((F.col("range") == "literal") & (F.col("o_kind") != "literal")).select("s", "p", "o", F.lit("range").alias("fault"))
        refs = used.where(F.col("range") != "literal")
        bad = refs.join(types, (refs["o"] == types["node"]) & (refs["range"] == types["super"]), "left_anti").select("s", "p", "o", F.lit("range").alias("fault"))
        return wrong.unionByName(literal).unionByName(bad)


def values(spark: SparkSession, rows: list[tuple], names: tuple[str, ...]) -> DataFrame:
    """A small constant table as a local relation, so that it can be folded and broadcast."""
    quoted = ", ".join("(" + ", ".join("'" + str(x).replace("'", "''") + "'" for x in r) + ")" for r in rows)
    return spark.sql(f"SELECT * FROM VALUES {quoted} AS t({', '.join(names)})")
