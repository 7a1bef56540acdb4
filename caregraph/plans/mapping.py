"""Declarative maps from tables to triples.

A map emits all of its triples in one scan: an array of structs, exploded. A
reference to another map's subject needs no join when that subject's template
uses only the foreign key; otherwise the parent's columns are joined first.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.operators import ontology
from caregraph.sources import records

XSD = {"bigint": "xsd:integer", "int": "xsd:integer", "double": "xsd:double", "string": "xsd:string", "date": "xsd:date", "timestamp_ntz": "xsd:dateTime", "boolean": "xsd:boolean"}


@dataclass(frozen=True)
class Template:
    """Text with {column} places; values are percent-encoded."""

    text: str

    def columns(self) -> list[str]:
        return re.findall(r"\{(\w+)\}", self.text)

    def render(self, rename: dict[str, str] | None = None) -> Column:
        parts = re.split(r"(\{\w+\})", self.text)
        cols = [F.lit(p) if not p.startswith("{") else F.replace(F.call_function("url_encode", F.col((rename or {}).get(p[1:-1], p[1:-1])).cast("string")), F.lit("+"), F.lit("%20")) for p in parts if p]
        return F.concat(*cols)


@dataclass(frozen=True)
class Literal:
    column: str
    datatype: str | None = None
    lang: str | None = None


@dataclass(frozen=True)
class Constant:
    iri: str


@dataclass(frozen=True)
class Ref:
    """The subject of another map, found by (child, parent) columns."""

    parent: "TriplesMap"
    join: tuple[tuple[str, str], ...]


@dataclass(frozen=True)
class TriplesMap:
    table: str
    subject: Template | None
    classes: tuple[str, ...]
    pairs: tuple[tuple[str, "Literal | Constant | Template | Ref"], ...]


def _iri(p: str, o: Column) -> Column:
    return F.struct(F.lit(p).alias("p"), o.alias("o"), F.lit("iri").alias("o_kind"), F.lit(None).cast("string").alias("datatype"), F.lit(None).cast("string").alias("lang"))


def apply(tm: TriplesMap, tables: dict[str, DataFrame]) -> DataFrame:
    """TRIPLE rows of one map; a null object, or a null in a template, emits nothing."""
    df = tables[tm.table]
    if tm.subject is None:
        # Rows without a key are blank nodes, named by their content and a number among equal rows.
        df = blank_nodes(df)
        subject = F.col("__node")
    else:
        subject = tm.subject.render()
    out = [_iri("rdf:type", F.lit(c)) for c in tm.classes]
    for k, (p, o) in enumerate(tm.pairs):
        if isinstance(o, Literal):
            kind = o.datatype or XSD.get(dict(df.dtypes)[o.column], "xsd:string")
            text = F.date_format(o.column, "yyyy-MM-dd'T'HH:mm:ss") if kind == "xsd:dateTime" else F.col(o.column).cast("string")
            out.append(F.struct(F.lit(p).alias("p"), text.alias("o"), F.lit("literal").alias("o_kind"), F.lit(None if o.lang else kind).cast("string").alias("datatype"), F.lit(o.lang).cast("string").alias("lang")))
        elif isinstance(o, Constant):
            out.append(_iri(p, F.lit(o.iri)))
        elif isinstance(o, Template):
            out.append(_iri(p, o.render()))
        else:
            need, keys = o.parent.subject.columns(), {b: a for a, b in o.join}
            if set(need) <= set(keys):
                out.append(_iri(p, o.parent.subject.render(keys)))
            else:
                parent = tables[o.parent.table].select(*(F.col(b).alias(f"__k{k}_{b}") for _, b in o.join), *(F.col(c).alias(f"__r{k}_{c}") for c in need))
                on = [df[a] == parent[f"__k{k}_{b}"] for a, b in o.join]
                df = df.join(parent, on, "left")
                out.append(_iri(p, o.parent.subject.render({c: f"__r{k}_{c}" for c in need})))
    t = df.select(subject.alias("s"), F.explode(F.array(*out)).alias("t"))
    bnode = "bnode" if tm.subject is None else "iri"
    return t.select("s", "t.*").where("s is not null and o is not null").withColumn("s_kind", F.lit(bnode))


def blank_nodes(df: DataFrame) -> DataFrame:
    from pyspark.sql import Window

    h = F.xxhash64(*df.columns)
    w = Window.partitionBy("__h").orderBy(*df.columns)
    return df.withColumn("__h", h).withColumn("__node", F.concat(F.lit("_:b"), F.lower(F.hex("__h")), F.lit("n"), F.row_number().over(w))).drop("__h")


def direct(df: DataFrame, name: str, pk: tuple[str, ...], fks: dict[str, tuple[str, str]]) -> DataFrame:
    """Direct mapping of any table: a type, a literal for each column, a reference for each foreign key {column: (table, its key)}."""
    subject = Template(f"cg:{name}/" + ";".join(f"{c}={{{c}}}" for c in pk)) if pk else None
    pairs: list = [(f"cg:{name}#{c}", Literal(c)) for c in df.columns]
    pairs += [(f"cg:{name}#ref-{c}", Template(f"cg:{t}/{k}={{{c}}}")) for c, (t, k) in fks.items()]
    return apply(TriplesMap(name, subject, (f"cg:{name}",), tuple(pairs)), {name: df})


#: Primary and foreign keys of the relational tables.
KEYS = {
    "region": (("r_regionkey",), {}),
    "nation": (("n_nationkey",), {"n_regionkey": ("region", "r_regionkey")}),
    "customer": (("c_custkey",), {"c_nationkey": ("nation", "n_nationkey")}),
    "supplier": (("s_suppkey",), {"s_nationkey": ("nation", "n_nationkey")}),
    "part": (("p_partkey",), {}),
    "orders": (("o_orderkey",), {"o_custkey": ("customer", "c_custkey")}),
    "lineitem": ((), {"l_orderkey": ("orders", "o_orderkey"), "l_partkey": ("part", "p_partkey"), "l_suppkey": ("supplier", "s_suppkey")}),
    "events": (("event_id",), {"user_id": ("customer", "c_custkey")}),
}

PATIENT = TriplesMap("rec_patient", Template("cg:patient/{patient_id}"), ("cg:Patient",), (("cg:label", Literal("name")), ("cg:category", Literal("category")), ("cg:birthday", Literal("birthday"))))


def _event_map(kind: str) -> TriplesMap:
    pairs: list = [("cg:hasBegin", Literal("begin_ts")), ("cg:hasEnd", Literal("end_ts")), ("cg:hasActor", Ref(PATIENT, (("patient_id", "patient_id"),)))]
    if kind != "stay":
        pairs.append(("cg:hasActor", Template("cg:entity/{entity_id}")))
    if kind in ("stay", "diagnosis"):
        pairs.append(("cg:situation", Literal("situation")))
    if kind == "assay":
        pairs += [("cg:assayResult", Literal("result")), ("cg:assayPrompt", Literal("prompt"))]
    return TriplesMap(f"rec_{kind}", Template("cg:event/{event_id}"), (f"cg:{ontology.EVENT_CLASS[kind]}",), tuple(pairs))


def clinical_maps() -> list[TriplesMap]:
    """The six shipped maps."""
    return [PATIENT, *(_event_map(k) for k in ontology.EVENT_CLASS)]


def entity_triples(ent: DataFrame) -> DataFrame:
    cls = F.create_map(*(x for k, v in ontology.OBJECT_CLASS.items() for x in (F.lit(k), F.lit("cg:" + v))))
    tm = TriplesMap("ent", Template("cg:entity/{entity_id}"), (), (("cg:label", Literal("label")), ("cg:broaderBrand", Literal("brand")), ("cg:broaderType", Literal("type"))))
    named = ent.withColumn("__cls", cls[F.col("kind")])
    typed = named.select(tm.subject.render().alias("s"), F.lit("rdf:type").alias("p"), F.col("__cls").alias("o"), F.lit("iri").alias("o_kind"), F.lit(None).cast("string").alias("datatype"), F.lit(None).cast("string").alias("lang"), F.lit("iri").alias("s_kind"))
    return typed.unionByName(apply(tm, {"ent": ent}))


def clinical(spark: SparkSession, sf_dir: str, ev: DataFrame, ent: DataFrame) -> DataFrame:
    """All entity and event triples, with their class (entity or event)."""
    tables = {"rec_patient": records.patients(spark, sf_dir)} | {f"rec_{k}": ev.where(F.col("kind") == k) for k in ontology.EVENT_CLASS}
    out = entity_triples(ent).withColumn("class", F.lit("entity"))
    for tm in clinical_maps():
        out = out.unionByName(apply(tm, tables).withColumn("class", F.lit("entity" if tm is PATIENT else "event")))
    return out


def temporal(rel: DataFrame) -> DataFrame:
    node = lambda c: F.concat(F.lit("cg:event/"), F.col(c))
    null = F.lit(None).cast("string")
    return rel.select(node("src").alias("s"), F.concat(F.lit("cg:"), "relation").alias("p"), node("dst").alias("o"), F.lit("iri").alias("o_kind"), null.alias("datatype"), null.alias("lang"), F.lit("iri").alias("s_kind"), F.lit("temporal").alias("class"))


def to_wide(t: DataFrame, predicates: list[str]) -> DataFrame:
    """One row a subject, a column a predicate; the layout that queries use."""
    return t.where(F.col("p").isin(*predicates)).groupBy("s").pivot("p", predicates).agg(F.max("o"))


def ego(t: DataFrame, node: str, hops: int = 1) -> DataFrame:
    """Triples around one node: its own, and up to ``hops`` steps those of what they mention."""
    held = t.where((F.col("s") == node) | (F.col("o") == node))
    for _ in range(hops - 1):
        seen = held.select(F.explode(F.array("s", F.when(F.col("o_kind") == "iri", F.col("o")))).alias("n")).where("n is not null").distinct()
        held = t.join(seen, t["s"] == seen["n"], "left_semi").unionByName(held).distinct()
    return held
