"""N-Triples as text: writing, reading, and a data source."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Namespaces of the prefixes in use.
PREFIXES = {"cg": "urn:caregraph:", "rdf": "http://www.w3.org/1999/02/22-rdf-syntax-ns#", "xsd": "http://www.w3.org/2001/XMLSchema#"}


def _expand(c: Column) -> Column:
    for k, v in PREFIXES.items():
        c = F.when(F.startswith(c, F.lit(k + ":")), F.concat(F.lit(v), F.substring(c, F.lit(len(k) + 2), F.length(c)))).otherwise(c)
    return c


def _shrink(c: Column) -> Column:
    for k, v in PREFIXES.items():
        c = F.when(F.startswith(c, F.lit(v)), F.concat(F.lit(k + ":"), F.substring(c, F.lit(len(v) + 1), F.length(c)))).otherwise(c)
    return c


def _escape(c: Column) -> Column:
    for raw, out in (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t")):
        c = F.replace(c, F.lit(raw), F.lit(out))
    return c


def _unescape(c: Column) -> Column:
    # A backslash pair is set aside first, so that what follows it isn't read as an escape.
    c = F.replace(c, F.lit("\\\\"), F.lit("\x00"))
    for raw, out in (('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t")):
        c = F.replace(c, F.lit(out), F.lit(raw))
    return F.replace(c, F.lit("\x00"), F.lit("\\"))


def lines(t: DataFrame) -> DataFrame:
    """(value): a line for each triple."""
    node = lambda c: F.when(F.startswith(c, F.lit("_:")), c).otherwise(F.concat(F.lit("<"), _expand(c), F.lit(">")))
    tail = F.when(F.col("lang").isNotNull(), F.concat(F.lit("@"), "lang")).when(F.col("datatype").isNotNull(), F.concat(F.lit("^^<"), _expand(F.col("datatype")), F.lit(">"))).otherwise("")
    obj = F.when(F.col("o_kind") == "literal", F.concat(F.lit('"'), _escape(F.col("o")), F.lit('"'), tail)).otherwise(node(F.col("o")))
    return t.select(F.concat(node(F.col("s")), F.lit(" "), node(F.col("p")), F.lit(" "), obj, F.lit(" .")).alias("value"))


LINE = r'^(<[^>]*>|_:\S+) <([^>]*)> (?:(<[^>]*>|_:\S+)|"(.*)"(?:@([\w-]+)|\^\^<([^>]*)>)?) \.$'


def parse_line(line: str) -> tuple | None:
    """``parse`` of one line, for readers outside the JVM."""
    m = re.match(LINE, line)
    if not m:
        return None

    def short(x: str) -> str:
        return next((k + ":" + x[len(v) :] for k, v in PREFIXES.items() if x.startswith(v)), x)

    def node(x: str) -> str:
        return short(x[1:-1]) if x.startswith("<") else x

    s, p, ref, literal, lang, kind = m.groups()
    if ref is None:
        plain = {"n": "\n", "r": "\r", "t": "\t"}
        o = re.sub(r"\\(.)", lambda x: plain.get(x[1], x[1]), literal)
    else:
        o = node(ref)
    return node(s), short(p), o, "literal" if ref is None else "bnode" if ref.startswith("_:") else "iri", short(kind) if kind else None, lang


def parse(text: DataFrame) -> DataFrame:
    """TRIPLE rows of lines (value); lines that aren't triples are left out."""
    pattern = LINE
    g = lambda k: F.regexp_extract("value", pattern, k)
    node = lambda c: _shrink(F.when(F.startswith(c, F.lit("<")), F.substring(c, F.lit(2), F.length(c) - 2)).otherwise(c))
    some = lambda c: F.when(c != "", c)
    kind = F.when(g(3) == "", "literal").when(F.startswith(g(3), F.lit("_:")), "bnode").otherwise("iri")
    return text.where(F.rlike("value", F.lit(pattern))).select(node(g(1)).alias("s"), _shrink(g(2)).alias("p"), F.when(g(3) == "", _unescape(g(4))).otherwise(node(g(3))).alias("o"), kind.alias("o_kind"), some(_shrink(g(6))).alias("datatype"), some(g(5)).alias("lang"))


def write(t: DataFrame, path: str, mode: str = "errorifexists") -> None:
    lines(t).write.mode(mode).text(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    return parse(spark.read.text(path))
