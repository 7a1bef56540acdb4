"""Terminology graph: typed terms, and how they relate."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.sources.records import KIND_INDEX, SYNONYMS, table


def terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(kind, label): the vocabulary of every entity type."""
    label = table(spark, sf_dir, "part", "p_name").select(F.lower("p_name").alias("label")).distinct()
    return label.select(F.explode(F.array(*map(F.lit, KIND_INDEX))).alias("kind"), "label")


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, rel, dst): label broader brand and type, brand broader all; synonym and abbreviation of a label; nation broader region."""
    part = table(spark, sf_dir, "part", "p_name", "p_brand", "p_type").distinct()
    pair = part.select(F.lower("p_name").alias("src"), F.explode(F.array("p_brand", "p_type")).alias("dst"))
    out = pair.select("src", F.lit("broader").alias("rel"), "dst").distinct()
    label = part.select(F.lower("p_name").alias("dst")).distinct()
    first, rest = F.substring_index("dst", " ", 1), F.substring_index("dst", " ", -1)
    other = F.lit(None).cast("string")
    for a, b in SYNONYMS.items():
        other = F.when(first == a, F.lit(b)).otherwise(other)
    out = out.unionByName(label.where(other.isNotNull()).select(F.concat(other, F.lit(" "), rest).alias("src"), F.lit("synonym").alias("rel"), "dst"))
    out = out.unionByName(label.select(F.concat(F.substring(first, 1, 1), F.lit(". "), rest).alias("src"), F.lit("abbreviation").alias("rel"), "dst"))
    n, r = table(spark, sf_dir, "nation", "n_name", "n_regionkey"), table(spark, sf_dir, "region", "r_regionkey", "r_name")
    place = n.join(r, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("src"), F.lit("broader").alias("rel"), F.col("r_name").alias("dst"))
    root = r.select(F.col("r_name").alias("src"), F.lit("broader").alias("rel"), F.lit("WORLD").alias("dst"))
    return out.unionByName(place).unionByName(root)


DEEPEST = 96
"""Steps that a hierarchy may have; a recursive query has a limit of a hundred rounds."""


def narrower(edge: DataFrame, top: str | None = None) -> DataFrame:
    """(term, broader, steps): the transitive closure of broader, as a recursive query; below one term with ``top``.

    The query's depth is raised until no path reaches it, so none is cut; deeper than DEEPEST is an error.
    """
    spark, view = edge.sparkSession, f"cg_edges_{uuid.uuid4().hex}"
    edge.createOrReplaceTempView(view)
    try:
        depth = 12
        while True:
            out = spark.sql(
                f"""WITH RECURSIVE up(term, broader, steps) AS (
                  SELECT src, dst, 1 FROM {view} WHERE rel = 'broader' AND (:top IS NULL OR dst = :top)
                  UNION ALL SELECT e.src, u.broader, u.steps + 1 FROM up u JOIN {view} e ON e.dst = u.term AND e.rel = 'broader' WHERE u.steps < {depth})
                SELECT term, broader, min(steps) AS steps FROM up GROUP BY term, broader""",
                args={"top": top},
            )
            if (out.agg(F.max("steps").alias("m")).first()["m"] or 0) < depth:
                return out
            if depth == DEEPEST:
                raise ValueError(f"a hierarchy of more than {DEEPEST} steps")
            depth = min(DEEPEST, depth * 3)
    finally:
        spark.catalog.dropTempView(view)


def synset(edge: DataFrame, label: str | None = None) -> DataFrame:
    """(label, name, rel): every name a label goes by, itself included."""
    own = edge.where("rel = 'broader'").select(F.col("src").alias("label")).distinct()
    named = edge.where("rel in ('synonym', 'abbreviation')").select(F.col("dst").alias("label"), F.col("src").alias("name"), "rel")
    labels = own.join(named.select("label"), "label", "left_semi")
    out = labels.select("label", F.col("label").alias("name"), F.lit("self").alias("rel")).unionByName(named)
    return out.where(F.col("label") == label) if label else out


def expand(edge: DataFrame, term: str) -> DataFrame:
    """(name): the term, what is narrower, and all of their other names."""
    below = narrower(edge, term).select(F.col("term").alias("label")).distinct()
    named = synset(edge).join(below, "label", "left_semi").select("name")
    spark = edge.sparkSession
    return named.unionByName(below.select(F.col("label").alias("name"))).unionByName(spark.sql("SELECT ? AS name", args=[term])).distinct()
