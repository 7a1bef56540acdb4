"""Source records of three profiles, read from the given tables.

commerce: customers are patients, orders stays, order lines the other events.
clicks: ``events``. dialogue: ``conversations``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def line_kind() -> Column:
    return F.when(F.col("l_returnflag") == "A", "assay").when(F.col("l_returnflag") == "N", "drug").when((F.col("l_returnflag") == "R") & (F.col("l_quantity") == 50), "surgery").when(F.col("l_returnflag") == "R", "diagnosis")


def line_id() -> Column:
    """Order, line, part and supplier aren't a key; with the ship date they are."""
    return F.concat_ws("-", F.lit("L"), "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.date_format("l_shipdate", "yyyyMMdd"))


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with their kind, patient and event id: one join, on the order key."""
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_returnflag", "l_linestatus", "l_extendedprice")
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    return li.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).withColumn("kind", line_kind()).withColumn("event_id", line_id())


def patients(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The categorical attribute stands where a gender would; no birthday exists."""
    c = table(spark, sf_dir, "customer", "c_custkey", "c_name", "c_mktsegment")
    return c.select(F.col("c_custkey").alias("patient_id"), F.col("c_name").alias("name"), F.col("c_mktsegment").alias("category"), F.lit(None).cast("date").alias("birthday"))


def stays(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An order lasts until its last line's ship date; never less than nothing."""
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_orderstatus")
    last = table(spark, sf_dir, "lineitem", "l_orderkey", "l_shipdate").groupBy("l_orderkey").agg(F.max("l_shipdate").alias("last"))
    return o.join(last, o["o_orderkey"] == last["l_orderkey"], "left").select(
        F.concat(F.lit("O-"), F.col("o_orderkey")).alias("event_id"),
        F.col("o_custkey").alias("patient_id"),
        F.col("o_orderdate").alias("begin_ts"),
        F.greatest("o_orderdate", "last").alias("end_ts"),
        F.col("o_orderstatus").alias("situation"),
    )


# Deterministic dirty variants, so that cleaning and linking have a known truth.

KIND_INDEX = {"diagnosis": 0, "drug": 1, "assay": 2}
SYNONYMS = {"hot": "heated", "cold": "chilled", "small": "mini"}


def dirty_name(name: Column, ptype: Column, key: Column, kind_index: Column | int) -> Column:
    """One of eight spellings of a two-word label: clean, shouted with a stop, initial, vowels dropped, swapped, synonym, type added, reversed."""
    first, second = F.substring_index(name, " ", 1), F.substring_index(name, " ", -1)
    other = first
    for a, b in SYNONYMS.items():
        other = F.when(first == a, F.lit(b)).otherwise(other)
    k = F.pmod(key + F.lit(3) * kind_index, F.lit(8))
    forms = [
        name,
        F.concat(F.upper(name), F.lit(".")),
        F.concat(F.substring(first, 1, 1), F.lit(". "), second),
        F.concat(first, F.lit(" "), F.regexp_replace(second, "[aeiou]", "")),
        F.concat(second, F.lit(" "), first),
        F.concat(other, F.lit(" "), second),
        F.concat(name, F.lit(" "), F.lower(ptype)),
        F.reverse(name),
    ]
    out = forms[-1]
    for i, f in enumerate(forms[:-1]):
        out = F.when(k == i, f).otherwise(out)
    return F.lower(F.trim(out))


def mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(kind, mention, gold, n): different dirty names of used entities; gold is null out of vocabulary; n: events that say it."""
    used = lines(spark, sf_dir).where(F.col("kind").isin(*KIND_INDEX)).groupBy("kind", "l_partkey").agg(F.count("*").alias("n"))
    return named(used, spark, sf_dir).groupBy("kind", "mention", "gold").agg(F.sum("n").alias("n"))


def named(used: DataFrame, spark: SparkSession, sf_dir: str) -> DataFrame:
    """``used`` (kind, l_partkey, …) with mention and gold."""
    part = table(spark, sf_dir, "part", "p_partkey", "p_name", "p_type")
    index = F.when(F.col("kind") == "diagnosis", 0).when(F.col("kind") == "drug", 1).otherwise(2)
    both = used.join(part, F.col("l_partkey") == F.col("p_partkey"))
    reversed_ = F.pmod(F.col("p_partkey") + 3 * index, F.lit(8)) == 7
    return both.withColumn("mention", dirty_name(F.col("p_name"), F.col("p_type"), F.col("p_partkey"), index)).withColumn("gold", F.when(~reversed_, F.lower("p_name"))).drop("p_partkey", "p_name", "p_type")


def dirty_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with raw spellings of prompts, mixed units and missing values; the clean columns stay beside them."""
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_linestatus", "l_extendedprice")
    way, neg = F.pmod("l_linenumber", F.lit(4)), F.col("l_linestatus") == "F"
    spell = lambda word, sign: F.when(way == 0, word).when(way == 1, f"{word} ({sign})").when(way == 2, f"({sign})").otherwise(sign)
    small = F.pmod("l_suppkey", F.lit(2)) == 0
    hole = F.pmod("l_orderkey", F.lit(50))
    return li.select(
        "*",
        F.when(neg, spell("negative", "-")).otherwise(spell("positive", "+")).alias("prompt_raw"),
        F.when(small, F.col("l_extendedprice")).otherwise(F.col("l_extendedprice") * 10).alias("value_raw"),
        F.when(small, "g/dL").otherwise("g/L").alias("unit_raw"),
        F.when(hole == 0, F.lit(None)).when(hole == 1, "").when(hole == 2, "-").when(hole == 3, "N/A").otherwise(F.col("l_quantity").cast("int").cast("string")).alias("quantity_raw"),
    )


def packed_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(order, labels_raw): an order's sorted diagnosis labels in one cell, joined by one of three separators."""
    part = table(spark, sf_dir, "part", "p_partkey", "p_name")
    d = lines(spark, sf_dir).where("kind = 'diagnosis'").join(part, F.col("l_partkey") == F.col("p_partkey"))
    cell = d.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.translate("p_name", " ", "_"))).alias("names"))
    k = F.pmod("l_orderkey", F.lit(3))
    return cell.select("l_orderkey", F.when(k == 0, F.array_join("names", ",")).when(k == 1, F.array_join("names", ";")).otherwise(F.array_join("names", " ")).alias("labels_raw"))
