"""Cleaning of source records."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Strings that stand for a missing value.
PLACEHOLDERS = ("", "-", "N/A")
#: Spellings of the two qualitative results, after folding.
LEXICON = {"negative": "negative", "neg": "negative", "-": "negative", "positive": "positive", "pos": "positive", "+": "positive"}
#: Unit, factor, offset, target unit.
UNITS = [("g/dL", 10.0, 0.0, "g/L"), ("g/L", 1.0, 0.0, "g/L")]
SEPARATORS = r"[,;\s　，；]+"


def null_missing(col: Column, placeholders: tuple[str, ...] = PLACEHOLDERS) -> Column:
    """Null for blanks and placeholders, else the trimmed string."""
    t = F.trim(col)
    return F.when(t.isin(*placeholders), F.lit(None)).otherwise(t)


def missing(df: DataFrame, rules: dict[str, str | object]) -> DataFrame:
    """Applies a policy to each column: "null" keeps missing values as null, "drop" drops their rows, anything else fills them."""
    for name, policy in rules.items():
        df = df.withColumn(name, null_missing(F.col(name)))
        if policy == "drop":
            df = df.where(F.col(name).isNotNull())
        elif policy != "null":
            df = df.withColumn(name, F.coalesce(F.col(name), F.lit(policy).cast("string")))
    return df


def missing_report(df: DataFrame, names: list[str]) -> DataFrame:
    """(column, nulls, placeholders, rows) in one pass."""
    one = [F.struct(F.lit(n).alias("column"), F.count_if(F.col(n).isNull()).alias("nulls"), F.count_if(F.trim(n).isin(*PLACEHOLDERS)).alias("placeholders"), F.count("*").alias("rows")) for n in names]
    return df.agg(F.array(*one).alias("r")).select(F.inline("r"))


def normalize_qualitative(col: Column, lexicon: dict[str, str] | None = None) -> Column:
    """positive, negative or null, from words and signs in any mixture, with ASCII or full-width brackets."""
    known = lexicon or LEXICON
    word = F.lower(F.trim(F.translate(F.translate(col, "（）＋－", "()+-"), "()[]", "    ")))
    table = F.create_map(*(x for k, v in known.items() for x in (F.lit(k), F.lit(v))))
    whole = F.try_element_at(table, word)
    return F.coalesce(whole, F.try_element_at(table, F.substring_index(word, " ", 1)), F.try_element_at(table, F.substring_index(word, " ", -1)))


def convert_units(df: DataFrame, value: str, unit: str, table: list[tuple[str, float, float, str]] = UNITS) -> DataFrame:
    """Adds value_std, unit_std and unit_known; a unit that the table lacks keeps its value and is flagged."""
    v, u, known = F.col(value), F.col(unit), F.lit(False)
    for name, factor, offset, target in table:
        here = F.col(unit) == name
        v = F.when(here, F.col(value) * factor + offset).otherwise(v)
        u = F.when(here, F.lit(target)).otherwise(u)
        known = known | F.coalesce(here, F.lit(False))
    return df.withColumn("value_std", v).withColumn("unit_std", u).withColumn("unit_known", known)


def split_cell(df: DataFrame, col: str, separators: str = SEPARATORS, distinct: bool = False) -> DataFrame:
    """One row for each item of a cell, with its position; empty items are dropped."""
    items = F.filter(F.transform(F.split(col, separators), F.trim), lambda x: x != "")
    items = F.array_distinct(items) if distinct else items
    return df.select("*", F.posexplode(items).alias("pos", "item"))


def merge_values(df: DataFrame, key: str, col: str, sep: str = ";") -> DataFrame:
    """The inverse: a key's values, sorted, in one cell."""
    return df.groupBy(key).agg(F.array_join(F.array_sort(F.collect_list(col)), sep).alias(col))


def fingerprint(col: Column) -> Column:
    """Key under which spellings of one value meet: its different lower-case words in order, without punctuation."""
    words = F.filter(F.split(F.regexp_replace(F.lower(col), "[^a-z0-9 ]", ""), " +"), lambda w: w != "")
    return F.array_join(F.array_sort(F.array_distinct(words)), " ")


def cluster_spellings(df: DataFrame, col: str) -> DataFrame:
    """(key, canonical, spellings, rows): the most frequent spelling stands for the cluster, ties to the lesser."""
    by = df.groupBy(fingerprint(F.col(col)).alias("key"), F.col(col).alias("v")).agg(F.count("*").alias("n"))
    return by.groupBy("key").agg(F.min_by("v", F.struct(-F.col("n"), F.col("v"))).alias("canonical"), F.count("*").alias("spellings"), F.sum("n").alias("rows"))


def repair_interval(df: DataFrame, begin: str, end: str, policy: str = "clamp", granularity: str | None = None) -> DataFrame:
    """Intervals that end before they begin: clamp the end to the begin, swap both, null the end, or drop the row. A missing end is the begin."""
    if granularity:
        for c in (begin, end):
            df = df.withColumn(c, F.date_trunc(granularity, c).cast("timestamp_ntz"))
    b, e = F.col(begin), F.coalesce(F.col(end), F.col(begin))
    bad = e < b
    df = df.withColumn("repaired", bad | F.col(end).isNull())
    if policy == "drop":
        return df.where(~bad).withColumn(end, e)
    if policy == "swap":
        return df.withColumn("__b", F.least(b, e)).withColumn(end, F.greatest(b, e)).withColumn(begin, F.col("__b")).drop("__b")
    return df.withColumn(end, F.when(bad, F.lit(None)).otherwise(e) if policy == "null" else F.greatest(b, e))


def report(df: DataFrame, rules: dict[str, Column]) -> DataFrame:
    """(rule, violations, rows) of named conditions, in one pass."""
    one = [F.struct(F.lit(k).alias("rule"), F.count_if(c).alias("violations"), F.count("*").alias("rows")) for k, c in rules.items()]
    return df.agg(F.array(*one).alias("r")).select(F.inline("r"))
