"""What several operators of this subpackage share.

Intermediate results that several plans read, and those of iterations, are
written as Parquet below the folder that the session names in
``spark.checkpoint.dir``, which driver and executors share; a lost executor
costs no more than the tasks it was running.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SIFT_BITS = 1 << 26
"""Most bits of a bitmap that is broadcast."""
SIFT_RATIO = 8
_LOCAL: dict[str, str] = {}


def work_dir(spark: SparkSession) -> str:
    """The shared folder; a temporary one only where the session names none and runs in one process (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    if "dir" not in _LOCAL:
        held = tempfile.TemporaryDirectory(prefix="caregraph-")
        atexit.register(held.cleanup)
        _LOCAL["dir"] = held.name
    return _LOCAL["dir"]


def saved(df: DataFrame) -> DataFrame:
    """``df`` written once and read back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{_own(spark)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _own(spark: SparkSession) -> str:
    return f"{work_dir(spark)}/caregraph-{spark.sparkContext.applicationId}"


def forget(spark: SparkSession) -> None:
    """Deletes what ``saved`` has written in this session; results that still read it end."""
    top = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(_own(spark))
    top.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(top, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crc_rest(doc_id: Column, mod: int) -> Column:
    """crc32 of the id's decimal text, modulo ``mod``; -1 for a null id."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % mod, F.lit(-1)).cast("int")


def text_key(*parts: Column) -> Column:
    """Two 64-bit hashes of a row's columns, as one struct; a null differs from an empty text."""
    nulls = [p.isNull() for p in parts]
    return F.struct(F.xxhash64(*nulls, *parts).alias("h1"), F.xxhash64(F.lit(1), *nulls, *parts).alias("h2"))


def maybe_in(ids: DataFrame, of: Column) -> Column:
    """True where the 64-bit ``of`` is in ``ids`` (one column, read twice), and by chance elsewhere.

    The ids are counted and held in a bitmap of some SIFT_RATIO bits each: rows
    that it rules out needn't be shuffled to a join with ``ids``. Where it would take
    more than SIFT_BITS bits it is given up, and all rows go to the join.
    """
    n = ids.count()
    size = max(1 << 16, 1 << (SIFT_RATIO * n - 1).bit_length()) if n else 32
    if size > SIFT_BITS:
        return of.isNotNull()
    slot = F.pmod(F.col(ids.columns[0]), F.lit(size))
    words = ids.where(F.col(ids.columns[0]).isNotNull()).groupBy(F.shiftright(slot, 5).cast("int").alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), (slot % 32).cast("int"))).alias("v"))
    held_words = words.toArrow()
    bits = np.zeros(size // 32, np.uint32)
    bits[held_words["w"].to_numpy()] = held_words["v"].to_numpy().astype(np.uint32)
    shared = ids.sparkSession.sparkContext.broadcast(bits)

    @F.pandas_udf("boolean")
    def held(n: pd.Series) -> pd.Series:
        k = n.to_numpy(np.int64)
        return pd.Series((shared.value[k >> 5] >> (k & 31).astype(np.uint32) & 1).astype(bool))

    return held(F.pmod(of, F.lit(size)))


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node with an edge; root: the component's least node.

    ``edges`` has two columns of one ordered type. Alternating large-star and
    small-star rounds; each round is written, so lineage doesn't grow, and only
    two numbers reach the driver. Null ends and loops are left out.
    """
    a, b = edges.columns
    now = saved(edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct())

    def mark(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    seen = mark(now)
    while seen[0]:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        now = saved(small.where("u <> v").distinct())
        was, seen = seen, mark(now)
        if was == seen:
            break
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
