"""The stored graph: EVENT, ENTITY, TRIPLE, RELATION, LINK, made once from the source tables and read by all questions.

EVENT and RELATION are bucketed by patient, so joins and windows on the patient need no
shuffle, and RELATION is made of EVENT without one; TRIPLE is partitioned by predicate and RELATION by relation, so a
pattern reads only what it names. Tables lie in the shared folder that the
session names in ``spark.checkpoint.dir``. They belong to one session and one
state of the source files: when a source's size or time of change differs, a
table is made anew.
"""

from __future__ import annotations

import atexit
import hashlib
import math
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SOURCES = ("region", "nation", "customer", "part", "orders", "lineitem")
BUCKET_BYTES = 8 << 20
"""Source bytes that one bucket of EVENT or RELATION stands for. A task makes the relations of one bucket, some ten times as large."""
_HELD: dict[tuple[str, str, str], tuple[str, str]] = {}
_TMP: list[tempfile.TemporaryDirectory] = []


def shared_folder(spark: SparkSession) -> str:
    """The session's own folder below ``spark.checkpoint.dir``. Only a session that runs in one process may go without; it gets a folder that ends with it."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return f"{named.rstrip('/')}/graph-{spark.sparkContext.applicationId}"
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    if not _TMP:
        _TMP.append(tempfile.TemporaryDirectory(prefix="caregraph-store-"))
        atexit.register(_TMP[0].cleanup)
    return _TMP[0].name


def _status(spark: SparkSession, path: str) -> tuple[int, int]:
    """(bytes, time of change) of a file or folder."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    fs = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return fs.getContentSummary(p).getLength(), fs.getFileStatus(p).getModificationTime()


def _stamp(spark: SparkSession, sf_dir: str) -> tuple[str, int]:
    found = [(t, *_status(spark, f"{sf_dir}/{t}.parquet")) for t in SOURCES]
    return repr(found), sum(size for _, size, _ in found)


@contextmanager
def dealt_by_patient(spark: SparkSession) -> Iterator[None]:
    """Plans of joins on the patient and more columns leave rows that are dealt by patient where they are."""
    name = "spark.sql.requireAllClusterKeysForCoPartition"
    was = spark.conf.get(name, None)
    spark.conf.set(name, "false")
    try:
        yield
    finally:
        spark.conf.set(name, was) if was is not None else spark.conf.unset(name)


def saved(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder once and read back; joins on a patient and more stay where the patient's rows are."""
    path = f"{shared_folder(df.sparkSession)}/graph-round-{uuid.uuid4().hex}"
    with dealt_by_patient(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame], by: str | None = None, bucket: str | None = None, dealt: bool = False) -> DataFrame:
    """The table ``name`` of the graph of ``sf_dir``, made and written at first use. ``by``: partition column; ``bucket``: bucket column; ``dealt``: rows come dealt by ``bucket`` already, from a table with the same buckets."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    stamp, size = _stamp(spark, sf_dir)
    if _HELD.get(key, ("", ""))[0] != stamp:
        tag = hashlib.md5(repr((key, stamp)).encode()).hexdigest()[:16]
        path = f"{shared_folder(spark)}/graph-{tag}-{name}"
        df = make()
        if bucket:
            n = max(spark.sparkContext.defaultParallelism, math.ceil(size / BUCKET_BYTES))
            table = f"caregraph_{name}_{tag}"
            w = (df if dealt else df.repartition(n, bucket)).write.mode("overwrite").bucketBy(n, bucket).option("path", path).format("parquet")
            with dealt_by_patient(spark):
                (w.partitionBy(by) if by else w.sortBy(bucket)).saveAsTable(table)
            _HELD[key] = (stamp, "table:" + table)
        else:
            # A large table is written where its rows are made, as a shuffle would hold all of it once more.
            (df.write.partitionBy(by) if by else df.hint("rebalance").write).mode("overwrite").parquet(path)
            _HELD[key] = (stamp, path)
    at = _HELD[key][1]
    return spark.table(at[6:]) if at.startswith("table:") else spark.read.parquet(at)


def forget(spark: SparkSession) -> None:
    """Drops all that this session has written below the shared folder: stored tables, rounds of inference, results of streams."""
    for key in [k for k in _HELD if k[0] == spark.sparkContext.applicationId]:
        _, at = _HELD.pop(key)
        if at.startswith("table:"):
            spark.sql(f"DROP TABLE IF EXISTS {at[6:]}")
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(shared_folder(spark))
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


# The tables of the commerce profile


def entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    from caregraph.operators import events

    return stored(spark, sf_dir, "entity", lambda: events.entities(spark, sf_dir))


def labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """EVENT with label, brand and type of its object."""
    from caregraph.operators import events

    return stored(spark, sf_dir, "event", lambda: events.with_labels(events.extract(spark, sf_dir), entities(spark, sf_dir)), bucket="patient_id")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """EVENT."""
    names = ("event_id", "patient_id", "kind", "entity_id", "begin_ts", "end_ts", "time_kind", "stay_id", "situation", "result", "prompt")
    return labelled(spark, sf_dir).select(*names)


def triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entity and event triples."""
    from caregraph.plans import mapping

    t = stored(spark, sf_dir, "triple", lambda: mapping.clinical(spark, sf_dir, events(spark, sf_dir), entities(spark, sf_dir)), by="p")
    return t.select("s", "p", "o", "o_kind", "datatype", "lang", "s_kind", "class")


def relations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """RELATION of default options."""
    from caregraph.operators import relations as r

    t = stored(spark, sf_dir, "relation", lambda: r.build(events(spark, sf_dir)), by="relation", bucket="patient_id", dealt=True)
    return t.select("patient_id", "src", "dst", "relation", "step", "origin")


def mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    from caregraph.sources import records

    return stored(spark, sf_dir, "mention", lambda: records.mentions(spark, sf_dir))


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """LINK: the best term of every mention, with its gold and number of events."""
    from caregraph.operators import linking, vocab

    def make() -> DataFrame:
        m = mentions(spark, sf_dir)
        return linking.best_pruned(linking.candidates(m, vocab.terms(spark, sf_dir))).join(m, ["kind", "mention"])

    return stored(spark, sf_dir, "link", make)
