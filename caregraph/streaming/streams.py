"""The graph from streams of events.

Times are cast to TIMESTAMP (in a UTC session) because watermarks need it.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from caregraph.operators.events import click_events
from caregraph.store import shared_folder

EDGE_ROW = "patient_id long, src string, dst string, op int"


def source(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of ``events`` files, or one file, as a stream. The path is given as a pattern of itself, which a stream takes for either."""
    schema = spark.read.parquet(path).schema
    path = path.rstrip("/")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{path[:-1]}[{path[-1]}]")


def with_watermark(stream: DataFrame, col: str = "ts", delay: str = "1 day") -> DataFrame:
    return stream.withColumn(col, F.col(col).cast("timestamp")).withWatermark(col, delay)


def triples(stream: DataFrame) -> DataFrame:
    """Stateless: type, begin and patient of every event."""
    e = click_events(stream)
    node = F.concat(F.lit("cg:event/"), "event_id")
    each = F.array(
        F.struct(F.lit("cg:kind").alias("p"), F.col("kind").alias("o")),
        F.struct(F.lit("cg:hasBegin").alias("p"), F.date_format("begin_ts", "yyyy-MM-dd'T'HH:mm:ss").alias("o")),
        F.struct(F.lit("cg:hasActor").alias("p"), F.concat(F.lit("cg:patient/"), "patient_id").alias("o")),
    )
    return e.select(node.alias("s"), F.inline(each)).where("o is not null")


def window_counts(stream: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "12 hours", delay: str = "1 day") -> DataFrame:
    """Events per window and type: tumbling, sliding, or session (which also goes by user)."""
    s = with_watermark(stream, delay=delay)
    if kind == "session":
        w = F.session_window("ts", size)
        return s.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")
    w = F.window("ts", size) if kind == "tumbling" else F.window("ts", size, slide)
    return s.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n")


def dedup(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    """Each event id once inside the watermark."""
    return with_watermark(stream, delay=delay).dropDuplicatesWithinWatermark(["event_id"])


def relations(stream: DataFrame, delay: str | None = None) -> DataFrame:
    """(patient_id, src, dst, op): changes of the Before chain of point events, op 1 adds and -1 retracts.

    A patient's state is its timeline. An event that arrives late splits an edge:
    the edge between its neighbours is retracted, two are added. Net of
    retractions the edges are those of a batch, whatever the order of arrival.
    With ``delay``, events later than that are dropped (see ``late_rows``), and of what lies
    before the watermark only the last group stays in the state: no later event can part earlier ones. A timer trims patients who send nothing more.
    """
    points = stream.where("event_type <> 'purchase'").select(F.col("user_id").alias("patient_id"), F.concat(F.lit("E-"), "event_id").alias("id"), F.col("ts").cast("timestamp").alias("ts"))
    if delay:
        points = points.withWatermark("ts", delay)
    points = points.withColumn("t", F.unix_micros("ts"))

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        times, ids = (list(x) for x in state.get) if state.exists else ([], [])
        groups: dict[int, list[str]] = {}
        for t, i in zip(times, ids, strict=True):
            groups.setdefault(t, []).append(i)
        was = _edges(groups)
        for pdf in batches:
            for t, i in zip(pdf["t"], pdf["id"], strict=True):
                held = groups.setdefault(int(t), [])
                if i not in held:
                    held.append(i)
        now = _edges(groups)
        if delay:
            past = sorted(t for t in groups if t < state.getCurrentWatermarkMs() * 1000)
            for t in past[:-1]:
                del groups[t]
        state.update(([t for t, g in groups.items() for _ in g], [i for g in groups.values() for i in g]))
        if delay and len(groups) > 1:
            # When the watermark has passed the last group, the state is trimmed to it.
            state.setTimeoutTimestamp(max(max(groups) // 1000, state.getCurrentWatermarkMs()) + 1)
        rows = [(key[0], a, b, 1) for a, b in sorted(now - was)] + [(key[0], a, b, -1) for a, b in sorted(was - now)]
        yield pd.DataFrame(rows, columns=["patient_id", "src", "dst", "op"])

    timeout = GroupStateTimeout.EventTimeTimeout if delay else GroupStateTimeout.NoTimeout
    return points.groupBy("patient_id").applyInPandasWithState(step, EDGE_ROW, "times array<long>, ids array<string>", "append", timeout)


def _edges(groups: dict[int, list[str]]) -> set[tuple[str, str]]:
    order = sorted(groups)
    return {(a, b) for s, t in zip(order, order[1:], strict=False) for a in groups[s] for b in groups[t]}


def during(points: DataFrame, periods: DataFrame, delay: str = "1 day", piece: str = "60 days") -> DataFrame:
    """Views inside purchase periods of one user: a stream-stream join with time bounds.

    Bounds let the state expire. Periods of any length are cut into pieces of at
    most ``piece``, each with its own time, so that no view is out of bounds.
    """
    a = with_watermark(points.where("event_type = 'view'"), delay=delay).select("user_id", F.col("event_id").alias("src"), "ts")
    e = click_events(periods.where("event_type = 'purchase'")).select(F.col("patient_id").alias("b_user"), F.col("event_id").alias("dst"), F.col("begin_ts").cast("timestamp").alias("b_ts"), F.col("end_ts").cast("timestamp").alias("e_ts"))
    b = e.withColumn("p_ts", F.explode(F.expr(f"sequence(b_ts, e_ts, INTERVAL {piece})"))).withWatermark("p_ts", delay)
    inside = F.expr(f"user_id = b_user AND ts >= p_ts AND ts < p_ts + INTERVAL {piece} AND ts <= e_ts")
    return a.join(b, inside).select("user_id", F.concat(F.lit("E-"), "src").alias("src"), "dst")


def annotate(stream: DataFrame, links: DataFrame) -> DataFrame:
    """Events with the term of their entity, from a static table (key, term)."""
    return click_events(stream).join(links, F.col("entity_id") == F.col("key"), "left").select("event_id", "entity_id", "term")


def upsert(path: str) -> Any:
    """A foreachBatch writer: every batch is one file set named by its id, so a replayed batch overwrites itself."""

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return write


def run(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there into Parquet files below the shared folder, and returns their rows: of mode complete those of the last batch, else of all."""
    spark = stream.sparkSession
    path = f"{shared_folder(spark)}/graph-stream-{name}-{uuid.uuid4().hex}"
    q = stream.writeStream.queryName(name).outputMode(mode).foreachBatch(upsert(path)).option("checkpointLocation", path + "-state").trigger(availableNow=True).start()
    q.awaitTermination()
    LATE[name] = late_rows(q)
    done = {p["batchId"] for p in q.recentProgress}
    if not done:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.parquet(f"{path}/epoch={max(done)}")
    return spark.read.parquet(path).drop("epoch").select(stream.columns)


LATE: dict[str, int] = {}
"""Rows that the last run of a stream by ``run`` dropped as too late."""


def late_rows(query: Any) -> int:
    """Rows that came after the watermark had passed them, over a query's recent batches."""
    return sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"])
