"""Functions for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph import session
from caregraph.functions.similarity import NATIVE_CHARS
from caregraph.operators.clean import LEXICON


def register(spark: SparkSession) -> None:
    """Registers native SQL functions, a UDAF and table functions under their names."""
    for text in (
        "lev_sim(a STRING, b STRING) RETURNS DOUBLE RETURN CASE WHEN greatest(length(a), length(b)) = 0 THEN 1D ELSE 1 - levenshtein(a, b) / greatest(length(a), length(b)) END",
        "jaccard_sim(a STRING, b STRING) RETURNS DOUBLE RETURN CASE WHEN a = '' AND b = '' THEN 1D WHEN a = '' OR b = '' THEN 0D ELSE size(array_intersect(split(a, ''), split(b, ''))) / size(array_union(split(a, ''), split(b, ''))) END",
        "same_span(ab TIMESTAMP_NTZ, ae TIMESTAMP_NTZ, bb TIMESTAMP_NTZ, be TIMESTAMP_NTZ) RETURNS BOOLEAN RETURN ab = bb AND ae = be",
        "is_before(ae TIMESTAMP_NTZ, bb TIMESTAMP_NTZ) RETURNS BOOLEAN RETURN ae < bb",
        f"lcs_sim(a STRING, b STRING) RETURNS DOUBLE RETURN CASE WHEN a = '' AND b = '' THEN 1D WHEN a = '' OR b = '' THEN 0D WHEN length(b) <= {NATIVE_CHARS} THEN {_LCS} / greatest(length(a), length(b)) END",
        "matchability(a STRING, b STRING) RETURNS DOUBLE RETURN round((lev_sim(a, b) + jaccard_sim(a, b) + lcs_sim(a, b)) / 3, 12)",
        f"allen_relation(ab TIMESTAMP_NTZ, ae TIMESTAMP_NTZ, bb TIMESTAMP_NTZ, be TIMESTAMP_NTZ) RETURNS STRING RETURN {_ALLEN}",
        "vote_majority(votes ARRAY<BOOLEAN>) RETURNS BOOLEAN RETURN size(filter(votes, v -> v)) * 2 > size(votes)",
        f"normalize_qualitative(x STRING) RETURNS STRING RETURN {_qualitative()}",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    spark.udf.register("auc_udaf", auc_udaf())
    spark.udtf.register("split_cell", split_cell_udtf())
    spark.udtf.register("timeline_edges", timeline_edges_udtf())


_MASK = "aggregate(transform(split(b, ''), (x, i) -> if(x = c, shiftleft(1L, i), 0L)), 0L, (s, x) -> s | x)"
_LCS = f"bit_count(aggregate(split(a, ''), 0L, (r, c) -> (r | {_MASK}) & ~((r | {_MASK}) - ((shiftleft(r, 1)) | 1L))) & (shiftleft(1L, length(b)) - 1))"
_ALLEN = """CASE WHEN ae < bb THEN 'before' WHEN ab > be THEN 'after' WHEN ab = bb AND ae = be THEN 'equal' WHEN ab = bb AND ae < be THEN 'starts' WHEN ab = bb THEN 'started_by'
    WHEN ae = be AND ab > bb THEN 'finishes' WHEN ae = be THEN 'finished_by' WHEN ae = bb THEN 'meets' WHEN ab = be THEN 'met_by' WHEN ab > bb AND ae < be THEN 'during'
    WHEN ab < bb AND ae > be THEN 'contains' WHEN ab < bb THEN 'overlaps' ELSE 'overlapped_by' END"""


def _qualitative() -> str:
    word = "lower(trim(translate(translate(x, '（）＋－', '()+-'), '()[]', '    ')))"
    table = "map(" + ", ".join(f"'{k}', '{v}'" for k, v in LEXICON.items()) + ")"
    return f"coalesce(try_element_at({table}, {word}), try_element_at({table}, substring_index({word}, ' ', 1)), try_element_at({table}, substring_index({word}, ' ', -1)))"


def register_graph(spark: SparkSession, tables: dict[str, DataFrame]) -> None:
    """The graph for SQL users: each table as a view, and with a view ``triple`` the table function ego_triples(node)."""
    session.register_views(tables)
    if "triple" in tables:
        spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ego_triples(node STRING) RETURNS TABLE (s STRING, p STRING, o STRING) RETURN SELECT s, p, o FROM triple WHERE s = node OR o = node")


def auc_udaf():
    """ROC AUC of a group small enough for one task; calibrate.roc_auc has no such bound."""

    @F.pandas_udf("double")
    def auc(score: pd.Series, label: pd.Series) -> float:
        ranks, pos = score.rank(), label.astype(bool)
        p, n = int(pos.sum()), int((~pos).sum())
        return float((ranks[pos].sum() - p * (p + 1) / 2) / (p * n)) if p and n else float("nan")

    return auc


def split_cell_udtf():
    @F.udtf(returnType="pos int, item string")
    class SplitCell:
        def eval(self, text: str, separators: str) -> Iterator[tuple[int, str]]:
            for s in separators[1:]:
                text = (text or "").replace(s, separators[0])
            yield from enumerate(x.strip() for x in (text or "").split(separators[0]) if x.strip())

    return SplitCell


def timeline_edges_udtf():
    @F.udtf(returnType="src string, dst string")
    class TimelineEdges:
        """Neighbours in one patient's sorted (time, id) list of points without ties."""

        def eval(self, ids: list) -> Iterator[tuple[str, str]]:
            yield from zip(ids or [], (ids or [])[1:], strict=False)

    return TimelineEdges
