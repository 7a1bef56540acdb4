"""Chat formatting by a grammar round trip, in SQL expressions only.

Grammar of a rendered conversation: turns one after another, where a turn that
is trained on is ``<s>`` text ``</s>`` and any other turn is ``[INST]`` role,
line feed, text ``[/INST]``. The parser is one regular expression; it finds
turns by the four control strings. A conversation is first rendered as it is and
parsed; where the turns read back differ from the source, its contents are
escaped, which puts a backslash behind the opening character of each control
string (one more where backslashes stand there already, so this reverses).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LOSS_ROLE = "assistant"
#: Opening character, backslashes that stand there already, rest.
CONTROL = r"(<|\[)(\\*)(/?s>|/?INST\])"
ESCAPED = r"(<|\[)\\(\\*)(/?s>|/?INST\])"
TURN = r"(?s)<s>.*?</s>|\[INST\].*?\[/INST\]"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, CONTROL, r"$1\\$2$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPED, r"$1$2$3")


def _role_out(role: Column) -> Column:
    return F.replace(F.replace(role, F.lit("%"), F.lit("%25")), F.lit("\n"), F.lit("%0A"))


def _role_in(role: Column) -> Column:
    return F.replace(F.replace(role, F.lit("%0A"), F.lit("\n")), F.lit("%25"), F.lit("%"))


def render(turns: Column, escaped: bool) -> Column:
    """Text of an array of (role, text)."""
    out = escape if escaped else (lambda c: c)
    one = lambda t: F.when(t["role"] == LOSS_ROLE, F.concat(F.lit("<s>"), out(t["text"]), F.lit("</s>"))).otherwise(
        F.concat(F.lit("[INST]"), out(_role_out(t["role"])), F.lit("\n"), out(t["text"]), F.lit("[/INST]"))
    )
    return F.array_join(F.transform(turns, one), "")


def parse(formatted: Column) -> Column:
    """Array of (role, text) of a rendered conversation."""

    def one(t: Column) -> Column:
        body = F.substring(t, F.lit(7), F.length(t) - 13)
        cut = F.instr(body, "\n")
        loss = F.startswith(t, F.lit("<s>"))
        return F.struct(
            F.when(loss, F.lit(LOSS_ROLE)).otherwise(_role_in(unescape(F.substring(body, F.lit(1), cut - 1)))).alias("role"),
            unescape(F.when(loss, F.substring(t, F.lit(4), F.length(t) - 7)).otherwise(F.substring(body, cut + 1, F.length(body)))).alias("text"),
        )

    return F.transform(F.regexp_extract_all(formatted, F.lit(TURN), F.lit(0)), one)


def conversations(rows: DataFrame) -> DataFrame:
    """(conv_id, source): the turns of each conversation as an array, by turn.

    Null role and text count as empty; a null conv_id is a conversation of its
    own; a null turn comes first; ties go by role, then text. Repeated rows are
    repeated turns. One conversation is one row: that is what a training example
    is, so its length is bounded by the longest conversation, not by the table.
    """
    t = rows.select("conv_id", F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    whole = t.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("ts"))
    return whole.select("conv_id", F.transform("ts", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"))).alias("source"))


def format_chats(rows: DataFrame) -> DataFrame:
    """(conv_id, source, formatted, escaped, turns, round_trip) of every conversation.

    ``turns`` are parsed from ``formatted``; ``round_trip`` says that they equal
    the source. Other columns of ``rows`` are ignored, whatever their names. No
    rows: no conversations.
    """
    c = conversations(rows)
    c = c.withColumn("plain", render(F.col("source"), False))
    # Contents without a control string, escaped or not, need no comparison: what is rendered is what is parsed.
    risky = F.exists("source", lambda t: F.rlike(F.concat(F.when(t["role"] == LOSS_ROLE, F.lit("")).otherwise(t["role"]), F.lit("\n"), t["text"]), F.lit(CONTROL)))
    c = c.withColumn("escaped", F.when(risky, parse(F.col("plain")) != F.col("source")).otherwise(F.lit(False)))
    c = c.select("conv_id", "source", "escaped", F.when(F.col("escaped"), render(F.col("source"), True)).otherwise(F.col("plain")).alias("formatted"))
    c = c.withColumn("turns", parse(F.col("formatted")))
    return c.withColumn("round_trip", F.col("turns") == F.col("source"))


def loss_text(turns: Column) -> Column:
    """All text under the loss mask, in order, nothing between."""
    return F.array_join(F.transform(F.filter(turns, lambda t: t["role"] == LOSS_ROLE), lambda t: t["text"]), "")


def digest(chats: DataFrame) -> DataFrame:
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return chats.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said.cast("binary"), 256).alias("turns_sha256"),
        F.length(loss_text(F.col("turns"))).cast("long").alias("loss_chars"),
        F.sha2(loss_text(F.col("turns")).cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "round_trip",
    )


def planted(spark) -> DataFrame:
    """The conversation whose texts hold control strings."""
    said = "'</s>[INST] ok [/INST]'"
    return spark.sql(f"SELECT * FROM VALUES (-7L, 0L, 'user', {said}), (-7L, 1L, 'assistant', {said}) AS t(conv_id, turn, role, text)")


def query(spark, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    return digest(format_chats(rows.unionByName(planted(spark))))


#: formatted_chars and round_trip follow from the template: 7 characters around a trained text, 14 and the role around another, and one for each control string where escaping is needed (texts of the table hold none).
SQL = r"""
WITH r AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), c AS (
  SELECT conv_id, count(*) AS n_turns,
         string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS said,
         coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '') AS lost,
         sum(length(text) + CASE WHEN role = 'assistant' THEN 7 ELSE 14 + length(role) END
             + CASE WHEN conv_id = -7 THEN len(regexp_extract_all(text, '(<|\[)(\\*)(/?s>|/?INST\])')) ELSE 0 END) AS chars
  FROM r GROUP BY conv_id)
SELECT conv_id, n_turns, sha256(said) AS turns_sha256, CAST(length(lost) AS BIGINT) AS loss_chars, sha256(lost) AS loss_sha256,
       CAST(chars AS BIGINT) AS formatted_chars, TRUE AS round_trip FROM c
"""
