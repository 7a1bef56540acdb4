"""Language identification by compression.

Each language has a raw-content zstandard dictionary; a text's language is the
one whose dictionary compresses it to the fewest bytes. Texts and dictionaries
are lower-cased and runs of other characters than letters become one blank, so
that case and symbols don't decide.
"""

from __future__ import annotations

import re

import pandas as pd
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from caregraph.llm.common import crc_rest

UNKNOWN = "und"
ROWS = 1000
"""Most texts that one language's dictionary is made from (a documented bound on the sample the classifier is fitted on)."""
ROW_CHARS = 1000
"""Most characters a sampled text gives to its dictionary, so that no long text fills it; they start at a place that the text's hash chooses."""
DICT_BYTES = 250 * 1024
BUCKETS = 4096
_OTHER = re.compile(r"[\W\d_]+")


def folded(text: str) -> str:
    return _OTHER.sub(" ", text.lower())


def learn(labelled: DataFrame, rows: int = ROWS) -> dict[str, bytes]:
    """language -> dictionary, from (text, lang). Texts are drawn by a hash of the text, so the draw doesn't depend on order, ids or partitions.

    Null or letterless texts and null languages are left out; repeated texts
    count once. The driver gets at most ``rows`` texts of each language, cut to
    ROW_CHARS, and a count for each language and bucket.
    """
    drawn = labelled.where(F.col("lang").isNotNull() & F.rlike("text", F.lit(r"\p{L}"))).withColumn("h", F.xxhash64("text"))
    by = drawn.groupBy("lang", F.pmod("h", F.lit(BUCKETS)).alias("b")).agg(F.approx_count_distinct("h").alias("n"))
    cuts: dict[str, list[int]] = {}
    for r in sorted(by.collect(), key=lambda r: (r["lang"], r["b"])):
        had = cuts.setdefault(r["lang"], [0, -1])
        if had[0] < 1.25 * rows:  # counts are approximate
            cuts[r["lang"]] = [had[0] + r["n"], r["b"]]
    if not cuts:
        return {}
    held = F.lit(False)
    for lang, (_, last) in cuts.items():
        held = held | ((F.col("lang") == lang) & (F.pmod("h", F.lit(BUCKETS)) <= last))
    texts: dict[str, dict[int, str]] = {}
    at = F.pmod(F.xxhash64(F.lit(1), "text"), F.greatest(F.length("text") - ROW_CHARS, F.lit(0)) + 1) + 1
    sample = drawn.where(held).select("lang", "h", F.substr("text", at.cast("int"), F.lit(ROW_CHARS)).alias("t")).dropDuplicates(["lang", "h"])
    # Each language has its own limit, so none crowds out another.
    first = F.row_number().over(Window.partitionBy("lang").orderBy(F.pmod("h", F.lit(BUCKETS)), "h"))
    for r in sample.withColumn("k", first).where(F.col("k") <= rows).collect():
        texts.setdefault(r["lang"], {})[r["h"]] = r["t"]
    out = {}
    for lang, got in sorted(texts.items()):
        kept = [folded(got[h]).encode() for h in sorted(got, key=lambda h: (h % BUCKETS, h))][:rows]
        out[lang] = b"\n".join(shared_out(kept, DICT_BYTES - len(kept)))
    return out


def shared_out(texts: list[bytes], most: int) -> list[bytes]:
    """The texts, the longest ones cut to one length so that all fit into ``most`` bytes: every text has its share."""
    if sum(map(len, texts)) <= most:
        return texts
    left, size = most, 0
    for k, n in enumerate(sorted(map(len, texts))):
        size = left // (len(texts) - k)
        if n >= size:
            break
        left -= n
    return [t[:size] for t in texts]


def predict(texts: DataFrame, dicts: dict[str, bytes], text: str = "text", margin: float = 0.0, level: int = 3) -> DataFrame:
    """``texts`` with lang_pred, score and accepted.

    score: 0 to 1, by how much the best dictionary's size lies under the next;
    ties go to the first language by name. Null texts, texts without a letter,
    and all texts where nothing was learned get ``und`` and 0. ``accepted``: the
    score is at least ``margin`` and the language known. Columns of these names
    are replaced.
    """
    names = sorted(dicts)
    shared = texts.sparkSession.sparkContext.broadcast(dicts)  # at most DICT_BYTES a language

    @F.pandas_udf("lang_pred string, score double")
    def run(col: pd.Series) -> pd.DataFrame:
        tools = []
        for name in names:
            d = zstandard.ZstdCompressionDict(shared.value[name], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(level=level)
            tools.append(zstandard.ZstdCompressor(dict_data=d, write_content_size=False, write_checksum=False))
        langs, scores = [], []
        for t in col:
            if t is None or not tools or not any(map(str.isalpha, t)):
                langs.append(UNKNOWN)
                scores.append(0.0)
                continue
            raw = folded(t).encode()
            sizes = [len(c.compress(raw)) for c in tools]
            best, *rest = sorted(range(len(sizes)), key=sizes.__getitem__)
            langs.append(names[best])
            scores.append(1.0 if not rest else min(1.0, (sizes[rest[0]] - sizes[best]) / sizes[rest[0]] * 4))
        return pd.DataFrame({"lang_pred": langs, "score": scores})

    out = texts.withColumn("__cg_p", run(F.col(text)))
    out = out.withColumn("lang_pred", F.col("__cg_p.lang_pred")).withColumn("score", F.col("__cg_p.score")).drop("__cg_p")
    return out.withColumn("accepted", (F.col("score") >= margin) & (F.col("lang_pred") != UNKNOWN))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, accepted) of every row of ``documents``; learns from the rows that the contract leaves for it. Rows without an id are never held out."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    rest = crc_rest(F.col("doc_id"), 3)
    dicts = learn(docs.where(rest != 1).select("text", "lang"))
    return predict(docs.select("doc_id", (rest == 1).alias("held_out"), "text"), dicts, margin=0.02).drop("text")
