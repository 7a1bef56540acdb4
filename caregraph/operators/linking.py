"""Linking entity mentions to terms of their type."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from caregraph.functions import similarity as sim

BROADCAST_BYTES = 32 << 20
"""Vocabularies up to this size are broadcast; larger ones are dealt into blocks of it."""
MENTION_PARTS = 64
"""Parts that a kind's mentions are dealt into where the vocabulary is not broadcast."""


def candidates(mentions: DataFrame, terms: DataFrame, blocking: str = "type", threshold: float = 0.0, q: int = 2) -> DataFrame:
    """(kind, mention, label): pairs to score.

    type: all of one kind, the exact space. gram: pairs that share a q-gram.
    length: pairs whose lengths alone can reach ``threshold``; exact above it,
    since a score is at most (2 * shorter / longer + 1) / 3.
    """
    m, t = mentions.select("kind", "mention").distinct(), terms.select("kind", "label").distinct()
    if blocking == "gram":
        grams = lambda c: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(c) - (q - 1), F.lit(1))), lambda i: F.substring(F.col(c), i, F.lit(q))))
        a = m.select("kind", "mention", F.explode(grams("mention")).alias("g"))
        b = t.select("kind", "label", F.explode(grams("label")).alias("g"))
        return a.join(b, ["kind", "g"]).select("kind", "mention", "label").distinct()
    pairs = every(m, t)
    if blocking == "length":
        la, lb = F.length("mention"), F.length("label")
        pairs = pairs.where((F.least(la, lb) / F.greatest(la, lb) * 2 + 1) / 3 > threshold)
    return pairs


def every(m: DataFrame, t: DataFrame) -> DataFrame:
    """All pairs (kind, mention, label) of one kind.

    The vocabulary is broadcast if its bytes allow; else both sides are dealt into
    blocks that meet pairwise, so that a kind is never one task's: each mention goes
    to every block of terms, each term to every part of the mentions.
    """
    size = t.agg(F.coalesce(F.sum(F.octet_length("label") + F.octet_length("kind") + 32), F.lit(0)).alias("n")).first()["n"]
    if size <= BROADCAST_BYTES:
        return m.join(F.broadcast(t), "kind")
    blocks = -(-size // BROADCAST_BYTES)
    a = m.withColumn("__part", F.pmod(F.xxhash64("mention"), F.lit(MENTION_PARTS))).withColumn("__block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    b = t.withColumn("__block", F.pmod(F.xxhash64("label"), F.lit(blocks)).cast("int")).withColumn("__part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(MENTION_PARTS - 1).cast("long"))))
    return a.withColumn("__block", F.col("__block").cast("int")).join(b, ["kind", "__part", "__block"]).drop("__part", "__block")


def minhash_candidates(mentions: DataFrame, terms: DataFrame, distance: float = 0.8, tables: int = 8, q: int = 2, seed: int = 7) -> DataFrame:
    """(kind, mention, label): pairs whose q-gram sets collide in one of ``tables`` MinHash tables; approximate, for vocabularies too large for exact blocking."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    tf = HashingTF(numFeatures=1 << 16, binary=True, inputCol="grams", outputCol="f")
    grams = lambda c: F.transform(F.sequence(F.lit(1), F.greatest(F.length(c) - (q - 1), F.lit(1))), lambda i: F.substring(F.col(c), i, F.lit(q)))
    m = tf.transform(mentions.select("kind", "mention").distinct().where("mention <> ''").withColumn("grams", grams("mention")))
    t = tf.transform(terms.select("kind", "label").distinct().where("label <> ''").withColumn("grams", grams("label")))
    model = MinHashLSH(inputCol="f", outputCol="h", numHashTables=tables, seed=seed).fit(t)
    near = model.approxSimilarityJoin(m, t, distance)
    return near.where(F.col("datasetA.kind") == F.col("datasetB.kind")).select("datasetA.kind", "datasetA.mention", "datasetB.label").distinct()


def scored(pairs: DataFrame, scorer: str = "mean", prune: float | None = None) -> DataFrame:
    """``pairs`` with lev, jac, lcs and score. ``prune`` leaves out pairs whose Jaccard similarity and lengths can't exceed it, before the costly two."""
    a, b = F.col("mention"), F.col("label")
    out = pairs.withColumn("jac", sim.jaccard_sim(a, b))
    if prune is not None:
        out = out.where(sim.upper_bound(F.length(a), F.length(b), F.col("jac")) > prune)
    out = out.withColumn("lev", sim.lev_sim(a, b)).withColumn("lcs", sim.lcs_sim(a, b))
    score = {"mean": sim.matchability(F.col("lev"), F.col("jac"), F.col("lcs")), "lev": F.round("lev", 12), "jaccard": F.round("jac", 12), "lcs": F.round("lcs", 12), "exact": F.when(a == b, 1.0).otherwise(0.0)}[scorer]
    return out.withColumn("score", score)


def best(pairs: DataFrame, k: int = 1) -> DataFrame:
    """The k best terms of each mention; ties go to the lesser term."""
    if k == 1:
        top = F.min_by(F.struct("label", "score", "lev", "jac", "lcs"), F.struct(-F.col("score"), F.col("label")))
        return pairs.groupBy("kind", "mention").agg(top.alias("b")).select("kind", "mention", F.col("b.label").alias("term"), "b.score", "b.lev", "b.jac", "b.lcs")
    w = Window.partitionBy("kind", "mention").orderBy(F.desc("score"), "label")
    return pairs.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("kind", "mention", F.col("label").alias("term"), "score", "rank")


def best_pruned(pairs: DataFrame) -> DataFrame:
    """``best`` of ``scored`` pairs, without scoring them all.

    The pair that could score most (by lengths and Jaccard similarity) is scored first; of a
    mention's other pairs only those that could score as much are looked at. Exact.
    """
    a, b = F.col("mention"), F.col("label")
    bound = pairs.select("kind", "mention", "label", sim.upper_bound(F.length(a), F.length(b), sim.jaccard_sim(a, b)).alias("bound"))
    first = bound.groupBy("kind", "mention").agg(F.max_by("label", F.struct("bound", "label")).alias("label"))
    least = scored(first).select("kind", "mention", F.col("score").alias("least"))
    some = bound.join(least, ["kind", "mention"]).where("bound >= least").select("kind", "mention", "label")
    return best(scored(some))


def accept(links: DataFrame, thresholds: DataFrame | float, inclusive: bool = False) -> DataFrame:
    """Links with accepted: the score is above the kind's threshold (kind, threshold), or above one for all."""
    if isinstance(thresholds, (int, float)):
        held = links.withColumn("threshold", F.lit(float(thresholds)))
    else:
        held = links.join(F.broadcast(thresholds.select("kind", "threshold")), "kind", "left")
    over: Column = F.col("score") >= F.col("threshold") if inclusive else F.col("score") > F.col("threshold")
    return held.withColumn("accepted", F.coalesce(over, F.lit(False)))


def annotate(ev: DataFrame, links: DataFrame) -> DataFrame:
    """Events (with kind and mention) with the term of their accepted link, else null."""
    return ev.join(links.where("accepted").select("kind", "mention", "term"), ["kind", "mention"], "left")


def normalize(ev: DataFrame, links: DataFrame) -> DataFrame:
    """Events with label: the linked term, or the mention as it is."""
    return annotate(ev, links).withColumn("label", F.coalesce("term", "mention"))


def link_triples(links: DataFrame) -> DataFrame:
    own = F.concat(F.lit("cg:mention/"), "kind", F.lit("/"), F.call_function("url_encode", F.col("mention")))
    term = F.concat(F.lit("cg:term/"), "kind", F.lit("/"), F.call_function("url_encode", F.col("term")))
    return links.where("accepted").select(own.alias("s"), F.lit("cg:linkedTo").alias("p"), term.alias("o"), F.lit("iri").alias("o_kind"), F.lit(None).cast("string").alias("datatype"), F.lit(None).cast("string").alias("lang"))
