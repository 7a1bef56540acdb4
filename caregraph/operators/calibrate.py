"""Thresholds from a marked sample."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

STEP = 0.05
RATERS = 6


SLOTS = 1000


def ranked(df: DataFrame, group: str, value: str, *ties: str, falling: bool = False) -> DataFrame:
    """``df`` with pos: the place in its group by ``value`` (0 to 1), then by ``ties``.

    A group is cut into SLOTS ranges of the value, whose counts are summed up
    first, so no task orders a whole group.
    """
    slot = F.floor(F.col(value) * SLOTS).cast("int")
    df = df.withColumn("__slot", -slot if falling else slot)
    n = df.groupBy(group, "__slot").agg(F.count("*").alias("__n"))
    before = n.select(group, "__slot", (F.sum("__n").over(Window.partitionBy(group).orderBy("__slot")) - F.col("__n")).alias("__before"))
    own = F.row_number().over(Window.partitionBy(group, "__slot").orderBy(F.desc(value) if falling else F.asc(value), *ties))
    return df.withColumn("__own", own).join(before, [group, "__slot"]).withColumn("pos", (F.col("__own") + F.col("__before")).cast("int")).drop("__slot", "__own", "__before")


def score_curve(links: DataFrame) -> DataFrame:
    """(kind, pos, score): scores by index, in falling order."""
    return ranked(links.select("kind", "mention", "score"), "kind", "score", "mention", falling=True)


def draw(seed: int, *columns: str) -> Column:
    """A number from 0 to 2**32 - 1 that only the columns' text decides."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), *columns)), 1, 8), 16, 10).cast("long")


def sample(links: DataFrame, ratio: float = 0.1, method: str = "systematic", seed: int = 7) -> DataFrame:
    """A share of each kind's links, uniform over the scores.

    systematic: each (1 / ratio)-th in score order. stratified: the first share
    of each tenth of the score range, in hash order. random: by a hash of the
    mention, without any sort.
    """
    if method == "random":
        return links.where(F.pmod(draw(seed, "kind", "mention"), F.lit(1_000_000)) < int(ratio * 1_000_000))
    if method == "stratified":
        w = Window.partitionBy("kind", F.floor(F.col("score") * 10))
        ranked_ = links.withColumn("__r", F.row_number().over(w.orderBy(draw(seed, "kind", "mention"), "mention"))).withColumn("__n", F.count("*").over(w))
        return ranked_.where(F.col("__r") <= F.ceil(F.col("__n") * ratio)).drop("__r", "__n")
    every = round(1 / ratio)
    return ranked(links, "kind", "score", "mention").where(F.pmod("pos", F.lit(every)) == 0).withColumn("pos", (F.col("pos") / every).cast("int"))


def votes(marked: DataFrame) -> DataFrame:
    """Simulated raters: rater r flips the truth of the k-th sampled pair when 7k + 13r leaves nothing modulo 20."""
    each = [F.when(F.pmod(F.col("pos") * 7 + 13 * r, F.lit(20)) == 0, ~F.col("truth")).otherwise(F.col("truth")) for r in range(1, RATERS + 1)]
    return marked.withColumn("votes", F.array(*each))


def majority(v: Column) -> Column:
    """More than half say yes; a tie rejects."""
    return F.size(F.filter(v, lambda x: x)) * 2 > F.size(v)


def agreement(v: Column) -> Column:
    """Share of raters who vote with the larger side."""
    yes = F.size(F.filter(v, lambda x: x))
    return F.greatest(yes, F.size(v) - yes) / F.size(v)


def sweep(marks: DataFrame, step: float = STEP) -> DataFrame:
    """(kind, threshold, tp, fp, tn, fn, tpr, fpr, auc) for thresholds 0, step, … 1; accepted is score > threshold.

    Marks are counted by the first threshold that rejects them, then summed up
    along the grid: one pass, however many marks there are.
    """
    n = round(1 / step)
    # A score is rejected from the least grid point at or above it.
    slot = F.greatest(F.least(F.ceil(F.round(F.col("score") / step, 9)), F.lit(n + 1)), F.lit(0)).cast("int")
    by = marks.groupBy("kind", slot.alias("k")).agg(F.sum(F.col("truth").cast("long")).alias("yes"), F.sum((~F.col("truth")).cast("long")).alias("no"))
    grid = by.select("kind").distinct().select("kind", F.explode(F.sequence(F.lit(0), F.lit(n))).alias("k"))
    up = Window.partitionBy("kind").orderBy("k")
    all_ = Window.partitionBy("kind")
    full = grid.withColumn("g", F.lit(1)).join(by, ["kind", "k"], "full")
    run = full.select("kind", "k", "g", F.sum(F.coalesce("yes", F.lit(0))).over(up).alias("fn"), F.sum(F.coalesce("no", F.lit(0))).over(up).alias("tn"), F.sum(F.coalesce("yes", F.lit(0))).over(all_).alias("p"), F.sum(F.coalesce("no", F.lit(0))).over(all_).alias("q"))
    out = run.where("g = 1").select("kind", F.round(F.col("k") * step, 6).alias("threshold"), (F.col("p") - F.col("fn")).alias("tp"), (F.col("q") - F.col("tn")).alias("fp"), "tn", "fn")
    tpr, tnr = F.when(F.col("tp") + F.col("fn") == 0, 0.0).otherwise(F.col("tp") / (F.col("tp") + F.col("fn"))), F.when(F.col("tn") + F.col("fp") == 0, 0.0).otherwise(F.col("tn") / (F.col("tn") + F.col("fp")))
    return out.withColumn("tpr", F.round(tpr, 6)).withColumn("fpr", F.round(1 - tnr, 6)).withColumn("auc", F.round((tpr + tnr) / 2, 6))


def best_threshold(curve: DataFrame) -> DataFrame:
    """(kind, threshold, auc): the best AUC; ties to the smallest threshold."""
    top = F.min_by(F.struct("threshold", "auc"), F.struct(-F.col("auc"), F.col("threshold")))
    return curve.groupBy("kind").agg(top.alias("b")).select("kind", "b.threshold", "b.auc")


def roc_auc(df: DataFrame, score: str, label: str) -> DataFrame:
    """(auc): the chance that a positive outranks a negative, ties counting half.

    Rows are summed up by score first; then the range of scores is cut into SLOTS
    parts, whose negatives are summed up before each part is ordered by itself.
    """
    by = df.where(F.col(score).isNotNull() & F.col(label).isNotNull()).groupBy(F.col(score).cast("double").alias("s")).agg(F.sum(F.col(label).cast("long")).alias("p"), F.sum(1 - F.col(label).cast("long")).alias("q"))
    ends = by.agg(F.min("s").alias("lo"), F.max("s").alias("hi"))
    slot = F.coalesce(F.floor((F.col("s") - F.col("lo")) * SLOTS / F.nullif(F.col("hi") - F.col("lo"), F.lit(0.0))), F.lit(0)).cast("int")
    cut = by.join(F.broadcast(ends), F.lit(True)).select("s", "p", "q", slot.alias("slot"))
    n = cut.groupBy("slot").agg(F.sum("q").alias("n"))
    before = n.select("slot", (F.sum("n").over(Window.orderBy("slot")) - F.col("n")).alias("before"))  # at most SLOTS + 1 rows
    own = F.coalesce(F.sum("q").over(Window.partitionBy("slot").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    wins = cut.withColumn("own", own).join(F.broadcast(before), "slot").select((F.col("p") * (F.col("own") + F.col("before") + F.col("q") / 2)).alias("w"), "p", "q")
    return wins.agg(F.round(F.sum("w") / (F.sum("p") * F.sum("q")), 6).alias("auc"))


def confusion(links: DataFrame) -> DataFrame:
    """(kind, tp, fp, fn, tn, precision, recall, f1, accuracy) of accepted links (term, gold) against the gold; a null gold is out of vocabulary."""
    right = F.col("term").eqNullSafe(F.col("gold"))
    c = links.groupBy("kind").agg(
        F.count_if(F.col("accepted") & right).alias("tp"),
        F.count_if(F.col("accepted") & ~right).alias("fp"),
        F.count_if(~F.col("accepted") & right).alias("fn"),
        F.count_if(~F.col("accepted") & ~right).alias("tn"),
    )
    p, r = F.col("tp") / (F.col("tp") + F.col("fp")), F.col("tp") / (F.col("tp") + F.col("fn"))
    return c.select("*", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * p * r / (p + r), 6).alias("f1"), F.round((F.col("tp") + F.col("tn")) / (F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn")), 6).alias("accuracy"))
