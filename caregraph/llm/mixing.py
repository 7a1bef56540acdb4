"""Mixing sources to target weights by temperature.

A source's weight is its share of tokens to the power of an exponent, made to
sum to one. The exponent is found by bisection on all sources' token counts: the
largest that reaches a target entropy, raised again where a source would repeat
more often than allowed. The weights are then realised as budgets: each source's
documents are dealt into blocks, every epoch is a permutation of its blocks, and
a source gives whole epochs and the start of one more until its budget is used.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from caregraph.llm.common import saved

SEED = 17
ENTROPY = 0.97
"""Target entropy, as a share of the most that the sources allow."""
REPEATS = 4.0
"""Most times that a source's tokens may be used."""
BLOCK_TOKENS = 1_000_000
BROADCAST_SOURCES = 100_000
"""Up to so many sources, their plan is broadcast; beyond, it is joined by shuffle."""
WAYS = 32


def tokens(text: str = "text"):
    """Tokens are runs of characters other than white space; none in null."""
    return F.coalesce(F.regexp_count(F.col(text), F.lit(r"\S+")), F.lit(0)).cast("long")


def source_key(source: str = "source"):
    """Null and empty are one source."""
    return F.coalesce(F.col(source), F.lit(""))


def measures(counts: DataFrame, exponents: list[float], budget: float | None = None) -> list[tuple[float, float]]:
    """(entropy, most repeats) for each exponent, by one aggregation over (source, n). Sources without tokens don't count."""
    total = counts.agg(F.sum("n").alias("t")).where("t > 0")
    p = counts.where("n > 0").crossJoin(F.broadcast(total)).select((F.col("n") / F.col("t")).alias("p"), "t")
    aggs = [F.min("p"), F.max("t")]
    for a in exponents:
        aggs += [F.sum(F.pow("p", F.lit(a))), F.sum(F.pow("p", F.lit(a)) * F.log("p"))]
    least, t, *sums = p.agg(*aggs).first()
    if least is None:
        return [(0.0, 0.0) for _ in exponents]
    out = []
    for k, a in enumerate(exponents):
        z, s = sums[2 * k], sums[2 * k + 1]
        out.append((math.log(z) - a * s / z, least ** (a - 1) / z * ((budget or t) / t)))
    return out


def exponent(counts: DataFrame, entropy: float = ENTROPY, repeats: float = REPEATS, budget: float | None = None) -> float:
    """The exponent in [0, 1]. Each round bisects WAYS-fold by one aggregation; entropy and repeats both fall as it rises, and the limit on repeats goes first."""
    most = math.log(max(1, counts.where("n > 0").count()))

    def last(holds, low: float, high: float) -> tuple[float, float]:
        for _ in range(4):
            grid = [low + (high - low) * k / WAYS for k in range(WAYS + 1)]
            ok = [holds(m) for m in measures(counts, grid, budget)]
            k = max((i for i in range(len(ok)) if ok[i]), default=-1)
            if k == WAYS:
                return grid[k], grid[k]
            low, high = grid[max(k, 0)], grid[k + 1]
        return low, high

    a = last(lambda m: m[0] >= entropy * most - 1e-12, 0.0, 1.0)[0]
    if measures(counts, [a], budget)[0][1] > repeats:
        a = last(lambda m: m[1] > repeats, a, 1.0)[1]
    return a


def plan(rows: DataFrame, entropy: float = ENTROPY, repeats: float = REPEATS, budget: float | None = None, block_tokens: int = BLOCK_TOKENS, seed: int = SEED) -> DataFrame:
    """(s, n, weight, budget, blocks, epochs, cut_block, cut_doc): what each source gives.

    ``rows`` (s, d, n): source, document key, tokens. A document's block is its
    key's hash modulo the source's number of blocks. Of the epoch after the whole
    ones, blocks are taken in the epoch's order while they fit; of the next, the
    documents in their order while they fit. ``cut_block`` and ``cut_doc`` are
    the order keys up to which that holds.
    """
    counts = saved(rows.groupBy("s").agg(F.sum("n").alias("n")))
    a = exponent(counts.withColumnRenamed("s", "source"), entropy, repeats, budget)
    p = counts.where("n > 0").select("s", "n", F.pow(F.col("n").cast("double"), F.lit(a)).alias("x"))
    sums = p.agg(F.sum("x").alias("z"), F.sum("n").alias("t"))
    w = p.crossJoin(F.broadcast(sums)).select("s", "n", (F.col("x") / F.col("z")).alias("weight"), (F.lit(budget) if budget else F.col("t").cast("double")).alias("all"))
    w = w.withColumn("budget", F.col("weight") * F.col("all")).drop("all")
    # A whole number of epochs is one, whatever rounding says.
    w = w.withColumn("epochs", F.floor(F.col("budget") / F.col("n") + F.lit(1e-9)).cast("long"))
    w = w.withColumn("rest", F.greatest(F.lit(0.0), F.col("budget") - F.col("epochs") * F.col("n"))).withColumn("blocks", F.ceil(F.col("n") / F.lit(block_tokens)).cast("long"))
    w = saved(w)
    small = w.count() <= BROADCAST_SOURCES
    own = w.select("s", "epochs", "rest", "blocks")
    r = rows.join(F.broadcast(own) if small else own, "s")
    r = r.select("s", "n", doc_order(seed), block_order(seed), "rest")
    blocks = saved(r.groupBy("s", "block_key", "rest").agg(F.sum("n").alias("m")))
    edge = first_over(blocks, "block_key").select("s", F.col("key").alias("cut_block"), F.col("upto").alias("before"))
    in_edge = r.join(F.broadcast(edge) if small else edge, "s").where("block_key = cut_block")
    each = saved(in_edge.groupBy("s", "doc_key", (F.col("rest") - F.col("before")).alias("rest"), "cut_block").agg(F.sum("n").alias("m")))
    # The last document that fits is the one before the first that doesn't; the edge block as a whole doesn't fit.
    over = first_over(each, "doc_key").select("s", F.col("key").alias("over_doc"))
    fits = each.join(F.broadcast(over) if small else over, "s").where("doc_key < over_doc")
    cut = edge.join(fits.groupBy("s").agg(F.max("doc_key").alias("cut_doc")), "s", "left").select("s", "cut_block", "cut_doc")
    return saved(w.join(cut, "s", "left"))


SLICES = 1024


def first_over(rows: DataFrame, key: str) -> DataFrame:
    """(s, key, upto): of each source's rows (s, key, m, rest) in the order of their keys, the first with which the sum of m exceeds rest, and the sum before it.

    Keys are hashes, so the source is cut into SLICES ranges of them; their sums
    are run through first, and only the range where it happens is put in order: no task orders a whole source.
    """
    part = F.shiftright(key, 64 - (SLICES - 1).bit_length())
    sums = rows.groupBy("s", part.alias("part"), "rest").agg(F.sum("m").alias("sum"))
    run = Window.partitionBy("s").orderBy("part")
    sums = sums.withColumn("upto", F.sum("sum").over(run)).where("upto > rest")
    edge = sums.groupBy("s").agg(F.min(F.struct("part", (F.col("upto") - F.col("sum")).alias("before"))).alias("e")).select(F.col("s").alias("of"), "e.part", "e.before")
    near = rows.join(edge, (F.col("s") == F.col("of")) & (part == F.col("part"))).drop("of", "part")
    near = near.withColumn("upto", F.sum("m").over(Window.partitionBy("s").orderBy(key)) + F.col("before")).where("upto > rest")
    return near.groupBy("s").agg(F.min(F.struct(F.col(key).alias("key"), (F.col("upto") - F.col("m")).alias("upto"))).alias("e")).select("s", "e.key", "e.upto")


def doc_order(seed: int):
    return F.xxhash64(F.lit(seed), F.col("d")).alias("doc_key")


def block_order(seed: int):
    """Order key of the row's block in the epoch after the whole ones (blocks and epochs come from the plan's columns)."""
    return _block_key(seed, F.col("epochs")).alias("block_key")


def _block_key(seed: int, epoch):
    return F.xxhash64(F.lit(seed), epoch, F.col("s"), F.pmod(F.xxhash64(F.lit(seed + 1), F.col("d")), F.greatest(F.col("blocks"), F.lit(1))))


def mix(docs: DataFrame, source: str = "source", entropy: float = ENTROPY, repeats: float = REPEATS, budget: float | None = None, block_tokens: int = BLOCK_TOKENS, seed: int = SEED) -> DataFrame:
    """``docs`` mixed: each row once for every epoch that uses it, with columns epoch and mix_key (the order inside an epoch).

    ``budget``: tokens of the mixture; that of the corpus without it. A source
    gives its budget up to less than its next document. Null and empty sources
    are one; documents without tokens come with each whole epoch, and sources
    without any token once. Rows that share an id are used together. Columns named
    epoch and mix_key are replaced. An empty table gives an empty mixture.
    """
    keyed = docs.drop("epoch", "mix_key").withColumn("__cg_s", source_key(source)).withColumn("__cg_n", tokens())
    rows = saved(keyed.select(F.col("__cg_s").alias("s"), F.col("doc_id").alias("d"), F.col("__cg_n").alias("n")))
    how = plan(rows, entropy, repeats, budget, block_tokens, seed)
    how = how.select(*(F.col(c).alias("__cg_" + c) for c in ("s", "blocks", "epochs", "cut_block", "cut_doc")))
    small = how.count() <= BROADCAST_SOURCES
    out = keyed.join(F.broadcast(how) if small else how, "__cg_s", "left")
    key = lambda e: F.xxhash64(F.lit(seed), e, F.col("__cg_s"), F.pmod(F.xxhash64(F.lit(seed + 1), F.col("doc_id")), F.greatest(F.col("__cg_blocks"), F.lit(1))))
    last = key(F.col("__cg_epochs"))
    partly = F.coalesce((last < F.col("__cg_cut_block")) | ((last == F.col("__cg_cut_block")) & (F.xxhash64(F.lit(seed), F.col("doc_id")) <= F.col("__cg_cut_doc"))), F.lit(False))
    times = F.coalesce(F.col("__cg_epochs"), F.lit(1)) + partly.cast("long")
    out = out.withColumn("__cg_t", times).where("__cg_t > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__cg_t") - 1)))
    out = out.withColumn("mix_key", key(F.col("epoch")))
    return out.drop("__cg_t", *(c for c in how.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, source, n_tokens, epoch, mix_key) of the mixture of ``documents``, by ``mix`` with its defaults."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text")
    return mix(docs).select("doc_id", "source", F.col("__cg_n").alias("n_tokens"), "epoch", "mix_key")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``mix`` of all documents: every column stays, epoch and mix_key are added. Null, empty and repeated inputs as there; an empty table gives none."""
    return mix(docs).drop("__cg_n")
