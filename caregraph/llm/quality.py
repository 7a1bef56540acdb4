"""Quality classifier: a sparse rule ensemble.

Small boosted trees over text statistics are cut into their paths; every path
is a conjunctive rule. Lasso logistic regression weights the rules, most get
zero, and the rest become one Spark column expression. Statistics are SQL
expressions, so scoring needs no Python on the executors.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.llm.common import crc_rest

SAMPLE_ROWS = 20_000
"""Most labelled rows that the ensemble is fitted on (a documented bound)."""
TREES, DEPTH, BINS, MIN_LEAF = 40, 3, 32, 10
LASSO = 0.002
CUT = 0.3


def statistics(text: Column) -> dict[str, Column]:
    """Named statistics of a text; an empty or null text has zeros."""
    t = F.coalesce(text, F.lit(""))
    n = F.greatest(F.length(t), F.lit(1)).cast("double")
    # A pattern of runs takes half the time of translate.
    without = lambda pattern: F.length(F.regexp_replace(t, pattern, ""))
    upper = n - without(r"\p{Lu}+")
    letters = n - without(r"\p{L}+")
    words = F.array_remove(F.split(t, r"\s+"), "")
    n_words = F.greatest(F.size(words), F.lit(1)).cast("double")
    lines = F.split(t, "\n")
    return {
        "log_chars": F.log1p(F.length(t).cast("double")),
        "upper": upper / n,
        "letters": letters / n,
        "symbols": (F.length(t) - without(r"[!#$%&*|<>{}\[\]=+~^_@\\/]+")) / n,
        "digits": (F.length(t) - without("[0-9]+")) / n,
        "stops": (F.length(t) - without("[.,;:?]+")) / n,
        "word_length": F.length(t) / n_words,
        "distinct_words": F.size(F.array_distinct(words)) / n_words,
        "distinct_lines": F.size(F.array_distinct(lines)) / F.size(lines).cast("double"),
        "words_a_line": n_words / F.size(lines),
    }


@dataclass(frozen=True)
class Rule:
    """Conjunction of (statistic, '<=' or '>', threshold)."""

    tests: tuple[tuple[str, str, float], ...]

    def on(self, names: list[str], x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for name, side, cut in self.tests:
            col = x[:, names.index(name)]
            out &= col <= cut if side == "<=" else col > cut
        return out

    def column(self, prefix: str) -> Column:
        out = F.lit(True)
        for name, side, cut in self.tests:
            out = out & (F.col(prefix + name) <= cut if side == "<=" else F.col(prefix + name) > cut)
        return out


@dataclass(frozen=True)
class Ensemble:
    rules: tuple[Rule, ...]
    weights: tuple[float, ...]
    bias: float

    def column(self, prefix: str = "") -> Column:
        """The score as one expression over the statistics' columns."""
        z = F.lit(float(self.bias))
        for rule, w in zip(self.rules, self.weights, strict=True):
            z = z + F.when(rule.column(prefix), F.lit(float(w))).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-z))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _grow(binned: np.ndarray, cuts: list[np.ndarray], grad: np.ndarray, hess: np.ndarray, rows: np.ndarray, depth: int) -> dict:
    """A tree by second-order gain over histograms."""
    g, h = grad[rows].sum(), hess[rows].sum()
    leaf = {"value": g / (h + 1.0), "rows": rows}
    if depth == 0 or len(rows) < 2 * MIN_LEAF:
        return leaf
    best = (1e-6, None)
    for f in range(binned.shape[1]):
        if not len(cuts[f]):
            continue
        size = len(cuts[f]) + 1
        b = binned[rows, f]
        gs, hs, ns = (np.cumsum(np.bincount(b, w, size))[:-1] for w in (grad[rows], hess[rows], np.ones(len(rows))))
        gain = gs**2 / (hs + 1) + (g - gs) ** 2 / (h - hs + 1) - g**2 / (h + 1)
        gain[(ns < MIN_LEAF) | (len(rows) - ns < MIN_LEAF)] = -1
        k = int(gain.argmax())
        if gain[k] > best[0]:
            best = (gain[k], (f, k))
    if best[1] is None:
        return leaf
    f, k = best[1]
    left = binned[rows, f] <= k
    return leaf | {"f": f, "cut": float(cuts[f][k]), "low": _grow(binned, cuts, grad, hess, rows[left], depth - 1), "high": _grow(binned, cuts, grad, hess, rows[~left], depth - 1)}


def _paths(tree: dict, names: list[str], so_far: tuple = ()) -> list[tuple]:
    """Every node but the root is a rule."""
    out = [so_far] if so_far else []
    if "f" in tree:
        for side, key in (("<=", "low"), (">", "high")):
            out += _paths(tree[key], names, so_far + ((names[tree["f"]], side, tree["cut"]),))
    return out


def lasso_logistic(x: np.ndarray, y: np.ndarray, strength: float = LASSO, rounds: int = 400) -> tuple[np.ndarray, float]:
    """Weights and bias by accelerated proximal gradient steps; the bias isn't penalised."""
    n, d = x.shape
    full = np.hstack([x, np.ones((n, 1))])
    step = 4.0 / max(np.linalg.eigvalsh(full.T @ full / n)[-1], 1e-9)
    w = v = np.zeros(d + 1)
    t = 1.0
    for _ in range(rounds):
        new = v - step * full.T @ (_sigmoid(full @ v) - y) / n
        new[:-1] = np.sign(new[:-1]) * np.maximum(np.abs(new[:-1]) - step * strength, 0)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, w, t = new + (t - 1) / t2 * (new - w), new, t2
    return w[:-1], float(w[-1])


def fit(x: np.ndarray, y: np.ndarray, names: list[str]) -> Ensemble:
    """Rules from boosted trees, weighted by the lasso. One class alone, or no rows: no rules, and the share of 1 (one half without rows) as the score."""
    share = float(np.clip(y.mean() if len(y) else 0.5, 1e-3, 1 - 1e-3))
    bias = float(np.log(share / (1 - share)))
    if len(np.unique(y)) < 2:
        return Ensemble((), (), bias)
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS + 1)[1:-1])) for f in range(x.shape[1])]
    binned = np.stack([np.searchsorted(c, x[:, f], side="left") for f, c in enumerate(cuts)], axis=1)
    z, found = np.full(len(y), bias), {}
    for _ in range(TREES):
        p = _sigmoid(z)
        tree = _grow(binned, cuts, y - p, np.maximum(p * (1 - p), 1e-6), np.arange(len(y)), DEPTH)
        stack = [tree]
        while stack:
            node = stack.pop()
            if "f" in node:
                stack += [node["low"], node["high"]]
            else:
                z[node["rows"]] += 0.3 * node["value"]
        for path in _paths(tree, names):
            found.setdefault(Rule(path), None)
    rules = list(found)
    on = np.stack([r.on(names, x) for r in rules], axis=1).astype(float) if rules else np.zeros((len(y), 0))
    w, b = lasso_logistic(on, y.astype(float))
    held = [k for k in range(len(rules)) if abs(w[k]) > 1e-9]
    return Ensemble(tuple(rules[k] for k in held), tuple(float(w[k]) for k in held), b)


def train(labelled: DataFrame, rows: int = SAMPLE_ROWS) -> Ensemble:
    """From (text, quality) rows; null labels are left out. At most ``rows`` rows reach the driver, those whose texts' hashes come first, and only their statistics."""
    named = statistics(F.col("text"))
    stats = labelled.where("quality is not null").select(*(c.cast("double").alias(k) for k, c in named.items()), F.col("quality").cast("double").alias("__cg_y"), F.xxhash64("text", "quality").alias("__cg_h"))
    got = stats.orderBy("__cg_h", *named).limit(rows).drop("__cg_h").collect()
    x = np.array([r[:-1] for r in got], float).reshape(len(got), len(named))
    y = np.array([r[-1] for r in got], float)
    order = np.lexsort(np.hstack([x, y[:, None]]).T)  # results don't depend on the order of collect
    return fit(x[order], (y[order] > 0.5).astype(float), list(named))


def score(docs: DataFrame, model: Ensemble, text: str = "text", out: str = "score") -> DataFrame:
    """``docs`` with column ``out`` (replaced if there); null and empty texts are scored by their zero statistics."""
    named = statistics(F.col(text))
    p = "__cg_q_"
    stats = docs.select("*", *(c.cast("double").alias(p + k) for k, c in named.items()))
    return stats.withColumn(out, model.column(p)).drop(*(p + k for k in named))


def learned(spark: SparkSession, sf_dir: str, docs: DataFrame) -> Ensemble:
    """From the labelled rows that the contract leaves for learning; at most SAMPLE_ROWS labels are drawn, so they can be broadcast to the documents and no text is shuffled."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where((crc_rest(F.col("doc_id"), 5) != 0) & F.col("doc_id").isNotNull() & F.col("quality").isNotNull())
    drawn = labels.select("doc_id", "quality").orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(SAMPLE_ROWS)
    return train(docs.select("doc_id", "text").join(F.broadcast(drawn), "doc_id").select("text", "quality"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row of ``documents``; null and empty texts are scored by their zero statistics, rows without an id are never held out."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = score(docs, learned(spark, sf_dir, docs))
    return out.select("doc_id", (crc_rest(F.col("doc_id"), 5) == 0).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier accepts, with their own columns. Null and empty texts are judged by their zero statistics, very long ones whole, repeated rows alike; an empty table gives none."""
    return score(docs, learned(spark, sf_dir, docs), out="__cg_score").where(F.col("__cg_score") >= CUT).drop("__cg_score")
