"""Queries on string similarities, linking, calibration and the terminology graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph import store
from caregraph.functions import similarity as sim
from caregraph.operators import calibrate, linking, profile, vocab
from caregraph.queries.base import LINES, sql
from caregraph.sources import records


def pairs(spark: SparkSession, d: str) -> DataFrame:
    return linking.candidates(store.mentions(spark, d), vocab.terms(spark, d))


def measured(column):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return pairs(spark, d).select("kind", "mention", "label", F.round(column(F.col("mention"), F.col("label")), 6).alias("sim"))

    return run


def links(spark: SparkSession, d: str, scorer: str = "mean") -> DataFrame:
    """Best term of every mention, with its gold; stored for the mean."""
    if scorer == "mean":
        return store.links(spark, d)
    got = linking.best(linking.scored(pairs(spark, d), scorer))
    return got.join(store.mentions(spark, d), ["kind", "mention"])


def shown(df: DataFrame) -> DataFrame:
    return df.select("kind", "mention", "term", F.round("score", 6).alias("score"))


def marks(spark: SparkSession, d: str, scorer: str = "mean") -> DataFrame:
    s = calibrate.sample(links(spark, d, scorer)).withColumn("truth", F.col("term").eqNullSafe(F.col("gold")))
    return calibrate.votes(s).withColumn("truth", calibrate.majority(F.col("votes")))


def accepted(spark: SparkSession, d: str) -> DataFrame:
    return linking.accept(links(spark, d), calibrate.best_threshold(calibrate.sweep(marks(spark, d))))


def one_for_all(spark: SparkSession, d: str) -> DataFrame:
    curve = calibrate.sweep(marks(spark, d).withColumn("kind", F.lit("all")))
    return calibrate.best_threshold(curve)


def roc(spark: SparkSession, d: str) -> DataFrame:
    docs, labels = records.table(spark, d, "documents", "doc_id", "n_chars"), records.table(spark, d, "labels", "doc_id", "quality")
    return calibrate.roc_auc(docs.join(labels, "doc_id"), "n_chars", "quality")


def rate(over: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return profile.link_rate(store.mentions(spark, d), accepted(spark, d), over)

    return run


def normalized(spark: SparkSession, d: str) -> DataFrame:
    ev = records.named(records.lines(spark, d).where("kind in ('diagnosis', 'drug', 'assay')").select("event_id", "kind", "l_partkey"), spark, d)
    return linking.normalize(ev, accepted(spark, d)).groupBy("kind", "label").agg(F.count("*").alias("events"))


def contains(spark: SparkSession, d: str) -> DataFrame:
    """Long strings: items that a document has word for word. Candidates share a run of words, by an equi-join; then the text decides."""
    items = records.table(spark, d, "benchmark").select("item_id", F.col("text").alias("item")).where("item is not null")
    docs = records.table(spark, d, "documents", "doc_id", "text").where("text is not null")
    key = F.xxhash64("text").alias("key")
    # An item lies inside a text with its first and last words perhaps cut off there, so runs are of the words between.
    inner = F.slice(_words(F.col("item")), 2, F.greatest(F.size(_words(F.col("item"))) - 2, F.lit(0)))
    item = items.withColumn("w", inner).withColumn("n", F.least(F.size("w"), F.lit(GRAM)))
    own = docs.select(key, "text").dropDuplicates(["key"]).select("key", "text", _words(F.col("text")).alias("w"))
    met = None
    for n in [r["n"] for r in item.select("n").distinct().collect()]:  # at most GRAM + 1 values
        if n < 1:  # items of two words or fewer are tried against every text, by blocks of a broadcast
            some = own.join(F.broadcast(item.where("n < 1").select("item_id", "item")), F.contains("text", "item")).select("key", "item_id")
        else:
            first = item.where(F.col("n") == n).select("item_id", F.element_at(_grams(F.col("w"), n), 1).alias("g"))
            some = own.select("key", F.explode(_grams(F.col("w"), n)).alias("g")).join(first, "g").select("key", "item_id")
        met = some if met is None else met.unionByName(some)
    if met is None:
        return docs.select("doc_id").crossJoin(items.limit(0).select("item_id"))
    both = docs.select("doc_id", "text", key).join(met.distinct(), "key").join(items, "item_id")
    return both.where(F.contains("text", "item")).select("doc_id", "item_id")


GRAM = 3
"""A line and an item are scored if they share a run of so many words, or all of an item with fewer."""


def raw_or_linked(spark: SparkSession, d: str) -> DataFrame:
    """Events that a question finds by an object's standard label: in the raw spelling, with the label's synonyms, and through accepted links (rightly or wrongly)."""
    names = vocab.synset(vocab.edges(spark, d)).where("rel <> 'self'").select(F.col("label").alias("gold"), F.col("name").alias("mention")).distinct().withColumn("other", F.lit(True))
    a = accepted(spark, d).join(names, ["gold", "mention"], "left")
    right = F.coalesce(F.col("term") == F.col("gold"), F.lit(False))
    n = lambda cond, name: F.sum(F.when(cond, F.col("n")).otherwise(0)).cast("long").alias(name)
    raw = F.coalesce(F.col("mention") == F.col("gold"), F.lit(False))
    return a.groupBy("kind").agg(F.sum("n").cast("long").alias("events"), n(raw, "raw"), n(raw | F.col("other").isNotNull(), "expanded"), n(F.col("accepted") & right, "linked"), n(F.col("accepted") & ~right, "wrong"))


def policies(spark: SparkSession, d: str) -> DataFrame:
    """Links under three policies: a threshold for each kind, one for all, none; how many are right."""
    held = links(spark, d)
    one = one_for_all(spark, d).select("threshold")
    some = [
        ("per kind", accepted(spark, d)),
        ("one", linking.accept(held.join(F.broadcast(one), F.lit(True)).withColumnRenamed("threshold", "__t"), -1.0).withColumn("accepted", F.col("score") > F.col("__t")).drop("__t")),
        ("none", held.withColumn("threshold", F.lit(None).cast("double")).withColumn("accepted", F.lit(True))),
    ]
    out = None
    for name, df in some:
        c = calibrate.confusion(df).select(F.lit(name).alias("policy"), "kind", "tp", "fp", "fn", "tn", "accuracy")
        out = c if out is None else out.unionByName(c)
    return out


def minhash_recall(spark: SparkSession, d: str) -> DataFrame:
    """Of the accepted links of the exact space, those whose pair the approximate candidates hold."""
    exact = accepted(spark, d).where("accepted").select("kind", "mention", "term")
    near = linking.minhash_candidates(store.mentions(spark, d), vocab.terms(spark, d)).select("kind", "mention", F.col("label").alias("term")).withColumn("met", F.lit(1))
    return exact.join(near, ["kind", "mention", "term"], "left").groupBy("kind").agg(F.count("*").alias("links"), F.count("met").alias("met"), F.round(F.count("met") / F.count("*"), 6).alias("recall"))


def _words(c):
    """Lower-cased words; other characters only part them."""
    return F.filter(F.split(F.regexp_replace(F.lower(c), r"(?U)[\W_]+", " "), " "), lambda w: w != "")


def _grams(w, n: int):
    """Different runs of n words."""
    return F.when(F.size(w) >= n, F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - n + 1, F.lit(1))), lambda i: F.array_join(F.slice(w, i, n), " "))))


def text_pairs(lines: DataFrame, items: DataFrame) -> DataFrame:
    """(mention, item_id, label): all lines (mention) and items (item_id, label) that share a run of GRAM words at any place, or hold all words of a shorter item."""
    line = lines.where("mention is not null").select("mention", F.md5("mention").alias("line"), _words(F.col("mention")).alias("w"))
    item = items.select("item_id", "label", _words(F.col("label")).alias("w")).where(F.size("w") > 0).withColumn("n", F.least(F.size("w"), F.lit(GRAM)))
    met = None
    for n in [r["n"] for r in item.select("n").distinct().collect()]:  # at most GRAM values
        own = item.where(F.col("n") == n).select("item_id", F.explode(_grams(F.col("w"), n)).alias("g"))
        some = line.select("line", F.explode(_grams(F.col("w"), n)).alias("g")).join(own, "g").select("line", "item_id").distinct()
        met = some if met is None else met.unionByName(some)
    if met is None:
        return line.select("mention").crossJoin(items.limit(0).select("item_id", "label"))
    return met.join(line.select("line", "mention"), "line").join(items.select("item_id", "label"), "item_id").select("mention", "item_id", "label")


def text_matches(spark: SparkSession, d: str) -> DataFrame:
    """Document lines against items that they share words with, by the Arrow form of the subsequence."""
    line = records.table(spark, d, "documents", "text").select(F.explode(F.split("text", "\n")).alias("mention")).distinct()
    both = text_pairs(line, records.table(spark, d, "benchmark").select("item_id", F.col("text").alias("label")))
    a, b = F.col("mention"), F.col("label")
    return both.select(F.md5("mention").alias("line_md5"), F.length(a).alias("line_chars"), F.length(b).alias("item_chars"), F.round(sim.lcs_sim(a, b, long=True), 6).alias("sim"))


MENTIONS = (
    LINES
    + """,
used AS (SELECT kind, l_partkey, count(*) AS n, CASE kind WHEN 'diagnosis' THEN 0 WHEN 'drug' THEN 1 ELSE 2 END AS ki FROM li WHERE kind IN ('diagnosis', 'drug', 'assay') GROUP BY 1, 2),
raw AS (SELECT kind, n, l_partkey, lower(p_name) AS label, p_name, (p_partkey + 3 * ki) % 8 AS way, split_part(p_name, ' ', 1) AS a, split_part(p_name, ' ', 2) AS b, lower(p_type) AS t FROM used JOIN part ON p_partkey = l_partkey),
spelt AS (SELECT kind, n, l_partkey, CASE WHEN way < 7 THEN label END AS gold, lower(trim(CASE way WHEN 0 THEN p_name WHEN 1 THEN upper(p_name) || '.' WHEN 2 THEN a[1] || '. ' || b
    WHEN 3 THEN a || ' ' || regexp_replace(b, '[aeiou]', '', 'g') WHEN 4 THEN b || ' ' || a
    WHEN 5 THEN (CASE a WHEN 'hot' THEN 'heated' WHEN 'cold' THEN 'chilled' WHEN 'small' THEN 'mini' ELSE a END) || ' ' || b WHEN 6 THEN p_name || ' ' || t ELSE reverse(p_name) END)) AS mention FROM raw),
men AS (SELECT kind, mention, gold, CAST(sum(n) AS BIGINT) AS n FROM spelt GROUP BY 1, 2, 3),
term AS (SELECT k.kind, l.label FROM (SELECT DISTINCT lower(p_name) AS label FROM part) l CROSS JOIN (SELECT unnest(['diagnosis', 'drug', 'assay']) AS kind) k)"""
)
_LCS = (
    "bit_count(list_reduce(list_prepend(0::BIGINT, list_transform(string_split({a}, ''), lambda c: list_sum(list_transform(range(length({b})), lambda i: CASE WHEN {b}[i + 1] = c THEN 1::BIGINT << i ELSE 0 END))::BIGINT)), "
    "lambda r, m: (r | m) & ~((r | m) - ((r << 1) | 1))) & ((1::BIGINT << length({b})) - 1))"
).format(a="mention", b="label")
SCORED = (
    MENTIONS
    + f""",
sim AS (SELECT *, 1 - levenshtein(mention, label) / greatest(length(mention), length(label)) AS lev, jaccard(mention, label) AS jac,
          {_LCS} / greatest(length(mention), length(label)) AS lcs
        FROM (SELECT DISTINCT kind, mention FROM men) JOIN term USING (kind)),
sc AS (SELECT *, round((lev + jac + lcs) / 3, 12) AS score FROM sim)"""
)


def _best(score: str = "score") -> str:
    return f"lk AS (SELECT b.*, men.gold, men.n FROM (SELECT kind, mention, label AS term, round({score}, 12) AS score FROM sc QUALIFY row_number() OVER (PARTITION BY kind, mention ORDER BY round({score}, 12) DESC, label) = 1) b JOIN men USING (kind, mention))"


def _sweep(kind: str = "kind") -> str:
    return f""",
smp AS (SELECT *, coalesce(term = gold, FALSE) AS truth, pos // 10 AS k FROM (SELECT *, row_number() OVER (PARTITION BY kind ORDER BY score, mention) AS pos FROM lk) WHERE pos % 10 = 0),
vote AS (SELECT *, list_transform([1, 2, 3, 4, 5, 6], lambda r: CASE WHEN (k * 7 + 13 * r) % 20 = 0 THEN NOT truth ELSE truth END) AS votes FROM smp),
mk AS (SELECT {kind} AS kind, score, len(list_filter(votes, lambda v: v)) * 2 > 6 AS truth FROM vote),
sw AS (SELECT kind, round(g * 0.05, 6) AS threshold, count(*) FILTER (WHERE truth AND score > round(g * 0.05, 6)) AS tp, count(*) FILTER (WHERE NOT truth AND score > round(g * 0.05, 6)) AS fp,
         count(*) FILTER (WHERE NOT truth AND score <= round(g * 0.05, 6)) AS tn, count(*) FILTER (WHERE truth AND score <= round(g * 0.05, 6)) AS fn
       FROM mk CROSS JOIN range(21) AS r(g) GROUP BY 1, 2),
cv AS (SELECT *, CASE WHEN tp + fn = 0 THEN 0 ELSE tp / (tp + fn) END AS tpr0, CASE WHEN tn + fp = 0 THEN 0 ELSE tn / (tn + fp) END AS tnr0 FROM sw),
bt AS (SELECT kind, threshold, round((tpr0 + tnr0) / 2, 6) AS auc FROM cv QUALIFY row_number() OVER (PARTITION BY kind ORDER BY round((tpr0 + tnr0) / 2, 6) DESC, threshold) = 1),
ac AS (SELECT lk.*, score > threshold AS accepted FROM lk JOIN bt USING (kind))"""


ACCEPTED = SCORED + ", " + _best() + _sweep()
_SHOW = "SELECT kind, mention, term, round(score, 6) AS score FROM lk"
_EDGES = """
ed AS (SELECT DISTINCT lower(p_name) AS src, 'broader' AS rel, dst FROM (SELECT p_name, unnest([p_brand, p_type]) AS dst FROM part)
  UNION ALL SELECT CASE split_part(d, ' ', 1) WHEN 'hot' THEN 'heated' WHEN 'cold' THEN 'chilled' ELSE 'mini' END || ' ' || split_part(d, ' ', 2), 'synonym', d FROM (SELECT DISTINCT lower(p_name) AS d FROM part) WHERE split_part(d, ' ', 1) IN ('hot', 'cold', 'small')
  UNION ALL SELECT d[1] || '. ' || split_part(d, ' ', 2), 'abbreviation', d FROM (SELECT DISTINCT lower(p_name) AS d FROM part)
  UNION ALL SELECT n_name, 'broader', r_name FROM nation JOIN region ON n_regionkey = r_regionkey UNION ALL SELECT r_name, 'broader', 'WORLD' FROM region)"""
_UP = "up AS (SELECT src AS term, dst AS broader, 1 AS steps FROM ed WHERE rel = 'broader' UNION ALL SELECT e.src, u.broader, u.steps + 1 FROM up u JOIN ed e ON e.dst = u.term AND e.rel = 'broader')"


def _sim(expr: str) -> str:
    return f"WITH {SCORED} SELECT kind, mention, label, round({expr}, 6) AS sim FROM sc"


_QGRAM = "list_distinct(list_transform(range(1, length({x})), lambda i: {x}[i : i + 1]))"
_TOKEN = "list_distinct(string_split({x}, ' '))"


def _sets(unit: str) -> str:
    a, b = unit.format(x="mention"), unit.format(x="label")
    return f"len(list_intersect({a}, {b})) / (len({a}) + len({b}) - len(list_intersect({a}, {b})))"


_DRAW = "CAST('0x' || substr(md5('7|' || kind || '|' || mention), 1, 8) AS BIGINT)"
_GRAMS = "{n} AS (SELECT *, list_filter(string_split(regexp_replace(lower({t}), '[^\\p{{L}}\\p{{N}}\\p{{M}}]+', ' ', 'g'), ' '), lambda x: x <> '') AS w FROM {src})"
QUERIES = {
    "sim_lev": measured(sim.lev_sim),
    "sim_jaccard_char": measured(sim.jaccard_sim),
    "sim_jaccard_qgram": measured(lambda a, b: sim.jaccard_sim(a, b, "qgram")),
    "sim_jaccard_token": measured(lambda a, b: sim.jaccard_sim(a, b, "token")),
    "sim_lcs": measured(sim.lcs_sim),
    "sim_matchability": measured(lambda a, b: sim.matchability(sim.lev_sim(a, b), sim.jaccard_sim(a, b), sim.lcs_sim(a, b))),
    "link_mentions": records.mentions,
    "link_best": lambda s, d: shown(linking.best_pruned(pairs(s, d))),
    "link_topk": lambda s, d: linking.best(linking.scored(pairs(s, d)), 3).select("kind", "mention", "term", F.round("score", 6).alias("score"), F.col("rank").cast("long").alias("rank")),
    "link_lev_only": lambda s, d: shown(links(s, d, "lev")),
    "link_jac_only": lambda s, d: shown(links(s, d, "jaccard")),
    "link_lcs_only": lambda s, d: shown(links(s, d, "lcs")),
    "link_exact": lambda s, d: shown(links(s, d, "exact")).where("score = 1"),
    "link_pruned": lambda s, d: shown(linking.best(linking.scored(linking.candidates(store.mentions(s, d), vocab.terms(s, d), "length", 0.6), prune=0.6)).where("score > 0.6")),
    "link_gram_blocking": lambda s, d: linking.candidates(store.mentions(s, d), vocab.terms(s, d), "gram").groupBy("kind").agg(F.count("*").alias("pairs")),
    "link_minhash": lambda s, d: shown(linking.best(linking.scored(linking.minhash_candidates(store.mentions(s, d), vocab.terms(s, d))))),
    "link_minhash_recall": minhash_recall,
    "link_triples": lambda s, d: linking.link_triples(accepted(s, d)).select("s", "p", "o"),
    "link_raw_or_linked": raw_or_linked,
    "cal_policies": policies,
    "cal_sample_random": lambda s, d: calibrate.sample(links(s, d), method="random").select("kind", "mention"),
    "cal_sample_stratified": lambda s, d: calibrate.sample(links(s, d), method="stratified").select("kind", "mention"),
    "link_score_curve": lambda s, d: calibrate.score_curve(links(s, d)).select("kind", "mention", F.round("score", 6).alias("score"), F.col("pos").cast("long").alias("pos")),
    "cal_sample": lambda s, d: calibrate.sample(links(s, d)).select("kind", "mention", F.col("pos").cast("long").alias("pos")),
    "cal_votes": lambda s, d: marks(s, d).select("kind", "mention", "truth", F.round(calibrate.agreement(F.col("votes")), 6).alias("agreement")),
    "cal_sweep": lambda s, d: calibrate.sweep(marks(s, d)),
    "cal_best_threshold": lambda s, d: calibrate.best_threshold(calibrate.sweep(marks(s, d))),
    "cal_best_threshold_lev": lambda s, d: calibrate.best_threshold(calibrate.sweep(marks(s, d, "lev"))),
    "cal_global_threshold": one_for_all,
    "cal_roc_auc_labels": roc,
    "cal_confusion": lambda s, d: calibrate.confusion(accepted(s, d)),
    "link_rate_events": rate("events"),
    "link_rate_entities": rate("entities"),
    "ev_normalized": normalized,
    "vocab_closure": lambda s, d: vocab.narrower(vocab.edges(s, d)),
    "vocab_synset": lambda s, d: vocab.synset(vocab.edges(s, d)),
    "vocab_expand": lambda s, d: vocab.expand(vocab.edges(s, d), "PROMO"),
    "link_text_contains": contains,
    "link_text_pairs": lambda s, d: text_matches(s, d).drop("sim"),
    "link_text_lcs": text_matches,
}

_RATE = "SELECT kind, CAST(sum(CASE WHEN accepted THEN {n} ELSE 0 END) AS BIGINT) AS linked, CAST(sum({n}) AS BIGINT) AS total, round(sum(CASE WHEN accepted THEN {n} ELSE 0 END) / sum({n}), 6) AS rate FROM ac GROUP BY kind"
SQL = {
    "sim_lev": _sim("lev"),
    "sim_jaccard_char": _sim("jac"),
    "sim_jaccard_qgram": _sim(_sets(_QGRAM)),
    "sim_jaccard_token": _sim(_sets(_TOKEN)),
    "sim_lcs": _sim("lcs"),
    "sim_matchability": _sim("score"),
    "link_mentions": f"WITH {MENTIONS} SELECT * FROM men",
    "link_best": f"WITH {SCORED}, {_best()} {_SHOW}",
    "link_topk": f"WITH {SCORED} SELECT * FROM (SELECT kind, mention, label AS term, round(score, 6) AS score, row_number() OVER (PARTITION BY kind, mention ORDER BY score DESC, label) AS rank FROM sc) WHERE rank <= 3",
    "link_lev_only": f"WITH {SCORED}, {_best('lev')} {_SHOW}",
    "link_jac_only": f"WITH {SCORED}, {_best('jac')} {_SHOW}",
    "link_lcs_only": f"WITH {SCORED}, {_best('lcs')} {_SHOW}",
    "link_exact": f"WITH {MENTIONS} SELECT DISTINCT kind, mention, mention AS term, 1.0::DOUBLE AS score FROM men WHERE mention IN (SELECT label FROM term)",
    "link_pruned": f"WITH {SCORED}, {_best()} {_SHOW} WHERE score > 0.6",
    "link_gram_blocking": f"WITH {SCORED} SELECT kind, count(*) AS pairs FROM sc WHERE len(list_intersect({_QGRAM.format(x='mention')}, {_QGRAM.format(x='label')})) > 0 GROUP BY 1",
    "link_triples": f"WITH {ACCEPTED} SELECT 'cg:mention/' || kind || '/' || replace(replace(url_encode(mention), '%20', '+'), '%2B', '%2B') AS s, 'cg:linkedTo' AS p, 'cg:term/' || kind || '/' || replace(url_encode(term), '%20', '+') AS o FROM ac WHERE accepted",
    "link_raw_or_linked": f"""WITH {ACCEPTED}, {_EDGES}, nm AS (SELECT DISTINCT dst AS gold, src AS mention FROM ed WHERE rel IN ('synonym', 'abbreviation'))
      SELECT kind, CAST(sum(n) AS BIGINT) AS events, CAST(coalesce(sum(n) FILTER (WHERE mention = gold), 0) AS BIGINT) AS raw,
        CAST(coalesce(sum(n) FILTER (WHERE mention = gold OR (gold, mention) IN (SELECT (gold, mention) FROM nm)), 0) AS BIGINT) AS expanded,
        CAST(coalesce(sum(n) FILTER (WHERE accepted AND term = gold), 0) AS BIGINT) AS linked, CAST(coalesce(sum(n) FILTER (WHERE accepted AND term IS DISTINCT FROM gold), 0) AS BIGINT) AS wrong FROM ac GROUP BY 1""",
    "cal_policies": f"""WITH {ACCEPTED}, mk1 AS (SELECT score, truth FROM mk),
      one AS (SELECT g * 0.05 AS threshold, (coalesce(count(*) FILTER (WHERE truth AND score > round(g * 0.05, 6)) / nullif(count(*) FILTER (WHERE truth), 0), 0) + coalesce(count(*) FILTER (WHERE NOT truth AND score <= round(g * 0.05, 6)) / nullif(count(*) FILTER (WHERE NOT truth), 0), 0)) / 2 AS auc FROM mk1 CROSS JOIN range(21) AS r(g) GROUP BY 1 QUALIFY row_number() OVER (ORDER BY round(auc, 6) DESC, threshold) = 1),
      x AS (SELECT 'per kind' AS policy, kind, accepted, coalesce(term = gold, FALSE) AS ok FROM ac UNION ALL SELECT 'one', kind, score > round((SELECT threshold FROM one), 6), coalesce(term = gold, FALSE) FROM ac UNION ALL SELECT 'none', kind, TRUE, coalesce(term = gold, FALSE) FROM ac)
      SELECT policy, kind, count(*) FILTER (WHERE accepted AND ok) AS tp, count(*) FILTER (WHERE accepted AND NOT ok) AS fp, count(*) FILTER (WHERE NOT accepted AND ok) AS fn, count(*) FILTER (WHERE NOT accepted AND NOT ok) AS tn, round((count(*) FILTER (WHERE accepted = ok)) / count(*), 6) AS accuracy FROM x GROUP BY 1, 2""",
    "cal_sample_random": f"WITH {SCORED}, {_best()} SELECT kind, mention FROM lk WHERE {_DRAW} % 1000000 < 100000",
    "cal_sample_stratified": f"WITH {SCORED}, {_best()} SELECT kind, mention FROM lk QUALIFY row_number() OVER (PARTITION BY kind, floor(score * 10) ORDER BY {_DRAW}, mention) <= ceil(count(*) OVER (PARTITION BY kind, floor(score * 10)) * 0.1)",
    "link_text_pairs": f"""WITH d AS (SELECT DISTINCT unnest(string_split(text, chr(10))) AS a FROM documents), {_GRAMS.format(n="dw", src="d", t="a")},
      i AS (SELECT item_id, text AS b FROM benchmark), {_GRAMS.format(n="iw", src="i", t="b")},
      dg AS (SELECT a, k, unnest(list_distinct(list_transform(range(1, greatest(len(w) - k + 2, 1)), lambda p: array_to_string(w[p : p + k - 1], ' ')))) AS g FROM dw CROSS JOIN (SELECT unnest([1, 2, 3]) AS k)),
      ig AS (SELECT item_id, b, least(len(w), 3) AS k, unnest(list_distinct(list_transform(range(1, greatest(len(w) - least(len(w), 3) + 2, 1)), lambda p: array_to_string(w[p : p + least(len(w), 3) - 1], ' ')))) AS g FROM iw WHERE len(w) > 0),
      m AS (SELECT DISTINCT a, item_id, b FROM dg JOIN ig USING (k, g))
      SELECT md5(a) AS line_md5, CAST(length(a) AS INTEGER) AS line_chars, CAST(length(b) AS INTEGER) AS item_chars FROM m""",
    "link_score_curve": f"WITH {SCORED}, {_best()} SELECT kind, mention, round(score, 6) AS score, row_number() OVER (PARTITION BY kind ORDER BY score DESC, mention) AS pos FROM lk",
    "cal_sample": f"WITH {ACCEPTED} SELECT kind, mention, k AS pos FROM smp",
    "cal_votes": f"WITH {ACCEPTED} SELECT kind, mention, len(list_filter(votes, lambda v: v)) > 3 AS truth, round(greatest(len(list_filter(votes, lambda v: v)), 6 - len(list_filter(votes, lambda v: v))) / 6, 6) AS agreement FROM vote",
    "cal_sweep": f"WITH {ACCEPTED} SELECT kind, threshold, tp, fp, tn, fn, round(tpr0, 6) AS tpr, round(1 - tnr0, 6) AS fpr, round((tpr0 + tnr0) / 2, 6) AS auc FROM cv",
    "cal_best_threshold": f"WITH {ACCEPTED} SELECT * FROM bt",
    "cal_best_threshold_lev": f"WITH {SCORED}, {_best('lev')}{_sweep()} SELECT * FROM bt",
    "cal_global_threshold": f"WITH {SCORED}, {_best()}{_sweep(chr(39) + 'all' + chr(39))} SELECT * FROM bt".replace("ac AS (SELECT lk.*, score > threshold AS accepted FROM lk JOIN bt USING (kind))", "ac AS (SELECT 1)"),
    "cal_roc_auc_labels": "WITH d AS (SELECT n_chars AS s, sum(quality) AS p, sum(1 - quality) AS q FROM documents JOIN labels USING (doc_id) GROUP BY 1), w AS (SELECT p, q, p * (coalesce(sum(q) OVER (ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + q / 2) AS w FROM d) SELECT round(sum(w) / (sum(p) * sum(q)), 6) AS auc FROM w",
    "cal_confusion": f"""WITH {ACCEPTED}, c AS (SELECT kind, count(*) FILTER (WHERE accepted AND coalesce(term = gold, FALSE)) AS tp, count(*) FILTER (WHERE accepted AND NOT coalesce(term = gold, FALSE)) AS fp,
        count(*) FILTER (WHERE NOT accepted AND coalesce(term = gold, FALSE)) AS fn, count(*) FILTER (WHERE NOT accepted AND NOT coalesce(term = gold, FALSE)) AS tn FROM ac GROUP BY 1)
      SELECT *, round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall, round(2 * (tp / (tp + fp)) * (tp / (tp + fn)) / (tp / (tp + fp) + tp / (tp + fn)), 6) AS f1, round((tp + tn) / (tp + fp + fn + tn), 6) AS accuracy FROM c""",
    "link_rate_events": f"WITH {ACCEPTED} " + _RATE.format(n="n"),
    "link_rate_entities": f"WITH {ACCEPTED} " + _RATE.format(n="1"),
    "ev_normalized": f"WITH {ACCEPTED} SELECT kind, CASE WHEN accepted THEN term ELSE mention END AS label, CAST(sum(n) AS BIGINT) AS events FROM ac GROUP BY ALL",
    "vocab_closure": sql(_EDGES, _UP, body="SELECT term, broader, min(steps) AS steps FROM up GROUP BY 1, 2", recursive=True),
    "vocab_synset": sql(_EDGES, body="SELECT dst AS label, dst AS name, 'self' AS rel FROM (SELECT DISTINCT dst FROM ed WHERE rel IN ('synonym', 'abbreviation')) UNION ALL SELECT dst, src, rel FROM ed WHERE rel IN ('synonym', 'abbreviation')"),
    "vocab_expand": sql(_EDGES, "lo AS (SELECT DISTINCT src AS l FROM ed WHERE rel = 'broader' AND dst = 'PROMO')", body="SELECT 'PROMO' AS name UNION SELECT l FROM lo UNION SELECT src FROM ed WHERE rel IN ('synonym', 'abbreviation') AND dst IN (SELECT l FROM lo)"),
    "link_text_contains": "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
}
