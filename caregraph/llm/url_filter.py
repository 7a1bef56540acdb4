"""URL filters by a ratio of character language models, in SQL expressions only.

Rules (host, path) accept or block the URLs they fit. The URLs that rules have
decided train two smoothed variable-order Markov models of characters, one for
accepted and one for blocked URLs; every other URL is judged by the difference
of the two log-likelihoods, divided by its length, against a calibrated cut.

Characters are counted as they are, so the models grow with the URLs. A context
that was never seen falls back on shorter ones. Models are joined by shuffle;
only where their counted rows are few are they broadcast.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.llm.common import saved

#: Verdict, host, path of the rules asked for.
RULES = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]
ORDER = 4
"""Characters of the longest context."""
CHARACTERS = 1_114_112
"""Code points: what a character's probability is without any context."""
WEIGHT = 4.0
"""Pseudo-observations that a context's lower-order estimate counts for."""
MARK = "\n"
"""Stands before and after a URL."""
BROADCAST_ROWS = 200_000
"""Models of at most so many strings of ORDER + 1 characters are broadcast."""
HELD_OUT = ("0", "1", "2")
"""Rule URLs whose md5 begins so calibrate the cut; the others train the models."""


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty for null or without ``://``."""
    u = F.coalesce(url, F.lit(""))
    host = F.translate(F.regexp_extract(u, r"(?s)^.*?://([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return host, F.regexp_extract(u, r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_column(host: Column, path: Column, rules: list[tuple[str, str, str]]) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, null without one. The list is a parameter of the plan, so its size is known."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for said, h, p in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), r)):
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(p))
        name, verdict = F.when(fits, F.lit(h + p)).otherwise(name), F.when(fits, F.lit(said)).otherwise(verdict)
    return name, verdict


def marked(url: Column) -> Column:
    return F.concat(F.lit(MARK * ORDER), F.coalesce(url, F.lit("")), F.lit(MARK))


def grams(lines: DataFrame) -> DataFrame:
    """Each line's contexts and next characters; its other columns stay."""
    n = F.length("line") - ORDER
    return lines.select("*", F.explode(F.sequence(F.lit(1), n)).alias("at")).withColumn("gram", F.substring("line", F.col("at"), F.lit(ORDER + 1))).drop("at", "line")


def train(labelled: DataFrame, needed: DataFrame) -> DataFrame:
    """(gram, llr) of the grams ``needed``: log-likelihood ratio of the last character after its context, from ``labelled`` (line, n, good).

    Order k is interpolated with order k - 1 by Dirichlet weights, down to a
    uniform distribution, so unseen characters and contexts have a probability too. ``n``: how
    often the line occurs.
    """
    counts = grams(labelled).groupBy("gram").agg(F.sum(F.when(F.col("good"), F.col("n")).otherwise(0)).alias("g"), F.sum(F.when(~F.col("good"), F.col("n")).otherwise(0)).alias("b"))
    out = needed
    pg = pb = F.lit(1.0 / CHARACTERS)
    for k in range(ORDER + 1):
        for name, size in (("t", k + 1), ("c", k)):
            part = lambda c: F.substring(c, ORDER + 1 - k, size)  # noqa: B023, E731
            sums = counts.groupBy(part("gram").alias(f"{name}{k}")).agg(F.sum("g").alias(f"g{name}{k}"), F.sum("b").alias(f"b{name}{k}"))
            out = out.withColumn(f"{name}{k}", part("gram")).join(sums, f"{name}{k}", "left").drop(f"{name}{k}")
        of = lambda c: F.coalesce(F.col(c), F.lit(0))
        pg, pb = (of(f"gt{k}") + WEIGHT * pg) / (of(f"gc{k}") + WEIGHT), (of(f"bt{k}") + WEIGHT * pb) / (of(f"bc{k}") + WEIGHT)
    return out.select("gram", (F.log(pg) - F.log(pb)).alias("llr"))


def score(urls: DataFrame, labelled: DataFrame) -> DataFrame:
    """(id, llr) of ``urls`` (id, line): mean over the characters, by models of ``labelled``."""
    each = grams(urls)
    model = saved(train(labelled, each.select("gram").distinct()))
    small = model.count() <= BROADCAST_ROWS
    return each.join(F.broadcast(model) if small else model, "gram").groupBy("id").agg(F.avg("llr").alias("llr"))


def filter_urls(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES) -> DataFrame:
    """(page_id, host, path, rule, verdict, llr) of every row of ``pages``.

    Null urls have empty host and path and are judged like an empty url; ties at
    the cut are allowed; repeated rows get equal verdicts; other columns of
    ``pages`` are ignored. The cut lies midway between the mean ratios of both classes
    of rule URLs that the models haven't seen (HELD_OUT), or of all of them where a class has none there. Without URLs of both classes all
    others are allowed.
    """
    host, path = split_url(F.col("url"))
    urls = pages.groupBy("url").agg(F.count("*").alias("n")).withColumn("host", host).withColumn("path", path)
    name, said = rule_column(F.col("host"), F.col("path"), rules)
    held = F.substring(F.md5(F.coalesce("url", F.lit(""))), 1, 1).isin(*HELD_OUT)
    # Positions carry a row's number, not its text.
    urls = saved(urls.withColumn("rule", name).withColumn("said", said).withColumn("held", held).withColumn("id", F.xxhash64(F.col("url").isNull(), "url")))
    known = urls.where("said is not null and not held").select(marked(F.col("url")).alias("line"), "n", (F.col("said") == "allow").alias("good"))
    llr = score(urls.select("id", marked(F.col("url")).alias("line")).dropDuplicates(["id"]), known)
    scored = saved(urls.join(llr, "id"))
    mean = lambda side, also: F.sum(F.when((F.col("said") == side) & also, F.col("llr") * F.col("n"))) / F.sum(F.when((F.col("said") == side) & also, F.col("n")))
    cut = lambda also: (mean("allow", also) + mean("block", also)) / 2
    means = scored.agg(F.coalesce(cut(F.col("held")), cut(F.lit(True))).alias("cut"))
    judged = scored.join(F.broadcast(means), F.lit(True), "left")
    judged = judged.select("url", "host", "path", "rule", F.coalesce("said", F.when(F.col("llr") < F.col("cut"), F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"), "llr")
    p = pages.select("page_id", F.col("url").alias("of"))
    return p.join(judged, p["of"].eqNullSafe(judged["url"])).select("page_id", "host", "path", "rule", "verdict", "llr")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, host, path, rule, verdict) of every row of ``pages``, by ``filter_urls`` with RULES."""
    return filter_urls(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")).drop("llr")


def sql(rules: list[tuple[str, str, str]] = RULES) -> str:
    """The query's oracle for DuckDB."""
    ordered = sorted(rules, key=lambda r: (-len(r[1]) - len(r[2]), r))
    case = lambda out: "CASE " + " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{out((s, h, p))}'" for s, h, p in ordered) + " END"
    steps, prob, joins = [], {x: f"{1.0 / CHARACTERS!r}" for x in "gb"}, []
    for k in range(ORDER + 1):
        for name, size in (("t", k + 1), ("c", k)):
            steps.append(f"{name}{k} AS (SELECT substr(gram, {ORDER + 1 - k}, {size}) AS part, sum(g) AS g, sum(b) AS b FROM cnt GROUP BY 1)")
            joins.append(f"LEFT JOIN {name}{k} ON {name}{k}.part = substr(need.gram, {ORDER + 1 - k}, {size})")
        prob = {x: f"((coalesce(t{k}.{x}, 0) + {WEIGHT} * {prob[x]}) / (coalesce(c{k}.{x}, 0) + {WEIGHT}))" for x in "gb"}
    gram = f"unnest(list_transform(range(1, length(line) - {ORDER} + 1), lambda i: substr(line, i, {ORDER + 1})))"
    mean = lambda side, also: f"sum(sc.llr * n) FILTER (WHERE said = '{side}'{also}) / sum(n) FILTER (WHERE said = '{side}'{also})"
    cut = lambda also: f"({mean('allow', also)} + {mean('block', also)}) / 2"
    return f"""
WITH u0 AS (SELECT url, count(*) AS n, coalesce(url, '') AS v FROM pages GROUP BY url),
u1 AS (SELECT *, translate(regexp_extract(v, '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(v, '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path,
         repeat(chr(10), {ORDER}) || v || chr(10) AS line, md5(v)[1] IN {HELD_OUT} AS held FROM u0),
u AS MATERIALIZED (SELECT *, {case(lambda r: r[1] + r[2])} AS rule, {case(lambda r: r[0])} AS said FROM u1),
kg AS (SELECT n, said = 'allow' AS good, {gram} AS gram FROM u WHERE said IS NOT NULL AND NOT held),
cnt AS MATERIALIZED (SELECT gram, sum(CASE WHEN good THEN n ELSE 0 END) AS g, sum(CASE WHEN good THEN 0 ELSE n END) AS b FROM kg GROUP BY 1),
{", ".join(steps)},
pos AS MATERIALIZED (SELECT url, {gram} AS gram FROM u),
need AS (SELECT DISTINCT gram FROM pos),
model AS MATERIALIZED (SELECT need.gram, ln({prob["g"]}) - ln({prob["b"]}) AS llr FROM need {" ".join(joins)}),
sc AS MATERIALIZED (SELECT url, avg(llr) AS llr FROM pos JOIN model USING (gram) GROUP BY url),
cut AS (SELECT coalesce({cut(" AND held")}, {cut("")}) AS cut FROM u JOIN sc ON u.url IS NOT DISTINCT FROM sc.url)
SELECT page_id, host, path, rule, coalesce(said, CASE WHEN sc.llr < cut.cut THEN 'block' ELSE 'allow' END) AS verdict
FROM pages p JOIN u ON p.url IS NOT DISTINCT FROM u.url JOIN sc ON u.url IS NOT DISTINCT FROM sc.url CROSS JOIN cut"""
