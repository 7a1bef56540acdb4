"""The pipeline's stages on the small table."""

import random
from collections import Counter, defaultdict
from itertools import combinations

from pyspark.sql import functions as F

import corpus_pipeline
from caregraph.llm import decontaminate, line_dedup, simhash


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_classifier", "line_dedup", "simhash_near_dedup", "benchmark_decontamination", "temperature_mixing"]
    held, columns = [docs.count()], docs.columns
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf).cache()
        held.append(docs.count())
        if name != names[-1]:
            assert docs.columns == columns
        if name == "simhash_near_dedup":
            again = simhash.similar_components(docs.select("doc_id", "text"))
            assert again.where("component_id <> doc_id").count() <= 1
        if name == "benchmark_decontamination":
            assert decontaminate.find_leaks(docs, spark.read.parquet(f"{sf}/benchmark.parquet")).count() == 0
    assert held[0] > held[1] and held[1] == held[2] and held[2] > held[3] >= held[4] > 0
    assert docs.where(F.col("epoch") < 0).count() == 0


def test_quality_stage_keeps_clean_documents(spark):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    good = spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1")
    kept = corpus_pipeline.STAGES[0][1](spark, docs, sf)
    assert kept.join(good, "doc_id").count() / docs.join(good, "doc_id").count() > 0.99


def rows_of(df):
    return sorted(((r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()), key=str)


def test_line_stage_against_all_pairs_of_lines(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = sorted(rows_of(docs), key=lambda r: r[0])
    norm = lambda x: x.strip(" ").lower()
    lines = list(dict.fromkeys(norm(x) for _, t in rows for x in (t or "").split("\n") if norm(x)))
    sign = [line_dedup._sign(x) for x in lines]
    up = {x: x for x in lines}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    long = [k for k, x in enumerate(lines) if len(x) >= line_dedup.FUZZY_CHARS]
    for i, j in combinations(long, 2):
        if abs(len(lines[i]) - len(lines[j])) <= 2 and (sign[i] ^ sign[j]).bit_count() <= 4 and line_dedup.within(lines[i], lines[j]):
            up[find(lines[i])] = find(lines[j])
    seen, want = set(), []
    for d, t in rows:
        kept = []
        for x in (t or "").split("\n") if t is not None else []:
            root = find(norm(x)) if norm(x) else None
            if root is None or root not in seen:
                kept.append(x)
                seen.add(root)
        want.append((d, None if t is None else "\n".join(kept)))
    assert rows_of(line_dedup.stage(spark, docs, sf)) == sorted(want, key=str)


def test_near_stage_against_exact_similarity(spark):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = sorted(rows_of(docs), key=lambda r: r[0])
    sets = [set(simhash.shingles(t, 5)) for _, t in rows]
    holders = defaultdict(list)
    for k, s in enumerate(sets):
        for x in s:
            holders[x].append(k)
    up = list(range(len(rows)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    empty = [k for k, s in enumerate(sets) if not s]
    for k in empty[1:]:
        up[find(k)] = find(empty[0])
    links = 0
    for k, s in enumerate(sets):
        for j, n in Counter(j for x in s for j in holders[x] if j > k).items():
            if n / (len(s) + len(sets[j]) - n) >= 0.8:
                links += 1
                up[max(find(j), find(k))] = min(find(j), find(k))
    want = [rows[k] for k in range(len(rows)) if find(k) == k]
    assert links > 50 and rows_of(simhash.stage(spark, docs, sf)) == sorted(want, key=str)


def test_decontamination_stage_against_all_alignments(spark, sf):
    """Every document is aligned with every item, in windows that no alignment of the score is wider than."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    items = [decontaminate.normal(r["text"]).split() for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    want = []
    for d, t in rows_of(docs):
        words = decontaminate.normal(t).split()
        at = defaultdict(list)
        for k, w in enumerate(words):
            at[w].append(k)
        leaks = False
        for item in items:
            wide = decontaminate.widest(len(item), decontaminate.SCORE)
            hits = sorted(k for w in set(item) for k in at.get(w, ()))
            need = decontaminate.least_score(len(item), decontaminate.SCORE) // 2
            # Windows with as many words of the item as the score takes; others can't reach it.
            stretches = []
            for a, z in zip(hits, hits[need - 1 :], strict=False):
                if z - a < wide:
                    if stretches and max(0, a - 1) <= stretches[-1][1]:
                        stretches[-1][1] = a + wide + 1
                    else:
                        stretches.append([max(0, a - 1), a + wide + 1])
            leaks = leaks or any(decontaminate.align(words[a:z], item)[0] >= decontaminate.least_score(len(item), decontaminate.SCORE) for a, z in stretches)
        if not leaks:
            want.append((d, t))
    assert rows_of(decontaminate.stage(spark, docs, sf)) == want and len(want) < docs.count()


def test_stages_on_awkward_tables(spark, sf):
    """Empty tables, null ids and texts, repeated rows, very long texts, and columns named as the stages' own."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    r = random.Random(1)
    long = "\n".join(" ".join(f"w{r.randrange(10**6)}" for _ in range(9)) for _ in range(5_000))
    odd = spark.createDataFrame([(None, None, None, None, None), (None, "a few words", "en", None, 11), (7, None, "en", "s", None), (7, "", "en", "s", 0), (8, "twice", "en", "s", 5), (8, "twice", "en", "s", 5), (9, long, "en", "s", len(long))], docs.schema)
    for name in ("score", "component", "component_id", "text_hash", "links", "dk", "s", "n", "epochs", "budget", "row", "key"):
        odd = odd.withColumn(name, F.lit("clash"))
    for name, stage in corpus_pipeline.STAGES[1:]:
        got = stage(spark, odd, sf)
        kept = {r["doc_id"] for r in got.collect()}
        assert stage(spark, odd.limit(0), sf).count() == 0
        if name == "temperature_mixing":  # a source gives its budget, up to less than its next document
            assert kept <= {None, 7, 8, 9} and kept and got.columns == [*odd.columns, "epoch", "mix_key"]
        else:
            assert kept == {None, 7, 8, 9} and got.columns == odd.columns, name
    first = corpus_pipeline.STAGES[0][1]
    assert first(spark, odd.limit(0), sf).count() == 0 and first(spark, odd, sf).columns == odd.columns


def test_saved_tables_are_forgotten(spark):
    from caregraph.llm import common

    kept = common.saved(spark.range(3).toDF("k"))
    assert kept.count() == 3
    common.forget(spark)
    assert common.saved(spark.range(4).toDF("k")).count() == 4
