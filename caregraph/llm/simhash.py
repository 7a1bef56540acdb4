"""SimHash near-duplicates by a byte-position inverted index with count filtering.

Fingerprints are cut into positional bytes. A pair within the allowed number of
differing bits must share a guaranteed number of positional bytes; the index is
keyed by small groups of positions, chosen so that any such set of shared
positions holds a whole group. Pairs that meet under a key are tallied (how many
positional bytes agree), kept from the guaranteed minimum on, and verified.

Groups of copies don't become all their pairs. Equal fingerprints are one node.
Under each key, nodes are first linked to their neighbour and to the key's first
node; after that, only pairs whose ends are in different components are looked
at, and of these only those with an end outside the key's largest component. No
link between components is lost: any two nodes that could join components share a key.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from itertools import combinations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from caregraph.llm.common import components, maybe_in, saved

SEED = 42
BITS_APART = 4
MANY = 1 << 29
"""From so many documents on, keys of three bytes would meet by chance too often, and 70 keys of four bytes take the place of 20."""
LANES = 12
"""64-bit lanes of a wide fingerprint."""
CROWD = 100_000
"""Nodes under one key that one task puts in order."""
KEYS = 2 * LANES
"""Index keys of a wide fingerprint: as many as its min-wise hashes."""


def position_groups(positions: int, shared: int, size: int = 3) -> list[tuple[int, ...]]:
    """Groups of ``size`` positions such that any ``shared`` of them hold a whole group.

    For four shared positions the triples of the known optimal design: three
    classes in a ring; all triples inside a class, and those with two positions
    in a class and one in the next. More shared positions need no more triples.
    Larger groups are all there are of that size.
    """
    if shared < 4 or size > 3:
        return list(combinations(range(positions), max(min(shared, size), 1)))
    of = [p % 3 for p in range(positions)]
    held = []
    for t in combinations(range(positions), 3):
        c = sorted(of[p] for p in t)
        two = next((x for x in c if c.count(x) == 2), None)
        if len(set(c)) == 1 or two is not None and (two + 1) % 3 in c:
            held.append(t)
    return held


def shingles(text: str | None, size: int) -> list[bytes]:
    """Space-joined word shingles, A-Z lower-cased; a shorter text's whole sequence; none without words."""
    w = (text or "").encode().lower().split()
    if not w:
        return []
    if len(w) <= size:
        return [b" ".join(w)]
    return [b" ".join(t) for t in zip(*(w[k:] for k in range(size)), strict=False)]


def majority(hashes: np.ndarray) -> np.ndarray:
    """Bytes of the bits that are set in over half of the rows of ``hashes`` (rows of bytes)."""
    n, total = len(hashes), np.zeros(hashes.shape[1] * 8, np.int64)
    for at in range(0, n, 4096):  # bounds memory for long texts
        total += np.unpackbits(hashes[at : at + 4096], axis=1).sum(axis=0, dtype=np.int32)
    return np.packbits(total * 2 > n)


def fingerprint(text: str | None, size: int) -> int:
    """64 bits, signed; zero for a text without words."""
    s = shingles(text, size)
    if not s:
        return 0
    raw = np.frombuffer(b"".join([xxhash.xxh64_digest(x, SEED) for x in s]), np.uint8).reshape(-1, 8)
    return int(majority(raw).view(">i8")[0])


_ODD = (np.arange(1, LANES + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def wide_fingerprint(text: str | None, size: int) -> tuple[list[int], list[int]]:
    """LANES * 64 bits, as signed 64-bit numbers, and KEYS index keys.

    Every lane mixes a shingle's hash with its own factor. A lane's least and
    greatest value over all shingles are two min-wise hashes: two texts agree in
    one with their similarity as probability. A key is a positional byte with two of them.
    Shingles count once, as the similarity is that of sets.
    """
    s = shingles(text, size)
    if not s:
        return [0] * LANES, [0]
    h = np.frombuffer(b"".join([xxhash.xxh64_digest(x, SEED) for x in set(s)]), ">u8").astype(np.uint64)
    total = np.zeros(LANES * 64, np.int64)
    least, most = np.full(LANES, 2**64 - 1, np.uint64), np.zeros(LANES, np.uint64)
    for at in range(0, len(h), 2048):
        x = h[at : at + 2048, None] * _ODD
        x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(32)
        least, most = np.minimum(least, x.min(axis=0)), np.maximum(most, x.max(axis=0))
        total += np.unpackbits(x.view(np.uint8).reshape(len(x), -1), axis=1).sum(axis=0, dtype=np.int32)
    bits = np.packbits(total * 2 > len(h))
    ends = np.concatenate([least, most])
    raw = np.empty((KEYS, 3), np.uint64)
    raw[:, 0] = bits[: KEYS * 4 : 4].astype(np.uint64) + np.arange(KEYS, dtype=np.uint64) * np.uint64(256)
    raw[:, 1], raw[:, 2] = ends, np.roll(ends, 7)
    keys = [xxhash.xxh64_intdigest(r.tobytes(), SEED) for r in raw]
    return bits.view("<i8").tolist(), np.array(keys, np.uint64).view(np.int64).tolist()


def fingerprints(docs: DataFrame, size: int = 4, text: str = "text") -> Column:
    @F.pandas_udf("long")
    def run(col: pd.Series) -> pd.Series:
        return pd.Series([fingerprint(t, size) for t in col], dtype="int64")

    return run(F.col(text))


def wide_fingerprints(text: str, size: int) -> Column:
    @F.pandas_udf("fp array<long>, keys array<long>")
    def run(col: pd.Series) -> pd.DataFrame:
        both = [wide_fingerprint(t, size) for t in col]
        return pd.DataFrame({"fp": pd.Series([f for f, _ in both], dtype=object), "keys": pd.Series([k for _, k in both], dtype=object)})

    return run(F.col(text))


def equal_bytes(a: Column, b: Column) -> Column:
    """How many of the eight positional bytes of two longs agree."""
    x = a.bitwiseXOR(b)
    for k in (4, 2, 1):
        x = x.bitwiseOR(F.shiftrightunsigned(x, k))
    return F.lit(8) - F.bit_count(x.bitwiseAND(F.lit(0x0101010101010101)))


def byte_of(x: Column, k: int) -> Column:
    return F.shiftrightunsigned(x, 8 * k).bitwiseAND(F.lit(255))


def _neighbours(post: DataFrame) -> DataFrame:
    """``post`` (key, node, sig) with an array ``o`` of (node, sig): the node before it under its key, and the key's first.

    A key that more than CROWD nodes have is split into parts of about half of that
    by the node's hash; each part has its own order, and the parts' first nodes are put in order again.
    """
    many = post.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > CROWD)
    ways = F.coalesce(F.ceil(F.col("n") / (CROWD // 2)), F.lit(1)).cast("long")
    parts = post.join(many, "key", "left").select("key", "node", "sig", F.pmod(F.xxhash64("node"), ways).alias("part"), F.col("n").isNotNull().alias("split"))
    w = Window.partitionBy("key", "part").orderBy("node")
    own = F.struct("node", "sig")
    met = parts.select("key", "node", "sig", "split", F.lag(own).over(w).alias("o1"), F.first(own).over(w).alias("o2"))
    heads = met.where("split and o1 is null").select("key", "node", "sig")
    w = Window.partitionBy("key").orderBy("node")
    again = heads.select("node", "sig", F.array(F.lag(own).over(w), F.first(own).over(w)).alias("o"))
    return met.select("node", "sig", F.array("o1", "o2").alias("o")).unionByName(again)


def linked(nodes: DataFrame, near: Callable[[Column, Column], Column], whole: DataFrame | None = None, close: Callable[[Column, Column], Column] | None = None, apart: Callable[[Column, Column], Column] | None = None, verify: Callable[[DataFrame], DataFrame] | None = None, sure: int = 0) -> DataFrame:
    """(node, root) of all nodes with a link, from ``nodes`` (node, sig, keys).

    ``keys``: the array of a node's index keys. ``near`` judges two ``sig``
    inside the joins; where it only sifts, ``close`` judges two ``fp`` of
    ``whole`` (node, fp), and ``verify`` keeps those of pairs (a, b) that hold; pairs that are at most ``sure`` ``apart`` need it not.
    Then groups of near copies of one text, which link to it but not to each
    other, are likely: a second round of links goes to each key's node with most links so far.
    These first links need not be all: of pairs that aren't sure, each node's nearest is verified. What they leave
    apart, the last step looks at: there, too, the nearest pairs come first, and of the others only those are verified that still join two components.
    """

    def nearest(pairs: DataFrame) -> DataFrame:
        """Of (a, b, apart), each node's pair with the least apart."""
        ends = pairs.select("a", "b", "apart", F.explode(F.array("a", "b")).alias("n"))
        return ends.groupBy("n").agg(F.min(F.struct("apart", "a", "b")).alias("m")).select("m.a", "m.b").distinct()

    def verified(pairs: DataFrame, all_: bool = False) -> DataFrame:
        pairs = pairs.distinct()
        if whole is None:
            return pairs
        if "apart" not in pairs.columns:
            fa, fb = (whole.select(F.col("node").alias(k), F.col("fp").alias("f" + k)) for k in "ab")
            pairs = pairs.join(fa, "a").join(fb, "b").where(close(F.col("fa"), F.col("fb"))).select("a", "b", apart(F.col("fa"), F.col("fb")).alias("apart"))
        pairs = saved(pairs)
        held, rest = pairs.where(F.col("apart") <= sure).select("a", "b"), pairs.where(F.col("apart") > sure)
        if not all_:
            return held.unionByName(verify(nearest(rest)))

        def joining(edges: DataFrame, open_: DataFrame) -> DataFrame:
            """Pairs whose ends the edges found so far leave in different components."""
            comp = components(star.unionByName(edges))
            for k in "ab":
                open_ = open_.join(comp.select(F.col("node").alias(k), F.col("root").alias("c" + k)), k, "left").withColumn("c" + k, F.coalesce("c" + k, k))
            return saved(open_.where("ca <> cb").select("a", "b", "apart"))

        if rest.isEmpty():
            return held
        first = nearest(rest)
        held = saved(held.unionByName(verify(first)))
        rest = joining(held, rest.join(first, ["a", "b"], "left_anti"))
        return held if rest.isEmpty() else held.unionByName(verify(rest.select("a", "b")))

    post = nodes.select(F.explode("keys").alias("key"), "node", "sig")
    by = _neighbours(post).select("node", "sig", F.explode("o").alias("o"))
    star = by.where((F.col("o.node") != F.col("node")) & near(F.col("sig"), F.col("o.sig"))).select(F.least("o.node", "node").alias("a"), F.greatest("o.node", "node").alias("b"))
    star = saved(verified(star))
    first = components(star)
    held = nodes.join(first, "node", "left").select("node", "sig", "keys", F.coalesce("root", "node").alias("comp"))
    if whole is not None:
        degree = star.select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count("*").alias("links"))
        post = held.join(degree, "node", "left").select(F.explode("keys").alias("key"), "node", "sig", "comp", F.coalesce("links", F.lit(0)).alias("links"))
        # The best-linked node of a key, by an aggregate that runs before the shuffle.
        best = post.groupBy("key").agg(F.max(F.struct("links", (-F.col("node")).alias("turn"), "node", "sig", "comp")).alias("o"), F.count("*").alias("n")).where("n > 1").select("key", "o")
        met = post.join(best, "key")
        more = met.where((F.col("o.comp") != F.col("comp")) & near(F.col("sig"), F.col("o.sig"))).select(F.least("o.node", "node").alias("a"), F.greatest("o.node", "node").alias("b"))
        star = star.unionByName(saved(verified(more)))
        first = components(star)
        held = nodes.join(first, "node", "left").select("node", "sig", "keys", F.coalesce("root", "node").alias("comp"))
    post = saved(held.select(F.explode("keys").alias("key"), "node", "sig", "comp"))
    sizes = post.groupBy("key", "comp").agg(F.count("*").alias("n"))
    main = sizes.groupBy("key").agg(F.max(F.struct("n", "comp")).alias("m"), F.count("*").alias("comps")).where("comps > 1").select("key", F.col("m.comp").alias("main"))
    some = post.join(main, "key")
    judge = near
    if whole is not None:
        # Few keys are left open, so their rows can carry whole fingerprints and the join itself sifts.
        some = saved(some.join(whole, "node").withColumn("sig", F.struct("sig", "fp")).drop("fp"))
        judge = lambda s, t: near(s["sig"], t["sig"]) & close(s["fp"], t["fp"])
    left = some.where("comp <> main").select("key", F.col("node").alias("a"), F.col("sig").alias("s"), F.col("comp").alias("ca"))
    right = some.select("key", F.col("node").alias("b"), F.col("sig").alias("t"), F.col("comp").alias("cb"))
    pairs = left.join(right, "key").where((F.col("ca") != F.col("cb")) & judge(F.col("s"), F.col("t")))
    ends = [F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")]
    if whole is None:
        return components(star.unionByName(pairs.select(*ends).distinct()))
    rest = pairs.select(*ends, apart(F.col("s.fp"), F.col("t.fp")).alias("apart"))
    return components(star.unionByName(saved(verified(rest, all_=True))))


def near_components(docs: DataFrame, size: int = 4, apart: int = BITS_APART) -> DataFrame:
    """(doc_id, fp, component_id) of every row of ``docs`` (doc_id, text).

    Fingerprints link at ``apart`` or fewer differing bits (at most 4, which
    leaves at least four of eight positional bytes shared); exact. Null and empty
    texts have fingerprint zero and are linked like any other. component_id is
    the smallest non-null doc_id reachable; null only where all are null.
    Repeated rows are kept as they are. Other columns are left out.
    """
    if not 0 <= apart <= 4:
        raise ValueError("the index guarantees pairs of up to 4 differing bits")
    rows = saved(docs.select("doc_id", fingerprints(docs, size).alias("fp")))
    groups = position_groups(8, 8 - apart, 3 if rows.count() <= MANY else 4)
    keys = F.array(*(sum((byte_of(F.col("sig"), p) * F.lit(256**k) for k, p in enumerate(g)), F.lit(i * 256**4)) for i, g in enumerate(groups)))

    def near(a: Column, b: Column) -> Column:
        return (equal_bytes(a, b) >= 8 - apart) & (F.bit_count(a.bitwiseXOR(b)) <= apart)

    nodes = rows.select(F.col("fp").alias("node")).distinct().withColumn("sig", F.col("node"))
    roots = linked(nodes.withColumn("keys", keys), near)
    fps = rows.groupBy(F.col("fp").alias("node")).agg(F.min("doc_id").alias("least")).join(roots, "node", "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    ids = fps.groupBy("root").agg(F.min("least").alias("component_id"))
    named = fps.join(ids, "root").select("node", "component_id")
    return rows.join(named, rows["fp"] == named["node"]).select("doc_id", "fp", "component_id")


def jaccard(a: str | None, b: str | None, size: int) -> float:
    """Of the texts' sets of word shingles; two texts without words are alike."""
    x, y = set(shingles(a, size)), set(shingles(b, size))
    return len(x & y) / len(x | y) if x or y else 1.0


def similar_groups(docs: DataFrame, size: int = 5, similarity: float = 0.8) -> DataFrame:
    """(doc_id, text_hash, component): groups of texts whose sets of word shingles have a Jaccard similarity of ``similarity`` or more, one row for each row of ``docs``.

    Similar texts differ in too many of 64 bits for a guarantee, so fingerprints
    are wide (LANES * 64 bits). A pair's share of differing bits estimates the
    angle between its shingle sets and so their similarity: pairs past three standard
    deviations of the limit are out, those as far within it are in, and between
    them the texts' exact similarity decides. A positional byte alone is too common
    at this similarity, and so are two: index keys hold one byte and two min-wise
    hashes, so that texts without a common shingle never meet, however many
    there are. At similarity 0.8, 98 of 100 pairs meet under one of the KEYS
    keys, at 0.85 over 99. Null and empty texts are one group; ``text_hash`` tells them apart.
    """
    bits = LANES * 64
    share = math.acos(2 * similarity / (1 + similarity)) / math.pi
    slack = 3 * math.sqrt(bits * share * (1 - share))
    sure, most = int(bits * share - slack), int(bits * share + slack)
    least_equal = int(bits / 8 * (1 - share) ** 8 * 0.35)
    docs = docs.select("doc_id", "text", F.xxhash64(F.col("text").isNull(), "text").alias("text_hash"))
    both = docs.select("doc_id", "text_hash", wide_fingerprints("text", size).alias("w")).select("doc_id", "text_hash", "w.fp", "w.keys")
    rows = saved(both.withColumn("node", F.xxhash64("fp")))
    nodes = saved(rows.groupBy("node").agg(F.first("fp").alias("fp"), F.min("keys").alias("keys"), F.min("text_hash").alias("text_hash")))

    def apart(a: Column, b: Column) -> Column:
        return sum((F.bit_count(a[k].bitwiseXOR(b[k])) for k in range(LANES)), F.lit(0))

    def close(a: Column, b: Column) -> Column:
        shared = sum((equal_bytes(a[k], b[k]) for k in range(LANES)), F.lit(0))
        return (apart(a, b) <= most) & (shared >= least_equal)

    @F.pandas_udf("boolean")
    def alike(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([jaccard(x, y, size) >= similarity for x, y in zip(a, b, strict=True)], dtype=bool)

    def verify(pairs: DataFrame) -> DataFrame:
        """Of (a, b), those whose texts are similar; only their texts are fetched, one for each node."""
        pairs = saved(pairs)
        ends = saved(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(nodes.select("node", "text_hash"), "node"))
        texts = docs.where(maybe_in(ends.select("text_hash"), F.col("text_hash"))).groupBy("text_hash", "text").agg(F.lit(1).alias("one"))
        held = saved(ends.join(texts, "text_hash").select("node", "text"))
        ta, tb = (held.select(F.col("node").alias(k), F.col("text").alias("t" + k)) for k in "ab")
        return pairs.join(ta, "a").join(tb, "b").where(alike("ta", "tb")).select("a", "b")

    # The first lane alone rules out most chance meetings: 64 bits, allowed four standard deviations past the mean.
    loose = int(64 * share + 4 * math.sqrt(64 * share * (1 - share)))
    index = nodes.select("node", F.element_at("fp", 1).alias("sig"), "keys")
    roots = linked(index, lambda a, b: F.bit_count(a.bitwiseXOR(b)) <= loose, nodes.select("node", "fp"), close, apart, verify, sure)
    return rows.select("doc_id", "text_hash", "node").join(roots, "node", "left").select("doc_id", "text_hash", F.coalesce("root", "node").alias("component"))


def similar_components(docs: DataFrame, size: int = 5, similarity: float = 0.8) -> DataFrame:
    """(doc_id, component_id) of ``similar_groups``; component_id is the smallest non-null doc_id reachable, null only where all are null."""
    rows = saved(similar_groups(docs, size, similarity))
    ids = rows.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    return rows.join(ids, "component").select("doc_id", "component_id")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row of ``documents``, by ``near_components``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return near_components(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: the one with the smallest id, of several texts under that id the one whose hash comes first.

    A document is an id with a text: rows that share both are one, of which one
    stays; other texts under a dropped document's id are judged by themselves.
    Rows without an id stay, as does all of an empty table; null and empty texts are one group. Very long texts and other columns are nothing special.
    """
    rows = saved(similar_groups(docs.select("doc_id", "text")).where("doc_id is not null"))
    first = rows.groupBy("component").agg(F.min(F.struct("doc_id", "text_hash")).alias("first"), F.count("*").alias("n")).where("n > 1")
    late = rows.join(first, "component").where((F.col("first.doc_id") != F.col("doc_id")) | (F.col("first.text_hash") != F.col("text_hash")))
    gone = saved(late.select("doc_id", "text_hash").distinct().withColumn("row", F.xxhash64("doc_id", "text_hash")))
    # Texts of documents that the bitmap rules out aren't shuffled.
    named = docs.withColumn("__cg_h", F.xxhash64(F.col("text").isNull(), "text"))
    maybe = F.col("doc_id").isNotNull() & maybe_in(gone.select("row"), F.xxhash64("doc_id", "__cg_h"))
    less = gone.select("doc_id", F.col("text_hash").alias("__cg_h"))
    kept = named.where(~maybe).unionByName(named.where(maybe).join(less, ["doc_id", "__cg_h"], "left_anti").select(named.columns))
    again = rows.groupBy("doc_id", "text_hash").agg(F.count("*").alias("n")).where("n > 1").select("doc_id", F.col("text_hash").alias("__cg_h"))
    again = saved(again)
    if again.isEmpty():
        return kept.select(docs.columns)
    twice = kept.join(again, ["doc_id", "__cg_h"], "left_semi").select(named.columns)
    plain = [f.name for f in docs.schema if f.dataType.typeName() not in ("map", "variant")]
    one = twice.groupBy("doc_id", "__cg_h").agg(F.min_by(F.struct(*docs.columns), F.xxhash64(*plain)).alias("r")).select("r.*")
    return kept.join(again, ["doc_id", "__cg_h"], "left_anti").select(docs.columns).unionByName(one)
