"""Benchmark decontamination: rare word pairs as seeds, then Smith-Waterman alignment.

A local alignment that reaches the score holds so many matches and so few errors
that a known number of its neighbouring matches have at most one error between
them (``least_pairs``). So a leak shows as that many close pairs of the item's words,
one or two words apart in both texts, within a bounded stretch of the document. One scan of the
corpus looks for them: of each item's pairs, those that are rarest in the corpus start
the join, as many as no alignment can miss; around them all pairs are
counted, and what has enough of them is aligned. Rarity only decides what is looked
at first; no passage that reaches the score is lost, however frequent its words
are. The alignment's score, as a share of the item's perfect score, decides.

The items are the query set: they reach the executors in blocks of a fixed number
of words, so what is broadcast doesn't grow with either table.
"""

from __future__ import annotations

import math
import re
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.llm.common import saved

SHORT_WORDS = 4
"""Items of fewer words leak only as a whole."""
SUPPORT = 3
"""So many of an item's starting pairs must lie together before all its pairs are counted."""
CHUNK_WORDS = 400_000
"""Words of documents that are looked at together."""
MEMO = 20_000
"""Alignments that a task remembers, so that copies of a passage cost one."""
SCORE = 0.5
BLOCK_WORDS = 2_000_000
"""Words of test items that one scan of the corpus looks for."""
MATCH, MISMATCH, GAP = 2, -1, -1
_BREAK = re.compile(r"[\W_]+")


def normal(text: str | None) -> str:
    """Lower-cased words between single blanks, with a blank at both ends."""
    return " " + _BREAK.sub(" ", (text or "").lower()).strip() + " "


def least_score(n: int, score: float) -> int:
    """The least alignment score that is at least the share ``score`` of n words' perfect one."""
    return math.ceil(score * MATCH * n - 1e-9)


def least_pairs(n: int, score: float) -> int:
    """How many neighbouring matches with at most one error between them any alignment of ``score`` has.

    m matches and e errors score 2m - e, so e <= 2m - s; at most half as many of the m - 1 neighbours have two errors or more.
    """
    return math.ceil(least_score(n, score) / 2) - 1


def widest(n: int, score: float) -> int:
    """The most words of a document that an alignment of ``score`` spans: its matches and errors."""
    return 3 * n - least_score(n, score)


def align(passage: list[str], item: list[str]) -> tuple[int, int, int]:
    """(score, start, end) of the best local alignment; positions of words in the passage.

    Cells of a row depend on their left neighbour by gaps only, so a running
    maximum settles a row at once.
    """
    ids: dict[str, int] = {}
    p = np.array([ids.setdefault(w, len(ids)) for w in passage], np.int64)
    n = len(p)
    drift = np.arange(n + 1) * -GAP
    score, start = np.zeros(n + 1, np.int64), np.arange(n + 1)
    best = (0, 0, 0)
    for w in item:
        gain = np.where(p == ids.get(w, -1), MATCH, MISMATCH)
        cell = np.zeros(n + 1, np.int64)
        diag, up = score[:-1] + gain, score[1:] + GAP
        cell[1:] = np.maximum(0, np.maximum(diag, up))
        came = np.arange(n + 1)
        came[1:] = np.where(cell[1:] == 0, np.arange(1, n + 1), np.where(diag >= up, start[:-1], start[1:]))
        lifted = np.maximum.accumulate(cell + drift)
        new = lifted - drift
        # Where a gap from the left is better, the start is that of the cell it came from.
        src = np.maximum.accumulate(np.where(cell + drift == lifted, np.arange(n + 1), 0))
        score, start = new, came[src]
        k = int(score.argmax())
        if score[k] > best[0]:
            best = (int(score[k]), int(start[k]), k)
    return best


class Items:
    """A block's items, and the pairs of their words as numbers."""

    def __init__(self, texts: list[str], score: float) -> None:
        self.texts, self.words = texts, [t.split() for t in texts]
        self.vocab: dict[str, int] = {}
        for w in self.words:
            for x in w:
                self.vocab.setdefault(x, len(self.vocab))
        self.width = np.array([widest(len(w), score) for w in self.words], np.int64)
        self.need = np.array([least_pairs(len(w), score) for w in self.words], np.int64)
        self.short: dict[int, dict[str, list[int]]] = {}
        self.free: list[int] = []  # a score so low that single words reach it
        self.starts: dict[int, list[np.ndarray]] = {}
        for k, w in enumerate(self.words):
            if len(w) < SHORT_WORDS:
                self.short.setdefault(len(w), {}).setdefault(" ".join(w), []).append(k)
            elif self.need[k] < 1:
                self.free.append(k)
            else:
                ids = np.array([self.vocab[x] for x in w], np.int64)
                self.starts[k] = [self.code(ids[:-g], ids[g:]) for g in (1, 2)]
        self.pairs = {k: np.unique(np.concatenate(c)) for k, c in self.starts.items()}
        self.known = np.unique(np.concatenate(list(self.pairs.values()))) if self.pairs else np.empty(0, np.int64)

    def code(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.where((a >= 0) & (b >= 0), a * len(self.vocab) + b, -1)

    def codes(self, ids: np.ndarray) -> list[np.ndarray]:
        """Of each word's place: its pair with the next word, and with the one after that; -1 if there is none."""
        out = []
        for g in (1, 2):
            c = np.full(len(ids), -1, np.int64)
            if len(ids) > g:
                c[:-g] = self.code(ids[:-g], ids[g:])
            out.append(c)
        return out

    def choose(self, seen: list[np.ndarray]) -> None:
        """Starting pairs: those at each item's places that are rarest in ``seen``; so many places that SUPPORT of any alignment's are among them."""
        n = np.zeros(len(self.known) + 1, np.int64)
        for c in seen:
            n += np.bincount(find(self.known, c), minlength=len(n))
        self.support = np.minimum(self.need, SUPPORT)
        keys, items = [], []
        for k, (one, two) in self.starts.items():
            freq = n[find(self.known, one)]
            freq[: len(two)] += n[find(self.known, two)]
            at = np.argsort(freq, kind="stable")[: len(one) - self.need[k] + self.support[k]]
            c = np.unique(np.concatenate([one[at], two[at[at < len(two)]]]))
            keys.append(c)
            items.append(np.full(len(c), k, np.int64))
        c, k = (np.concatenate(x) if x else np.empty(0, np.int64) for x in (keys, items))
        order = np.argsort(c, kind="stable")
        self.of = k[order]
        self.first, self.begin, self.count = np.unique(c[order], return_index=True, return_counts=True)

    def candidates(self, codes: list[np.ndarray], doc: np.ndarray) -> Iterator[tuple[int, int, int]]:
        """(item, from, to) of stretches where enough starting pairs of an item lie together; words are numbered through all documents, ``doc`` is each word's."""
        at, item = [], []
        for c in codes:
            f = find(self.first, c)
            place = np.flatnonzero(f < len(self.first))
            f = f[place]
            n = self.count[f]
            at.append(np.repeat(place, n))
            item.append(self.of[np.repeat(self.begin[f] - np.cumsum(n) + n, n) + np.arange(n.sum())])
        met = np.unique(np.concatenate(item) * len(doc) + np.concatenate(at))
        item, at = np.divmod(met, len(doc))
        for s in range(1, SUPPORT + 1):
            size = len(at) - s + 1
            if size < 1:
                break
            last = at[s - 1 :]
            ok = (self.support[item[:size]] == s) & (item[:size] == item[s - 1 :]) & (doc[at[:size]] == doc[last]) & (last - at[:size] < self.width[item[:size]])
            hit = np.flatnonzero(ok)
            yield from merged(item[hit], last[hit] - self.width[item[hit]], at[hit] + self.width[item[hit]] + 1, doc[at[hit]])

    def dense(self, k: int, codes: list[np.ndarray], lo: int, hi: int) -> list[tuple[int, int]]:
        """The parts of a stretch, by its own numbers, where as many pairs of item k lie together as an alignment needs."""
        own = self.pairs[k]
        at = np.flatnonzero(np.logical_or(*(find(own, c[lo:hi]) < len(own) for c in codes)))
        need, width = int(self.need[k]), int(self.width[k])
        if len(at) < need:
            return []
        a, z = at[: len(at) - need + 1], at[need - 1 :]
        a, z = a[z - a < width], z[z - a < width]
        return [(max(0, x), min(hi - lo, y)) for _, x, y in merged(np.zeros(len(a), np.int64), z - width, a + width + 1, np.zeros(len(a), np.int64))]


def find(known: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Places of numbers in a sorted array; its length for those that it hasn't."""
    if not len(known):
        return np.zeros(len(c), np.int64)
    at = np.searchsorted(known, c)
    return np.where(known[np.minimum(at, len(known) - 1)] == c, at, len(known))


def merged(item: np.ndarray, lo: np.ndarray, hi: np.ndarray, doc: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """Sorted stretches, those of one item and document that overlap joined."""
    held = None
    for k, a, b, d in zip(item.tolist(), lo.tolist(), hi.tolist(), doc.tolist(), strict=True):
        if held and held[0] == k and held[3] == d and a <= held[2]:
            held[1], held[2] = min(held[1], a), max(held[2], b)
            continue
        if held:
            yield held[0], held[1], held[2]
        held = [k, a, b, d]
    if held:
        yield held[0], held[1], held[2]


def leaks_in(docs: list[list[str]], items: Items) -> Iterator[tuple[int, int, int, list[str]]]:
    """(document, item, pairs, passage) of all stretches of ``docs`` (lists of words) that may reach the score."""
    sizes = np.array([len(w) for w in docs], np.int64)
    begin = np.cumsum(sizes) - sizes
    get = items.vocab.get
    ids = np.array([get(x, -1) for w in docs for x in w], np.int64)
    doc = np.repeat(np.arange(len(docs)), sizes)
    codes = items.codes(ids)
    for g in (1, 2):  # no pair spans two documents
        over = np.flatnonzero(doc[g:] != doc[:-g])
        codes[g - 1][over] = -1
    if not hasattr(items, "first"):
        items.choose(codes)
    if items.pairs and len(ids):
        for k, lo, hi in items.candidates(codes, doc):
            d = int(doc[min(max((lo + hi) // 2, 0), len(doc) - 1)])
            lo, hi = max(lo, int(begin[d])), min(hi, int(begin[d] + sizes[d]))
            for x, y in items.dense(k, codes, lo, hi):
                at = lo - int(begin[d])
                own = np.concatenate([c[lo + x : lo + y] for c in codes])
                yield d, k, len(np.intersect1d(own, items.pairs[k])), docs[d][at + x : at + y]
    for n, texts in items.short.items():
        for d, w in enumerate(docs):
            for t in {" ".join(w[j : j + n]) for j in range(len(w) - n + 1)} & texts.keys():
                for k in texts[t]:
                    yield d, k, 1, t.split()
    for k in items.free:
        for d, w in enumerate(docs):
            if not set(items.words[k]).isdisjoint(w):
                yield d, k, 1, w


def _blocks(items: DataFrame, words: int) -> Iterator[list[tuple[int, str]]]:
    """Test items (item_id, normal text) in blocks of a bounded number of words, by a streaming read; the driver holds one block at a time."""
    block, n = [], 0
    for r in items.select("item_id", "text").where("item_id is not null").toLocalIterator(prefetchPartitions=False):
        text = normal(r["text"])
        size = len(text.split())
        if size:
            if block and n + size > words:
                yield block
                block, n = [], 0
            block.append((r["item_id"], text))
            n += size
    if block:
        yield block


_PREPARED: dict[tuple[str, float], Items] = {}


def _prepared(name: str, block: list[tuple[int, str]], score: float) -> Items:
    """A block's items, prepared once in each worker process and kept until it gets another block."""
    if (name, score) not in _PREPARED:
        _PREPARED.clear()
        _PREPARED[name, score] = Items([t for _, t in block], score)
    return _PREPARED[name, score]


def _scan(docs: DataFrame, block: list[tuple[int, str]], score: float) -> DataFrame:
    """(doc_id, item_id, score, n_seeds, passage_words, aligned) of the passages that reach ``score`` for an item of the block."""
    shared = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, block))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        name, held_block = shared.value
        names = [i for i, _ in held_block]
        items = _prepared(name, held_block, score)
        memo: dict[tuple[int, str], tuple[int, int, str]] = {}

        def found(k: int, has: list[str]) -> tuple[int, int, str]:
            want, p = items.words[k], f" {' '.join(has)} "
            got = memo.get((k, p))
            if got is None:
                if items.texts[k] in p:
                    got = MATCH * len(want), len(want), " ".join(want)
                else:
                    s, lo, hi = align(has, want)
                    got = s, hi - lo, " ".join(has[lo:hi])
                if len(memo) >= MEMO:
                    memo.clear()
                memo[k, p] = got
            return got

        def chunks(batch: pd.DataFrame) -> Iterator[tuple[list, list[list[str]]]]:
            ids, held, n = [], [], 0
            for doc_id, text in zip(batch["doc_id"], batch["text"], strict=True):
                if text:
                    ids.append(doc_id)
                    held.append(normal(text).split())
                    n += len(held[-1])
                if n >= CHUNK_WORDS:
                    yield ids, held
                    ids, held, n = [], [], 0
            if held:
                yield ids, held

        for batch in batches:
            rows = []
            for ids, held in chunks(batch):
                for d, k, n, passage in leaks_in(held, items):
                    s, size, text = found(k, passage)
                    if s / (MATCH * len(items.words[k])) >= score:
                        rows.append((ids[d], names[k], s / (MATCH * len(items.words[k])), n, size, text))
            yield pd.DataFrame(rows, columns=["doc_id", "item_id", "score", "n_seeds", "passage_words", "aligned"])

    # Ids travel as text so that null stays null.
    return docs.select(F.col("doc_id").cast("string").alias("doc_id"), "text").mapInPandas(run, "doc_id string, item_id long, score double, n_seeds int, passage_words int, aligned string")


def find_leaks(docs: DataFrame, items: DataFrame, score: float = SCORE) -> DataFrame:
    """(doc_id, item_id, score, n_seeds, passage_words, aligned): the best passage of each document for each item that it leaks.

    Every alignment that reaches ``score`` is found; ``n_seeds``: different close pairs of
    the item's words in the passage. Items of fewer than SHORT_WORDS words leak as a whole.
    Null, empty and wordless texts and items leak nothing, nor do items without
    an id. Documents without an id are reported under null. Repeated rows are one. Ties between
    passages go to the longer, then the lesser text. Items may be any number.
    """
    spark = docs.sparkSession
    out = None
    for block in _blocks(items, BLOCK_WORDS):
        found = _scan(docs, block, score)
        best = found.groupBy("doc_id", "item_id").agg(F.max(F.struct("score", "passage_words", "aligned", "n_seeds")).alias("m"))
        got = best.select(F.col("doc_id").cast(docs.schema["doc_id"].dataType).alias("doc_id"), "item_id", "m.score", F.col("m.n_seeds").alias("n_seeds"), F.col("m.passage_words").alias("passage_words"), F.col("m.aligned").alias("aligned"))
        out = got if out is None else out.unionByName(got)
    if out is None:
        out = spark.createDataFrame([], "doc_id long, item_id long, score double, n_seeds int, passage_words int, aligned string").withColumn("doc_id", F.col("doc_id").cast(docs.schema["doc_id"].dataType))
    return out


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``find_leaks`` of ``benchmark`` in ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return find_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that leak no test item. Of documents without an id none is taken out; null and empty texts leak nothing, of rows that share an id all go if one leaks; an empty table gives none."""
    leaks = saved(find_leaks(docs.select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select("doc_id"))
    return docs.join(leaks, "doc_id", "left_anti")
