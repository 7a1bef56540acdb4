"""Line dedup by a segment-partition edit join.

Two lines within t edits share one of t + 1 segments: lines are cut into t + 1
segments, which are indexed under the line's length, and each line probes the
index with those of its substrings that could be a segment of a line of its own
or a shorter length. Lines that meet are sifted by the parity of their
characters' counts (an edit changes two at most), and verified by a banded
bit-parallel edit distance. Equal lines are one; the join is over different lines.

A segment that very many lines share isn't joined as it is: what is left of two
lines without the segment they share is again within t edits, so it is cut and
looked up in the same way, until few enough lines meet or LEVELS is reached.

No row is made for a pair. Lines that meet under a key are verified there with
their texts, as far as links don't join them yet, and links that join them are
passed on; then the links of each class are counted where its lines are.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from caregraph.llm.common import components, maybe_in, saved, text_key
from caregraph.llm.rolling import Runs, codes_of, counted, mixed

EDITS = 2
FUZZY_CHARS = 24
"""Shorter lines count as the same only if they are equal."""
PARITY = (1 << 48) - 1
OWN = 1 << 60
PAIRS = 50_000
"""Lines that share a segment are joined if they make no more pairs than this; else what is left of them is cut again."""
LEVELS = 6
CHARS = 1 << 19
"""Characters that a task hashes at once (or one line, if it is longer)."""
TOGETHER = 250_000
"""Pairs that a task compares at once."""
ROWS = 200_000
"""Most rows of one key that a task holds before it passes them on to the next level."""
SMALL = 256
"""Links of a class of up to so many lines are counted in one task; those of a larger one by the segments that they share."""


def normal(line: Column) -> Column:
    """What is compared: trimmed, lower-cased."""
    return F.lower(F.trim(line))


def segments(n: int, edits: int = EDITS) -> list[tuple[int, int]]:
    """(start, length) of the edits + 1 segments of a line of n characters; the last ones are longer by one."""
    return [_segment(n, k, edits) for k in range(edits + 1)]


def _segment(n, k: int, edits: int):
    """(start, length) of segment k; n is a number or an array."""
    base, long = n // (edits + 1), n % (edits + 1)
    shorter = edits + 1 - long
    return k * base + np.maximum(0, k - shorter), base + (k >= shorter)


@cache
def windows(edits: int = EDITS) -> tuple[tuple[int, int, int], ...]:
    """(gap, segment, offset) of all substrings that a line looks up, gap being by how much the indexed line is shorter.

    Offsets are those that leave enough edits on both sides: k edits at most
    before segment k, and edits - k after it, given the lengths' difference.
    A line's own segments are those of gap and offset 0.
    """
    return tuple((gap, k, off) for gap in range(edits + 1) for k in range(edits + 1) for off in range(max(-k, gap - (edits - k)), min(k, gap + edits - k) + 1))


def place(n, window: tuple[int, int, int], edits: int = EDITS):
    """(start, length) of a window's substring in a line of n characters; out of the line where there is none."""
    gap, k, off = window
    at, size = _segment(n - gap, k, edits)
    return at + off, size


def probes(n: int, edits: int = EDITS) -> Iterator[tuple[int, int, int, int]]:
    """(indexed length, segment, start, size) of the substrings that a line of n characters looks up."""
    for w in windows(edits):
        at, size = place(n, w, edits)
        if w[0] <= n and 0 <= at <= n - size:
            yield n - w[0], w[1], int(at), int(size)


def _common(a: str, b: str) -> int:
    """Length of the common start, by bisection."""
    lo, hi = 0, min(len(a), len(b))
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid - 1
    return lo


def within(a: str, b: str, edits: int = EDITS) -> bool:
    """Whether the edit distance is at most ``edits``: common ends are cut, then a diagonal band of 2 * edits + 1 cells is held in the bits of an integer for each number of edits."""
    k = _common(a, b)
    a, b = a[k:], b[k:]
    k = _common(a[::-1], b[::-1])
    a, b = a[: len(a) - k], b[: len(b) - k]
    if abs(len(a) - len(b)) > edits:
        return False
    if not a or not b:
        return True
    width = 2 * edits + 1
    full = (1 << width) - 1
    # Bit d of row e: the diagonal d - edits is reached at this place of ``a`` with at most e edits.
    rows = [sum(1 << (edits + d) for d in range(0, e + 1)) for e in range(edits + 1)]
    for i, c in enumerate(a):
        same = 0
        for d in range(width):
            j = i + d - edits
            if 0 <= j < len(b) and b[j] == c:
                same |= 1 << d
        new: list[int] = []
        for e in range(edits + 1):
            r = rows[e] & same
            if e:
                r |= rows[e - 1] | (rows[e - 1] >> 1) | (new[e - 1] << 1)
            # Cells outside b don't exist.
            lo, hi = edits - i - 1, len(b) - i - 1 + edits
            ok = full & ((1 << (hi + 1)) - 1 if hi >= 0 else 0)
            r &= ok & ~((1 << max(lo, 0)) - 1)
            new.append(r)
        if not new[edits]:
            return False
        rows = new
    return bool(rows[edits] >> (len(b) - len(a) + edits) & 1)


class Lines:
    """Some lines' characters as one array, with sums from which any substring's hash follows."""

    def __init__(self, texts: list[str]) -> None:
        self.size = np.fromiter(map(len, texts), np.int64, len(texts))
        self.start = np.cumsum(self.size) - self.size
        self.codes = codes_of("".join(texts))
        self.runs = Runs(self.codes)

    def signs(self) -> np.ndarray:
        """48 bits of character count parities for each line."""
        n = len(self.size)
        at = np.repeat(np.arange(n), self.size) * 48 + (self.codes % 47).astype(np.int64)
        odd = (np.bincount(at, minlength=n * 48) & 1).astype(np.uint8).reshape(n, 48)
        out = np.zeros((n, 8), np.uint8)
        out[:, :6] = np.packbits(odd, axis=1)
        return out.view("<i8")[:, 0]

    def keys(self, before: np.ndarray, gaps: np.ndarray, edits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(line, window, key) of what the lines look up, each after its own key ``before``; ``gaps``: the only gap a line looks up, -1 for all."""
        which, window, keys = [], [], []
        for p, w in enumerate(windows(edits)):
            at, size = place(self.size, w, edits)
            ok = np.flatnonzero((self.size >= w[0]) & (at >= 0) & (at + size <= self.size) & ((gaps < 0) | (gaps == w[0])))
            tag = mixed(((self.size[ok] - w[0]) * 64 + w[1]).astype(np.uint64) ^ before[ok])
            which.append(ok)
            window.append(np.full(len(ok), p, np.int64))
            keys.append(mixed(self.runs.of(self.start[ok] + at[ok], size[ok]) ^ tag))
        return np.concatenate(which), np.concatenate(window), np.concatenate(keys).view(np.int64)


def _sign(line: str) -> int:
    return int(Lines([line]).signs()[0])


def _groups(texts: list[str]) -> Iterator[tuple[int, int]]:
    """Ranges of lines of at most CHARS characters together."""
    at = n = 0
    for k, t in enumerate(texts):
        if n and n + len(t) > CHARS:
            yield at, k
            at, n = k, 0
        n += len(t)
    if at < len(texts):
        yield at, len(texts)


def _own(window: np.ndarray, edits: int) -> np.ndarray:
    own = np.array([w[0] == w[2] == 0 for w in windows(edits)])
    return own[window]


def _gap(window: np.ndarray, edits: int) -> np.ndarray:
    return np.array([w[0] for w in windows(edits)], np.int64)[window]


def _postings(lines: DataFrame, edits: int) -> DataFrame:
    """(key, id, sig) of all that ``lines`` (id, line) look up, index entries among them.

    ``sig``: 48 bits of parities, the gap from bit 48, the window from bit 50, and OWN on
    index entries. A task gives a line that it meets again only once, so frequent lines arrive once a task.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        met: set[int] = set()
        for batch in batches:
            if len(met) > 500_000:
                met.clear()
            fresh = {i: line for i, line in zip(batch["id"].tolist(), batch["line"], strict=True) if i not in met}
            met |= fresh.keys()
            ids, texts = np.array(list(fresh), np.int64), list(fresh.values())
            for lo, hi in _groups(texts):
                held = Lines(texts[lo:hi])
                n = hi - lo
                which, window, keys = held.keys(np.zeros(n, np.uint64), np.full(n, -1), edits)
                sig = held.signs()[which] | _gap(window, edits) << 48 | window << 50 | np.where(_own(window, edits), OWN, 0)
                yield pd.DataFrame({"key": keys, "id": ids[lo:hi][which], "sig": sig})

    return lines.select("id", "line").mapInPandas(run, "key long, id long, sig long")


def _deeper(hot: DataFrame, lines: DataFrame, edits: int) -> DataFrame:
    """(key, id, sig, path) of the next level: what is left of the lines of ``hot`` (id, key, sig, path) without the windows of their paths, cut and looked up."""
    by = hot.groupBy("id").agg(F.collect_set(F.struct("key", "sig", "path")).alias("held"))
    texts = lines.where(maybe_in(hot.select("id").distinct(), F.col("id"))).groupBy("id", "line").agg(F.lit(1).alias("one")).select("id", "line")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        plan = windows(edits)
        for batch in batches:
            ids, before, sigs, paths, rest = [], [], [], [], []

            def rows() -> Iterator[pd.DataFrame]:
                id_, key, sig, path = (np.array(x, np.int64) for x in (ids, before, sigs, paths))
                for lo, hi in _groups(rest):
                    s = sig[lo:hi]
                    which, window, keys = Lines(rest[lo:hi]).keys(key[lo:hi].view(np.uint64), s >> 48 & 3, edits)
                    own = (s[which] >= OWN) & _own(window, edits)
                    yield pd.DataFrame({"key": keys, "id": id_[lo:hi][which], "sig": s[which] & PARITY | _gap(window, edits) << 48 | window << 50 | np.where(own, OWN, 0), "path": path[lo:hi][which]})

            size = 0
            for i, line, held in zip(batch["id"], batch["line"], batch["held"], strict=True):
                for h in held:
                    text, path = line, h["path"] << 8 | (h["sig"] >> 50 & 255) + 1
                    for k in range(path.bit_length() // 8 * 8, -1, -8):
                        if path >> k & 255:
                            at, n = place(len(text), plan[(path >> k & 255) - 1], edits)
                            text = text[:at] + text[at + n :]
                    for out, x in zip((ids, before, sigs, paths, rest), (i, h["key"], h["sig"], path, text), strict=True):
                        out.append(x)
                    size += len(text)
                if size > CHARS:
                    yield from rows()
                    ids, before, sigs, paths, rest = [], [], [], [], []
                    size = 0
            yield from rows()

    return by.join(texts, "id").select("id", "line", "held").mapInPandas(run, "key long, id long, sig long, path long")


def _pairs(start: np.ndarray, end: np.ndarray, owns: np.ndarray, ids: np.ndarray, sig: np.ndarray, edits: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Each index entry with all rows of its key that pass the sift; ranges of rows by key, whose index entries go first."""
    own = np.repeat(start, owns) + counted(owns)
    size = np.repeat(end - start, owns)
    cuts = np.searchsorted(np.cumsum(size), np.arange(1, int(size.sum()) // TOGETHER + 1) * TOGETHER)
    for part in np.split(np.arange(len(own)), np.unique(cuts)):
        if not len(part):
            continue
        a = np.repeat(own[part], size[part])
        b = np.repeat(np.repeat(start, owns)[part], size[part]) + counted(size[part])
        i, j, s, t = ids[a], ids[b], sig[a], sig[b]
        # A probe of an equal length meets each pair from both sides, one of a lesser length only from the longer line's.
        ok = (i != j) & ((t >> 48 & 3 > 0) | (i < j)) & (np.bitwise_count((s ^ t) & PARITY) <= 2 * edits)
        if ok.any():
            yield a[ok], b[ok]


def _meet(rows: DataFrame, edits: int, last: bool) -> DataFrame:
    """(key, id, sig, path, met): rows that meet another under their key and pass the sift (``met``), and all rows under keys that more than PAIRS pairs would meet in (none if ``last``).

    Rows arrive sorted by key, so a task streams them and holds one key at a time; of a crowded key it holds ROWS rows at most before it passes them on.
    """
    deep = "path" in rows.columns

    def told(rows: np.ndarray | slice, met: bool, key: np.ndarray, ids: np.ndarray, sig: np.ndarray, path: np.ndarray) -> pd.DataFrame:
        return pd.DataFrame({"key": key[rows], "id": ids[rows], "sig": sig[rows], "path": path[rows], "met": met})

    def whole(*cols: np.ndarray) -> Iterator[pd.DataFrame]:
        """Rows of whole keys; most keys have one row and go first."""
        same = cols[0][1:] == cols[0][:-1]
        some = np.r_[False, same] | np.r_[same, False]
        cols = tuple(c[some[: len(c)]] for c in cols)
        if not len(cols[0]):
            return
        order = np.lexsort((cols[3], cols[1], -cols[2], cols[0]))
        cols = tuple(c[order] for c in cols)
        again = np.r_[False, np.logical_and.reduce([c[1:] == c[:-1] for c in cols])]
        key, ids, sig, path = (c[~again] for c in cols)
        start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        end = np.r_[start[1:], len(key)]
        owns = np.add.reduceat((sig >= OWN).astype(np.int64), start)
        some = (owns > 0) & (end - start > 1)
        start, end, owns = start[some], end[some], owns[some]
        crowded = (owns * (end - start) > PAIRS) & (not last)
        met = np.zeros(len(key), bool)
        for a, b in _pairs(start[~crowded], end[~crowded], owns[~crowded], ids, sig, edits):
            met[a] = met[b] = True
        yield told(met, True, key, ids, sig, path)
        for lo, hi in zip(start[crowded], end[crowded], strict=True):
            yield told(slice(lo, hi), False, key, ids, sig, path)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[np.ndarray] | None = None
        streaming = None
        for batch in batches:
            cols = [batch[c].to_numpy(np.int64) for c in ("key", "id", "sig")]
            cols.append(batch["path"].to_numpy(np.int64) if deep else np.zeros(len(batch), np.int64))
            if streaming is not None and len(batch):
                n = int(np.searchsorted(cols[0] != streaming, True))
                yield told(slice(n), False, *cols)
                cols = [c[n:] for c in cols]
                streaming = None if len(cols[0]) else streaming
            if held is not None:
                cols = [np.concatenate(x) for x in zip(held, cols, strict=True)]
            if not len(cols[0]):
                continue
            at = int(np.searchsorted(cols[0] == cols[0][-1], True)) if cols[0][0] != cols[0][-1] else 0
            yield from whole(*(c[:at] for c in cols))
            held = [c[at:] for c in cols]
            if len(held[0]) > ROWS and not last:
                yield told(slice(None), False, *held)
                streaming, held = int(held[0][0]), None
        if held is not None:
            yield from whole(*held)

    sorted_rows = rows.repartition("key").sortWithinPartitions("key")
    return sorted_rows.mapInPandas(run, "key long, id long, sig long, path long, met boolean")


def _by_key(batches: Iterator[pd.DataFrame]) -> Iterator[tuple[np.ndarray, pd.DataFrame]]:
    """(starts, rows) of whole keys, from rows sorted by key; a task holds one key and a batch."""
    held = None
    for batch in batches:
        rows = batch if held is None else pd.concat([held, batch], ignore_index=True)
        if not len(rows):
            continue
        key = rows["key"].to_numpy()
        at = int(np.searchsorted(key == key[-1], True)) if key[0] != key[-1] else 0
        if at:
            yield np.flatnonzero(np.r_[True, key[1:at] != key[: at - 1]]), rows[:at]
        held = rows[at:]
    if held is not None:
        yield np.zeros(1, np.int64), held


def _tied(met: DataFrame, texts: DataFrame, edits: int) -> DataFrame:
    """(a, b): links of lines that meet under a key, as many as join them; a pair that others join already isn't verified."""

    def joined(ids: np.ndarray, sig: np.ndarray, texts: list[str]) -> Iterator[tuple[int, int]]:
        _, of = np.unique(ids, return_inverse=True)
        root = of.copy()
        for o in np.flatnonzero(sig >= OWN):
            ok = ((sig >> 48 & 3 > 0) | (ids[o] < ids)) & (np.bitwise_count((sig ^ sig[o]) & PARITY) <= 2 * edits)
            for k in np.flatnonzero(ok & (root != root[o])):
                if root[k] != root[o] and within(texts[o], texts[k], edits):
                    root[root == root[k]] = root[o]
                    yield int(ids[o]), int(ids[k])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for starts, rows in _by_key(batches):
            ids, sig, texts = rows["id"].to_numpy(np.int64), rows["sig"].to_numpy(np.int64), rows["line"].tolist()
            found = [x for lo, hi in zip(starts, [*starts[1:], len(ids)], strict=True) for x in joined(ids[lo:hi], sig[lo:hi], texts[lo:hi])]
            yield pd.DataFrame(found, columns=["a", "b"], dtype=np.int64)

    rows = met.join(texts.select("id", "line"), "id").select("key", "id", "sig", "line")
    return rows.repartition("key").sortWithinPartitions("key").mapInPandas(run, "a long, b long")


def _members(lines: DataFrame, edits: int) -> DataFrame:
    """(id, key, line, root, n) of all lines with a link: of ``lines`` (key, line), which may repeat; ``n``: how many its class has.

    Texts aren't shuffled to find what meets: its rows are hashes, and only lines
    that met another are fetched, once.
    """
    if not 0 <= edits <= 3:
        raise ValueError("up to 3 edits")
    lines = lines.withColumn("id", F.xxhash64("line"))
    rows, met = _postings(lines, edits), None
    for level in range(LEVELS):
        out = saved(_meet(rows, edits, level == LEVELS - 1))
        found = out.where("met").select("key", "id", "sig")
        met = found if met is None else met.unionByName(found)
        hot = out.where("not met").select("id", "key", "sig", "path")
        if hot.isEmpty():
            break
        # Rows that were passed on unseen may have no index entry among them.
        rows = _deeper(hot.join(hot.where(F.col("sig") >= OWN).select("key").distinct(), "key", "left_semi"), lines, edits)
    texts = saved(lines.where(maybe_in(met.select("id").distinct(), F.col("id"))).groupBy("id", "key", "line").agg(F.lit(1).alias("one")).drop("one"))
    own = saved(components(saved(_tied(met, texts, edits))))
    sized = own.join(own.groupBy("root").agg(F.count("*").alias("n")), "root").select(F.col("node").alias("id"), "root", "n")
    return saved(texts.join(sized, "id"))


def _links(members: DataFrame, edits: int, listed: bool) -> DataFrame:
    """(i, j) of all links of ``members`` if they are ``listed``, else (id, links) of lines that have some, in several rows.

    A small class is compared as a whole. Of a large one, lines meet by their
    segments, none of which is cut again; a pair counts under the first that it shares.
    """
    plan = windows(edits)

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for lo, hi in _groups(batch["line"].tolist()):
                part = batch[lo:hi]
                held, ids, root = Lines(part["line"].tolist()), part["id"].to_numpy(np.int64), part["root"].to_numpy(np.int64)
                sign, large = held.signs(), part["n"].to_numpy() > SMALL
                few = np.flatnonzero(~large)
                # A class as one key: each line is an index entry, with no window.
                yield pd.DataFrame({"key": root[few], "id": ids[few], "sig": sign[few] | OWN, "line": part["line"].to_numpy()[few]})
                which, window, keys = held.keys(mixed(root.view(np.uint64)), np.full(len(ids), -1), edits)
                some = large[which]
                which, window, keys = which[some], window[some], keys[some]
                sig = sign[which] | _gap(window, edits) << 48 | (window + 1) << 50 | np.where(_own(window, edits), OWN, 0)
                yield pd.DataFrame({"key": keys, "id": ids[which], "sig": sig, "line": part["line"].to_numpy()[which]})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for starts, rows in _by_key(batches):
            order = np.lexsort((rows["sig"].to_numpy() < OWN, rows["key"].to_numpy()))
            ids, sig, texts = rows["id"].to_numpy(np.int64)[order], rows["sig"].to_numpy(np.int64)[order], rows["line"].to_numpy()[order].tolist()
            ends = np.r_[starts[1:], len(ids)]
            held, window = Lines(texts), (sig >> 50 & 255) - 1
            n = np.zeros(len(ids), np.int64)
            for a, b in _pairs(starts, ends, np.add.reduceat((sig >= OWN).astype(np.int64), starts), ids, sig, edits):
                far = np.abs(held.size[a] - held.size[b]) > edits
                for p, w in enumerate(plan):
                    later = np.flatnonzero(~far & (window[b] > p) & (sig[b] >> 48 & 3 == w[0]))
                    x, y = a[later], b[later]
                    at, size = place(held.size[y], w, edits)
                    own, _ = _segment(held.size[x], w[1], edits)
                    there = (at >= 0) & (at + size <= held.size[y])
                    x, y, at, size, own = x[there], y[there], at[there], size[there], own[there]
                    far[later[there]] = held.runs.of(held.start[x] + own, size) == held.runs.of(held.start[y] + at, size)
                a, b = a[~far], b[~far]
                near = np.fromiter((within(texts[x], texts[y], edits) for x, y in zip(a.tolist(), b.tolist(), strict=True)), bool, len(a))
                if listed:
                    yield pd.DataFrame({"i": ids[a[near]], "j": ids[b[near]]})
                else:
                    n += np.bincount(a[near], minlength=len(n)) + np.bincount(b[near], minlength=len(n))
            if not listed:
                yield pd.DataFrame({"id": ids[n > 0], "links": n[n > 0]})

    rows = members.select("id", "root", "n", "line").mapInPandas(cut, "key long, id long, sig long, line string")
    return rows.repartition("key").sortWithinPartitions("key").mapInPandas(run, "i long, j long" if listed else "id long, links long")


def edit_links(lines: DataFrame, edits: int = EDITS) -> DataFrame:
    """(a, b): keys of different lines within ``edits`` edits (3 at most), each pair once, from ``lines`` (key, line), which may repeat; a line has one key. As many rows as there are links: ``edit_classes`` makes none for a pair."""
    members = _members(lines, edits)
    links = _links(members, edits, True)
    return links.join(members.select(F.col("id").alias("i"), F.col("key").alias("a")), "i").join(members.select(F.col("id").alias("j"), F.col("key").alias("b")), "j").select("a", "b")


def edit_classes(lines: DataFrame, edits: int = EDITS) -> DataFrame:
    """(key, root, links) of every line that has one within ``edits`` edits (3 at most), from ``lines`` (key, line), which may repeat; lines that links join, through others too, share ``root``, and ``links`` is how many different lines this one links to."""
    members = _members(lines, edits)
    # Of two lines each has one link.
    more = _links(members.where("n > 2"), edits, False).groupBy("id").agg(F.sum("links").alias("links"))
    return members.join(more, "id", "left").select("key", "root", F.coalesce("links", F.lit(1)).alias("links"))


def doc_key(docs: DataFrame) -> Column:
    """A document: its id and text. Rows that share both are one."""
    return text_key(docs["doc_id"], F.coalesce(docs["text"], F.lit("")))


def occurrences(docs: DataFrame) -> DataFrame:
    """(dk, doc_id, pos, norm, key, place) of every line that isn't blank; ``place`` orders them by doc_id and position, null without an id."""
    base = docs.select("doc_id", doc_key(docs).alias("dk"), F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("pos", "line"))
    named = base.select("dk", "doc_id", "pos", normal(F.col("line")).alias("norm")).where("norm <> ''")
    place = F.col("doc_id").cast("decimal(20,0)") * F.lit(2**31).cast("decimal(11,0)") + F.col("pos")
    return named.withColumn("key", text_key(F.col("norm"))).withColumn("place", place.cast("decimal(38,0)"))


def classes(docs: DataFrame, places: DataFrame, edits: int = EDITS) -> DataFrame:
    """(key, place, links) of every line whose class occurs more than once.

    A class is what links join, equal lines counting as one; ``place``: of its
    first occurrence; ``links``: how many different lines this line links to.
    ``places`` are the occurrences of ``docs`` without texts.
    """
    lines = places.groupBy("key").agg(F.count("*").alias("n"), F.min("place").alias("place"))
    texts = occurrences(docs).where(F.length("norm") >= FUZZY_CHARS).select("key", F.col("norm").alias("line"))
    tied = edit_classes(texts, edits).withColumn("root", F.struct(F.col("root").alias("h1"), F.lit(0).cast("long").alias("h2")))
    held = saved(lines.join(tied, "key", "left").where("n > 1 or root is not null").select("key", "place", F.coalesce("root", "key").alias("root"), F.coalesce("links", F.lit(0)).alias("links")))
    least = held.groupBy("root").agg(F.min("place").alias("first"))
    return held.join(least, "root").select("key", F.col("first").alias("place"), "links")


def decisions(docs: DataFrame, edits: int = EDITS) -> DataFrame:
    """(dk, repeats, dropped): for each document with repeated lines, (pos, class_doc, class_line, links) of those, and the positions of those that aren't their class's first."""
    # Where lines stand, without their texts, is written once and read by both steps.
    places = saved(occurrences(docs).select("dk", "pos", "key", "place"))
    which = saved(classes(docs, places, edits)).select("key", F.col("place").alias("first"), "links")
    occ = places.join(which, "key")
    late = F.coalesce(F.col("first") != F.col("place"), F.col("first").isNotNull())
    # place = doc_id * 2**31 + pos, undone.
    doc = F.floor(F.col("first") / F.lit(2**31).cast("decimal(11,0)")).cast("long")
    line = (F.col("first") - doc.cast("decimal(20,0)") * F.lit(2**31).cast("decimal(11,0)")).cast("int")
    own = F.struct("pos", doc.alias("class_doc"), line.alias("class_line"), F.col("links").cast("long").alias("links"))
    by = occ.select("dk", own.alias("own"), F.when(late, F.col("pos")).alias("gone"))
    return by.groupBy("dk").agg(F.array_sort(F.collect_set("own")).alias("repeats"), F.array_sort(F.collect_set("gone")).alias("dropped"))


def dedup(docs: DataFrame, edits: int = EDITS) -> DataFrame:
    """``docs`` with every line left out that repeats an earlier one, equal or within ``edits`` edits (through others too).

    Earlier is by doc_id, then by position; of documents without an id, only
    lines that others with an id have go. Blank lines stay, as do documents that
    lose all lines (empty text) and null texts. Repeated rows get the same
    decision. n_chars, if there, is set anew; other columns stay.
    """
    gone = decisions(docs, edits).where(F.size("dropped") > 0).select(F.col("dk").alias("__cg_dk"), F.col("dropped").alias("__cg_gone"))
    both = docs.withColumn("__cg_dk", doc_key(docs)).join(gone, "__cg_dk", "left")
    held = F.filter(F.split("text", "\n"), lambda x, i: ~F.array_contains("__cg_gone", i))
    out = both.withColumn("text", F.when(F.col("__cg_gone").isNull(), F.col("text")).otherwise(F.array_join(held, "\n"))).drop("__cg_dk", "__cg_gone")
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, n_lines, dropped, repeats) of every row of ``documents``: positions of lines that go, and of all that repeat, with their class's first place and number of links. Null and empty texts have one blank line, which never repeats."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    own = docs.select("doc_id", doc_key(docs).alias("dk"), F.size(F.split(F.coalesce("text", F.lit("")), "\n")).cast("long").alias("n_lines"))
    none = F.expr("array()")
    out = own.join(decisions(docs), "dk", "left")
    return out.select("doc_id", "n_lines", F.coalesce("dropped", none.cast("array<int>")).alias("dropped"), F.coalesce("repeats", none.cast("array<struct<pos:int,class_doc:bigint,class_line:int,links:bigint>>")).alias("repeats"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``dedup`` of all documents: none goes, repeated lines do; null texts, rows without an id, repeated rows and empty tables as there."""
    return dedup(docs)
