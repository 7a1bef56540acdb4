"""What stored edges imply."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from caregraph.store import saved

PAIR = ("patient_id", "src", "dst")
BLOCK = 1 << 13
"""Events that a patient's other events are held against at once."""
TOGETHER = 100_000
"""Edges that a task sends on at once."""


def before(a_end: Column, b_begin: Column) -> Column:
    """Whether Before is in the closure, without iteration: on events with times it's their comparison."""
    return a_end < b_begin


def _then(left: DataFrame, right: DataFrame) -> DataFrame:
    """Pairs (a, c) with (a, b) on the left and (b, c) on the right."""
    far = right.select("patient_id", F.col("src").alias("dst"), F.col("dst").alias("far"))
    return left.join(far, ["patient_id", "dst"]).select("patient_id", "src", F.col("far").alias("dst"))


def _turned(df: DataFrame) -> DataFrame:
    return df.select("patient_id", F.col("dst").alias("src"), F.col("src").alias("dst"))


def _components(n: int, after: list[list[int]]) -> tuple[list[int], list[list[int]]]:
    """Strongly connected components of nodes 0 .. n - 1: each node's number, and the members; what a component leads to has a lesser number."""
    of, low, at, count = [-1] * n, [0] * n, [0] * n, 0
    members: list[list[int]] = []
    open_: list[int] = []
    seen = [0] * n
    for root in range(n):
        if seen[root]:
            continue
        walk = [root]
        while walk:
            x = walk[-1]
            if not seen[x]:
                count += 1
                seen[x] = low[x] = count
                open_.append(x)
            while at[x] < len(after[x]):
                y = after[x][at[x]]
                if not seen[y]:
                    walk.append(y)
                    break
                if of[y] < 0:
                    low[x] = min(low[x], low[y])
                at[x] += 1
            else:
                walk.pop()
                if low[x] == seen[x]:
                    own = []
                    while not own or own[-1] != x:
                        own.append(open_.pop())
                        of[own[-1]] = len(members)
                    members.append(own)
    return of, members


def reach(n: int, edges: Iterable[tuple[int, int]], targets: list[int] | None = None, block: int = BLOCK) -> Iterator[tuple[int, np.ndarray]]:
    """(node, those of ``targets`` that one or more edges lead to) for nodes 0 .. n - 1; a node may come several times, with different ones.

    Sets are bits of integers, which are handed back along the edges once for each
    ``block`` targets, so a node holds no more bits than that.
    """
    after: list[list[int]] = [[] for _ in range(n)]
    for x, y in edges:
        after[x].append(y)
    of, members = _components(n, after)
    targets = list(range(n)) if targets is None else targets
    for lo in range(0, len(targets), block):
        some = np.array(targets[lo : lo + block])
        bit = dict(zip(some.tolist(), range(len(some)), strict=True))
        held: list[int] = []  # of each component: what it holds or leads to
        for k, own in enumerate(members):
            inside = leads = 0
            for x in own:
                if x in bit:
                    inside |= 1 << bit[x]
                for y in after[x]:
                    leads |= inside if of[y] == k else held[of[y]]
            if len(own) > 1 or own[0] in after[own[0]]:
                leads |= inside
            held.append(leads | inside)
            if leads:
                found = some[np.flatnonzero(np.unpackbits(np.frombuffer(leads.to_bytes(len(some) // 8 + 1, "little"), np.uint8), bitorder="little"))]
                yield from ((x, found) for x in own)


def _by_patient(rows: DataFrame, names: tuple[str, ...], work: Callable[[int, np.ndarray, np.ndarray, np.ndarray], Iterator[tuple[np.ndarray, np.ndarray, int]]]) -> DataFrame:
    """(patient_id, src, dst, kind): what ``work`` makes of each patient's ``rows`` (patient_id, src, dst, kind), kind being a place in ``names``.

    One shuffle brings a patient's rows together; what comes out is as large as it is, but goes on as
    a stream. ``work`` gets the number of different ids, and ends and kinds of the rows, ids being numbers in their order as text.
    """
    key = rows.schema["patient_id"].dataType

    def one(patient: pa.Scalar, src: pa.Array, dst: pa.Array, kind: pa.Array) -> Iterator[pa.RecordBatch]:
        ids = pc.unique(pa.concat_arrays([src, dst]).drop_null()).sort()
        place = lambda x: pc.index_in(x, ids).fill_null(-1).to_numpy(zero_copy_only=False)
        held: list[tuple[np.ndarray, np.ndarray, int]] = []
        size = 0

        def batch() -> pa.RecordBatch:
            s, d = (ids.take(pa.array(np.concatenate([h[k] for h in held]))) for k in (0, 1))
            kinds = np.repeat([h[2] for h in held], [len(h[0]) for h in held])
            return pa.RecordBatch.from_arrays([pa.repeat(patient, len(s)), s, d, pa.array(names).take(pa.array(kinds))], names=["patient_id", "src", "dst", "kind"])

        for found in work(len(ids), place(src), place(dst), kind.to_numpy(zero_copy_only=False)):
            held.append(found)
            size += len(found[0])
            if size > TOGETHER:
                yield batch()
                held, size = [], 0
        if size:
            yield batch()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[pa.RecordBatch] = []

        def whole(end: bool) -> Iterator[pa.RecordBatch]:
            """Of all patients that are complete; the last one's rows stay."""
            t = pa.Table.from_batches(parts).combine_chunks()
            who, src, dst, kind = (t[c].combine_chunks() if t[c].num_chunks != 1 else t[c].chunk(0) for c in ("patient_id", "src", "dst", "kind"))
            code = pc.dictionary_encode(who).indices.to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero(code[1:] != code[:-1]) + 1).tolist(), len(code)]
            parts.clear()
            if not end:
                parts.extend(t.slice(cuts[-2]).to_batches())
                cuts.pop()
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                yield from one(who[lo], src.slice(lo, hi - lo), dst.slice(lo, hi - lo), kind.slice(lo, hi - lo))

        for b in batches:
            if b.num_rows:
                more = not parts or parts[0]["patient_id"][0] != b["patient_id"][-1]
                parts.append(b)
                if more:
                    yield from joined(whole(False))
        if parts:
            yield from joined(whole(True))

    def joined(found: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Small results as one."""
        held: list[pa.RecordBatch] = []
        for b in found:
            held.append(b)
            if sum(x.num_rows for x in held[-64:]) > TOGETHER or len(held) > 1024:
                yield from pa.Table.from_batches(held).combine_chunks().to_batches()
                held = []
        if held:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()

    dealt = rows.where("patient_id is not null").select("patient_id", "src", "dst", F.col("kind").cast("int").alias("kind")).repartition("patient_id").sortWithinPartitions("patient_id")
    return dealt.mapInArrow(run, f"patient_id {key.simpleString()}, src string, dst string, kind string")


def _closed(n: int, src: np.ndarray, dst: np.ndarray, targets: list[int] | None = None) -> Iterator[tuple[int, np.ndarray]]:
    return reach(n, set(zip(src.tolist(), dst.tolist(), strict=True)), targets)


def transitive(pairs: DataFrame) -> DataFrame:
    """(patient_id, src, dst): the transitive closure of pairs of one patient's events, cycles among them."""

    def work(n: int, src: np.ndarray, dst: np.ndarray, kind: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
        for x, found in _closed(n, src, dst):
            yield np.full(len(found), x), found, 0

    return _by_patient(pairs.select(*PAIR, F.lit(0).alias("kind")), ("",), work).select(*PAIR)


def closure(rel: DataFrame, among: DataFrame | None = None) -> DataFrame:
    """(patient_id, src, dst, origin): the transitive closure of Before, for edges that come without times.

    Paths go through all events; with ``among`` (patient_id, event_id) only pairs whose ends are both in it come out.
    """
    rows = rel.where("relation = 'Before'").select(*PAIR, F.lit(0).alias("kind"))
    chosen = among is not None
    if chosen:
        rows = rows.unionByName(among.select("patient_id", F.col("event_id").alias("src"), F.lit(None).cast("string").alias("dst"), F.lit(1).alias("kind")))

    def work(n: int, src: np.ndarray, dst: np.ndarray, kind: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
        only = sorted(set(src[kind == 1].tolist())) if chosen else None
        src, dst = src[kind == 0], dst[kind == 0]
        order = np.lexsort((dst, src))
        known = np.split(dst[order], np.flatnonzero(np.diff(src[order])) + 1)
        asserted = dict(zip(np.unique(src).tolist(), known, strict=True)) if len(src) else {}
        starts = None if only is None else set(only)
        for x, found in _closed(n, src, dst, only):
            if starts is not None and x not in starts:
                continue
            old = np.isin(found, asserted.get(x, dst[:0]))
            for k, some in ((0, found[old]), (1, found[~old])):
                if len(some):
                    yield np.full(len(some), x), some, k

    return _by_patient(rows, ("asserted", "inferred"), work).withColumnRenamed("kind", "origin")


def derived(rel: DataFrame) -> DataFrame:
    """(patient_id, src, dst, relation, rule): edges that one application of the other rules gives.

    Concurrent is symmetric, and its ends stand for each other; what is during
    something is before all that this is before, and after all that it is after.
    All joins are of one patient's edges, so stored relations aren't shuffled.
    """
    ends = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    same = rel.where("relation = 'Concurrent'").select("patient_id", F.inline(ends)).distinct()
    b = rel.where("relation = 'Before'").select(*PAIR)
    d = rel.where("relation = 'During'").select(*PAIR)
    found = [
        ("Concurrent", "symmetric", same),
        ("Before", "substitute", _then(b, same)),
        ("Before", "inside_before", _then(d, b)),
        ("Before", "before_inside", _then(b, _turned(d))),
    ]
    return reduce(DataFrame.unionByName, [saved(df.select(*PAIR).distinct()).select("*", F.lit(r).alias("relation"), F.lit(rule).alias("rule")) for r, rule, df in found])


def fixpoint(rel: DataFrame) -> DataFrame:
    """(patient_id, src, dst, relation): all that the stored edges imply, by all rules until no more come.

    Concurrent is an equivalence: it is closed first, and each group is one node,
    so that the other rules work on groups; at the end every member has what its group has. The rules:
    Before and During are transitive; what is inside another, or what another overlaps
    into, is before what that is before, and after what that is after. Concurrent comes once a pair, Before with its inverse After.

    So a is before c iff a path leads from a to c that has Before edges, with steps into
    what surrounds or is overlapped ahead of one, and out of it behind one. Two states a node tell which is allowed,
    and paths of such states are a closure again.
    """
    names = ("Before", "After", "Concurrent", "During", "Overlap")
    code = F.array_position(F.array(*map(F.lit, names)), F.col("relation")) - 1
    # After is the inverse of stored Before edges and comes from them.
    rows = rel.where(F.col("relation").isin("Before", "Concurrent", "During", "Overlap")).select(*PAIR, code.alias("kind"))

    def work(n: int, src: np.ndarray, dst: np.ndarray, kind: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
        c = kind == 2
        both = [*zip(src[c].tolist(), dst[c].tolist(), strict=True)]
        after: list[list[int]] = [[] for _ in range(n)]
        for x, y in both:
            after[x].append(y)
            after[y].append(x)
        group, members = _components(n, after)
        who = [np.array(sorted(m)) for m in members]
        one = np.array(group, np.int64)

        def edges(k: int) -> list[tuple[int, int]]:
            return sorted(set(zip(one[src[kind == k]].tolist(), one[dst[kind == k]].tolist(), strict=True)))

        def expanded(x: int, found: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            ends = np.concatenate([who[y] for y in found.tolist()])
            return np.repeat(who[x], len(ends)), np.tile(ends, len(who[x]))

        for m in who:
            for k in range(len(m) - 1):
                yield np.full(len(m) - 1 - k, m[k]), m[k + 1 :], 2
        size = len(members)
        during, over = edges(3), edges(4)
        for x, y in over:
            yield *expanded(x, np.array([y])), 4
        for x, found in reach(size, during):
            yield *expanded(x, found), 3
        # State x: ahead of a Before edge; state x + size: behind one.
        ahead = [*during, *((y, x) for x, y in over)]
        behind = [(y, x) for x, y in (*during, *over)]
        steps = [(x + k * size, y + size) for x, y in edges(0) for k in (0, 1)]
        steps += [(x + k * size, y) for x, y in ahead for k in (0, 1)] + [(x + size, y + size) for x, y in behind]
        for x, found in reach(2 * size, steps, [*range(size, 2 * size)]):
            if x < size:
                a, b = expanded(x, found - size)
                yield a, b, 0
                yield b, a, 1

    return _by_patient(rows, names, work).withColumnRenamed("kind", "relation")
