"""Packing of tokenised documents into sequences of a fixed length.

Only the number of items of each length matters for a good packing, and there are at most `capacity` lengths. So the
plan is made on a histogram: best fit by decreasing length, whole batches of equal bins at a time, then a local
search over underfull bins that exchanges one item for one, two for one, or moves an item, whenever the sum of
squared fills rises, until bins empty. The plan is a list of bin patterns with their numbers. Items find their
bin by their rank among the items of their length, which is counted per task and offset by prefix sums, so no
length, however common, is gathered in one place.
"""

from __future__ import annotations

import bisect
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from certgraph.llm.tokens import coder
from certgraph.plans.staging import Stages


def _piece_rows(path: str, end_id: int | None, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        c = coder(path)
        tail = b"" if end_id is None else np.array([end_id], dtype=c.type).tobytes()
        seen: Counter = Counter()
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            out: list[list] = [[] for _ in range(7)]
            for doc, raw in zip(ids, c.encode(texts), strict=True):
                t = np.frombuffer(raw + tail, dtype=c.type).astype("<u4")
                n = len(t)
                if n == 0:
                    continue
                first = n if n <= capacity else (n % capacity or capacity)
                cuts = [0, *range(first, n + 1, capacity)]
                for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                    for col, v in zip(out, (doc, k, a, b - a, zlib.crc32(t[a:b].tobytes()), part, seen[b - a]), strict=True):
                        col.append(v)
                    seen[b - a] += 1
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(out, kinds, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32", "part", "nth"])

    return run


# ------------------------------------------------------------------------------------------------ the plan


def best_fit_patterns(counts: dict[int, int], capacity: int) -> dict[tuple[int, ...], int]:
    """Best fit decreasing on a histogram; bins that are alike are handled together."""
    by_room: dict[int, dict[tuple[int, ...], int]] = {}
    rooms: list[int] = []  # rooms above 0 that have bins, ascending

    def put(pattern, room, n):
        if room not in by_room:
            by_room[room] = {}
            if room:
                bisect.insort(rooms, room)
        by_room[room][pattern] = by_room[room].get(pattern, 0) + n

    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            k = bisect.bisect_left(rooms, length)
            if k == len(rooms):
                each = capacity // length
                full, rest = divmod(left, each)
                if full:
                    put((length,) * each, capacity - each * length, full)
                if rest:
                    put((length,) * rest, capacity - rest * length, 1)
                left = 0
                continue
            room = rooms[k]
            pattern, n = next(iter(by_room[room].items()))
            fits = room // length
            take = min(n, left // fits)
            if take == 0:
                take, fits = 1, left
            if take == n:
                del by_room[room][pattern]
                if not by_room[room]:
                    del by_room[room]
                    rooms.pop(k)
            else:
                by_room[room][pattern] = n - take
            put(pattern + (length,) * fits, room - fits * length, take)
            left -= take * fits
    return _same(p for group in by_room.values() for p in group.items())


def _same(patterns) -> dict[tuple[int, ...], int]:
    out: dict[tuple[int, ...], int] = {}
    for p, n in patterns:
        if p and n:
            key = tuple(sorted(p, reverse=True))
            out[key] = out.get(key, 0) + n
    return out


def _better(a: tuple[int, ...], b: tuple[int, ...], capacity: int) -> tuple[tuple[int, ...], tuple[int, ...]] | None:
    """The exchange between two bins that raises the sum of squared fills most: `a` grows, `b` shrinks."""
    fa, fb = sum(a), sum(b)
    if fa < fb:
        a, b, fa, fb = b, a, fb, fa
    room, best, found = capacity - fa, 0, None
    for y in set(b):  # move one
        if best < y <= room:
            best, found = y, ((), (y,))
    if best < room:
        small = sorted(set(a))
        for y in set(b):  # one for one
            for x in small:
                if x >= y:
                    break
                if best < y - x <= room:
                    best, found = y - x, ((x,), (y,))
        many = Counter(a)
        for y in set(b):  # two for one
            for i, x in enumerate(small):
                if x >= y:
                    break
                for z in small[i:]:
                    if x + z >= y:
                        break
                    if (x != z or many[x] > 1) and best < y - x - z <= room:
                        best, found = y - x - z, ((x, z), (y,))
    if not found:
        return None
    ca, cb = Counter(a), Counter(b)
    ca.subtract(found[0])
    ca.update(found[1])
    cb.subtract(found[1])
    cb.update(found[0])
    return tuple(sorted(ca.elements(), reverse=True)), tuple(sorted(cb.elements(), reverse=True))


def improved_patterns(patterns: dict[tuple[int, ...], int], capacity: int) -> dict[tuple[int, ...], int]:
    """Local search over all underfull bins until no exchange is left; the number of bins never rises, and falls when one is emptied.

    Partners are looked up by the length that they give: an index holds, for each length, the underfull patterns with it by
    fill. Every exchange raises the sum of squared fills, so the search ends.
    """
    now = dict(patterns)
    holders: dict[int, list[tuple[int, tuple[int, ...]]]] = {}  # length: (fill, pattern), ascending
    todo: list[tuple[int, tuple[int, ...]]] = []  # patterns that may grow, ascending by fill

    def enter(p):
        if sum(p) < capacity:
            for y in set(p):
                bisect.insort(holders.setdefault(y, []), (sum(p), p))

    def leave(p):
        if sum(p) < capacity:
            for y in set(p):
                own = holders[y]
                own.pop(bisect.bisect_left(own, (sum(p), p)))
                if not own:
                    del holders[y]

    def partner(a):
        """The emptiest pattern that can give `a` an item for none, one or two smaller ones and leave it no more than full."""
        fill, many = sum(a), Counter(a)
        room, small = capacity - fill, sorted(many)
        gives = {0, *small} | {x + z for i, x in enumerate(small) for z in small[i:] if x != z or many[x] > 1}
        best = None
        for s in gives:
            for y in range(s + 1, s + room + 1):
                for f, b in holders.get(y, ())[:2]:  # the second one if the first is `a`, alone
                    if f <= fill and (b != a or now[a] > 1):
                        best = min(best or (f, b), (f, b))
                        break
        return best and best[1]

    for p in now:
        enter(p)
    todo = sorted((sum(p), p) for p in now if sum(p) < capacity)
    waits = set(todo)
    while todo:
        top = todo.pop()
        waits.discard(top)
        a = top[1]
        while now.get(a, 0) and (b := partner(a)) is not None:
            better = _better(a, b, capacity)
            times = now[a] // 2 if a == b else min(now[a], now[b])
            for p in (a, b):
                now[p] -= times
            for p in {a, b}:
                if not now[p]:
                    del now[p]
                    leave(p)
            for p in better:
                if not p:
                    continue
                if p not in now:
                    enter(p)
                now[p] = now.get(p, 0) + times
                if sum(p) < capacity and (sum(p), p) not in waits:
                    waits.add((sum(p), p))
                    bisect.insort(todo, (sum(p), p))
        if not todo:  # what stands may have got new partners since it was looked at
            again = [(sum(p), p) for p in now if sum(p) < capacity and partner(p) is not None]
            todo, waits = sorted(again), set(again)
    return now


def packing_plan(counts: dict[int, int], capacity: int) -> dict[tuple[int, ...], int]:
    """Patterns of bins (descending item lengths) with their numbers, for a histogram of item lengths."""
    first = best_fit_patterns(counts, capacity)
    return improved_patterns(first, capacity)


class _Slots:
    """For each length, which ranks go to which bins, and at what offset."""

    def __init__(self, plan: dict[tuple[int, ...], int], capacity: int):
        self.capacity = capacity
        lengths, sizes, firsts, offsets = [], [], [], []
        base = 0
        for pattern, n in sorted(plan.items(), reverse=True):
            at = 0
            for length in pattern:
                lengths.append(length)
                sizes.append(n)
                firsts.append(base)
                offsets.append(at)
                at += length
            base += n
        self.bins = base
        order = np.argsort(np.array(lengths, dtype=np.int64), kind="stable")
        self.length = np.array(lengths, dtype=np.int64)[order]
        size = np.array(sizes, dtype=np.int64)[order]
        self.first, self.offset = np.array(firsts, dtype=np.int64)[order], np.array(offsets, dtype=np.int64)[order]
        ends = np.cumsum(size)
        self.begin = ends - size  # in the list of all items by length and rank
        self.class_begin = np.zeros(capacity + 2, dtype=np.int64)
        for k in range(len(self.length) - 1, -1, -1):
            self.class_begin[self.length[k]] = self.begin[k]

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = self.class_begin[length] + rank
        k = np.searchsorted(self.begin, at, side="right") - 1
        return self.first[k] + at - self.begin[k], self.offset[k]


def pack_documents(docs: DataFrame, tokenizer_path: str, capacity: int = 1024, end_id: int | None = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Return doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row for each piece of a document.

    A document longer than `capacity` ids is cut into pieces of `capacity`, the first one shorter if need be; no other
    document is cut. A null text is empty and, with an end id, one id long; without one it has no piece. Null and
    repeated ids are packed row by row like any other; an empty table gives an empty result; other columns are not
    read. Sequences hold at most `capacity` ids without gaps.
    """
    spark = docs.sparkSession
    st = Stages(spark, "packing")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    items = st.keep(texts.mapInArrow(_piece_rows(tokenizer_path, end_id, capacity), "doc_id long, piece int, start long, length long, ids_crc32 long, part long, nth long"), "pieces")

    per_part = items.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = per_part.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("earlier"))
    counts = {r.length: r.n for r in items.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    slots = _Slots(packing_plan(counts, capacity), capacity)
    ranked = items.join(offsets, ["part", "length"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("earlier") + F.col("nth")).alias("rank"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seq, off = slots.place(batch.column(3).to_numpy(zero_copy_only=False), batch.column(5).to_numpy(zero_copy_only=False))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(5)), pa.array(seq, pa.int64()), pa.array(off, pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
