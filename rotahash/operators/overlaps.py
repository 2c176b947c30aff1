"""How much sets have in common, counted by blocks of sets: no row is made for a pair of sets at an element."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Counters of a block of sets against all sets, and pairs that numpy counts at once.
COUNTERS, CHUNK = 1 << 24, 1 << 22
DEALT = "block int, kind int, ids array<int>, own array<int>, size array<int>"
_SETS: dict = {}


def _ranges(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start, start+1, .. of each range in turn."""
    ends = np.cumsum(size)
    return np.repeat(start - (ends - size), size) + np.arange(ends[-1] if len(ends) else 0)


def _pieces(size: np.ndarray, most: int = CHUNK) -> Iterator[slice]:
    """Runs of ranges of about ``most`` places in all."""
    at, ends = 0, np.cumsum(size)
    while at < len(size):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")))
        yield slice(at, to)
        at = to


def _lists(values: np.ndarray, sizes: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(values.astype(np.int32)))


def _sets(shared) -> tuple[np.ndarray, np.ndarray, int]:
    """(ids in order, sizes, sets of a block), unpacked once in a worker."""
    name, ids, sizes, width = shared.value
    if name not in _SETS:
        _SETS.clear()
        _SETS[name] = np.frombuffer(ids, np.int64), np.frombuffer(sizes, np.int64), width
    return _SETS[name]


def dealt(elem: np.ndarray, at: np.ndarray, width: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(block, ids, own, size) of places ``at`` in the sets' order: of each element its sets from the first that is in the block on, and how many are in it."""
    order = np.lexsort((at, elem))
    elem, at = elem[order], at[order]
    new = np.ones(len(elem), bool)
    new[1:] = (elem[1:] != elem[:-1]) | (at[1:] != at[:-1])
    elem, at = elem[new], at[new]
    head = np.flatnonzero(np.concatenate([[True], elem[1:] != elem[:-1]])) if len(elem) else np.zeros(0, np.int64)
    end = np.repeat(np.append(head[1:], len(elem)), np.diff(np.append(head, len(elem))))
    block = at // width
    first = np.ones(len(elem), bool)
    first[1:] = (elem[1:] != elem[:-1]) | (block[1:] != block[:-1])
    begin = np.flatnonzero(first)
    own = np.diff(np.append(begin, len(elem)))
    size = end[begin] - begin if len(begin) else begin
    some = np.flatnonzero(size > 1)
    some = some[np.argsort(block[begin[some]], kind="stable")]
    for part in _pieces(size[some]):
        k = some[part]
        b = block[begin[k]]
        cut = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]]))
        yield b[cut], at[_ranges(begin[k], size[k])], np.add.reduceat(size[k], cut), own[k], size[k], np.diff(np.append(cut, len(k)))


def counted(ids: np.ndarray, own: np.ndarray, size: np.ndarray, base: int, n: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(pair, times) of what a block was dealt, pair being (place of the first set - base) * n + place of the second."""
    start = np.cumsum(size) - size
    left = _ranges(start, own)  # each set of the block at each element
    more = np.repeat(start + size, own) - left - 1
    for part in _pieces(more):
        pair = np.repeat((ids[left[part]] - base).astype(np.int64) * n, more[part]) + ids[_ranges(left[part] + 1, more[part])]
        if len(pair) * 8 > COUNTERS:
            times = np.bincount(pair)
            pair = np.flatnonzero(times)
            yield pair, times[pair]
        else:
            yield np.unique(pair, return_counts=True)


def _sum(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    if len(parts) == 1:
        return parts[0]
    pair, times = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(pair, kind="stable")
    pair, times = pair[order], times[order]
    at = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]]))
    return pair[at], np.add.reduceat(times, at)


def overlaps(postings: DataFrame, tau: float = 0.0, beside: DataFrame | None = None) -> DataFrame:
    """(id1, id2, inter, uni, hits) of all pairs that share an element and have similarity tau at least, exact. Repeated postings count once.

    beside: other postings of the same sets, say the slots of their signatures; hits is what the pair has in common there.

    The sets are numbered in the order of their ids, and runs of numbers are blocks. An element's sets go to each block
    that has some of them, from the first of these on, and a block counts all its pairs in arrays. So what is shuffled
    grows with the lists and not with their squares, as far as sets near in number share elements. Ids and sizes of the
    sets, 16 bytes each, go to all tasks.
    """
    spark = postings.sparkSession
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def whole(of: DataFrame) -> DataFrame:
        return of.select(F.col("set_id").cast("long").alias("set_id"), F.col("elem").cast("long").alias("elem")).where("set_id is not null and elem is not null")

    rows = whole(postings)
    known = rows.groupBy("set_id").agg(F.count_distinct("elem").alias("n")).toArrow()
    ids, sizes = (known.column(c).to_numpy() for c in ("set_id", "n"))
    order, n = np.argsort(ids), len(ids)
    width = max(16, min(COUNTERS // max(1, n), -(-n // (2 * tasks))))
    shared = spark.sparkContext.broadcast((uuid.uuid4().hex, ids[order].astype(np.int64).tobytes(), sizes[order].astype(np.int64).tobytes(), width))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, _, w = _sets(shared)
        own = [(b.column(1).to_numpy(), np.searchsorted(names, b.column(0).to_numpy()).astype(np.int32), b.column(2).to_numpy()) for b in batches]
        if not own:
            return
        elem, at, kinds = (np.concatenate(x) for x in zip(*own, strict=True))
        for kind in np.unique(kinds):
            for block, places, ends, part, size, many in dealt(elem[kinds == kind], at[kinds == kind], w):
                yield pa.RecordBatch.from_arrays([pa.array(block.astype(np.int32)), pa.array(np.full(len(block), kind, np.int32)), _lists(places, ends), _lists(part, many), _lists(size, many)], ["block", "kind", "ids", "own", "size"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, many, w = _sets(shared)
        block, parts, held = -1, ([], []), 0

        def settle() -> Iterator[pa.RecordBatch]:
            if not parts[0]:
                return
            pair, inter = _sum(parts[0])
            one, two = pair // len(names) + block * w, pair % len(names)
            uni, hits = many[one] + many[two] - inter, np.zeros(len(pair), np.int64)
            if parts[1]:
                other, times = _sum(parts[1])
                at = np.minimum(np.searchsorted(other, pair), len(other) - 1)
                hits = np.where(other[at] == pair, times[at], 0)
            keep = np.flatnonzero(inter >= tau * uni)
            for lo in range(0, len(keep), 1 << 16):
                k = keep[lo : lo + (1 << 16)]
                yield pa.RecordBatch.from_arrays([pa.array(x[k].astype(np.int64)) for x in (names[one], names[two], inter, uni, hits)], ["id1", "id2", "inter", "uni", "hits"])

        for batch in batches:
            for k, (b, kind) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                if b != block:
                    yield from settle()
                    block, parts, held = b, ([], []), 0
                places, own, size = (batch.column(c)[k].values.to_numpy() for c in (2, 3, 4))
                for new in counted(places, own.astype(np.int64), size.astype(np.int64), block * w, len(names)):
                    parts[kind].append(new)
                    held += len(new[0])
                if held > CHUNK:
                    parts = tuple([_sum(x)] if x else [] for x in parts)
                    held = 0
        yield from settle()

    rows = rows.withColumn("kind", F.lit(0))
    if beside is not None:
        rows = rows.unionByName(whole(beside).withColumn("kind", F.lit(1)))
    lists = rows.repartition(tasks, "kind", "elem").select("set_id", "elem", "kind").mapInArrow(deal, DEALT)
    blocks = lists.repartition(tasks, "block").sortWithinPartitions("block")
    return blocks.mapInArrow(count, "id1 long, id2 long, inter long, uni long, hits long")
