"""Removal of repeated byte strings by merged Burrows-Wheeler transforms.

A byte goes if a string of ``LENGTH`` bytes that covers it also starts earlier in the corpus (smaller
doc_id, or earlier in the same document).

1. Anchors. Of the ``GRAM``-byte windows in a string of LENGTH bytes the one of least hash is its anchor,
   so equal strings have equal anchors at the same place. Strings with one anchor are neighbours and form
   a stretch. A task keeps the first of equal stretches and marks the others at once.
2. Stretches meet by anchor. All but the first of equal stretches are marked. An anchor with several
   different stretches is a boundary of a repeated passage: only these need suffix order.
3. The bytes of boundary stretches are fetched and dealt out by anchor. Each group of stretches is split
   into shards, the Burrows-Wheeler transform of each shard is built, and the transforms are merged: the
   interleaving of the shards is refined one symbol at a time, by a stable distribution of the symbols
   that precede the suffixes, and after h rounds the blocks of the interleaving are exactly the suffixes
   with h common symbols. No suffix of the union is sorted again, and suffixes alone in their block are
   settled and leave the refinement. After LENGTH rounds the blocks are the repeated strings.
4. An anchor with more than ``CROWD`` different stretches in one task, or more than ``WIDE`` in all tasks together
   (a short line on very many documents), would gather an unbounded group. Its strings are compared by 128-bit
   hash instead, one row per distinct string and task, so a common line is spread over all tasks and no group of
   step 3 holds more than ``WIDE`` stretches, whatever the number of tasks.

Defined results: null text is empty; a text shorter than LENGTH loses nothing; rows of equal doc_id are
taken as one document (a string that two such rows share at one place is not repeated by that alone).
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.llm.bytesops import U, Windows, lean, mix, pack, raw, slices, unpack
from rotahash.llm.durable import durable, partitions

LENGTH, GRAM, CROWD = 100, 32, 64
#: Different stretches of one anchor in all tasks together that are merged in one group.
WIDE = 4096
FLUSH, SHARD, CHUNK = 1 << 19, 1 << 18, 1 << 22
PLACE = U((1 << 24) - 1)
#: Of one stretch in a packed cell: hashes of anchor (within its bucket) and bytes, document, first start, number of starts.
STRETCH = (("anchor", np.uint32), ("bytes", np.uint64), ("doc", np.int64), ("start", np.int32), ("count", np.uint8))
RANGE = (("key", np.int64), ("doc", np.int64), ("start", np.int32), ("count", np.int32))


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each window of ``width`` values."""
    size = 1
    while size * 2 <= width:
        values = np.minimum(values[:-size], values[size:])
        size *= 2
    return values if size == width else np.minimum(values[: len(values) - (width - size)], values[width - size :])


def stretches(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, ...]:
    """Row, first start in the buffer, number of starts, and the hashes of anchor and bytes, of every stretch."""
    n = len(data)
    if n < LENGTH:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, U, U))
    windows = Windows(data)
    place = np.arange(n - GRAM + 1)
    grams = windows.hash(place, place + GRAM)
    anchor = (_least((grams & ~PLACE) | place.astype(U), LENGTH - GRAM + 1) & PLACE).astype(np.int64)
    size = np.diff(at)
    count = np.maximum(size - LENGTH + 1, 0)  # starts of each row
    row = np.repeat(np.arange(len(size)), count)
    start = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(at[:-1], count)
    anchor = anchor[start]
    new = np.ones(len(start), bool)
    new[1:] = (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1])
    first = np.flatnonzero(new)
    length = np.diff(np.append(first, len(start)))
    lo, anchor, row = start[first], anchor[first], row[first]
    return row, lo, length, grams[anchor], mix(windows.hash(lo, lo + length + LENGTH - 1) ^ (anchor - lo).astype(U))


def _pieces(column):
    """Slices of a text column whose buffers are short enough for PLACE; a longer text comes in overlapping pieces."""
    for lo, _, data, at in slices(column):
        if len(data) <= CHUNK:
            yield lo, data, at, 0
        else:
            for base in range(0, len(data), CHUNK):
                piece = data[base : base + CHUNK + LENGTH - 1]
                yield lo, piece, np.array([0, len(piece)]), base


def _firsts(keys: list[np.ndarray], doc: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order by keys, document and start; and whether each in that order is the first of its keys."""
    order = np.lexsort((start, doc, *reversed(keys)))
    new = np.ones(len(order), bool)
    if len(order):
        new[1:] = np.logical_or.reduce([k[order][1:] != k[order][:-1] for k in keys])
    return order, new


ROWS = "kind int, key long, other long, doc long, start long, count long, cell binary"
MARKED, PACKED, BOUNDARY, CROWDED, HASHED = range(5)
NAMES = ("kind", "key", "other", "doc", "start", "count", "cell")


def _batch(kind: int, n: int, **columns) -> pa.RecordBatch:
    """Rows of one kind; columns that are not given are null."""
    kinds = (pa.int32(), *[pa.int64()] * 5, pa.binary())
    own = {"kind": np.full(n, kind, np.int32)} | columns
    return pa.RecordBatch.from_arrays([pa.array(own[c], t) if c in own else pa.nulls(n, t) for c, t in zip(NAMES, kinds, strict=True)], names=list(NAMES))


def _cells(kind: int, cells: list[bytes], keys: np.ndarray | None = None):
    for i in range(0, len(cells), 64):
        own = cells[i : i + 64]
        yield _batch(kind, len(own), cell=own, key=(np.zeros(len(own), np.int64) if keys is None else keys[i : i + 64]))


def _ranges(kind: int, doc, start, count, key=None):
    """One packed row of ranges."""
    if len(doc):
        order = np.lexsort((start, doc))
        columns = [np.zeros(len(doc), np.int64) if key is None else key, doc, start, count]
        yield from _cells(kind, [pack([c[order] for c in columns], RANGE)])


def _merge_runs(doc, start, count):
    """Neighbouring marked stretches of a document as one."""
    order = np.lexsort((start, doc))
    doc, start, count = doc[order], start[order], count[order].astype(np.int64)
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (start[1:] != start[:-1] + count[:-1])
    at = np.flatnonzero(new)
    return doc[at], start[at], np.add.reduceat(count, at) if len(at) else count


def _string_hashes(data: np.ndarray, lo: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, ...]:
    """Stretch number, start and two hashes of every string."""
    which = np.repeat(np.arange(len(lo)), count)
    start = np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count) + lo[which]
    windows = Windows(data)
    return which, start, windows.hash(start, start + LENGTH), mix(windows.hash(start, start + LENGTH // 2) + U(3) * windows.hash(start + LENGTH // 2, start + LENGTH))


def _scan(docs: DataFrame, buckets: int) -> DataFrame:
    """Step 1: packed stretches by bucket of their anchor, what the task can mark by itself, and crowded anchors with their strings."""

    def scan(batches):
        held, buffers, size = [], [], 0

        def flush():
            nonlocal size
            if not held:
                return
            bucket, anchor, content, doc, start, count, buffer, place = (np.concatenate([h[i] for h in held]) for i in range(8))
            held.clear()
            size = 0
            order, new = _firsts([bucket, anchor, content], doc, start)
            again = order[~new]
            yield from _ranges(MARKED, *_merge_runs(doc[again], start[again], count[again]))
            keep = order[new]
            key = (bucket[keep] << 32) | anchor[keep].astype(np.int64)
            at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            many = np.diff(np.append(at, len(key)))
            if (many > CROWD).any():
                hot = key[at[many > CROWD]]
                yield _batch(CROWDED, len(hot), key=hot >> 32, other=hot & 0xFFFFFFFF)
                crowd = np.repeat(many > CROWD, many)
                own, keep = keep[crowd], keep[~crowd]
                for k in np.unique(buffer[own]):
                    i = own[buffer[own] == k]
                    which, string, a, b = _string_hashes(buffers[k], place[i], count[i])
                    d, s = doc[i][which], (start[i] - place[i])[which] + string
                    order, new = _firsts([a, b], d, s)
                    yield from _ranges(MARKED, *_merge_runs(d[order[~new]], s[order[~new]], np.ones(int((~new).sum()), np.int64)))
                    j = order[new]
                    yield _batch(HASHED, len(j), key=a[j].view(np.int64), other=b[j].view(np.int64), doc=d[j], start=s[j])
            at = np.searchsorted(bucket[keep], np.arange(buckets + 1))
            full = np.flatnonzero(np.diff(at))
            cells = [pack([c[keep[at[k] : at[k + 1]]] for c in (anchor, content, doc, start, count)], STRETCH) for k in full]
            yield from _cells(PACKED, cells, full.astype(np.int64))
            buffers.clear()

        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            for lo, data, at, base in _pieces(batch.column("text")):
                row, start, count, gram, content = stretches(data, at)
                held.append(((gram % U(buckets)).astype(np.int64), (gram >> U(32)).astype(np.uint32), content, ids[lo + row], start - at[row] + base, count, np.full(len(row), len(buffers)), start))
                buffers.append(data)
                size += len(row)
                if size >= FLUSH:
                    yield from flush()
        yield from flush()

    return docs.select("doc_id", "text").where("doc_id is not null").mapInArrow(lean(scan), ROWS)


def _meet(scanned: DataFrame) -> DataFrame:
    """Step 2, by bucket: marks of equal stretches, boundary stretches, and those of anchors that are crowded in another task or in all together; other rows pass."""

    def meet(table):
        table = table.select(NAMES)
        kind = table.column("kind").to_numpy()
        cells = table.column("cell").filter(pa.array(kind == PACKED)).to_pylist()
        out = [table.filter(pa.array((kind == MARKED) | (kind == HASHED)))]
        if cells:
            bucket = table.column("key").filter(pa.array(kind == PACKED))[0].as_py()
            hot = table.column("other").filter(pa.array(kind == CROWDED)).to_numpy()
            anchor, content, doc, start, count = unpack(cells, STRETCH)
            order, new = _firsts([anchor, content], doc, start)
            again, keep = order[~new], order[new]
            key = anchor[keep].astype(np.int64)
            many = np.diff(np.append(np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])), len(key)))
            several, crowd = np.repeat(many > 1, many), np.isin(key, hot) | np.repeat(many > WIDE, many)
            key |= np.int64(bucket) << 32
            for what, i, k in ((MARKED, again, None), (BOUNDARY, keep[several & ~crowd], key[several & ~crowd]), (CROWDED, keep[crowd], key[crowd])):
                out += [pa.Table.from_batches([b]) for b in _ranges(what, doc[i], start[i], count[i], k)]
        return pa.concat_tables(out)

    #: rows of kinds that pass go where they are spread evenly
    deal = F.when(F.col("kind").isin(PACKED, CROWDED), F.col("key")).otherwise(-1 - F.pmod(F.xxhash64("key", "other", "cell"), F.lit(partitions(scanned.sparkSession))))
    return scanned.withColumn("bucket", deal).groupBy("bucket").applyInArrow(lean(meet), ROWS)


def transform(text: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Suffix order, predecessor's row and preceding symbol (-1: the border of a string) of the strings of ``text``; ends: their ends.

    A border sorts below every byte, and borders sort in the order of the strings.
    """
    border = ends + np.arange(len(ends))
    size = len(text) + len(ends)
    symbol = np.zeros(size + 7, np.int64)
    inside = np.ones(size, bool)
    inside[border] = False
    symbol[:size][inside] = text.astype(np.int64) + 1
    until = np.repeat(border, np.diff(np.concatenate([[-1], border]))) - np.arange(size)  # symbols before the next border
    key = np.zeros(size, np.int64)
    for j in range(7):
        key = (key << 9) | np.where(until >= j, symbol[j : j + size], 0)
    order = np.argsort(key)
    short = np.flatnonzero(until[order] < 7)  # equal keys that hold a border are in the order of the strings
    order[short] = order[short][np.lexsort((order[short], key[order[short]]))]
    key = key[order]
    head = np.ones(size, bool)
    head[1:] = key[1:] != key[:-1]
    head[short] = True
    rank = np.empty(size, np.int64)
    rank[order] = np.maximum.accumulate(np.where(head, np.arange(size), 0))
    tied, h = np.flatnonzero(~(head & np.append(head[1:], True))), 7
    while len(tied):  # prefix doubling of the suffixes that are still tied
        own = order[tied]
        key = rank[own] * size + rank[own + h]
        sort = np.argsort(key)
        own, key = own[sort], key[sort]
        order[tied] = own
        head = np.ones(len(tied), bool)
        head[1:] = key[1:] != key[:-1]
        rank[own] = np.maximum.accumulate(np.where(head, tied, 0))
        tied, h = tied[~(head & np.append(head[1:], True))], 2 * h
    before = order - 1
    return order, rank[before], symbol[:size][before] - 1


def merge(texts: list[tuple[np.ndarray, np.ndarray]], depth: int = LENGTH) -> tuple[np.ndarray, np.ndarray]:
    """Places (in all texts joined) of the suffixes that share ``depth`` symbols with another, and their blocks, from the shards' transforms.

    A round puts ``step`` symbols before every suffix at once: the symbols and rows of ``step``
    predecessors are read off the shards' transforms beforehand.
    """
    places, lf, symbols, rows, base = [], [], [], 0, 0
    for text, ends in texts:
        order, back, symbol = transform(text, ends)
        border = ends + np.arange(len(ends))
        strings = np.repeat(np.arange(len(ends)), np.diff(np.concatenate([[-1], border])))
        places.append(order - strings[order] + base)
        lf.append(back + rows)
        symbols.append(symbol)
        rows, base = rows + len(order), base + len(text)
    places, lf, symbols = np.concatenate(places), np.concatenate(lf), np.concatenate(symbols)
    step = 4 if depth % 4 == 0 else 1
    code, last, valid = np.zeros(rows, np.int64), np.arange(rows), np.ones(rows, bool)
    for j in range(step):  # the farthest symbol is the most significant
        valid &= symbols[last] >= 0
        code |= np.maximum(symbols[last], 0) << (8 * j)
        last = lf[last]
    known, code = np.unique(code, return_inverse=True)
    code = code.astype(np.uint16 if len(known) <= 1 << 16 else np.int64)
    now, block = np.arange(rows), np.zeros(rows, np.int32)
    for _ in range(depth // step):
        inner = valid[now]  # a border begins no repeated string: it is settled
        now, block = now[inner], block[inner]
        symbol = code[now]
        order = np.argsort(symbol, kind="stable")
        symbol, block = symbol[order], block[order]
        new = np.ones(len(now), bool)
        new[1:] = (symbol[1:] != symbol[:-1]) | (block[1:] != block[:-1])
        end = np.append(new[1:], True)
        open_ = ~(new & end)  # a suffix alone in its block is settled
        block = np.cumsum(new, dtype=np.int32)[open_]
        now = last[now[order[open_]]]
        if not len(now):
            break
    return places[now], block


def _boundaries(fetched: DataFrame) -> DataFrame:
    """Step 3: marks of the strings in boundary stretches that also start earlier; other rows pass."""

    def compare(batches):
        rest = None
        for b in batches:
            boundary = pa.array(b.column("kind").to_numpy() == BOUNDARY)
            yield b.filter(pa.compute.invert(boundary))
            t = pa.Table.from_batches([b.filter(boundary)])
            if not t.num_rows:
                continue
            t = t if rest is None else pa.concat_tables([rest, t])
            keys = t.column("key").to_numpy()
            cut = int(np.searchsorted(keys, keys[-1]))
            if cut and t.nbytes > SHARD:
                yield from merged(t.slice(0, cut))
                t = t.slice(cut)
            rest = t
        if rest is not None and rest.num_rows:
            yield from merged(rest)

    def merged(t):
        data, at = raw(t.column("cell"))
        doc, start = t.column("doc").to_numpy(), t.column("start").to_numpy()
        shards, lo, step = [], 0, max(SHARD // 4, len(data) // 8)
        while lo < len(doc):  # whole stretches, in shards of a like size
            hi = max(lo + 1, int(np.searchsorted(at, at[lo] + step, "right")) - 1)
            shards.append((data[at[lo] : at[hi]], at[lo + 1 : hi + 1] - at[lo]))
            lo = hi
        place, block = merge(shards)
        own = np.searchsorted(at, place, "right") - 1
        d, s = doc[own], start[own] + place - at[own]
        order, new = _firsts([block], d, s)
        hit = order[~new]
        yield from _ranges(MARKED, *_merge_runs(d[hit], s[hit], np.ones(len(hit), np.int64)))

    spark = fetched.sparkSession
    return fetched.repartition(partitions(spark), "key").sortWithinPartitions("key").mapInArrow(lean(compare), ROWS)


def _unpacked(rows: DataFrame) -> DataFrame:
    def open_(batches):
        for b in batches:
            for kind, cell in zip(b.column("kind").to_numpy(), b.column("cell").to_pylist(), strict=True):
                key, doc, start, count = unpack([cell], RANGE)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), kind)), *(pa.array(c) for c in (key, doc, start, count))], ["kind", "key", "doc", "start", "count"])

    return rows.select("kind", "cell").mapInArrow(open_, "kind int, key long, doc long, start int, count int")


def _fetch(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """The wanted stretches with their bytes; crowded ones as hashed strings."""
    per_doc = _unpacked(wanted).groupBy("doc").agg(F.collect_list(F.struct("kind", "key", "start", "count")).alias("want"))
    joined = docs.select("doc_id", "text").join(per_doc, F.col("doc_id") == F.col("doc")).select("doc", "text", "want")

    def fetch(batches):
        for b in batches:
            for lo, hi, data, at in slices(b.column("text")):
                want = b.column("want").slice(lo, hi - lo)
                flat = want.flatten()
                row = np.repeat(np.arange(hi - lo), np.diff(want.offsets.to_numpy()))
                kind, key, start, count = (flat.field(i).to_numpy() for i in range(4))
                doc = b.column("doc").slice(lo, hi - lo).to_numpy()[row]
                begin = at[row] + start
                whole = begin + count + LENGTH - 1 <= at[row + 1]  # rows of equal doc_id may be shorter
                k = np.flatnonzero((kind == BOUNDARY) & whole)
                cells = [data[i : i + c + LENGTH - 1].tobytes() for i, c in zip(begin[k].tolist(), count[k].tolist(), strict=True)]
                for i in range(0, len(k), 4096):
                    j = k[i : i + 4096]
                    yield _batch(BOUNDARY, len(j), key=key[j], doc=doc[j], start=start[j].astype(np.int64), count=count[j].astype(np.int64), cell=cells[i : i + 4096])
                k = np.flatnonzero((kind == CROWDED) & whole)
                if len(k):
                    which, place, a, c = _string_hashes(data, begin[k], count[k])
                    yield _batch(HASHED, len(which), key=a.view(np.int64), other=c.view(np.int64), doc=doc[k][which], start=place - at[row[k]][which])

    return joined.mapInArrow(lean(fetch), ROWS)


def marked(docs: DataFrame) -> DataFrame:
    """(doc, start, count): starts of strings that also start earlier, as ranges."""
    met = durable(_meet(_scan(docs, partitions(docs.sparkSession))))
    merged = durable(_boundaries(_fetch(docs, met.where(F.col("kind").isin(BOUNDARY, CROWDED)))))
    strings = met.where(F.col("kind") == HASHED).unionByName(merged.where(F.col("kind") == HASHED)).select("key", "other", "doc", "start")
    first = strings.groupBy("key", "other").agg(F.min(F.struct("doc", "start")).alias("first"), F.count("*").alias("n")).where("n > 1")
    repeated = strings.join(first.drop("n"), ["key", "other"]).where(F.struct("doc", "start") > F.col("first"))
    ranges = _unpacked(met.unionByName(merged).where(F.col("kind") == MARKED)).select("doc", "start", "count")
    return ranges.unionByName(repeated.select("doc", F.col("start").cast("int").alias("start"), F.lit(1).alias("count")))


def deduplicate(docs: DataFrame, text: bool = False) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256; with ``text`` also the spans and the remaining bytes."""
    per_doc = marked(docs).groupBy("doc").agg(F.collect_list(F.struct("start", "count")).alias("ranges"))
    joined = docs.select("doc_id", "text").join(per_doc, F.col("doc_id") == F.col("doc"), "left").select("doc_id", "text", "ranges")
    extra = ", spans array<struct<start: long, end: long>>, kept binary" if text else ""

    def cut(batches):
        for b in batches:
            for lo, hi, data, at in slices(b.column("text")):
                n = hi - lo
                ranges = b.column("ranges").slice(lo, n)
                flat, counts = ranges.flatten(), np.diff(ranges.offsets.to_numpy())
                row = np.repeat(np.arange(n), np.where(ranges.is_valid().to_numpy(zero_copy_only=False), counts, 0))
                start, count = (flat.field(i).to_numpy() for i in range(2))
                begin = np.minimum(at[row] + start, at[row + 1])
                end = np.minimum(begin + count + LENGTH - 1, at[row + 1])
                depth = np.bincount(begin, minlength=len(data) + 1) - np.bincount(end, minlength=len(data) + 1)
                gone = np.cumsum(depth[:-1]) > 0
                edge = gone.copy()
                edge[1:] &= ~gone[:-1]
                heads = at[:-1][at[:-1] < at[1:]]
                edge[heads] = gone[heads]
                sums, spans = (np.concatenate([[0], np.cumsum(x)]) for x in (gone, edge))
                kept = [data[at[i] : at[i + 1]][~gone[at[i] : at[i + 1]]].tobytes() for i in range(n)]
                out = [b.column("doc_id").slice(lo, n), pa.array(np.diff(at)), pa.array(sums[at[1:]] - sums[at[:-1]]), pa.array(spans[at[1:]] - spans[at[:-1]]), pa.array([hashlib.sha256(k).hexdigest() for k in kept])]
                names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
                if text:
                    cells = []
                    for i in range(n):
                        own = np.concatenate([[0], gone[at[i] : at[i + 1]].astype(np.int8), [0]])
                        step = np.diff(own)
                        cells.append([{"start": int(s), "end": int(e)} for s, e in zip(np.flatnonzero(step > 0), np.flatnonzero(step < 0), strict=True)])
                    out += [pa.array(cells, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), pa.array(kept, pa.binary())]
                    names += ["spans", "kept"]
                yield pa.RecordBatch.from_arrays(out, names)

    return joined.mapInArrow(lean(cut), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + extra)
