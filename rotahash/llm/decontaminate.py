"""Benchmark decontamination by greedy string tiling.

Seeds, the windows of ``min_tile`` words that a document shares with a benchmark item, pick the pairs to
compare. A pair is then tiled: Karp-Rabin hashes find the longest matches of unmarked words, these are
marked, and the search length falls until it reaches ``min_tile``. Tiles may stand in any order, so a
passage whose sentences were moved is still covered. A document is contaminated by an item if the tiles
cover at least ``threshold`` of the item's words.

Words are runs of letters, digits and non-ASCII bytes after lower-casing. The seed index is broadcast in
chunks of at most ``chunk_chars`` characters of benchmark, one pass over the documents for each chunk; a larger
benchmark takes more passes, never a larger broadcast.

Defined results: null or empty texts share nothing; items of fewer than ``min_tile`` words have no seed
and match nothing; repeated items count each for itself; an empty benchmark leaves every document clean.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.llm.bytesops import U, lean, mix, shingles, slices, word_hashes

MIN_TILE, THRESHOLD, CHUNK_CHARS = 5, 0.6, 16_000_000
FILTER_BITS = 20


def _rolling(tokens: np.ndarray, s: int) -> np.ndarray:
    value = np.zeros(len(tokens) - s + 1, U)
    for j in range(s):
        value = value * U(0x9E3779B97F4A7C15) + tokens[j : j + len(value)]
    return mix(value)


def tile(item: np.ndarray, text: np.ndarray, min_tile: int = MIN_TILE) -> list[tuple[int, int, int]]:
    """Tiles (item start, text start, length) of two arrays of word hashes, longest first and then leftmost."""
    tiles: list[tuple[int, int, int]] = []
    free_item, free_text = np.ones(len(item), bool), np.ones(len(text), bool)
    s = max(min_tile, min(len(item), len(text)) // 2)
    while len(item) >= s and len(text) >= s:
        open_item = np.flatnonzero(np.convolve(free_item, np.ones(s), "valid") > s - 0.5)
        open_text = np.flatnonzero(np.convolve(free_text, np.ones(s), "valid") > s - 0.5)
        found, longer = [], 0
        if len(open_item) and len(open_text):
            where = defaultdict(list)
            for i, h in zip(open_item.tolist(), _rolling(item, s)[open_item].tolist(), strict=True):
                where[h].append(i)
            hashes = _rolling(text, s)[open_text]
            keep = np.isin(hashes, np.fromiter(where, U, len(where)))
            for j, h in zip(open_text[keep].tolist(), hashes[keep].tolist(), strict=True):
                for i in where[h]:
                    if i and j and free_item[i - 1] and free_text[j - 1] and item[i - 1] == text[j - 1]:
                        continue  # inside a match that begins earlier
                    n = 0
                    while i + n < len(item) and j + n < len(text) and free_item[i + n] and free_text[j + n] and item[i + n] == text[j + n]:
                        n += 1
                    if n >= s:
                        found.append((-n, i, j))
                        longer = max(longer, n)
        if longer > 2 * s:
            s = longer
            continue
        occluded = False
        for n, i, j in sorted(found):
            n = -n
            if free_item[i : i + n].all() and free_text[j : j + n].all():
                tiles.append((i, j, n))
                free_item[i : i + n] = free_text[j : j + n] = False
            else:
                occluded = True
        if occluded:
            continue  # what is left of a match that lost words to another is looked for again at this length
        if s == min_tile:
            break
        s = max(min_tile, s // 2)
    return tiles


class _Index:
    """Items' words and the sorted hashes of their seeds."""

    def __init__(self, ids: list[int], texts: list[str | None], min_tile: int):
        column = pa.array(texts, pa.string())
        self.ids, self.min_tile, self.items = ids, min_tile, []
        for _, _, data, at in slices(column, 1 << 62, lower=True):
            words, rows = word_hashes(data, at)
            self.items = [words[rows[i] : rows[i + 1]] for i in range(len(ids))]
        seeds, owners = [], []
        for i, words in enumerate(self.items):
            if len(words) >= min_tile:
                own, _ = shingles(words, np.array([0, len(words)]), min_tile)
                seeds.append(own)
                owners.append(np.full(len(own), i))
        seeds, owners = (np.concatenate(seeds), np.concatenate(owners)) if seeds else (np.zeros(0, U), np.zeros(0, np.int64))
        order = np.argsort(seeds, kind="stable")
        self.seeds, self.owners = seeds[order], owners[order]
        self.filter = np.zeros(1 << FILTER_BITS, bool)
        self.filter[(self.seeds >> U(64 - FILTER_BITS)).astype(np.int64)] = True

    def matches(self, words: np.ndarray, at: np.ndarray):
        """(row, item index, coverage) of the pairs that share a seed."""
        grams, rows = shingles(words, at, self.min_tile)
        maybe = np.flatnonzero(self.filter[(grams >> U(64 - FILTER_BITS)).astype(np.int64)])
        lo, hi = np.searchsorted(self.seeds, grams[maybe]), np.searchsorted(self.seeds, grams[maybe], "right")
        maybe, lo, hi = maybe[hi > lo], lo[hi > lo], hi[hi > lo]
        row_of = np.searchsorted(rows, maybe, "right") - 1
        pairs = defaultdict(list)
        for p, r, a, b in zip(maybe.tolist(), row_of.tolist(), lo.tolist(), hi.tolist(), strict=True):
            if at[r + 1] - at[r] >= self.min_tile:
                for k in self.owners[a:b].tolist():
                    pairs[r, k].append(p - rows[r])
        for (r, k), seen in pairs.items():
            item, own = self.items[k], words[at[r] : at[r + 1]]
            near = np.zeros(len(own), bool)
            for p in sorted(set(seen)):  # a tile holds a seed: words a whole item away from every seed can't be in one
                near[max(0, p - len(item)) : p + len(item) + self.min_tile] = True
            # a gap between such stretches counts as one word that matches nothing
            cut = np.flatnonzero(near)
            gap = np.flatnonzero(np.diff(cut) > 1) + 1
            text = np.insert(own[cut], gap, U(0))
            yield r, k, sum(n for _, _, n in tile(item, text, self.min_tile)) / len(item)


def _indexes(docs: DataFrame, benchmark: DataFrame, min_tile: int = MIN_TILE, chunk_chars: int = CHUNK_CHARS) -> Iterator:
    """Broadcast seed indexes that together hold the whole benchmark."""
    items = benchmark.select("item_id", "text")
    size = items.agg(F.sum(F.length("text"))).first()[0] or 0
    chunks = -(-size // chunk_chars) or 1
    for c in range(chunks):
        rows = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(chunks)) == c).collect()
        yield docs.sparkSession.sparkContext.broadcast(_Index([r[0] for r in rows], [r[1] for r in rows], min_tile))


def decontaminate(docs: DataFrame, benchmark: DataFrame, threshold: float = THRESHOLD, **options) -> DataFrame:
    """The rows of docs, all columns as they were, that no item covers to the threshold; decided text by text."""
    for shared in _indexes(docs, benchmark, **options):

        def keep(batches, shared=shared):
            for b in batches:
                good = np.ones(b.num_rows, bool)
                for lo, _, data, at in slices(b.column("text"), lower=True):
                    for r, _, c in shared.value.matches(*word_hashes(data, at)):
                        good[lo + r] &= c < threshold
                yield b.filter(pa.array(good))

        docs = docs.mapInArrow(lean(keep), docs.schema)
    return docs


def report(docs: DataFrame, benchmark: DataFrame, threshold: float = THRESHOLD, **options) -> DataFrame:
    """One row per document: the item that covers most (the least id on a tie), its coverage, and all items over the threshold."""
    out = docs.select("doc_id", "text", F.lit(None).cast("long").alias("item_id"), F.lit(0.0).alias("coverage"), F.array().cast("array<long>").alias("items"))
    for shared in _indexes(docs, benchmark, **options):

        def find(batches, shared=shared):
            for b in batches:
                best, cover, over = (b.column(c).to_pylist() for c in ("item_id", "coverage", "items"))
                for lo, _, data, at in slices(b.column("text"), lower=True):
                    for r, k, c in shared.value.matches(*word_hashes(data, at)):
                        i, r = shared.value.ids[k], lo + r
                        if (c, best[r] is None, -i) > (cover[r], False, -(best[r] or 0)):
                            best[r], cover[r] = i, c
                        if c >= threshold:
                            over[r].append(i)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("text"), pa.array(best, pa.int64()), pa.array(cover, pa.float64()), pa.array([sorted(x) for x in over], pa.list_(pa.int64()))], ["doc_id", "text", "item_id", "coverage", "items"])

        out = out.mapInArrow(lean(find), "doc_id long, text string, item_id long, coverage double, items array<long>")
    return out.drop("text").withColumn("contaminated", F.size("items") > 0)
