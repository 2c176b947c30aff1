"""Prediction by partial matching over bytes.

A model of order N is a trie of byte contexts: the child of a node is its context with one more byte
before it, and a node has the counts of the symbols seen after its context. Training counts strings of
N+1 bytes; the counts of lower orders are sums of these. A model made by ``of`` is bounded: the strings of an
order that were seen least are pruned until at most ``limit`` are left, whatever was read. Unless a model is
``exact``, counts are kept in 16 bits: a node's counts are halved, never to 0, until they fit.

Coding of a symbol starts at order N. With T the sum of a node's counts and D their number, a symbol seen c
times has probability (c-1/2)/T and the escape D/(2T) (estimate "D"), or c/(T+D) and D/(T+D) (estimate "C").
After an escape the next lower order codes, where all symbols of the nodes passed are excluded. A node
without counts is passed at no cost. Below order 0 the symbols not yet excluded are equally likely. The
probabilities of all 256 symbols after any context sum to 1. A text ends with the byte 0xFF, which UTF-8
never holds, and is preceded by N of them.
"""

from __future__ import annotations

import math
from collections import defaultdict

import numpy as np

from rotahash.llm.bytesops import U

END = 0xFF
#: Escape estimates: what a count gives up, and what is added to the sum for each kind of symbol.
ESCAPES = {"C": (0.0, 1.0), "D": (0.5, 0.0)}


def framed(data: np.ndarray, at: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The texts with END bytes around: symbols, places of the symbols to code, and the texts' offsets among these places."""
    n = np.diff(at)
    out = np.full(len(data) + (order + 1) * len(n), END, np.uint8)
    shift = (order + 1) * np.arange(len(n)) + order
    begin = at[:-1] + shift
    out[np.repeat(shift, n) + np.arange(len(data))] = data
    coded = np.ones(len(out), bool)
    for j in range(order):
        coded[begin - order + j] = False
    return out, np.flatnonzero(coded), at + np.arange(len(at))


def grams(symbols: np.ndarray, places: np.ndarray, order: int) -> np.ndarray:
    """The symbol at each place below the ``order`` bytes before it, the farthest in the highest byte."""
    out = np.zeros(len(symbols), U)
    for j in range(order, -1, -1):
        out[order:] = (out[order:] << U(8)) | symbols[order - j : len(symbols) - j]
    return out[places]


class Grams:
    """Counts of the (order+1)-byte strings of what has been read, as sorted arrays; all lower orders follow from them."""

    def __init__(self, order: int):
        self.order, self.parts, self.size = order, [], 0

    def add(self, data: np.ndarray, at: np.ndarray, weight: int = 1) -> None:
        symbols, places, _ = framed(data, at, self.order)
        keys, counts = np.unique(grams(symbols, places, self.order), return_counts=True)
        self.parts.append((keys, counts * weight))
        self.size += len(keys)
        if self.size > 1 << 22:
            self.fold()

    def fold(self) -> tuple[np.ndarray, np.ndarray]:
        """Distinct strings and their counts so far."""
        keys, counts = total([k for k, _ in self.parts], [c for _, c in self.parts])
        self.parts, self.size = [(keys, counts)], 0
        return keys, counts


def total(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Sum of counts by key."""
    keys = np.concatenate([np.zeros(0, U), *keys])
    counts = np.concatenate([np.zeros(0, np.int64), *counts])
    order = np.argsort(keys)
    keys, counts = keys[order], counts[order]
    at = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[at], np.add.reduceat(counts, at) if len(at) else counts


def lower(keys: np.ndarray, counts: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """Counts of the order below: the farthest byte is dropped."""
    return total([keys & U((1 << (8 * order)) - 1)], [counts])


def prune(keys: np.ndarray, counts: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """At most ``limit`` strings: all that were seen at least so often."""
    if len(keys) <= limit:
        return keys, counts
    least = np.partition(counts, len(counts) - limit - 1)[len(counts) - limit - 1] + 1
    return keys[counts >= least], counts[counts >= least]


class Model:
    """Frozen statistics."""

    def __init__(self, order: int, seen: list[tuple[np.ndarray, np.ndarray]], escape: str = "D", exact: bool = False):
        """seen: keys and counts of each order 0..N, keys sorted and distinct. exact: counts are never halved."""
        self.order = order
        self.less, self.more = ESCAPES[escape]
        used = np.unique((seen[0][0]).astype(np.int64)) if len(seen) else np.zeros(0, np.int64)
        self.size = len(used) + 1
        self.letter = np.full(256, len(used), np.int64)  # a byte never seen is the last letter
        self.letter[used] = np.arange(len(used))
        self.counts, self.total, self.kinds, self.child = [], [], [], []
        above = np.zeros(1, np.int64)
        contexts = np.zeros(1, U)
        for n, (keys, counts) in enumerate(seen):
            own = np.unique(keys >> U(8))
            if n:  # the node of a context whose shorter form was pruned can't be reached and goes
                short = own & U((1 << (8 * (n - 1))) - 1) if n > 1 else np.zeros(len(own), U)
                at = np.minimum(np.searchsorted(contexts, short), len(contexts) - 1)
                known = contexts[at] == short if len(contexts) else np.zeros(len(own), bool)
                own, parent = own[known], at[known]
                child = np.zeros((len(above) + 1, self.size), np.int32)  # row 0: no such node
                child[parent + 1, self.letter[(own >> U(8 * (n - 1))).astype(np.int64)]] = np.arange(1, len(own) + 1)
                self.child.append(child)
                keep = np.isin(keys >> U(8), own)
                keys, counts = keys[keep], counts[keep]
            node = np.searchsorted(own, keys >> U(8))
            counts = counts.astype(np.int64)
            most = np.zeros(len(own), np.int64)
            np.maximum.at(most, node, counts)
            halvings = np.zeros(len(own), np.int64)
            while not exact and (over := (most >> halvings) > 0xFFFF).any():
                halvings += over
            table = np.zeros((len(own) + 1, self.size), np.int64 if exact else np.uint16)
            table[node + 1, self.letter[(keys & U(0xFF)).astype(np.int64)]] = np.maximum(counts >> halvings[node], 1)
            self.counts.append(table)
            self.total.append(table.sum(1, dtype=np.int64).astype(np.float64))
            self.kinds.append((table > 0).sum(1).astype(np.float64))
            contexts = above = own
        if not self.counts:
            raise ValueError("a model has at least order 0")

    @classmethod
    def of(cls, order: int, keys: np.ndarray, counts: np.ndarray, limit: int = 1 << 21, escape: str = "D") -> Model:
        """From the counts of one place, as Grams.fold gives them."""
        seen = [(keys, counts)]
        for n in range(order, 0, -1):
            seen.insert(0, lower(*seen[0], n))
        return cls(order, [prune(*x, limit) for x in seen], escape)

    def _nodes(self, letters: np.ndarray, places: np.ndarray) -> list[np.ndarray]:
        """Node of each order before each place; 0 where there is none."""
        node = np.full(len(places), 1 if len(self.counts[0]) > 1 else 0, np.int32)
        out = [node]
        for n in range(1, self.order + 1):
            node = self.child[n - 1][node, letters[places - n]]
            out.append(node)
        return out

    def code(self, symbols: np.ndarray, places: np.ndarray) -> np.ndarray:
        """log10 probability of the symbol at each place."""
        letters, n = self.letter[symbols], self.order
        nodes = self._nodes(letters, places)
        letter = letters[places]
        count = self.counts[n][nodes[n], letter]
        total, kinds = self.total[n][nodes[n]], self.kinds[n][nodes[n]]
        with np.errstate(divide="ignore", invalid="ignore"):
            out = np.log10(np.where(count > 0, count - self.less, kinds * (1 - self.less)) / (total + kinds * self.more))
        open_ = np.flatnonzero(count == 0)
        out[open_[total[open_] == 0]] = 0
        # the rest escapes: places with the same nodes on their way are worked out once
        state, inverse = np.unique(nodes[n][open_], return_inverse=True)
        excluded = self.counts[n][state] > 0
        while len(open_) and n:
            n -= 1
            width = len(self.counts[n])
            pair, first, inverse = np.unique(inverse * width + nodes[n][open_], return_index=True, return_inverse=True)
            before = pair // width
            rows = np.where(excluded[before], 0, self.counts[n][pair % width])
            total, kinds = rows.sum(1, dtype=np.int64), (rows > 0).sum(1)
            count = rows[inverse, letter[open_]]
            t, k = total[inverse], kinds[inverse]
            with np.errstate(divide="ignore", invalid="ignore"):
                step = np.log10(np.where(count > 0, count - self.less, k * (1 - self.less)) / (t + k * self.more))
            step[t == 0] = 0
            out[open_] += step
            left = count == 0
            excluded = excluded[before] | (rows > 0)
            open_, inverse = open_[left], inverse[left]
            used, inverse = np.unique(inverse, return_inverse=True)
            excluded = excluded[used]
        if len(open_):
            out[open_] -= np.log10(256 - excluded.sum(1))[inverse]
        return out

    def score(self, data: np.ndarray, at: np.ndarray) -> np.ndarray:
        """log10 probability of each text and its end."""
        symbols, places, offsets = framed(data, at, self.order)
        return np.add.reduceat(self.code(symbols, places), offsets[:-1]) if len(at) > 1 else np.zeros(0)


def adaptive(text: bytes, order: int, escape: str = "D") -> float:
    """log10 probability of one text and its end under a model that starts empty and learns each symbol once it is coded."""
    seen: list[dict] = [defaultdict(lambda: defaultdict(int)) for _ in range(order + 1)]
    symbols, total = bytes([END] * order) + text + bytes([END]), 0.0
    less, more = ESCAPES[escape]
    for i in range(order, len(symbols)):
        excluded: set[int] = set()
        for n in range(order, -2, -1):
            if n < 0:
                total -= math.log10(256 - len(excluded))
                break
            node = {s: c for s, c in seen[n][symbols[i - n : i]].items() if s not in excluded}
            if not node:
                continue
            mass = sum(node.values()) + more * len(node)
            if symbols[i] in node:
                total += math.log10((node[symbols[i]] - less) / mass)
                break
            total += math.log10((1 - less) * len(node) / mass)
            excluded |= node.keys()
        for n in range(order + 1):
            seen[n][symbols[i - n : i]][symbols[i]] += 1
    return total
