"""Functions for SQL text and Arrow-batched twins of the relational sketches."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from rotahash.params import SketchParams

SEED = 42


def jaccard(a: Column, b: Column) -> Column:
    """Similarity of two arrays as sets; null for two empty ones."""
    inter, uni = F.size(F.array_intersect(a, b)), F.size(F.array_union(a, b))
    return F.when(uni > 0, inter / uni)


def agreement(a: Column, b: Column) -> Column:
    """Share of equal places of two packed signatures; empty slots never agree."""
    hits = F.aggregate(F.zip_with(a, b, lambda x, y: F.when(x == y, 1).otherwise(0)), F.lit(0), lambda s, x: s + x)
    return F.when(F.size(a) > 0, hits / F.size(a))


def md5_permutation(tag: str, n: int, seed: int) -> np.ndarray:
    order = sorted(range(n), key=lambda i: (hashlib.md5(f"{seed}:{tag}:{i}".encode()).hexdigest(), i))
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n)
    return rank


class PackedSketcher:
    """Rotating binned signatures of whole sets in numpy: the packed path for sets that fit an array. Equal to the relational path, integer by integer."""

    def __init__(self, p: SketchParams, seed: int = SEED):
        if p.fill != "rotate" or p.donor != "uniform" or p.first_scan != "rotate" or p.split not in ("perm", "2u", "identity") or p.inner != "perm":
            raise ValueError("the packed path has fill 'rotate', uniform donors, and splits 'perm', '2u' or 'identity'")
        self.p, self.seed = p, seed
        self.sigma = md5_permutation("sigma", p.D, seed) if p.split == "perm" else None
        self.pi = md5_permutation("pi", p.d, seed)
        self.probes = np.array([[p.probe(s, t, seed) for t in range(p.attempts)] for s in range(p.slots)])
        self.turn = np.array([p.rotation(s) for s in range(p.slots)])

    def __call__(self, elems) -> list[int | None]:
        p = self.p
        x = np.unique(np.asarray(elems, np.int64))
        if not len(x):
            return [None] * p.slots
        if self.sigma is not None:
            q = self.sigma[x]
        elif p.split == "2u":
            a, b, prime = p.linear(self.seed)
            q = np.array([(a * int(v) + b) % prime % p.D for v in x])
        else:
            q = x
        bins, off = q // p.d, q % p.d
        order = np.argsort(bins, kind="stable")
        bins, off = bins[order], off[order]
        occupied = np.unique(bins)
        at = np.searchsorted(bins, np.append(occupied, p.K))
        full = np.zeros(p.K, bool)
        full[occupied] = True
        read = np.arange(p.slots) % p.K
        for s in np.flatnonzero(~full[read]):
            hit = np.flatnonzero(full[self.probes[s]])
            nearest = occupied[np.searchsorted(occupied, read[s]) % len(occupied)]
            read[s] = self.probes[s][hit[0]] if len(hit) else nearest
        out = []
        for s, b in enumerate(read):
            k = int(np.searchsorted(occupied, b))
            own = off[at[k] : at[k + 1]]
            out.append(int(self.pi[(own - self.turn[s]) % p.d].min()) + int(b) * p.d)
        return out


def packed_udf(p: SketchParams, seed: int = SEED):
    """Arrow-batched function from an array of elements to a packed signature."""

    @pandas_udf("array<long>")
    def sig(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        make = PackedSketcher(p, seed)
        for s in batches:
            yield s.map(lambda x: None if x is None else make(x))

    return sig


def aggregate_udf(p: SketchParams, seed: int = SEED):
    """Grouped aggregate from the elements of a group to a packed signature; a group is one set."""

    @pandas_udf("array<long>")
    def sig(elems: pd.Series) -> list:
        return PackedSketcher(p, seed)(elems.dropna())

    return sig


@udtf(returnType="band int, key string")
class Bands:
    """Rows (band, key) of a packed signature: md5 of each run of ``rows`` slots."""

    def eval(self, sig, rows: int):
        for band in range(len(sig) // rows):
            part = sig[band * rows : (band + 1) * rows]
            yield band, hashlib.md5(",".join("" if h is None else str(h) for h in part).encode()).hexdigest()


def register(spark: SparkSession, p: SketchParams) -> None:
    """SQL names: rh_jaccard and rh_estimate as SQL functions, rh_rotbin_sig, rh_sig_agg and the table function rh_bands."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rh_jaccard(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE RETURN CASE WHEN size(array_union(a, b)) > 0 THEN size(array_intersect(a, b)) / size(array_union(a, b)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rh_estimate(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> CASE WHEN x = y THEN 1 ELSE 0 END), 0, (s, x) -> s + x) / size(a)")
    spark.udf.register("rh_rotbin_sig", packed_udf(p))
    spark.udf.register("rh_sig_agg", aggregate_udf(p))
    spark.udtf.register("rh_bands", Bands)
