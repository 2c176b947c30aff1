"""The sketches against a plain Python version of their definitions, and the invariances they promise."""

import hashlib
import random

import pytest
from pyspark.sql import functions as F

from rotahash.functions import hashes
from rotahash.functions.sqlfns import PackedSketcher, md5_permutation
from rotahash.operators import apps as A
from rotahash.operators import estimates as E
from rotahash.operators import sketches as S
from rotahash.operators.permutations import permutation
from rotahash.params import SketchParams, next_prime
from rotahash.sources import tables as T

SETS = {1: {5, 7, 11, 14}, 2: {0}, 3: set(range(64)), 4: {5, 7, 11, 14}, 5: {1, 2, 3, 60, 61}, 6: {40, 41, 42}}


@pytest.fixture(scope="module")
def postings(spark):
    return spark.createDataFrame([(s, e) for s, es in SETS.items() for e in es], "set_id long, elem long").cache()


def table(sig, seed=42):
    out = {}
    for r in sig.where(F.col("seed") == seed).collect():
        out.setdefault(r.set_id, {})[r.slot] = r.h
    return {k: [v[s] for s in sorted(v)] for k, v in out.items()}


def naive(elems, p, seed=42):
    """One set, one slot at a time, from the definition."""
    sigma = md5_permutation("sigma", p.D, seed) if p.split == "perm" else None
    if p.split == "2u":
        a, b, prime = p.linear(seed)
    q = [int(sigma[x]) if p.split == "perm" else (a * x + b) % prime % p.D if p.split == "2u" else x for x in elems]
    bins = {}
    for x in q:
        bins.setdefault(x // p.d, []).append(x % p.d)
    pi, out = md5_permutation("pi", p.d, seed), []
    for s in range(p.slots):
        own = p.bin_of(s, seed)
        dist = 0
        if own not in bins:
            right = next(t for t in range(p.K) if (own + t) % p.K in bins)
            left = next(t for t in range(p.K) if (own - t) % p.K in bins)
            if p.fill == "none":
                out.append(None)
                continue
            dist = right
            if p.donor == "uniform":
                own = next((b for b in (p.probe(s, t, seed) for t in range(p.attempts)) if b in bins), (own + right) % p.K)
            elif p.donor == "clockwise" or p.coin(s, seed) > 0:
                own = (own + right) % p.K
            else:
                own, dist = (own - left) % p.K, left
        if p.fill in ("none", "copy"):
            h = min(bins[own]) + own * p.d + (dist * (p.D + 1) if p.copy_offset else 0)
        elif p.fill == "rotate":
            h = min(int(pi[(o - p.rotation(s)) % p.d]) for o in bins[own]) + own * p.d
        else:
            perm = md5_permutation(f"inner{s}", p.d, seed)
            h = min(o if p.implicit and not dist and s < p.K else int(perm[o]) for o in bins[own]) + own * p.d
        out.append(h)
    return out


CASES = [
    dict(fill="none"),
    dict(fill="copy"),
    dict(fill="copy", donor="clockwise", copy_offset=True),
    dict(fill="copy", donor="two_way"),
    dict(fill="fresh"),
    dict(fill="fresh", implicit=True, M=12),
    dict(fill="rotate"),
    dict(fill="rotate", split="2u"),
    dict(fill="rotate", split="identity", donor="clockwise"),
    dict(fill="rotate", first_scan="random", attempts=1),
    dict(fill="rotate", M=20, shift="lcm"),
    dict(fill="rotate", M=3),
]


@pytest.mark.parametrize("case", CASES, ids=str)
def test_relational_equals_naive(postings, case):
    p = SketchParams(64, 8, **case)
    assert table(S.sketch(postings, p)) == {k: naive(v, p) for k, v in SETS.items()}


@pytest.mark.parametrize("K", [1, 64])
def test_one_bin_and_bins_of_one(postings, K):
    p = SketchParams(64, K, shift="lcm")
    assert table(S.sketch(postings, p)) == {k: naive(v, p) for k, v in SETS.items()}


@pytest.mark.parametrize("case", [dict(), dict(split="2u"), dict(split="identity", M=20, shift="lcm")], ids=str)
def test_packed_equals_relational(postings, case):
    p = SketchParams(64, 8, **case)
    make = PackedSketcher(p)
    assert {k: make(list(v)) for k, v in SETS.items()} == table(S.sketch(postings, p))
    assert make([]) == [None] * p.slots


def test_toy(spark):
    toy = spark.createDataFrame([(1, e) for e in (5, 7, 11, 14)], "set_id long, elem long")
    sig = S.sketch(toy, SketchParams(16, 4, split="identity", fill="none"))
    assert table(sig) == {1: [None, 5, 11, 14]}
    filled = table(S.sketch(toy, SketchParams(16, 4, split="identity", fill="copy", donor="clockwise")))
    assert filled == {1: [5, 5, 11, 14]}


def test_rotating_minhash(postings):
    p = SketchParams(64, 8)
    sigma, pi = md5_permutation("sigma", 64, 42), md5_permutation("pi", 64, 42)
    want = {k: [min(int(pi[(sigma[x] - s - 1) % 64]) for x in v) for s in range(8)] for k, v in SETS.items()}
    assert table(S.rot_minhash(postings, p)) == want
    shared = {k: [min(int(sigma[(sigma[x] - s - 1) % 64]) for x in v) for s in range(8)] for k, v in SETS.items()}
    assert table(S.rot_minhash(postings, p.with_(share=True))) == shared


def test_standard_minhash(postings):
    perms = [md5_permutation(f"std{s}", 64, 42) for s in range(4)]
    want = {k: [min(int(q[x]) for x in v) for q in perms] for k, v in SETS.items()}
    assert table(S.std_minhash(postings, SketchParams(64, 4))) == want


def test_equal_sets_agree_and_bins_never_cross(postings):
    p = SketchParams(64, 8)
    sig = S.sketch(postings, p)
    pairs = postings.sparkSession.createDataFrame([(1, 4), (2, 6)], "id1 long, id2 long")
    got = {(r.id1, r.id2): r.j_hat for r in E.estimate_pairs(sig, pairs).collect()}
    assert got == {(1, 4): 1.0, (2, 6): 0.0}


def test_invariance_to_rows_and_partitions(postings):
    p = SketchParams(64, 8, split="2u")
    want = table(S.sketch(postings, p))
    assert table(S.sketch(postings.repartition(7).orderBy(F.rand(3)), p)) == want
    assert table(S.sketch(postings.union(postings), p)) == want


def test_merge_of_minima(postings):
    p = SketchParams(64, 8, fill="none")
    halves = [A.bin_minima(S.binned(postings.where(F.col("elem") % 2 == k), p)) for k in (0, 1)]
    key = lambda df: sorted(map(tuple, df.select("set_id", "bin", "v").collect()))
    assert key(A.merge_minima(*halves)) == key(A.bin_minima(S.binned(postings, p)))


def test_unfilled_estimator_and_firstk(spark, postings):
    p = SketchParams(64, 8, fill="none")
    pairs = spark.createDataFrame([(1, 4), (1, 5)], "id1 long, id2 long")
    sig = table(S.sketch(postings, p))
    got = {(r.id1, r.id2): (r.hits, r.m) for r in E.estimate_unfilled(S.sketch(postings, p), pairs).collect()}
    for a, b in got:
        both = [(x, y) for x, y in zip(sig[a], sig[b], strict=True) if x is not None or y is not None]
        assert got[a, b] == (sum(x == y for x, y in both), len(both))
    first = E.estimate_firstk(S.firstk_sketch(postings, SketchParams(64, 16)), pairs, 16).collect()
    assert {(r.id1, r.id2): r.j_hat for r in first} == {(1, 4): 1.0, (1, 5): 0.0}


def test_likelihood_is_exact_when_sketches_hold_everything(spark):
    rng = random.Random(5)
    a, b = set(rng.sample(range(256), 60)), set(rng.sample(range(256), 80))
    post = spark.createDataFrame([(1, x) for x in a] + [(2, x) for x in b], "set_id long, elem long")
    sizes = post.groupBy("set_id").agg(F.count("*").alias("n"))
    pairs = spark.createDataFrame([(1, 2)], "id1 long, id2 long")
    r = E.mle_two_way(S.firstk_sketch(post, SketchParams(256, 128)), pairs, sizes, SketchParams(256, 128)).first()
    assert abs(r.a_hat - len(a & b)) < 1e-3


def test_permutation_is_md5_order(spark):
    got = {r.pos: r["rank"] for r in permutation(spark, "pi", 50, (9,)).collect()}
    assert [got[i] for i in range(50)] == list(md5_permutation("pi", 50, 9))
    assert hashlib.md5(b"9:pi:0").hexdigest()


@pytest.mark.parametrize("kind", ["mix", "feistel"])
def test_bijections(spark, kind):
    from rotahash.operators.permutations import feistel_keys, mix_constants

    x = F.col("id")
    q = hashes.mix_bijection(x, mix_constants(3, 10), 10) if kind == "mix" else hashes.feistel(x, feistel_keys(3), 10)
    rows = sorted(r.q for r in spark.range(1024).select(q.alias("q")).collect())
    assert rows == list(range(1024))


def test_mulmod_is_exact(spark):
    p = next_prime(1 << 40)
    a = (1 << 40) - 3
    got = spark.range(100).select("id", hashes.mulmod(F.lit(a), F.col("id") + (1 << 39), p).alias("q")).collect()
    assert all(r.q == a * (r.id + (1 << 39)) % p for r in got)


def test_parameters():
    with pytest.raises(ValueError):
        SketchParams(10, 4)
    assert SketchParams.padded(10, 4).D == 12
    with pytest.warns(UserWarning):
        SketchParams(64, 16)
    p = SketchParams(1 << 40, 1 << 10, split="2u")
    assert p.budget("rotbin") == 1 << 30
    turns = lambda shift, K, d: {(SketchParams(K * d, K, M=K * d, shift=shift).rotation(K * r)) % d for r in range(d)}
    assert len(turns("lcm", 4, 8)) == 8 and len(turns("per_round", 4, 8)) == 8
    with pytest.warns(UserWarning):
        assert len(turns("plain", 4, 8)) == 2


def test_jaccard_join_is_exact(spark):
    rng = random.Random(2)
    sets = {}
    for i in range(60):
        base = sets[rng.randrange(i)] if i and rng.random() < 0.5 else set(rng.sample(range(200), 20))
        sets[i] = set(rng.sample(sorted(base), max(1, len(base) - rng.randrange(4)))) | set(rng.sample(range(200), rng.randrange(3)))
    post = spark.createDataFrame([(i, e) for i, s in sets.items() for e in s], "set_id long, elem long")
    want = {(i, j) for i in sets for j in sets if i < j and len(sets[i] & sets[j]) >= 0.6 * len(sets[i] | sets[j])}
    assert {(r.id1, r.id2) for r in A.jaccard_join(post, 0.6).collect()} == want


def test_star_links_keep_buckets_connected(spark):
    bands = spark.createDataFrame([(1, i, 0, "x") for i in range(30)], "seed int, set_id long, band int, key string")
    pairs = A.candidate_pairs(bands, max_bucket=10)
    assert pairs.count() == 29
    assert A.clusters(pairs).where("component = 0").count() == 30


def test_components_of_a_long_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (7, 7)], "id1 long, id2 long")
    got = {r.id: r.component for r in A.clusters(links).collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100}
    assert A.clusters(links.limit(0)).count() == 0


def test_nulls_and_empty_tables(spark):
    rows = spark.createDataFrame([(None, "a"), (1, None), (1, "a"), (1, "a")], "s long, e string")
    assert [tuple(r) for r in T.load_sets(rows, "s", "e").collect()] == [(1, "a")]
    texts = spark.createDataFrame([(1, None), (2, ""), (3, "one two"), (4, "a b c d e f")], "doc_id long, text string")
    assert {r.set_id for r in T.shingle_postings(texts, "doc_id", F.col("text")).collect()} == {4}
    empty = spark.createDataFrame([], "set_id long, elem long")
    assert S.sketch(empty, SketchParams(64, 8)).count() == 0


def test_plan_has_no_python_and_few_exchanges(spark, tiny):
    post = T.supplier_postings(T.load_table(spark, tiny, "lineitem"))
    plan = S.sketch(post, SketchParams(1 << 15, 64, split="2u"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan
    scan = T.load_table(spark, tiny, "documents").where("lang = 'en'").select("doc_id")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in scan and "ReadSchema: struct<doc_id:bigint,lang:string>" in scan


def test_long_permutations_rank_alike(spark, monkeypatch):
    from rotahash.operators import permutations

    monkeypatch.setattr(permutations, "RANKED_IN_ONE", 10)
    got = {r.pos: r["rank"] for r in permutation(spark, "pi", 500, (9, 10)).where("seed = 9").collect()}
    assert [got[i] for i in range(500)] == list(md5_permutation("pi", 500, 9))


def test_the_proposed_method_reads_and_deals_its_elements_once(spark, tiny):
    """The plan that ran: one scan, and exchanges of the elements, the occupied bins and the reads."""
    docs = T.load_table(spark, tiny, "documents")
    sig = S.rotbin_minhash(T.word_postings(docs, distinct=False), SketchParams(1 << 10, 16, split="2u"))
    sig.collect()
    plan = sig._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
    assert "ReusedExchange" in plan
    lines = [x for x in plan.splitlines() if "Exchange hashpartitioning" in x and "ReusedExchange" not in x]
    assert len(lines) == 3, plan
    assert sum("FileScan parquet" in x for x in plan.splitlines()) == 1


def test_donors_of_many_bins_agree_with_the_bit_set(spark, monkeypatch):
    rows = spark.createDataFrame([(s, (s * 7919 + e * 104729) % 4096) for s in range(40) for e in range(1 + s % 7)], "set_id long, elem long").distinct()
    for donor in ("uniform", "clockwise", "two_way"):
        p = SketchParams(4096, 128, donor=donor)
        monkeypatch.setattr(S, "BIT_BINS", 4096)
        one = sorted(map(tuple, S.rotbin_minhash(rows, p).collect()))
        monkeypatch.setattr(S, "BIT_BINS", 1)
        assert one == sorted(map(tuple, S.rotbin_minhash(rows, p).collect())) and len(one) == 40 * 128


@pytest.mark.parametrize("size", [5, 64, 1000, 2048])
def test_feistel_is_a_bijection_of_any_size(spark, size):
    from rotahash.operators.permutations import hashed

    p = SketchParams(size, 1)
    got = sorted(r.y for r in spark.range(size).withColumn("seed", F.lit(42)).select(hashed(F.col("id"), "feistel", p, size, "pi").alias("y")).collect())
    assert got == list(range(size))
