"""Overlaps counted by blocks of sets equal brute force, whatever the blocks are, and no row is made for a pair at an element."""

import random
from collections import Counter

import numpy as np
import pytest

from rotahash.operators import overlaps as V
from rotahash.plans import app_queries
from rotahash.plans.operator_queries import QUERIES


def test_small_pieces_count_the_same(monkeypatch):
    rng = np.random.default_rng(3)
    elem, at = rng.integers(0, 20, 900), rng.integers(0, 60, 900).astype(np.int32)
    sets = [set(elem[at == k].tolist()) for k in range(60)]
    want = {(a, b): len(sets[a] & sets[b]) for a in range(60) for b in range(a + 1, 60) if sets[a] & sets[b]}
    for counters, chunk in ((1 << 24, 1 << 22), (64, 50)):
        monkeypatch.setattr(V, "COUNTERS", counters)
        monkeypatch.setattr(V, "CHUNK", chunk)
        got = Counter()
        for block, ids, ends, own, size, many in V.dealt(elem, at, 7):
            for k, b in enumerate(block):
                i, j = ends[:k].sum(), many[:k].sum()
                for pair, times in V.counted(ids[i : i + ends[k]], own[j : j + many[k]], size[j : j + many[k]], int(b) * 7, 60):
                    got.update({(int(p) // 60 + int(b) * 7, int(p) % 60): int(t) for p, t in zip(pair, times, strict=True)})
        assert got == want


@pytest.mark.parametrize("counters", [1 << 24, 64])
def test_overlaps_equal_brute_force(spark, monkeypatch, counters):
    monkeypatch.setattr(V, "COUNTERS", counters)  # of the driver, so of the blocks
    rng = random.Random(5)
    sets = {s * 37 - 500: {rng.randrange(60) for _ in range(rng.randrange(1, 25))} | ({-7} if s % 2 else set()) for s in range(70)}
    rows = [(s, e) for s, x in sets.items() for e in x] * 2 + [(None, 3), (5, None)]
    post = spark.createDataFrame(rows, "set_id long, elem long").repartition(5)
    for tau in (0.0, 0.3):
        want = set()
        for a in sets:
            for b in sets:
                inter, uni = len(sets[a] & sets[b]), len(sets[a] | sets[b])
                if a < b and inter and inter >= tau * uni:
                    want.add((a, b, inter, uni))
        got = [tuple(r) for r in V.overlaps(post, tau).drop("hits").collect()]
        assert len(got) == len(want) and set(got) == want
    assert V.overlaps(post.where("false")).count() == 0


def test_similar_suppliers_joins_no_postings(spark, tiny):
    plan = app_queries.QUERIES["similar_suppliers"](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan


def test_sql_surface_equals_the_functions_of_pairs(spark, tiny):
    """The functions of SQL text, pair by pair, give what the counts give; and the query sends no set for a pair."""
    df = QUERIES["sql_surface"](spark, tiny)
    assert "Join" not in df._jdf.queryExecution().executedPlan().toString()
    got = sorted(map(tuple, df.collect()))
    want = spark.sql(
        """WITH sets AS (SELECT l_suppkey AS id, collect_set(l_partkey) AS e FROM rotahash_lines GROUP BY 1),
        sigs AS (SELECT id, e, rh_rotbin_sig(e) AS s FROM sets)
        SELECT a.id AS id1, b.id AS id2, round(rh_estimate(a.s, b.s), 6) AS j_hat, round(rh_jaccard(a.e, b.e), 6) AS j FROM sigs a JOIN sigs b ON a.id < b.id WHERE rh_jaccard(a.e, b.e) > 0"""
    )
    assert got == sorted(map(tuple, want.collect())) and got
