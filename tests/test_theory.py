"""Exact laws against listing, sums to one, and the order of the variances."""

from fractions import Fraction

import pytest
from pyspark.sql import functions as F

from rotahash.operators import estimates as E
from rotahash.operators import sketches as S
from rotahash.operators import theory as t
from rotahash.params import SketchParams
from rotahash.sources import tables as T


@pytest.mark.parametrize(("d", "a", "f"), [(5, 1, 2), (5, 1, 3), (5, 2, 3), (5, 2, 4), (5, 0, 3), (5, 3, 3), (5, 2, 5), (6, 2, 4)])
def test_pair_collision_equals_listing(d, a, f):
    assert t.pair_collision(a, f, d) == t.pair_collision_brute(a, f, d)


def test_fixed_values():
    # fixed values: of the laws at small sizes
    assert round(float(t.pair_collision(1, 3, 6)), 6) == 0.081111
    assert round(float(t.var_fresh(1024, 32, 12, 6)), 7) == 0.0072836
    assert round(float(t.var_rotating(1024, 32, 12, 6)), 7) == 0.0072343


def test_laws_sum_to_one():
    assert sum(t.empty_bins_pmf(256, 16, 10)) == 1
    for m in (3, 7):
        assert sum(t.bin_law(64, 8, 7, 3, m).values()) == 1


def test_pair_collision_is_below_independence():
    for d in (5, 7):
        for f in range(2, d):
            for a in range(1, f):
                assert t.pair_collision(a, f, d) < Fraction(a, f) ** 2


def test_order_of_variances():
    for D, K, f, a in ((256, 16, 10, 5), (256, 16, 20, 4), (1024, 32, 12, 6)):
        assert t.var_rotating(D, K, f, a) < t.var_fresh(D, K, f, a)
    assert t.variance_ratio(256, 16, 10, 5) > 1
    assert t.var_rot(64, 8, 12, 6) < t.var_standard(8, 12, 6)
    assert abs(t.pair_collision_mc(2, 4, 7, 4000) - float(t.pair_collision(2, 4, 7))) < 0.03


def errors(spark, kinds, f, tenths):
    """Mean squared error and bias of each kind over its seeds."""
    post = T.synthetic_pairs(spark, f, (tenths,))
    pairs = spark.createDataFrame([(2 * tenths, 2 * tenths + 1)], "id1 long, id2 long")
    truth = E.exact_jaccard(post, pairs)
    return {k: E.error_profile(E.estimate_pairs(make(post, p), pairs), truth).first() for k, (make, p) in kinds.items()}


def test_extra_rotation_removes_repeats(spark):
    """Beyond K*M = D the extra shift keeps the rotations of a bin apart."""
    seeds = tuple(range(150))
    with pytest.warns(UserWarning):
        plain = SketchParams(256, 16, M=64, seeds=seeds)
    got = errors(spark, {"plain": (S.sketch, plain), "lcm": (S.sketch, plain.with_(shift="lcm"))}, 40, 5)
    assert got["lcm"].mse * 1.7 < got["plain"].mse


def test_sparse_fillings_are_ordered_and_unbiased(spark):
    p = SketchParams(1024, 32, seeds=tuple(range(200)))
    kinds = {"clockwise": p.with_(fill="copy", donor="clockwise"), "copy": p.with_(fill="copy"), "fresh": p.with_(fill="fresh"), "rotbin": p, "rotbin_2u": p.with_(split="2u")}
    got = errors(spark, {k: (S.sketch, q) for k, q in kinds.items()}, 12, 5)
    assert got["clockwise"].mse > got["copy"].mse > got["rotbin"].mse
    for r in got.values():
        assert abs(r.mse - r.variance - r.bias**2) < 2e-5
        assert abs(r.bias) < 4 * (r.variance / r.n) ** 0.5 + 1e-6
    law = float(t.var_rotating(1024, 32, 12, 6))
    assert abs(got["rotbin"].mse / law - 1) < 0.4


def test_merged_positions_bias_upward(spark):
    """Hashing into a range that is not wide merges elements and inflates similarity; the bijective mixer does not."""
    p = SketchParams(1024, 32, seeds=tuple(range(60)))
    got = errors(spark, {"4u": (S.sketch, p.with_(split="4u")), "mix": (S.sketch, p.with_(split="mix"))}, 200, 5)
    assert got["4u"].bias > 0.015 > abs(got["mix"].bias)


def test_observed_empty_bins_follow_the_law(spark):
    p = SketchParams(256, 16, seeds=tuple(range(300)))
    post = spark.range(10).select(F.lit(1).alias("set_id"), F.col("id").alias("elem"))
    rows = S.binned(post, p).groupBy("seed").agg((F.lit(16) - F.count_distinct("bin")).alias("e")).collect()
    mean = sum(r.e for r in rows) / len(rows)
    want = float(sum(j * x for j, x in enumerate(t.empty_bins_pmf(256, 16, 10))))
    assert abs(mean - want) < 0.25


def test_empty_bins_report_has_every_basket_size(spark, tmp_path):
    from rotahash.plans.sketch_queries import empty_pmf

    spark.range(1, 101).selectExpr("id p_partkey").write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame([(1, k) for k in range(1, 4)] + [(2, k) for k in range(1, 31)], "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert sorted((r.f, r.sets) for r in empty_pmf(spark, str(tmp_path)).collect()) == [(3, 1), (30, 1)]


def test_laws_of_bins_are_for_the_baskets_of_a_table(spark, tiny):
    from rotahash.plans.sketch_queries import QUERIES
    from rotahash.sources.tables import load_table

    orders = load_table(spark, tiny, "lineitem").select("l_orderkey").distinct().count()
    rows = QUERIES["bin_law"](spark, tiny).collect()
    kinds = {(r["f"], r["a"], r["m"]): r["sets"] for r in rows}
    assert sum(kinds.values()) == orders
    for kind in kinds:
        assert abs(sum(r["probability"] for r in rows if (r["f"], r["a"], r["m"]) == kind) - 1) < 1e-6
    rows = QUERIES["collision_laws"](spark, tiny).collect()
    assert {r["d"] for r in rows} == {4, 5} and all(abs(r["law"] - r["listed"]) < 1e-12 for r in rows)
    assert sum(r["bins"] * r["f"] for r in rows if r["d"] == 4) > orders
