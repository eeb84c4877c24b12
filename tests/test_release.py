import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from worldfold.context import QueryContext, attack_bound
from worldfold.functions import lift as L
from worldfold.functions.release import Posterior, diversity_guard, gaussian, null_chance, release, release_sequential, rounded, simulate_attack, weighted_var
from worldfold.workloads.distributions import masks_of

CTX = QueryContext("k", 5, hash="md5")


def _vec(spark, values, n=1):
    return spark.range(n).select("id", F.array(*[F.lit(float(x)) if x is not None else F.lit(None).cast("double") for x in values]).alias("v"))


def test_variance_with_and_without_weights(spark):
    v = [float(i * i % 17) for i in range(64)]
    w = np.random.default_rng(0).random(64)
    w /= w.sum()
    a, b = _vec(spark, v).select(weighted_var("v"), weighted_var("v", w.tolist())).collect()[0]
    assert a == pytest.approx(np.var(v))
    assert b == pytest.approx((w * (np.array(v) - (w * v).sum()) ** 2).sum())


def test_noise_has_the_calibrated_variance_and_repeats(spark):
    v = [float(i) for i in range(64)]
    df = _vec(spark, v, 6000)
    one = [r[0] for r in df.select(release("v", CTX, "n", "id")).collect()]
    two = [r[0] for r in df.repartition(7).select("id", release("v", CTX, "n", "id").alias("y")).orderBy("id").select("y").collect()]
    assert one == two
    noise = np.array(one) - v[5]
    assert noise.var() == pytest.approx(np.var(v) / (2 * CTX.mi), rel=0.08) and abs(noise.mean()) < 6


def test_agreeing_worlds_get_no_noise(spark):
    assert _vec(spark, [7.0] * 64).select(release("v", CTX, "n", "id")).collect()[0][0] == 7.0


def test_null_worlds_count_as_zero_and_null_draw_frequency(spark):
    v = [None if j % 4 == 0 else 10.0 for j in range(64)]
    bits = sum(1 << j for j in range(63) if j % 4)
    df = _vec(spark, v, 4000).withColumn("t", F.lit(bits))
    got = [r[0] for r in df.select(release("v", CTX, "n", "id", touched="t")).collect()]
    share = sum(x is None for x in got) / len(got)
    assert share == pytest.approx((64 - bits.bit_count()) / 64, abs=0.03)
    assert df.select(null_chance("t")).first()[0] == (64 - bits.bit_count()) / 64
    other = [r[0] for r in df.select(release("v", CTX.but(secret_world=9), "n", "id", touched="t")).collect()]
    assert [x is None for x in got] == [x is None for x in other]  # nulls don't depend on the secret


def test_diversity_guard(spark):
    df = spark.createDataFrame([(0xFFFFFFFF, 100)], "t long, n long")
    with pytest.raises(Exception, match="single privacy unit"):
        df.select(diversity_guard(F.lit(1.0), "t", "n")).collect()
    few = spark.createDataFrame([(0xFFFFFFFF, 10), (-1, 1000)], "t long, n long")
    assert [r[0] for r in few.select(diversity_guard(F.lit(1.0), "t", "n")).collect()] == [1.0, 1.0]


def test_posterior_is_bayes():
    y = [np.arange(64.0), np.arange(64.0)[::-1] ** 1.5]
    p = Posterior(64, 11, 1 / 32, 0)
    want = np.full(64, 1 / 64)
    for v in y:
        mean = (want * v).sum()
        delta = (want * (v - mean) ** 2).sum() / (2 / 32)
        out = p.release(v, noise=0.3)
        assert out == pytest.approx(v[11] + 0.3 * math.sqrt(delta))
        want = want * np.exp(-((out - v) ** 2) / (2 * delta))
        want /= want.sum()
        assert p.weights == pytest.approx(want)
        assert p.weights.sum() == pytest.approx(1)


def test_sequential_release_is_a_fold_in_key_order(spark):
    df = spark.createDataFrame([(k, [float((k * j) % 13) for j in range(64)]) for k in (3, 1, 2)], "k int, v array<double>")
    got = {r["k"]: r["v"] for r in release_sequential(df, ["k"], ["v"], CTX).collect()}
    noise = {r["k"]: r["g"] for r in df.select("k", gaussian(CTX, "v", "k").alias("g")).collect()}
    p = Posterior(64, 5, CTX.mi)
    for k in (1, 2, 3):
        assert got[k] == pytest.approx(p.release(np.array([float((k * j) % 13) for j in range(64)]), noise[k]))


def test_sequential_release_goes_on_from_an_earlier_posterior_and_skips_nulls(spark):
    def rows(keys):
        return spark.createDataFrame([(k, [float((k * j) % 13) for j in range(64)], 0 if k == 2 else -1) for k in keys], "k int, v array<double>, t long")

    whole = release_sequential(rows((1, 2, 3, 4)), ["k"], ["v"], CTX, touched={"v": "t"}).orderBy("k").collect()
    first = release_sequential(rows((1, 2)), ["k"], ["v"], CTX, touched={"v": "t"}, carry=True).collect()
    left = max((r["__place"], r["__posterior"]) for r in first if r["__posterior"])[1]
    rest = release_sequential(rows((3, 4)), ["k"], ["v"], CTX, touched={"v": "t"}, start=left).orderBy("k").collect()
    assert whole[1]["v"] is None  # no world was reached
    assert [r["v"] for r in whole[2:]] == pytest.approx([r["v"] for r in rest])


def test_attack_stays_under_its_bound():
    masks = np.unpackbits(masks_of(1).view(np.uint8), bitorder="little")
    vectors = np.array([np.random.default_rng(1).normal(100, 10, 64) + 20 * masks])
    for mi in (1 / 4, 1 / 32):
        s = simulate_attack(vectors, masks, mi, 1500)
        assert s <= attack_bound(mi) + 0.03 and s > 0.5


def test_rounding_is_post_processing(spark):
    r = spark.range(1).select(rounded(F.lit(-3.6), "bigint"), rounded(F.lit(-3.6), "bigint", clamp=True)).collect()[0]
    assert tuple(r) == (-4, 0)


def test_lift_equals_a_loop(spark):
    a, b = [float(j) for j in range(64)], [float(j % 5) for j in range(64)]
    df = spark.range(1).select(F.array(*map(F.lit, a)).alias("a"), F.array(*map(F.lit, b)).alias("b"), F.lit(3.0).alias("c"))
    got = df.select(L.lift(lambda x, y: F.try_divide(x * F.col("c"), y), "a", "b")).collect()[0][0]
    assert got == [None if y == 0 else x * 3 / y for x, y in zip(a, b, strict=True)]
    three = df.select(L.lift(lambda x, y, z: x + y - z, "a", "b", "a")).collect()[0][0]
    assert three == b


@pytest.mark.parametrize("op", list(L.OPS))
def test_mask_forms_agree_and_only_clear_bits(spark, op):
    df = spark.createDataFrame([(int(m), float(i % 7), [float((i + j) % 7) if j % 9 else None for j in range(64)]) for i, m in enumerate(masks_of(40))], "m long, v double, w array<double>")
    flags = F.transform("w", lambda x: L.OPS[op](F.col("v"), x))
    rows = df.select("m", L.mask_cmp("m", "v", op, "w").alias("a"), L.mask_and("m", flags).alias("b")).collect()
    assert all(r["a"] == r["b"] and r["a"] & ~r["m"] == 0 for r in rows)


def test_coin_keeps_the_share(spark):
    df = spark.range(4000).select("id", F.array(*[F.lit(j < 16) for j in range(64)]).alias("f"))
    kept = df.where(L.coin_filter("f", CTX, "id"))
    n = kept.count()
    assert n == pytest.approx(1000, abs=90) and n == kept.count()
