import numpy as np
import pytest
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions.masks import in_world, world_mask

CTX = QueryContext("k", 3, hash="md5")


def _masks(spark, n=400, **changes):
    ctx = CTX.but(**changes)
    return np.array([r[0] for r in spark.range(n).select(world_mask("id", ctx=ctx)).collect()])


@pytest.mark.parametrize("balance", ["complement", "exact", "repair"])
@pytest.mark.parametrize("hash_", ["md5", "xxhash64"])
def test_balanced_masks_have_half_of_the_worlds(spark, balance, hash_):
    m = _masks(spark, balance=balance, hash=hash_).astype(np.int64)
    assert set(np.bitwise_count(m.view(np.uint64)).tolist()) == {32}


def test_raw_masks_vary_and_average_to_half(spark):
    c = np.bitwise_count(_masks(spark, 2000, balance="none").view(np.uint64))
    assert len(set(c.tolist())) > 5 and abs(c.mean() - 32) < 0.5


def test_bits_are_independent_but_for_complements(spark):
    m = _masks(spark, 3000)
    b = np.unpackbits(m.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(float)
    c = np.corrcoef(b.T)
    assert all(c[j, j + 32] == pytest.approx(-1) for j in range(32))
    off = c[:32, :32][~np.eye(32, dtype=bool)]
    assert np.abs(off).max() < 0.12


def test_new_key_changes_half_of_the_bits(spark):
    a, b = _masks(spark, 500), _masks(spark, 500, key="other")
    assert abs(np.bitwise_count((a ^ b).view(np.uint64)).mean() - 32) < 1.5


def test_null_keys_have_no_mask_and_composites_differ(spark):
    df = spark.createDataFrame([(1, 2), (1, 3), (None, 2)], "a int, b int")
    got = [r[0] for r in df.select(world_mask("a", "b", ctx=CTX)).collect()]
    assert got[2] is None and got[0] != got[1]


def test_wide_masks(spark):
    df = spark.range(50).select(world_mask("id", ctx=CTX.but(worlds=128)).alias("m"))
    assert df.select(F.size("m")).distinct().collect()[0][0] == 2
    n = df.select(sum(in_world("m", j, 128).cast("int") for j in range(128)).alias("n")).distinct().collect()
    assert [r[0] for r in n] == [64]
