"""Which worlds a privacy unit is in: a keyed hash whose bits are worlds."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from worldfold.context import QueryContext

LOW32 = 0xFFFFFFFF


def key_text(*cols: Column | str, key: str) -> Column:
    parts = [F.col(c) if isinstance(c, str) else c for c in cols]
    return F.concat(F.lit(f"{key}:"), F.concat_ws("|", *[p.cast("string") for p in parts]))


def _hash(cols, ctx: QueryContext, word: int) -> Column:
    if ctx.hash == "xxhash64":
        return F.xxhash64(*cols, F.lit(f"{ctx.key}#{word}"))
    if ctx.hash != "md5":
        raise ValueError(f"unknown hash {ctx.hash}")
    return F.conv(F.substring(F.md5(key_text(*cols, key=ctx.key)), 1 + 16 * word, 16), 16, -10).cast("long")


def world_mask(*cols: Column | str, ctx: QueryContext) -> Column:
    """Membership of the unit named by ``cols``: a long of 64 bits, or two of them in an array for 128 worlds.

    Null key parts make a null mask: such rows belong to no unit. Balance: "none" leaves the bits to chance,
    "complement" turns the low half over into the high half (exactly half are set, one operation), "exact" draws
    uniformly among all halves (costly: do it on the unit table), "repair" flips hash-chosen surplus bits until half are.
    """
    parts = [F.col(c) if isinstance(c, str) else c for c in cols]
    words = [_balanced(parts, ctx, w) for w in range(ctx.worlds // 64)]
    some = parts[0].isNotNull()
    for p in parts[1:]:
        some = some & p.isNotNull()
    return F.when(some, words[0] if len(words) == 1 else F.array(*words))


def _balanced(parts, ctx: QueryContext, word: int) -> Column:
    h = _hash(parts, ctx, word)
    if ctx.balance == "none":
        return h
    if ctx.balance == "complement":
        return h.bitwiseAND(F.lit(LOW32)).bitwiseOR(F.shiftleft(F.bitwise_not(h).bitwiseAND(F.lit(LOW32)), 32))
    draw = lambda j: F.struct(F.xxhash64(*parts, F.lit(f"{ctx.key}#{word}"), j).alias("h"), j.alias("j"))
    order = F.transform(F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(63)), draw)), lambda x: x["j"])
    bit = lambda j: F.call_function("shiftleft", F.lit(1).cast("long"), j)
    if ctx.balance == "exact":
        return F.aggregate(F.slice(order, 1, 32), F.lit(0).cast("long"), lambda a, j: a.bitwiseOR(bit(j)))
    if ctx.balance == "repair":
        surplus = F.bit_count(h) - 32
        set_ = F.filter(order, lambda j: h.bitwiseAND(bit(j)) != 0)
        clear = F.filter(order, lambda j: h.bitwiseAND(bit(j)) == 0)
        flips = F.when(surplus >= 0, F.slice(set_, F.lit(1), surplus)).otherwise(F.slice(clear, F.lit(1), -surplus))
        return F.aggregate(flips, h, lambda a, j: a.bitwiseXOR(bit(j)))
    raise ValueError(f"unknown balance {ctx.balance}")


def in_world(mask: Column | str, j: int, worlds: int = 64) -> Column:
    """Whether the mask has world j."""
    m = F.col(mask) if isinstance(mask, str) else mask
    word = m if worlds == 64 else F.element_at(m, j // 64 + 1)
    return F.call_function("getbit", word, F.lit(j % 64)) == 1


def worlds_of(mask: Column | str) -> Column:
    """The numbers of the mask's worlds, for ``explode`` (64 worlds)."""
    m = F.col(mask) if isinstance(mask, str) else mask
    return F.filter(F.sequence(F.lit(0), F.lit(63)), lambda j: F.call_function("getbit", m, j) == 1)


def mia_prior(units: DataFrame, mask: str = "mask") -> DataFrame:
    """Per unit: the share of worlds that has it, which is an attacker's chance before any release (64 worlds)."""
    return units.withColumn("prior", F.bit_count(mask) / F.lit(64.0))


# ---- the same masks in DuckDB, for tests that compare engines

def duckdb_hash(pk: str, key: str) -> str:
    return f"CAST('0x' || substr(md5('{key}:' || CAST({pk} AS VARCHAR)), 1, 16) AS UBIGINT)"


def duckdb_in_world(pk: str, key: str, j: str = "j") -> str:
    """Membership in world j with complement balance."""
    return f"((({duckdb_hash(pk, key)} >> ({j} % 32)) & 1) = CASE WHEN {j} < 32 THEN 1 ELSE 0 END)"
