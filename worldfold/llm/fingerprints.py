"""One-permutation MinHash fingerprints with optimal densification and b-bit storage.

All shingles of a text are hashed once. The high bits of a hash choose a bin, the rest compete for the bin's minimum.
Bins that got nothing borrow from a bin that a universal hash of (bin, attempt) names, tried until it is a filled one.
The low bits of each bin are packed; agreement by chance is taken out of the likeness.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.llm.common import documents

BINS, BITS, WORDS = 256, 4, 5
#: Bytes of texts in a key range, and the most ranges (their limits are part of the plan); beyond it ranges grow, and a task
#: still holds but a batch of texts at a time.
RANGE_BYTES, MOST_RANGES = 256 << 20, 16_384
U = np.uint64


def _mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finalizer: every input bit reaches every output bit."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


@lru_cache(2)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number modulo 2**64 and of its inverse."""
    base = 0x9E3779B97F4A7C15
    up, down = np.full(n, base, U), np.full(n, pow(base, -1, 2**64), U)
    up[0] = down[0] = 1
    return np.cumprod(up, dtype=U), np.cumprod(down, dtype=U)


_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Bytes that are hashed together.
_STEP = 1 << 20


def shingle_hashes(data: np.ndarray, ends: np.ndarray, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the word shingles of texts laid end to end, and the text each one belongs to.

    A text with fewer words is one shingle of them all; one without words has none.
    """
    data = _LOWER[data]
    gap = _SPACE[data]
    first = np.concatenate(([0], ends[:-1])).astype(np.int64)
    filled = first[first < ends]
    before = np.ones(len(data), bool)
    before[1:] = gap[:-1]
    before[filled] = True
    begin = np.flatnonzero(before & ~gap)
    if not len(begin):
        return np.empty(0, U), np.empty(0, np.int64)
    after = np.ones(len(data), bool)
    after[:-1] = gap[1:]
    after[ends[first < ends] - 1] = True
    end = np.flatnonzero(after & ~gap) + 1
    word = np.empty(len(begin), U)
    at = 0
    while at < len(begin):  # by blocks of words, so that the 64-bit working arrays stay small for any text
        to = max(at + 1, int(np.searchsorted(end, begin[at] + _STEP, side="right")))
        s, e = begin[at:to] - begin[at], end[at:to] - begin[at]
        block = data[begin[at] : end[to - 1]]
        up, down = _powers(max(_STEP, 1 << (len(block) - 1).bit_length()))
        # a word's polynomial hash is a difference of prefix sums, moved to the word's own start
        sums = np.zeros(len(block) + 1, U)
        np.cumsum((block.astype(U) + U(1)) * up[: len(block)], dtype=U, out=sums[1:])
        word[at:to] = _mix((sums[e] - sums[s]) * down[s] + (e - s).astype(U))
        at = to
    text = np.searchsorted(ends, begin, side="right")
    count = np.bincount(text, minlength=len(ends))
    n = len(word) - words + 1
    out, owner = [], []
    if n > 0:
        h = word[:n].copy()
        for k in range(1, words):
            h = h * U(0x9FB21C651E98DF25) + word[k : k + n]
        whole = text[:n] == text[words - 1 :]
        out.append(_mix(h[whole]))
        owner.append(text[:n][whole])
    at = np.concatenate(([0], np.cumsum(count)))
    for t in np.flatnonzero((count > 0) & (count < words)):
        h = word[at[t] : at[t] + 1]
        for i in range(at[t] + 1, at[t + 1]):
            h = h * U(0x9FB21C651E98DF25) + word[i : i + 1]
        out.append(_mix(h))
        owner.append(np.array([t]))
    return np.concatenate(out), np.concatenate(owner)


def densify(least: np.ndarray, empty: np.ndarray) -> np.ndarray:
    """Fills empty bins, row by row; rows without any filled bin are left."""
    bins = least.shape[1]
    row, bin_ = np.nonzero(empty & ~empty.all(1)[:, None])
    attempt = 0
    while len(row):
        attempt += 1
        to = (_mix(np.arange(bins, dtype=U) * U(0xD6E8FEB86659FD93) + U(attempt)) >> U(32)).astype(np.int64) % bins
        to = to[bin_]
        found = ~empty[row, to]
        least[row[found], bin_[found]] = least[row[found], to[found]]
        row, bin_ = row[~found], bin_[~found]
    return least


def sketch(texts: list[bytes], bins: int = BINS, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Bin minima of each text (rows x bins) and which texts have words at all."""
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    data = np.frombuffer(b"".join(texts), np.uint8)
    h, owner = shingle_hashes(data, np.cumsum(lengths), words)
    least = np.full(len(texts) * bins, np.iinfo(U).max, U)
    shift = U(64 - (bins - 1).bit_length())
    np.minimum.at(least, owner * bins + (h >> shift).astype(np.int64), h & ((U(1) << shift) - U(1)))
    least = least.reshape(-1, bins)
    empty = least == np.iinfo(U).max
    return densify(least, empty), ~empty.all(1)


def pack(least: np.ndarray, some: np.ndarray, bits: int = BITS) -> np.ndarray:
    """The low bits of each bin, mixed with the bin's number first; texts without words are all zero.

    A borrowed minimum stands in several bins: with the number its low bits agree by chance in each on its own.
    """
    at = np.arange(least.shape[1], dtype=U) * U(0xA24BAED4963EE407)
    low = (_mix(least + at) & U((1 << bits) - 1)).astype(np.uint8)
    low[~some] = 0
    return low


def hex_of(low: np.ndarray, bits: int = BITS) -> list[str]:
    lanes = np.unpackbits(low[:, :, None], axis=2)[:, :, 8 - bits :].reshape(len(low), -1)
    return [x.tobytes().hex() for x in np.packbits(lanes, axis=1)]


def likeness(a: np.ndarray, b: np.ndarray, some_a: np.ndarray, some_b: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Estimated Jaccard likeness of rows: the share of equal bins, without the share that is equal by chance.

    Two texts without words are alike (1); one without words is unlike any with words (0).
    """
    chance = 2.0**-bits
    j = np.clip(((a == b).mean(1) - chance) / (1 - chance), 0, 1)
    return np.where(some_a & some_b, j, (some_a == some_b).astype(float))


def fingerprint(df: DataFrame, text: str = "text", out: str = "fingerprint") -> DataFrame:
    """Adds the packed fingerprint of ``text`` as hex. Null text counts as empty; texts without words get zeros."""
    schema = df.drop(out).schema.add(out, "string")
    kept = [f.name for f in schema.fields if f.name != out]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [(x or "").encode() for x in b.column(b.schema.get_field_index(text)).to_pylist()]
            fp = [f for part in _parts(texts) for f in hex_of(pack(*sketch(part)))]
            yield pa.RecordBatch.from_arrays([*[b.column(b.schema.get_field_index(c)) for c in kept], pa.array(fp, pa.string())], [*kept, out])

    return df.mapInArrow(run, schema)


def _parts(texts: list[bytes]) -> Iterator[list[bytes]]:
    """Consecutive texts of about a megabyte together; a longer one stands alone."""
    part: list[bytes] = []
    size = 0
    for t in texts:
        if part and size + len(t) > _STEP:
            yield part
            part, size = [], 0
        part.append(t)
        size += len(t)
    if part:
        yield part


def ranged(docs: DataFrame, key: str, parts: int) -> DataFrame:
    """Key ranges in descending key order, each followed by the row that comes next after its last.

    Adds ``__part`` (0 for the highest keys) and ``__extra`` (true for that following row). Splitters are at most
    ``parts`` quantiles of the keys; the table of range heads is no longer.
    """
    spark = docs.sparkSession
    share = [i / parts for i in range(1, parts)]
    at = docs.agg(F.percentile_approx(key, F.array(*map(F.lit, share)), 10_000)).first()[0] if share else None
    cuts = sorted(set(at or []), reverse=True)
    step = max(1, int(len(cuts) ** 0.5))
    coarse, fine = cuts[step - 1 :: step], [cuts[i : i + step] for i in range(0, len(cuts), step)]

    def below(col: Column, values: list[int]) -> Column:
        return F.size(F.filter(F.array(*[F.lit(v).cast("long") for v in values]), lambda v: v >= col)) if values else F.lit(0)

    k = F.col(key)
    block = below(k, coarse)
    part = F.coalesce(block * step + (F.element_at(F.array(*[below(k, f) for f in [*fine, []]]), (block + 1).cast("int")) if fine else F.lit(0)), F.lit(len(cuts)))
    rows = docs.withColumn("__part", part.cast("int"))
    heads = rows.groupBy("__part").agg(F.max(key).alias("__head")).collect()  # one row a range
    heads = sorted((h[0], h[1]) for h in heads)
    if not heads:
        return rows.withColumn("__extra", F.lit(False))
    follows = {p: heads[i - 1][0] for i, (p, _) in enumerate(heads)}  # range -> the range it is the next of (the first: the last)
    table = spark.createDataFrame([(p, h, follows[p]) for p, h in heads], "__part int, __head long, __to int")
    first = rows.join(F.broadcast(table), "__part").where(k.eqNullSafe(F.col("__head"))).groupBy("__part", "__to").agg(F.min_by(F.struct(*docs.columns), F.xxhash64("text")).alias("r"))
    first = first.select("r.*", F.col("__to").alias("__part"), F.lit(True).alias("__extra"))
    return rows.withColumn("__extra", F.lit(False)).unionByName(first)


def edited(text: str, other: str) -> str:
    """``text`` with its last third of code points replaced by as many first ones of ``other``."""
    n = len(text) // 3
    return text[: len(text) - n] + other[:n]


def compare_with_next(docs: DataFrame, key: str = "doc_id", text: str = "text", parts: int | None = None) -> DataFrame:
    """Fingerprints of each text and its edited text, and how like they and the next document's are.

    The next document is the one with the next lower key; equal keys are ordered by a hash of the text, null keys come
    last, and after the last comes the first. The texts are dealt out once, by key range; each task walks its range in
    order and sees one row beyond it. A document alone is its own next one. Null text is empty. Keys are cast to long.
    There are as many ranges as the texts have RANGE_BYTES (the session's shuffle partitions at least).
    """
    if parts is None:
        spark = docs.sparkSession
        size = docs.agg(F.sum(F.octet_length(text))).first()[0] or 0
        parts = max(1, min(MOST_RANGES, max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // RANGE_BYTES))))
    rows = ranged(docs.select(F.col(key).cast("long").alias("key"), F.coalesce(text, F.lit("")).alias("text")), "key", parts)
    rows = rows.repartition(parts, "__part").sortWithinPartitions("__part", "__extra", F.col("key").desc_nulls_last(), F.xxhash64("text"))
    schema = f"{key} long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left: tuple[list, list, list] = ([], [], [])

        def some(keys: list, parts_: list, texts: list[str]) -> pa.RecordBatch | None:
            """Rows whose next one is here and in the same range."""
            mine = [i for i in range(len(keys) - 1) if parts_[i] == parts_[i + 1]]
            if not mine:
                return None
            raw = [t.encode() for t in texts]
            low, full = sketch(raw)
            low = pack(low, full)
            new = [edited(texts[i], texts[i + 1]).encode() for i in mine]
            low2, full2 = sketch(new)
            low2 = pack(low2, full2)
            m = np.array(mine)
            cols = [[keys[i] for i in mine], [len(texts[i]) for i in mine], [hashlib.sha256(x).hexdigest() for x in new], hex_of(low[m]), hex_of(low2), likeness(low[m], low2, full[m], full2), likeness(low[m], low[m + 1], full[m], full[m + 1])]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()), strict=True)], names)

        for b in batches:
            for i in range(b.num_rows):
                for have, c in zip(left, ("key", "__part", "text"), strict=True):
                    have.append(b.column(b.schema.get_field_index(c))[i].as_py())
                if len(left[0]) > 1 and (len(left[0]) > 2000 or sum(map(len, left[2][-1:])) > _STEP or (len(left[0]) & 63) == 0 and sum(map(len, left[2])) > _STEP):
                    if (out := some(*left)) is not None:
                        yield out
                    left = tuple(x[-1:] for x in left)
        if (out := some(*left)) is not None:
            yield out

    return rows.mapInArrow(run, schema)


def op2_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare_with_next(documents(spark, sf_dir))
