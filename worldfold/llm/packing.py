"""Packing token pieces into fixed-length sequences: shortest pack first over the length histogram."""

from __future__ import annotations

import base64
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.llm.common import buckets_for, cut, documents, running, small_batches

LENGTH = 2048

class Encoder:
    """Byte-level BPE ids as little-endian 32-bit bytes, by the faster of two libraries that hold the same vocabulary."""

    def __init__(self, ranks_path: str | None = None, json_path: str | None = None):
        import public_tokenizers
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in open(ranks_path or public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb"))}
        self.fast = tiktoken.Encoding("words", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.json_path = json_path or public_tokenizers.path("byte_bpe_50k.json")
        self.full = None

    def __call__(self, text: str) -> bytes:
        if "<|endoftext|>" not in text:
            return np.array(self.fast.encode_ordinary(text), "<u4").tobytes()
        if self.full is None:  # the special token's string is one id, which only this library gives
            from tokenizers import Tokenizer

            self.full = Tokenizer.from_file(self.json_path)
        return np.array(self.full.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


@lru_cache(2)
def encoder(ranks_path: str | None = None, json_path: str | None = None) -> Encoder:
    return Encoder(ranks_path, json_path)


def pieces(docs: DataFrame, key: str = "doc_id", text: str = "text", length: int = LENGTH, end_id: int = 1, ranks_path: str | None = None, json_path: str | None = None, ids: bool = False) -> DataFrame:
    """A row a piece: a document's ids and the end id, cut every ``length`` ids. With ``ids`` the ids themselves, too."""
    schema = f"{key} long, start long, length long, ids_crc32 long, doc_tokens long" + (", ids array<int>" if ids else "")
    tail = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(ranks_path, json_path)
        for b in batches:
            rows: list[tuple] = []
            for k, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                raw = encode(t.as_py() or "") + tail
                n = len(raw) // 4
                for s in range(0, n, length):
                    p = raw[4 * s : 4 * (s + length)]
                    rows.append((k, s, len(p) // 4, zlib.crc32(p), n, *([np.frombuffer(p, "<i4").tolist()] if ids else [])))
            cols = list(zip(*rows, strict=True)) or [()] * (5 + ids)
            names = [c.split()[0] for c in schema.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if i < 5 else pa.list_(pa.int32())) for i, c in enumerate(cols)], names)

    return docs.select(F.col(key).cast("long").alias(key), F.col(text).alias("text")).mapInArrow(run, schema)


def patterns(histogram: dict[int, int], length: int = LENGTH) -> list[tuple[int, list[tuple[int, int]]]]:
    """Packing patterns as (number of packs, [(piece length, pieces a pack)]).

    Lengths are placed longest first, each into the emptiest packs that are there, as many at once as a pattern has
    packs; a pattern of which only some packs are used is divided. Packs too full for the length at hand are closed
    for it only: shorter lengths may still go there.
    """
    open_: dict[int, list[list]] = {}  # filled so far -> patterns, each [count, parts]
    for size in sorted((s for s, n in histogram.items() if n > 0), reverse=True):
        left = histogram[size]
        # emptiest first; packs that got a piece wait for the next round, when they are fuller
        while left:
            fits = sorted(f for f in open_ if f + size <= length and open_[f])
            if not fits:
                per = length // size
                whole, rest = divmod(left, per)
                for n, k in ((whole, per), (1 if rest else 0, rest)):
                    if n:
                        open_.setdefault(k * size, []).append([n, [(size, k)]])
                break
            f = fits[0]
            same = open_.pop(f)
            after = open_.setdefault(f + size, [])
            while same and left:
                count, parts = same.pop()
                used = min(count, left)
                if used < count:
                    same.append([count - used, parts])
                last = parts[-1]
                after.append([used, [*parts[:-1], (size, last[1] + 1)] if last[0] == size else [*parts, (size, 1)]])
                left -= used
            if same:
                open_[f] = same
    merged: Counter = Counter()
    for same in open_.values():
        for count, parts in same:
            merged[tuple(parts)] += count
    return [(n, list(parts)) for parts, n in sorted(merged.items(), reverse=True)]


def places(found: list[tuple[int, list[tuple[int, int]]]]) -> dict[int, tuple[np.ndarray, ...]]:
    """For each length: where ranks begin, packs of the pattern, its first sequence and the first piece's offset."""
    table: dict[int, list[tuple[int, int, int, int]]] = {}
    used: Counter = Counter()
    sequence = 0
    for count, parts in found:
        at = 0
        for size, k in parts:
            table.setdefault(size, []).append((used[size], count, sequence, at))
            used[size] += count * k
            at += size * k
        sequence += count
    return {s: tuple(np.array(c, np.int64) for c in zip(*rows, strict=True)) for s, rows in table.items()}


def locate(table: dict[int, tuple[np.ndarray, ...]], size: int, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sequence and offset of the pieces of one length by their ranks."""
    begin, count, first, at = table[size]
    i = np.searchsorted(begin, rank, side="right") - 1
    within = rank - begin[i]
    return first[i] + within % count[i], at[i] + within // count[i] * size


def pack(docs: DataFrame, key: str = "doc_id", text: str = "text", length: int = LENGTH, end_id: int = 1, **paths) -> DataFrame:
    """A row a piece: key, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    The histogram has at most ``length`` lengths and the patterns made of it are as few, whatever the corpus; they go to
    the executors as a table of that bounded size. Pieces join it by their rank among those of their length, which is
    numbered by buckets, so that a length that most pieces have is numbered by many tasks.

    Null or empty text is just the end id. Repeated rows are packed each. An empty table gives no rows. Other columns are
    ignored.
    """
    spark = docs.sparkSession
    with small_batches(spark):
        p = cut(pieces(docs, key, text, length, end_id, **paths))
    histogram = {r["length"]: r["n"] for r in p.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `length` rows
    table = spark.sparkContext.broadcast(places(patterns(histogram, length)))
    n = buckets_for(sum(histogram.values()))
    ranked = running(p.withColumn("__bucket", F.pmod(F.xxhash64(key, "start"), F.lit(n))), ["length"], "__bucket", [F.col(key), F.col("start"), F.col("ids_crc32")], F.lit(1), "__rank").drop("__bucket")

    @F.pandas_udf("sequence_id long, offset long")
    def place(size: pd.Series, rank: pd.Series) -> pd.DataFrame:
        out = np.zeros((2, len(size)), np.int64)
        for s in size.unique():
            at = np.flatnonzero(size == s)
            out[:, at] = locate(table.value, int(s), rank.to_numpy()[at])
        return pd.DataFrame({"sequence_id": out[0], "offset": out[1]})

    return ranked.withColumn("__at", place("length", "__rank")).select(key, "start", "length", "ids_crc32", "doc_tokens", "__at.sequence_id", "__at.offset")


def padding(packed: DataFrame, length: int = LENGTH) -> DataFrame:
    """One row: sequences, tokens and the share of padding; a sequence filled to a power of two needs none."""
    per = packed.groupBy("sequence_id").agg(F.sum("length").alias("filled"))
    even = F.expr("bit_count(filled) = 1")
    per = per.withColumn("padded", F.when(even, F.col("filled")).otherwise(length))
    return per.agg(F.count("*").alias("sequences"), F.sum("filled").alias("tokens"), (1 - F.sum("filled") / F.sum("padded")).alias("padding"))


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(documents(spark, sf_dir))
