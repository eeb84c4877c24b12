"""SimHash near-duplicates by pivot distance tables.

A table of Hamming distances to many reference fingerprints (pivots) is computed once for each different value. Distances
are a metric, so no column of the table differs by more than the radius between two fingerprints that close. Values are
joined in ranges of one column: within a group those whose first column is in reach are candidates, pairs whose largest
coordinate difference over all columns exceeds the radius are discarded, and the survivors are verified.

One column's range holds over a third of all values, so an index stands in front, made of pivots too: the base (0) and
the base with one pair of bits turned over, for each of the 32 pairs. Two of these columns tell how far a fingerprint is
from the base within that pair (its coordinate). At most ``radius`` coordinates can differ between close fingerprints, so
when the coordinates are dealt into radius + 2 sections, two sections at least agree as a whole, and only values that
agree in two sections come into one group.

Work on fingerprints is done once for each different value, never for each document.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType

from worldfold.llm.common import cut, documents, small, small_batches

#: The index: the base pivot is 0, the others 3 << 2b; a section is a run of bit pairs.
PAIRS = 32
#: Fingerprints that agree in two sections and are compared with each other in one task; larger groups go by neighbours
#: (radius 1 and 2) or block by block.
GROUP = 2000
#: Reference fingerprints of the table that pairs are discarded by.
PIVOTS = 24


def references(n: int = PIVOTS) -> np.ndarray:
    """``n`` reference fingerprints: bits of a mixed counter, so each has about half of its bits set."""
    x = np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return _remix(x, 77)


def distance_table(bits: np.ndarray) -> np.ndarray:
    """values x PIVOTS: Hamming distances to the reference fingerprints."""
    return np.bitwise_count(bits[:, None] ^ references()[None, :]).astype(np.int8)


def simhash_of(text: bytes, words: int, seed: int = 42) -> int:
    """Bit j is set if over half of the shingles' hashes have it set; no words: 0."""
    w = text.lower().split()
    if not w:
        return 0
    joined = b" ".join(w)
    if len(w) <= words:
        return xxhash.xxh64_intdigest(joined, seed)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    h64, view = xxhash.xxh64_intdigest, memoryview(joined)
    total, n = np.zeros(64, np.int64), len(w) - words + 1
    for a in range(0, n, 1 << 16):  # long texts by parts
        b = min(n, a + (1 << 16))
        h = np.array([h64(view[s:e], seed) for s, e in zip(starts[a:b].tolist(), ends[a + words - 1 : b + words - 1].tolist(), strict=True)], "<u8")
        total += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(total * 2 > n, bitorder="little").view("<u8")[0])


def with_fingerprint(docs: DataFrame, keep: list[str], text: str = "text", words: int = 3, out: str = "fp") -> DataFrame:
    """``keep`` columns and the fingerprint of the whole text as a signed long. Null text counts as empty."""
    schema = docs.select(*keep).schema.add(out, "long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([simhash_of((x.as_py() or "").encode(), words) for x in b.column(0)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*b.columns[1:], pa.array(fp)], names=[*keep, out])

    return docs.select(F.col(text).alias("__text"), *keep).mapInArrow(run, schema)


def pivot_table(fps: DataFrame) -> DataFrame:
    """Adds ``base`` (distance to the base pivot) and ``pivots`` (to the 32 others) to a table of ``fp``."""
    others = F.array(*[F.bit_count(F.col("fp").bitwiseXOR(F.lit(_signed(3 << (2 * b))))) for b in range(PAIRS)])
    return fps.withColumn("base", F.bit_count("fp")).withColumn("pivots", others)


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def sections(radius: int) -> list[tuple[int, int]]:
    edges = [PAIRS * i // (radius + 2) for i in range(radius + 3)]
    return list(zip(edges[:-1], edges[1:], strict=True))


def links(fps: DataFrame, radius: int = 2, group: int = GROUP) -> DataFrame:
    """Links (a, b), a < b in signed order, that connect all different fingerprints within ``radius`` bits.

    Within a group that agrees in two sections only a spanning set of links is kept: what is connected is the same, and
    no group lists its pairs. A group of over ``group`` values is not compared in one task. Up to radius 2 each of its
    values is sent to all values one bit off: at radius 2 two values are close just if they share such a neighbour, where at
    most 65 can meet and are linked with the smallest one; at radius 1, just if one is the other's neighbour. At larger
    radii the group is dealt into blocks, and every block is held against every other. Radius 0 links nothing.
    """
    if not 0 <= radius <= 14:
        raise ValueError("radius must be from 0 to 14")
    if radius == 0:
        return fps.select(F.col("fp").alias("a"), F.col("fp").alias("b")).limit(0)
    coordinate = [((F.col("base") - F.element_at("pivots", b + 1) + 2) / 2).cast("int") for b in range(PAIRS)]
    table = pivot_table(fps)
    parts = sections(radius)

    def code(lo: int, hi: int):
        out = F.lit(0).cast("long")
        for b in range(lo, hi):
            out = out * 3 + coordinate[b]
        return out

    packed = table.select("fp", *[code(lo, hi).alias(f"s{i}") for i, (lo, hi) in enumerate(parts)])
    keys = F.array(*[F.struct(F.lit(n).alias("t"), F.col(f"s{i}").alias("x"), F.col(f"s{j}").alias("y")) for n, (i, j) in enumerate(combinations(range(len(parts)), 2))])
    dealt = packed.select("fp", F.explode(keys).alias("k")).select("fp", "k.*")
    sizes = dealt.groupBy("t", "x", "y").agg(F.count("*").alias("n")).where("n > 1")
    met = cut(dealt.join(sizes, ["t", "x", "y"]))
    few = met.where(F.col("n") <= group).select("t", "x", "y", F.lit(0).alias("i"), F.lit(0).alias("j"), "fp")
    many = met.where(F.col("n") > group)
    if radius > 2:
        blocks = F.ceil(F.col("n") / group).cast("int")
        block = F.pmod(F.xxhash64("fp", F.lit(5)), F.col("blocks")).cast("int")
        other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
        held = many.withColumn("blocks", blocks).withColumn("block", block).withColumn("other", other)
        few = few.unionByName(held.select("t", "x", "y", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "fp"))

    # a task takes many groups in one call: rows come sorted by group
    cols = ["t", "x", "y", "i", "j"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            rows = np.stack([b.column(c).to_numpy().astype(np.int64) for c in (*cols, "fp")], axis=1)
            held = rows if held is None else np.concatenate((held, rows))
            if len(held):
                last = int(np.flatnonzero((held[:, :-1] != held[-1, :-1]).any(1)).max(initial=-1)) + 1
                yield _spans(held[:last], radius)
                held = held[last:]
        if held is not None:
            yield _spans(held, radius)

    near = few.repartition(*cols).sortWithinPartitions(*cols).mapInArrow(run, "a long, b long")
    if radius > 2:
        return near.distinct()
    turned = [F.col("fp").bitwiseXOR(F.lit(_signed(1 << j))) for j in range(64)]
    values = many.select("fp").distinct()
    if radius == 1:
        off = values.select("fp", F.explode(F.array(*turned)).alias("near")).where("fp < near")
        stars = off.join(values.withColumnRenamed("fp", "v"), F.col("near") == F.col("v")).select(F.col("fp").alias("a"), F.col("near").alias("b"))
    else:
        off = values.select("fp", F.explode(F.array(F.col("fp"), *turned)).alias("near"))
        least = off.groupBy("near").agg(F.min("fp").alias("a"), F.count("*").alias("n")).where("n > 1").drop("n")
        stars = off.join(least, "near").where("fp <> a").select("a", F.col("fp").alias("b"))
    return near.unionByName(stars).distinct()


def _spans(rows: np.ndarray, radius: int) -> pa.RecordBatch:
    """Spanning links of groups: rows of a group's key and a fingerprint, sorted by the key."""
    out = [np.empty((0, 2), np.int64)]
    if len(rows):
        edge = np.flatnonzero(np.concatenate(([True], (rows[1:, :-1] != rows[:-1, :-1]).any(1), [True])))
        out += [_span(rows[s:e, -1], radius) for s, e in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True) if e - s > 1]
    both = np.concatenate(out)
    return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], names=["a", "b"])


def close_pairs(u: np.ndarray, radius: int, seen: dict[str, int] | None = None) -> Iterator[tuple[int, int]]:
    """Pairs (places in ``u``, different values) within the radius, by the table of pivot distances.

    ``seen`` counts pairs in reach of the first column, pairs that the other columns leave, and pairs that are verified.
    """
    bits = u.view(np.uint64)
    table = distance_table(bits)
    order = np.argsort(table[:, 0], kind="stable")
    table, bits = table[order], bits[order]
    reach = np.searchsorted(table[:, 0], table[:, 0] + radius, side="right")
    seen = {} if seen is None else seen
    for i in range(len(u) - 1):
        at = slice(i + 1, reach[i])
        left = np.flatnonzero(np.abs(table[at, 1:8] - table[i, 1:8]).max(1, initial=0) <= radius) + i + 1
        left = left[np.abs(table[left, 8:] - table[i, 8:]).max(1, initial=0) <= radius]
        same = left[np.bitwise_count(bits[left] ^ bits[i]) <= radius]
        for k, v in (("in_reach", reach[i] - i - 1), ("left", len(left)), ("verified", len(same))):
            seen[k] = seen.get(k, 0) + int(v)
        for j in same.tolist():
            yield int(order[i]), int(order[j])


def _span(fp: np.ndarray, radius: int) -> np.ndarray:
    """A spanning set of the links among a group's fingerprints."""
    u = np.unique(fp.astype(np.int64))
    parent = np.arange(len(u))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    out = []
    for i, j in close_pairs(u, radius):
        a, b = root(i), root(j)
        if a != b:
            parent[max(a, b)] = min(a, b)
            out.append((u[min(i, j)], u[max(i, j)]))
    return np.array(out, np.int64).reshape(-1, 2)


def components(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """node, root for every node of ``edges`` (a, b): root is the smallest node reachable.

    Each round every node points its neighbours to the smallest one it sees, first to larger neighbours and then among
    smaller ones, so chains shrink by a constant factor or better. Edges are cut each round; only their number and a
    checksum come to the driver.
    """
    e = cut(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    before = None
    for _ in range(rounds):
        # large star: larger neighbours of u, and u, go to the smallest of u's neighbours and u
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("m", "u"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # small star: u and its smaller neighbours go to the smallest
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u"), F.col("m").alias("v")))).alias("e")).select("e.*").where("u <> v").distinct()
        e = cut(small)
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def groups(docs: DataFrame, key: str = "doc_id", text: str = "text", words: int = 3, radius: int = 2) -> DataFrame:
    """A row a document: key, fingerprint (16 hex digits), component_id (smallest key of its group).

    Documents with equal fingerprints are one node; nodes within ``radius`` bits are linked, and groups are what links
    connect. Null or empty text: fingerprint zero, linked like any other. Repeated rows are rows of their own. Null keys
    never name a group unless it has no other. An empty table gives no rows. Other columns are ignored.
    """
    marked = cut(with_fingerprint(docs.select(F.col(key).alias("key"), F.col(text).alias("text")), ["key"], words=words))
    nodes = cut(marked.groupBy("fp").agg(F.min("key").alias("first")))
    roots = components(links(nodes.select("fp"), radius))
    of = nodes.join(roots, nodes.fp == roots.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    smallest = of.groupBy("root").agg(F.min("first").alias("component_id"))
    of = of.join(smallest, "root").select(F.col("fp").alias("__fp"), "component_id")
    out = marked.join(of, F.col("fp") == F.col("__fp"))
    return out.select(F.col("key").alias(key), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return groups(documents(spark, sf_dir))


# ---- near copies by similarity: wide fingerprints, candidates by fingerprints of small samples

#: Bits of the wide fingerprint, and the most that may differ. At a Jaccard similarity of 0.8 some 39 of 256 differ
#: (deviation 6), at 0.6 some 59.
WIDE, WIDE_RADIUS = 256, 56
SIMILAR = 0.8
#: Samples of a text and shingles in each: two texts of similarity s agree in a sample with chance s**SAMPLED.
SAMPLES, SAMPLED = 12, 3
LEVELS = 3
#: A block of a group holds some so many nodes and shingles at most; a task holds two blocks against each other.
BLOCK, BLOCK_SHINGLES = 1000, 1 << 18


def _wide(h: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Wide fingerprints (texts x WIDE/64) of different shingle hashes ``h``; those of text i are h[at[i]:at[i + 1]]."""
    lanes = WIDE // 64
    out = np.zeros((len(at) - 1, lanes), np.uint64)
    for k in range(lanes):
        m = _remix(h, 2 * k + 1)
        for i in range(len(at) - 1):
            n = at[i + 1] - at[i]
            if n:
                total = np.zeros(64, np.int64)
                for a in range(at[i], at[i + 1], 1 << 16):
                    part = m[a : min(at[i + 1], a + (1 << 16))]
                    total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int32)
                out[i, k] = np.packbits(total * 2 > n, bitorder="little").view("<u8")[0]
    return out


def _remix(h: np.ndarray, seed: int) -> np.ndarray:
    x = h ^ np.uint64(seed * 0x9E3779B97F4A7C15 & (2**64 - 1))
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _samples(h: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Fingerprints (texts x SAMPLES) of the shingles that come first in SAMPLED orders each; texts without shingles: 0."""
    out = np.zeros((len(at) - 1, SAMPLES), np.uint64)
    some = np.flatnonzero(at[1:] > at[:-1])
    if len(some):
        for t in range(SAMPLES):
            key = np.zeros(len(some), np.uint64)
            for j in range(SAMPLED):
                least = np.minimum.reduceat(_remix(h, 1000 + t * SAMPLED + j), at[some])
                key = _remix(key + least, j + 1)
            out[some, t] = key
    return out


def _same(h: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Two sums (texts x 2) over the shingles of each text; texts without shingles: 0."""
    out = np.zeros((len(at) - 1, 2), np.uint64)
    some = np.flatnonzero(at[1:] > at[:-1])
    if len(some):
        for k in range(2):
            out[some, k] = np.add.reduceat(_remix(h, 2001 + k), at[some])
    return out


def wide_fingerprints(docs: DataFrame, keep: list[str], text: str = "text", words: int = 5) -> DataFrame:
    """``keep`` columns, ``wide`` (the fingerprint as longs), ``samples`` (a long each) and ``same`` of whole texts.

    ``same`` (two longs) is equal for texts with equal sets of shingles, and for others by a chance of 2**-128 only.
    """
    from worldfold.llm.fingerprints import _parts, shingle_hashes

    schema = docs.select(*keep).schema.add("wide", ArrayType(LongType())).add("samples", ArrayType(LongType())).add("same", ArrayType(LongType()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [(x.as_py() or "").encode() for x in b.column(0)]
            wide, samples, same = [], [], []
            for part in _parts(texts):
                ends = np.cumsum(np.fromiter(map(len, part), np.int64, len(part)))
                h, owner = shingle_hashes(np.frombuffer(b"".join(part), np.uint8), ends, words)
                order = np.lexsort((h, owner))
                h, owner = h[order], owner[order]
                new = np.ones(len(h), bool)  # a shingle counts once a text, as it does in its set
                new[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
                h, owner = h[new], owner[new]
                at = np.concatenate(([0], np.cumsum(np.bincount(owner, minlength=len(part))))).astype(np.int64)
                wide.append(_wide(h, at))
                samples.append(_samples(h, at))
                same.append(_same(h, at))
            both = [pa.FixedSizeListArray.from_arrays(pa.array(np.concatenate(x).ravel().view(np.int64)), n).cast(pa.list_(pa.int64())) for x, n in ((wide, WIDE // 64), (samples, SAMPLES), (same, 2))]
            yield pa.RecordBatch.from_arrays([*b.columns[1:], *both], names=[*keep, "wide", "samples", "same"])

    return docs.select(F.col(text).alias("__text"), *keep).mapInArrow(run, schema)


def _near(a: str, b: str):
    """Whether two wide fingerprints are within the radius."""
    differ = F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y)))
    return F.aggregate(differ, F.lit(0), lambda s, x: s + x) <= WIDE_RADIUS


def meetings(rows: DataFrame) -> DataFrame:
    """The rows (id, wide, t, key, ...) of samples that several nodes share, with their number and their smallest node."""
    sizes = rows.groupBy("t", "key").agg(F.count("*").alias("n"), F.min(F.struct("id", "wide")).alias("first")).where("n > 1")
    return cut(rows.join(sizes, ["t", "key"]))


def sampled(nodes: DataFrame) -> DataFrame:
    return nodes.select("id", "wide", F.posexplode("samples").alias("t", "key"), "samples")


def near_links(nodes: DataFrame, group: int = GROUP, met: DataFrame | None = None) -> DataFrame:
    """First links (a, b) among nodes (id, wide, samples) whose wide fingerprints are within the radius.

    Candidates share a sample's fingerprint (``met``: their meetings, if there already). In groups of up to ``group``
    nodes pairs are discarded by a pivot table of distances to members, then verified, and a spanning set is kept. In a
    larger group all nodes are verified against its smallest one; those that are not near it go on to groups that agree in
    two samples, and so on for LEVELS levels. These links only spare work: what they miss is left to ``rest_links``.
    """
    found = None
    for level in range(LEVELS):
        if level or met is None:
            met = meetings(rows if level else sampled(nodes))
        small = met.where(F.col("n") <= group).select("t", "key", "id", "wide")
        more = small.repartition("t", "key").sortWithinPartitions("t", "key", "id").mapInArrow(_group_links, "a long, b long")
        large = met.where((F.col("n") > group) & (F.col("id") != F.col("first.id"))).withColumn("near", _near("wide", "first.wide"))
        more = more.unionByName(large.where("near").select(F.col("first.id").alias("a"), F.col("id").alias("b")))
        found = more if found is None else found.unionByName(more)
        rows = large.where("not near")
        again = F.transform(F.sequence(F.lit(1), F.lit(4)), lambda j: F.xxhash64("key", j, F.element_at("samples", (F.pmod(F.col("t") + j * (3 ** level), F.lit(SAMPLES)) + 1).cast("int"))))
        if level + 1 == LEVELS or rows.isEmpty():
            break
        rows = rows.select("id", "wide", "t", F.explode(again).alias("key"), "samples")
    return found.distinct()


def _group_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Spanning links of groups; rows come sorted by group, a group at a time is held."""
    held: list[pa.RecordBatch] = []
    rows = 0

    def flush(table: pa.Table) -> pa.RecordBatch:
        t, key, node = (table.column(c).to_numpy() for c in ("t", "key", "id"))
        flat = table.column("wide").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(t), -1).view(np.uint64) if len(t) else np.zeros((0, WIDE // 64), np.uint64)
        edge = np.flatnonzero(np.concatenate(([True], (t[1:] != t[:-1]) | (key[1:] != key[:-1]), [True]))) if len(t) else []
        out = [np.empty((0, 2), np.int64), *[_wide_span(node[s:e], flat[s:e]) for s, e in zip(edge[:-1], edge[1:], strict=True) if e - s > 1]]
        both = np.concatenate(out)
        return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], names=["a", "b"])

    for b in batches:
        held.append(b)
        rows += b.num_rows
        if rows > 5 * GROUP:
            table = pa.Table.from_batches(held).combine_chunks()
            t, key = table.column("t").to_numpy(), table.column("key").to_numpy()
            last = int(np.flatnonzero((t != t[-1]) | (key != key[-1])).max(initial=-1)) + 1
            yield flush(table.slice(0, last).combine_chunks())
            held, rows = table.slice(last).to_batches(), len(t) - last
    if rows:
        yield flush(pa.Table.from_batches(held).combine_chunks())


def _wide_span(node: np.ndarray, wide: np.ndarray) -> np.ndarray:
    distance = lambda x, y: np.bitwise_count(x ^ y).sum(-1, dtype=np.int16)
    pivots = wide[np.linspace(0, len(wide) - 1, min(8, len(wide))).astype(int)]
    columns = np.stack([distance(wide, p) for p in pivots], axis=1)
    parent = np.arange(len(node))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    pairs = []
    for i in range(len(node) - 1):
        at = np.flatnonzero(np.abs(columns[i + 1 :] - columns[i]).max(1) <= WIDE_RADIUS) + i + 1
        d = distance(wide[at], wide[i])
        pairs.append(np.stack([d, np.full(len(at), i), at], axis=1)[d <= WIDE_RADIUS])
    pairs = np.concatenate(pairs)
    out = []
    for _, i, j in pairs[np.argsort(pairs[:, 0], kind="stable")].tolist():  # closest first: links that hold are kept
        a, b = root(i), root(j)
        if a != b:
            parent[max(a, b)] = min(a, b)
            out.append((node[i], node[j]))
    return np.array(out, np.int64).reshape(-1, 2)


def shingle_sets(docs: DataFrame, keep: list[str], text: str = "text", words: int = 5) -> DataFrame:
    """``keep`` columns and ``shingles``, the sorted different hashes of the whole text's shingles."""
    from worldfold.llm.fingerprints import shingle_hashes

    schema = docs.select(*keep).schema.add("shingles", ArrayType(LongType()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = []
            for t in b.column(0):
                raw = (t.as_py() or "").encode()
                sets.append(np.unique(shingle_hashes(np.frombuffer(raw, np.uint8), np.array([len(raw)]), words)[0]).view(np.int64))
            yield pa.RecordBatch.from_arrays([*b.columns[1:], pa.array(sets, pa.list_(pa.int64()))], names=[*keep, "shingles"])

    return docs.select(F.col(text).alias("__text"), *keep).mapInArrow(run, schema)


def sets_of(ids: DataFrame, nodes: DataFrame, base: DataFrame, words: int = 5) -> DataFrame:
    """id, shingles of the nodes ``ids``, cut. Their texts are read again: ``base`` holds key, h, text, ``nodes`` names one a node."""
    one = nodes.join(ids, "id").select("id", F.col("first.key").alias("k"), F.col("first.h").alias("hh"))
    texts = base.join(one, F.col("key").eqNullSafe(F.col("k")) & (F.col("h") == F.col("hh"))).select("id", "text")
    with small_batches(base.sparkSession):
        return cut(shingle_sets(texts, ["id"], "text", words).dropDuplicates(["id"]))


def verified(links: DataFrame, sets: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """The links whose texts have at least ``similar`` of their shingles in common, by their exact ``sets``."""
    both = links.join(sets.select(F.col("id").alias("a"), F.col("shingles").alias("sa")), "a").join(sets.select(F.col("id").alias("b"), F.col("shingles").alias("sb")), "b")
    common = F.size(F.array_intersect("sa", "sb"))
    return both.where(common >= similar * (F.size("sa") + F.size("sb") - common)).select("a", "b")


def rest_links(met: DataFrame, roots: DataFrame, sets: DataFrame, similar: float = SIMILAR) -> DataFrame | None:
    """Links that join different ``roots``: all nodes that share a sample and are not connected yet, by their exact sets.

    Only groups of more than one root are read. Groups of the same nodes (copies meet in most samples) are one. With the
    verified links that made ``roots``, the result connects just what all pairs of ``similar`` that share a sample connect.
    None: every group has one root. A large group is dealt into blocks and every block is held against every other, so no
    task grows with the group.
    """
    of = met.select("t", "key", "id").join(roots, met.id == roots.node, "left").select("t", "key", "id", F.coalesce("root", "id").alias("root"))
    members = [F.bit_xor(F.xxhash64("id", F.lit(i))).alias(f"m{i}") for i in range(2)]
    open_ = of.groupBy("t", "key").agg(F.count("*").alias("n"), *members, F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi")
    open_ = cut(open_.groupBy("n", "m0", "m1").agg(F.min(F.struct("t", "key")).alias("g")).select("g.*"))
    if open_.isEmpty():
        return None
    of = cut(of.join(small(open_), ["t", "key"]))
    total = of.join(sets.select("id", F.size("shingles").alias("size")), "id").groupBy("t", "key").agg(F.count("*").alias("n"), F.sum("size").alias("size"))
    total = cut(total.select("t", "key", F.greatest(F.ceil(F.col("n") / BLOCK), F.ceil(F.col("size") / BLOCK_SHINGLES)).cast("int").alias("blocks")))
    of = of.join(small(total), ["t", "key"]).withColumn("block", F.pmod(F.xxhash64("id", F.lit(2)), F.col("blocks")).cast("int"))
    pairs = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.struct(F.least("block", j).alias("i"), F.greatest("block", j).alias("j")))
    dealt = of.join(sets, "id").withColumn("pair", F.explode(pairs)).select("t", "key", "pair.i", "pair.j", "block", "id", "root", "shingles")
    keys = ["t", "key", "i", "j"]
    with small_batches(met.sparkSession, 200):
        return cut(dealt.repartition(*keys).sortWithinPartitions(*keys, "block", "id").mapInArrow(lambda b: _rest_links(b, similar), "a long, b long").distinct())


def _rest_links(batches: Iterator[pa.RecordBatch], similar: float) -> Iterator[pa.RecordBatch]:
    """Links of pairs of blocks; rows come sorted by pair, a pair at a time is held."""
    held: list[pa.RecordBatch] = []
    now = None
    for b in batches:
        keys = np.stack([b.column(c).to_numpy() for c in ("t", "key", "i", "j")], axis=1)
        edge = np.flatnonzero(np.concatenate(([True], (keys[1:] != keys[:-1]).any(1), [True]))) if len(keys) else []
        for s, e in zip(edge[:-1], edge[1:], strict=True):
            if now is not None and (keys[s] != now).any():
                yield _compared(held, similar)
                held = []
            now = keys[s]
            held.append(b.slice(s, e - s))
    if held:
        yield _compared(held, similar)


def _compared(held: list[pa.RecordBatch], similar: float) -> pa.RecordBatch:
    """Spanning links between the roots of a block pair: nodes of block j are held against all of block i by exact sets."""
    table = pa.Table.from_batches(held).combine_chunks()
    node, root, block = (table.column(c).to_numpy() for c in ("id", "root", "block"))
    shingles = table.column("shingles").combine_chunks()
    flat, size = shingles.flatten().to_numpy(), shingles.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    at = np.concatenate(([0], np.cumsum(size)))
    left, right = (np.flatnonzero(block == table.column(c)[0].as_py()) for c in ("i", "j"))
    label = np.unique(root, return_inverse=True)[1]
    out = []
    if len(left) and len(right) and (label != label[0]).any():
        spread = np.repeat(np.arange(len(node)), size)
        mine = np.isin(spread, left)
        order = np.argsort(flat[mine], kind="stable")
        word, owner = flat[mine][order], spread[mine][order]
        for b in right.tolist():
            open_ = (label[left] != label[b]) & (size[left] >= similar * size[b]) & (size[b] >= similar * size[left])
            if not open_.any():
                continue
            here = flat[at[b] : at[b + 1]]
            lo = np.searchsorted(word, here, "left")
            n = np.searchsorted(word, here, "right") - lo
            places = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())
            common = np.bincount(owner[places], minlength=len(node))[left]
            for a in left[open_ & (common >= similar * (size[left] + size[b] - common))].tolist():
                if label[a] != label[b]:
                    out.append((node[a], node[b]))
                    label[label == label[a]] = label[b]
    both = np.array(out, np.int64).reshape(-1, 2)
    return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], names=["a", "b"])


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text", words: int = 5) -> DataFrame:
    """``docs`` without all but the first (smallest key) of each group of exact or near copies, similarity 0.8 or more.

    Texts with equal sets of shingles are one node (exact copies among them); nodes are linked by ``near_links``, links are held
    against the exact shingle sets, and so are all other pairs that share a sample and are not connected by then; groups
    are what links connect. Texts without words are all alike. Of repeated rows one stays. Columns are those of ``docs``.
    """
    h = F.xxhash64(F.coalesce(F.col(text), F.lit("")))
    base = docs.select(F.col(key).alias("key"), F.col(text).alias("text"), h.alias("h"))
    with small_batches(docs.sparkSession):
        marked = cut(wide_fingerprints(base, ["key", "h"], "text", words))
    nodes = marked.groupBy("same").agg(F.min(F.struct("key", "h")).alias("first"), F.first("wide").alias("wide"), F.first("samples").alias("samples"))
    nodes = cut(nodes.withColumn("id", F.monotonically_increasing_id()))  # unique; fixed by the checkpoint, and no result depends on it
    met = meetings(sampled(nodes))
    sets = sets_of(met.select("id").distinct(), nodes, base, words)  # once, for both kinds of links
    links_ = cut(verified(cut(near_links(nodes, GROUP, met)), sets))
    roots = components(links_)
    rest = rest_links(met, roots, sets)
    if rest is not None and not rest.isEmpty():
        roots = components(links_.unionByName(rest))
    of = nodes.join(roots, nodes.id == roots.node, "left").select("id", "first", F.coalesce("root", "id").alias("root"))
    best = of.groupBy("root").agg(F.min("first").alias("first"))
    kept = cut(best.select("first.key", "first.h"))
    # what goes is listed, as it is less than what stays; repeated rows of what stays are made one
    row = marked.groupBy("key", "h").agg(F.count("*").alias("n"))
    k = kept.select(F.col("key").alias("k2"), F.col("h").alias("h2"))
    row = cut(row.join(k, F.col("key").eqNullSafe(F.col("k2")) & (F.col("h") == F.col("h2")), "left").where("n > 1 or h2 is null").withColumn("stays", F.col("h2").isNotNull()).select(F.col("key").alias("__k"), F.col("h").alias("__h"), "stays"))
    same = F.col(key).eqNullSafe(F.col("__k")) & (F.col("__hash") == F.col("__h"))
    with_hash = docs.withColumn("__hash", h)
    out = with_hash.join(small(row), same, "left_anti").select(*docs.columns)
    again = row.where("stays")
    if not again.isEmpty():
        out = out.unionByName(with_hash.join(again, same, "left_semi").dropDuplicates([key, "__hash"]).select(*docs.columns))
    return out
