"""Mixing sources to target weights with a low-discrepancy schedule.

A schedule of equal-token slots names a source for each slot: slot i is the point frac(i * golden ratio) of the unit
interval, which is divided among the sources in proportion to their targets. The k-th slot of a source takes block k of
that source's shuffled token stream; past the stream's end it starts again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from worldfold.llm.common import buckets_for, cut, documents, running, small, word_count

#: Fixed value: 2**32 divided by the golden ratio, made odd; multiples modulo 2**32 are the schedule's points.
GOLDEN = 2654435769
CELLS = 4096


def sized(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """key, source, size (words; null text 0) and the shuffle order, cut so that texts are read once."""
    order = F.md5(F.coalesce(F.col(key).cast("string"), F.lit("")))
    return cut(docs.select(F.col(key).alias("key"), F.col(source).alias("source"), word_count(F.col(text)).alias("size"), order.alias("shuffled")))


def targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), cap: int = 3) -> DataFrame:
    """A row a source: source, place, source_size, target.

    Weights repeat over the sources in code-point order, null last. Targets share all tokens by weight; a source whose
    share is over ``cap`` times its size stops there, and the rest is shared again. Sorted by size for a unit of weight,
    the stopped sources come first, so two passes over the (short) table of sources find them.
    """
    place = Window.orderBy(F.col("source").asc_nulls_last())
    s = sizes.groupBy("source").agg(F.sum("size").alias("source_size")).withColumn("place", F.row_number().over(place) - 1)
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("place") % len(weights) + 1).cast("int"))
    s = s.withColumn("weight", weight.cast("long")).withColumn("most", F.col("source_size") * cap)
    ratio = Window.orderBy(F.col("most") / F.col("weight"), "place")
    whole = Window.partitionBy()
    s = s.withColumn("total", F.sum("source_size").over(whole))
    rest = F.col("total") - F.coalesce(F.sum("most").over(ratio.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    weigh = F.sum("weight").over(ratio.rowsBetween(0, Window.unboundedFollowing))
    s = s.withColumn("stopped", F.col("most").cast("double") * weigh <= rest.cast("double") * F.col("weight"))
    free = F.sum(F.when(~F.col("stopped"), F.col("weight"))).over(whole)
    left = F.col("total") - F.coalesce(F.sum(F.when(F.col("stopped"), F.col("most"))).over(whole), F.lit(0))
    share = left.cast("double") * F.col("weight") / free
    return s.select("source", "place", "source_size", F.when(F.col("stopped"), F.col("most").cast("double")).otherwise(share).alias("target"))


def slots_of(spark: SparkSession, per_source: DataFrame, total: int, block: int) -> DataFrame:
    """A row a slot: slot, place (its source's) and blocks (of the source's stream).

    There are total/block slots. They find their source by a join on cells of the unit interval.
    """
    cum = F.sum("target").over(Window.orderBy("place").rowsBetween(Window.unboundedPreceding, 0))
    bound = per_source.withColumn("hi", F.round(cum / max(total, 1) * float(2**32)).cast("long"))
    bound = bound.withColumn("lo", F.coalesce(F.lag("hi").over(Window.orderBy("place")), F.lit(0))).where("hi > lo")
    bound = bound.withColumn("blocks", F.ceil(F.col("source_size") / block))
    cells = bound.select("place", "lo", "hi", "blocks", F.explode(F.expr(f"sequence(lo div {2**32 // CELLS}, (hi - 1) div {2**32 // CELLS})")).alias("cell"))
    slots = spark.range(max(1, round(total / block)) if total else 0).withColumnRenamed("id", "slot")
    # the product modulo 2**32 by halves of the slot's number, so that no number of slots overflows
    point = F.expr(f"((slot div 65536 % 65536 * {GOLDEN} % 65536) * 65536 + slot % 65536 * {GOLDEN}) % {2**32}")
    slots = slots.withColumn("point", point).withColumn("cell", F.expr(f"point div {2**32 // CELLS}"))
    return slots.join(small(cut(cells)), "cell").where("point >= lo and point < hi").select("slot", "place", "blocks")


def schedule(spark: SparkSession, per_source: DataFrame, total: int, block: int, cap: int = 3) -> DataFrame:
    """A row a slot: slot, place (its source's), rank (among the source's slots) and block (of the source's stream).

    A source gets at most ``cap`` passes over its blocks. Ranks are a window by source: this lists a schedule to read it;
    ``mix`` needs the number of a source's slots only.
    """
    found = slots_of(spark, per_source, total, block)
    found = found.withColumn("rank", F.row_number().over(Window.partitionBy("place").orderBy("slot")) - 1)
    return found.where(F.col("rank") < F.col("blocks") * cap).select("slot", "place", "rank", (F.col("rank") % F.col("blocks")).alias("block"))


def mix(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[int, ...] = (5, 2, 1), cap: int = 3, min_block: int = 16) -> DataFrame:
    """A row a document: key, source, size, source_size, target, taken (words the mix takes of it, repeats counted).

    Blocks hold ``min_block`` words however large the corpus is, so the error stays a few such blocks a source. The k-th
    slot of a source takes block k modulo its blocks: of n slots every block gets n div blocks, and the first n modulo
    blocks get one more. So slots are only counted by source, and never listed, ranked or shuffled. A source's documents
    are shuffled by a hash of the key and laid end to end; a prefix sum by buckets keeps a source with most rows spread out.

    Null text or source: no words; the null source is a source. Repeated rows are documents of their own. A document
    without words takes nothing. An empty table gives no rows. Other columns are ignored.
    """
    spark = docs.sparkSession
    sizes = sized(docs, key, text, source)
    rows, total = sizes.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    per_source = targets(sizes, weights, cap)
    count = slots_of(spark, per_source, total, min_block).groupBy("place", "blocks").agg(F.count("*").alias("slots"))
    count = count.withColumn("slots", F.least("slots", F.col("blocks") * cap))
    # whole passes over a source's stream, and the words of its start that are taken once more
    count = count.select("place", F.expr("slots div blocks").alias("passes"), (F.col("slots") % F.col("blocks") * min_block).alias("more"))
    per_source = cut(per_source.join(count, "place", "left").fillna(0, ["passes", "more"]))
    n = buckets_for(rows)
    placed = running(sizes.withColumn("bucket", F.expr(f"cast(conv(substr(shuffled, 1, 8), 16, 10) as bigint) * {n} div {2**32}")), ["source"], "bucket", [F.col("shuffled"), F.col("key"), F.col("size")], F.col("size"), "start")
    s = per_source.withColumnRenamed("source", "__source")
    placed = placed.join(s, F.col("source").eqNullSafe(F.col("__source")), "left").drop("__source")
    # words taken of the stream before a place of it: the mix of a document is a difference of two
    def before(at: Column) -> Column:
        return F.col("passes") * at + F.least(at, F.col("more"))

    taken = F.when(F.col("size") > 0, before(F.col("start") + F.col("size")) - before(F.col("start"))).otherwise(0)
    out = placed.select("key", "source", "size", "source_size", "target", taken.cast("long").alias("taken"))
    return out.withColumnRenamed("key", key).withColumnRenamed("source", source)


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus, as rows of ``docs``: a document appears as often as the mix takes it, rounded to whole copies.

    A document without words is kept once. Columns are those of ``docs``.
    """
    key, text = options.get("key", "doc_id"), options.get("text", "text")
    m = mix(docs, **options)
    # repeated rows of one key take the copies that all of them are given, spread evenly by the join's group
    m = m.groupBy(F.col(key).alias("__key"), F.col("size").alias("__size")).agg(F.sum("taken").alias("__taken"), F.count("*").alias("__n"))
    copies = F.when(F.col("__size") > 0, F.round(F.col("__taken") / F.col("__size") / F.col("__n"))).otherwise(1).cast("int")
    m = m.select("__key", "__size", copies.alias("__copies")).where("__copies > 0")
    out = docs.withColumn("__words", word_count(F.col(text))).join(m, F.col(key).eqNullSafe(F.col("__key")) & (F.col("__words") == F.col("__size")))
    return out.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__copies")))).select(*[F.col(f"`{c}`") for c in docs.columns])


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken", "source")


ORACLE = r"""
WITH sizes AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         md5(CAST(doc_id AS VARCHAR)) AS shuffled
  FROM documents),
per AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sizes GROUP BY source),
pos AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS place FROM per),
wei AS (SELECT *, CAST([5, 2, 1][(place % 3) + 1] AS BIGINT) AS weight, source_size * 3 AS most,
               CAST(sum(source_size) OVER () AS BIGINT) AS total FROM pos),
lim AS (SELECT *, CAST(most AS DOUBLE) * sum(weight) OVER (ORDER BY most / weight, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)
                  <= CAST(total - coalesce(sum(most) OVER (ORDER BY most / weight, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE) * weight AS stopped FROM wei),
tar AS (SELECT source, place, source_size, total,
               CASE WHEN stopped THEN CAST(most AS DOUBLE)
                    ELSE CAST(total - coalesce(sum(CASE WHEN stopped THEN most END) OVER (), 0) AS DOUBLE) * weight
                         / CAST(sum(CASE WHEN NOT stopped THEN weight END) OVER () AS DOUBLE) END AS target FROM lim),
blk AS (SELECT greatest(16, CAST(ceil(max(total) / 1048576.0) AS BIGINT)) AS block, max(total) AS total FROM tar),
cum AS (SELECT tar.*, CAST(round(sum(target) OVER (ORDER BY place) / tar.total * 4294967296.0) AS BIGINT) AS hi FROM tar),
bou AS (SELECT *, coalesce(lag(hi) OVER (ORDER BY place), 0) AS lo,
               CAST(ceil(source_size / CAST((SELECT block FROM blk) AS DOUBLE)) AS BIGINT) AS blocks FROM cum),
slo AS (SELECT i AS slot, (i * 2654435769) % 4294967296 AS point
        FROM (SELECT unnest(range(CAST(greatest(1, round(total / CAST(block AS DOUBLE))) AS BIGINT))) AS i FROM blk WHERE total > 0)),
ran AS (SELECT place, blocks, row_number() OVER (PARTITION BY place ORDER BY slot) - 1 AS rnk
        FROM slo JOIN bou ON point >= lo AND point < hi),
tim AS (SELECT place, rnk % blocks AS b, count(*) AS n FROM ran WHERE rnk < blocks * 3 GROUP BY 1, 2),
run AS (SELECT sizes.*, coalesce(sum(size) OVER (PARTITION BY source ORDER BY shuffled, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start FROM sizes),
pie AS (SELECT doc_id, place, start, size, unnest(range(CAST(start // block AS BIGINT), CAST((start + size - 1) // block + 1 AS BIGINT))) AS b, block
        FROM run JOIN tar ON run.source IS NOT DISTINCT FROM tar.source CROSS JOIN blk WHERE size > 0),
tak AS (SELECT doc_id, sum((least(start + size, (pie.b + 1) * block) - greatest(start, pie.b * block)) * coalesce(n, 0)) AS taken
        FROM pie LEFT JOIN tim ON pie.place = tim.place AND pie.b = tim.b GROUP BY doc_id)
SELECT run.doc_id, run.size, tar.source_size, tar.target, CAST(coalesce(tak.taken, 0) AS BIGINT) AS taken, run.source
FROM run JOIN tar ON run.source IS NOT DISTINCT FROM tar.source LEFT JOIN tak ON run.doc_id = tak.doc_id
"""
