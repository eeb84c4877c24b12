"""Boilerplate lines by their frequency relative to the site."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.llm.common import cut, documents

#: A line is boilerplate on a host if it is on more than this share of the host's pages, and on so many at least.
RATIO, LEAST = 0.02, 4
#: Boilerplate lines that are sent to every executor; more than that are joined by shuffle.
BROADCAST_ROWS = 200_000
#: In a shuffle by host a host is dealt into parts of so many pages, or of a thousandth of all pages where that is more.
PART_PAGES = 50_000


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def mark(line: Column) -> Column:
    """96 hash bits of a trimmed line."""
    t = F.trim(line)
    return F.struct(F.xxhash64(t).alias("a"), F.hash(t).alias("b"))


def boilerplate(docs: DataFrame, host: str = "source", text: str = "text", ratio: float = RATIO, least: int = LEAST) -> DataFrame:
    """host, line (its hash), pages (with it), share: lines over the ratio of their host's pages.

    A page counts a line once, however often it repeats. Counting combines before the shuffle, so a line on a third of
    all pages is a few partial counts; at most 1/ratio times a page's lines pass for one host.
    """
    pages = docs.groupBy(F.col(host).alias("host")).agg(F.count("*").alias("total"))
    once = F.array_distinct(F.transform(F.filter(lines_of(F.col(text)), lambda x: F.trim(x) != ""), mark))
    seen = docs.select(F.col(host).alias("host"), F.explode(once).alias("line")).groupBy("host", "line").agg(F.count("*").alias("pages")).where(F.col("pages") >= least)
    joined = seen.join(pages.withColumnRenamed("host", "__host"), F.col("host").eqNullSafe(F.col("__host"))).drop("__host")
    return joined.withColumn("share", F.col("pages") / F.col("total")).where(F.col("share") > ratio).drop("total")


def _free(docs: DataFrame, name: str) -> str:
    """A column name that ``docs`` does not have."""
    while name in docs.columns:
        name = "_" + name
    return name


def _dealt(docs: DataFrame, by_host: DataFrame, host: str, own: str, part: str, copy: str, part_pages: int) -> tuple[DataFrame, DataFrame]:
    """``docs`` with a column ``part`` and ``by_host`` with ``copy``, to be joined by host and these two.

    Pages of a large host are dealt by a hash of the row, and the host's lines stand once in each of its parts. Large
    hosts have over a thousandth of all pages each, so they are under 1,000 and can be broadcast; rows that are equal in all
    columns share a part.
    """
    far, parts = _free(docs, "far"), _free(docs, "parts")
    pages = cut(docs.groupBy(F.col(host).alias(far)).agg(F.count("*").alias(parts)))
    each = max(part_pages, -(-(pages.agg(F.sum(parts)).first()[0] or 0) // 1000))
    large = F.broadcast(pages.where(F.col(parts) > each).withColumn(parts, F.ceil(F.col(parts) / each).cast("int")))
    whole = [F.col(f"`{f.name}`") for f in docs.schema.fields if not any(x in f.dataType.simpleString() for x in ("map<", "variant"))]
    many = F.coalesce(F.col(parts), F.lit(1))
    rows = docs.join(large, F.col(host).eqNullSafe(F.col(far)), "left").withColumn(part, F.pmod(F.xxhash64(*whole), many).cast("int")).drop(far, parts)
    lines = by_host.join(large, F.col(own).eqNullSafe(F.col(far)), "left").withColumn(copy, F.explode(F.sequence(F.lit(0), many - 1))).drop(far, parts)
    return rows, lines


def dedup(docs: DataFrame, host: str = "source", text: str = "text", ratio: float = RATIO, least: int = LEAST, broadcast_rows: int = BROADCAST_ROWS, part_pages: int = PART_PAGES) -> DataFrame:
    """``docs`` with boilerplate lines taken out of ``text``, and n_lines, n_dropped.

    Columns of these two names are replaced, all others are kept. Blank lines stay. Null text stays null; its counts are 0. A null host is a host. A document that is all boilerplate is left with
    empty text. Repeated rows count as pages of their own. Rows come out one for one; an empty table gives none.
    Up to ``broadcast_rows`` boilerplate lines texts stay where they are; beyond, they are shuffled by host and part.
    """
    found = cut(boilerplate(docs, host, text, ratio, least))
    own, bad, new, part, copy = (_free(docs, x) for x in ("host", "bad", "clean", "part", "copy"))
    by_host = found.groupBy("host").agg(F.collect_set("line").alias(bad)).withColumnRenamed("host", own)
    same = F.col(host).eqNullSafe(F.col(own))
    if found.count() <= broadcast_rows:
        out = docs.join(F.broadcast(by_host), same, "left").drop(own)
    else:
        rows, lines = _dealt(docs, by_host, host, own, part, copy, part_pages)
        out = rows.join(lines, same & (F.col(part) == F.col(copy)), "left").drop(own, part, copy)
    all_ = lines_of(F.col(text))
    good = F.filter(all_, lambda x: ~F.array_contains(bad, mark(x)))
    clean = F.when(F.col(text).isNull() | F.col(bad).isNull(), F.col(text)).otherwise(F.array_join(good, "\n"))
    n = F.when(F.col(text).isNull(), 0).otherwise(F.size(all_))
    left = F.when(F.col(text).isNull(), 0).when(F.col(bad).isNull(), F.size(all_)).otherwise(F.size(good))
    return out.withColumns({new: clean, "n_lines": n.cast("long"), "n_dropped": (n - left).cast("long")}).withColumn(text, F.col(new)).drop(new, bad)


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(documents(spark, sf_dir)).select("doc_id", "source", "text", "n_lines", "n_dropped")


ORACLE = f"""
WITH li AS (
  SELECT doc_id, source, unnest(string_split(text, chr(10))) AS line,
         generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents WHERE text IS NOT NULL),
tot AS (SELECT source, count(*) AS total FROM documents GROUP BY source),
bad AS (
  SELECT f.source, f.t FROM (SELECT source, trim(line, ' ') AS t, count(DISTINCT doc_id) AS pages FROM li WHERE trim(line, ' ') <> '' GROUP BY 1, 2) f
  JOIN tot ON f.source IS NOT DISTINCT FROM tot.source WHERE pages >= {LEAST} AND pages / total > {RATIO}),
mar AS (SELECT li.*, bad.t IS NOT NULL AS drop FROM li LEFT JOIN bad ON li.source IS NOT DISTINCT FROM bad.source AND trim(li.line, ' ') = bad.t)
SELECT d.doc_id, d.source, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(m.kept, '') END AS text, CAST(coalesce(m.n, 0) AS BIGINT) AS n_lines, CAST(coalesce(m.dropped, 0) AS BIGINT) AS n_dropped
FROM documents d LEFT JOIN (
  SELECT doc_id, string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT drop) AS kept, count(*) AS n, count(*) FILTER (WHERE drop) AS dropped
  FROM mar GROUP BY doc_id) m ON d.doc_id = m.doc_id
"""
