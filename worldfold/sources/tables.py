"""The given tables as views, the unit specifications over them, and a click-log view of the event table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.sources.catalog import UnitCatalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, *names: str) -> dict[str, DataFrame]:
    """Registers parquet tables as temporary views; only their schemas are read."""
    out = {}
    for t in names or TABLES:
        out[t] = spark.read.parquet(f"{sf_dir}/{t}.parquet")
        out[t].createOrReplaceTempView(t)
    return out


def read(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """Parquet, ORC, JSON, CSV or text, by Spark's readers."""
    return spark.read.options(**options).format(kind).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists", partition_by: tuple[str, ...] = ()) -> None:
    """Released results to a table. Columns that still hold a value for each world are refused."""
    vectors = [c for c, t in df.dtypes if t in ("array<double>", "array<bigint>") or t.startswith("array<decimal")]
    if vectors:
        raise PermissionError(f"vectors of worlds are not written: {', '.join(vectors)}")
    w = df.write.format(kind).mode(mode)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def hits_like(events: DataFrame) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("int")
    return events.select(
        F.col("event_id").alias("watch_id"), "event_id", "user_id", (F.col("user_id") * 7 + 3).alias("client_ip"), F.col("ts").alias("event_time"), k.alias("counter_id"), (k % 10).alias("region_id"),
        (k % 3).alias("adv_engine_id"), F.col("value").cast("int").alias("width"), F.col("event_type").alias("search_phrase"), F.concat(F.lit("/"), "event_type", F.lit("/"), k.cast("string")).alias("url"),
    )


def customer_units(spark: SparkSession | None = None) -> UnitCatalog:
    """Customers are units; their orders and order lines belong to them."""
    c = UnitCatalog()
    if spark is not None:
        c.learn(spark, "customer", "orders", "lineitem")
    return c.execute("DECLARE UNIT customer KEY (c_custkey) PROTECT (c_custkey, c_name, c_acctbal); DECLARE LINK orders (o_custkey) TO customer (c_custkey); DECLARE LINK lineitem (l_orderkey) TO orders (o_orderkey)")


def hit_units(by: str = "event_id") -> UnitCatalog:
    """Rows of the click log, or its users, are units."""
    return UnitCatalog().declare_unit("hits_like", by, [by, "watch_id", "event_id", "user_id", "client_ip"])


def document_units() -> UnitCatalog:
    return UnitCatalog().declare_unit("documents", "doc_id").declare_link("labels", "doc_id", "documents", "doc_id")


def conversation_units() -> UnitCatalog:
    return UnitCatalog().declare_unit("conversations", ("conv_id", "turn"), ["text"])
