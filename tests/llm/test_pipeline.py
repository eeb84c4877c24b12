import corpus_pipeline
from pyspark.sql import functions as F

from worldfold.llm.queries import ORACLES, QUERIES


def test_stages_keep_columns_and_clean_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "line_dedup", "near_dedup", "mix_sources", "pack"]
    at = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, at, sf)
        assert out.columns == docs.columns and out.dtypes == docs.dtypes, name
        if name in ("language_id", "line_dedup"):
            assert out.count() == at.count()
        if name == "near_dedup":
            assert 0 < out.count() < at.count() and out.groupBy("text").count().where("count > 1").count() == 0
        at = out
    packed = corpus_pipeline.STAGES[-1][1](spark, at, sf)
    assert packed.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 2048").count() == 0


def test_stages_on_awkward_rows(spark, sf):
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (2, "", "en", "a", 0), (3, "the and of to in is that it was for", "en", "a", 3), (None, "the and of to in is that it was with", "en", None, None), (4, "x " * 30_000, "en", "a", 1)]
    rows += [(i, f"the and of number {i} to in is that it was for {i * 7} with", "en", "b", 1) for i in range(10, 40)]
    schema = spark.read.parquet(f"{sf}/documents.parquet").schema
    for some in (rows, []):
        at = spark.createDataFrame(some, schema)
        for name, stage in corpus_pipeline.STAGES[:-1]:
            at = stage(spark, at, sf)
            assert at.columns == schema.names, name
        assert corpus_pipeline.STAGES[-1][1](spark, at, sf).count() >= bool(some)


def test_extra_columns_with_clashing_names(spark, sf):
    from worldfold.llm import fingerprints, langid, linededup, mixing, packing, pii, secrets, sharding, simhash, tiff

    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    odd = docs.withColumns({c: F.lit(1) for c in ("size", "key", "k", "range", "slot", "h", "fp", "start", "length", "target", "taken", "host", "line", "score", "wide", "place", "block", "__text", "spans", "total", "declared")})
    for f in (mixing.mix, fingerprints.compare_with_next, packing.pack, pii.detect, simhash.groups, sharding.shard, tiff.digests, secrets.scan, langid.posteriors):
        assert f(odd).count() >= 0, f.__module__
    assert linededup.dedup(odd).count() == simhash.keep_one(odd).count() + odd.count() - simhash.keep_one(docs).count()
    assert mixing.mixed_documents(odd).columns == odd.columns


def test_registered():
    assert sorted(int(k.split("_")[0][2:]) for k in QUERIES if k.startswith("op")) == list(range(1, 11)) and set(ORACLES) <= set(QUERIES)
