"""Language identification by Bayesian fusion of evidence.

Four sources of evidence are multiplied: the text's likelihood under a model of byte pairs for each language, what the
page's markup declares, what its address suffix suggests, and a prior of its host. Host priors are smoothed towards
those of their suffix and these towards the whole corpus; all of them are grouped sums of text posteriors.

Declarations label the texts that the models are fitted on. So that no declaration counts twice, a text that was fitted on
is scored by its language's model without that text, and what it declares is then evidence of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, FloatType

from worldfold.llm.common import cut, documents, small, small_batches

#: Labelled texts that the model is fitted on: so many a language at most, and so many bytes of each.
FIT_TEXTS, FIT_BYTES = 400, 4000
#: Languages that fewer texts declare have no model: they are open to what declares them, as are those that do not fit
#: into a model of so many bytes (the rarest ones).
FEWEST, MODEL_BYTES = 3, 256 << 20
#: What a pair of bytes counts at least in every model, and the number of pairs of bytes there are.
FLOOR, ALL_PAIRS = 0.02, 65536
#: Bytes of evidence count at most as so many independent ones; neighbouring pairs are not independent.
WEIGHT, MOST = 0.25, 400.0
#: How often a declaration is right, and how many texts' worth of weight a wider level has in a narrower one's prior.
DECLARED, SUFFIX, STRENGTH = 0.9, 0.6, 20.0
#: A text is kept if its language is this sure and its bytes are this likely under it (mean log-probability of a pair).
SURE, LIKELY = 0.5, -11.0
#: The logarithm of no chance.
NEVER = -1e6

_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_FOLD[[9, 10, 11, 12, 13]] = 32
_FOLD[[c for c in range(33, 127) if not chr(c).isalpha()]] = 32


def pair_codes(text: bytes, more_before: bool = False, more_after: bool = False) -> np.ndarray:
    """Codes of neighbouring bytes, ASCII letters in lower case, other ASCII as spaces; pairs of spaces are left out.

    A space stands before and after a whole text; a part of one has its neighbour there.
    """
    b = _FOLD[np.frombuffer((b"" if more_before else b" ") + text + (b"" if more_after else b" "), np.uint8)]
    code = b[:-1].astype(np.int32) << 8 | b[1:]
    return code[code != 0x2020]


@dataclass
class Model:
    """Counts of byte pairs by language, over the pairs (``codes``, sorted) that any language's texts have.

    ``cutoff``: texts of the language with a hash up to this one were fitted on.
    """

    names: list[str]
    codes: np.ndarray
    counts: np.ndarray
    cutoff: dict[str, int]
    seed: int = 1
    place: np.ndarray = field(init=False, repr=False)

    def __post_init__(self) -> None:
        self.place = np.full(ALL_PAIRS, len(self.codes), np.int32)
        self.place[self.codes] = np.arange(len(self.codes))
        self.total = self.counts.sum(1, dtype=np.float64) + FLOOR * ALL_PAIRS
        seen = np.concatenate((self.counts, np.zeros((len(self.names), 1))), axis=1) + FLOOR
        self.log = np.log(seen / self.total[:, None]).astype(np.float32)

    def score(self, raw: bytes, fitted: str | None) -> tuple[np.ndarray, int]:
        """Log-likelihoods of a whole text and its number of pairs; ``fitted``: the language it was fitted on as."""
        out, n = np.zeros(len(self.names)), 0
        mine = self.names.index(fitted) if fitted is not None else -1
        if mine >= 0:
            own = np.bincount(self.place[pair_codes(raw[:FIT_BYTES])], minlength=len(self.codes) + 1)[:-1]
            left = np.append(self.counts[mine] - own, 0) + FLOOR
            left = np.log(left / (self.total[mine] - own.sum())).astype(np.float32)
        for lo in range(0, max(1, len(raw)), 1 << 20):  # long texts by parts
            c = self.place[pair_codes(raw[max(0, lo - 1) : lo + (1 << 20)], lo > 0, lo + (1 << 20) < len(raw))]
            n += len(c)
            if len(self.names) > 16:
                out += self.log @ np.bincount(c, minlength=len(self.codes) + 1).astype(np.float32)
            else:
                out += [row[c].sum(dtype=np.float64) for row in self.log]
            if mine >= 0:
                out[mine] += left[c].sum(dtype=np.float64) - self.log[mine][c].sum(dtype=np.float64)
        return out, n


def label(declared: Column | str) -> Column:
    """The primary part of a language tag in lower case; blank is null."""
    c = F.col(declared) if isinstance(declared, str) else declared
    return F.nullif(F.regexp_extract(F.lower(F.trim(c.cast("string"))), "^[^-_]*", 0), F.lit(""))


def fit(base: DataFrame, seed: int = 1, languages: tuple[str, ...] | None = None) -> Model:
    """A model of byte pairs for each language, from a bounded sample of the texts (columns text, declared) that declare it.

    Of each language the different texts with the smallest hashes are taken, in one pass: a table of hash limits by
    language says which rows may be among them. Only counts of pairs come to the driver.
    """
    known = base.where(F.col("declared").isNotNull() & (F.length(F.trim("text")) > 0)).select(F.col("declared").alias("l"), F.xxhash64("text", F.lit(seed)).alias("h"), "text")
    if languages is not None:
        known = known.where(F.col("l").isin(*languages))
    share = F.least(F.lit(1.0), F.lit(1.5 * FIT_TEXTS) / F.col("n"))
    top = (F.lit(2.0**63) * (share * 2 - 1)).cast("decimal(20,0)")
    limits = cut(known.groupBy("l").agg(F.approx_count_distinct("h").alias("n")).withColumn("top", F.least(top, F.lit((1 << 63) - 1).cast("decimal(20,0)")).cast("long")))
    limits = limits.where(F.col("n") >= FEWEST - 1) if languages is None else limits
    chosen = known.join(small(limits.select("l", "top")), "l").where("h <= top").select("l", "h", F.expr(f"substr(text, 1, {FIT_BYTES})").alias("t"))

    def count(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.drop_duplicates("h").nsmallest(FIT_TEXTS, "h")
        total = np.zeros(ALL_PAIRS, np.int64)
        for t in rows["t"]:
            total += np.bincount(pair_codes(t.encode()[:FIT_BYTES]), minlength=ALL_PAIRS)
        at = np.flatnonzero(total)
        return pd.DataFrame({"l": [rows["l"].iloc[0]], "n": [len(rows)], "last": [int(rows["h"].max())], "codes": [at.tolist()], "counts": [total[at].tolist()]})

    found = chosen.groupBy("l").applyInPandas(count, "l string, n long, last long, codes array<int>, counts array<long>").where(F.col("n") >= FEWEST).collect()
    room = MODEL_BYTES // (12 * ALL_PAIRS)
    found = sorted(sorted(found, key=lambda r: (-r["n"], r["l"]))[:room], key=lambda r: r["l"])
    codes = np.unique(np.concatenate([np.zeros(0, np.int64), *[np.array(r["codes"], np.int64) for r in found]]))
    counts = np.zeros((len(found), len(codes)), np.int32)
    for i, r in enumerate(found):
        counts[i, np.searchsorted(codes, r["codes"])] = r["counts"]
    return Model([r["l"] for r in found], codes, counts, {r["l"]: r["last"] for r in found}, seed)


def text_scores(base: DataFrame, keep: list[str], model: Model) -> DataFrame:
    """``keep`` columns, ``score`` (log-likelihoods of the whole text, one a language) and ``pairs`` (their number)."""
    schema = base.select(*keep).schema.add("score", ArrayType(FloatType())).add("pairs", "long")
    held = base.sparkSession.sparkContext.broadcast(model)  # MODEL_BYTES at most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        for b in batches:
            score, pairs = [], []
            for t, h, l in zip(b.column(0), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                s, n = m.score((t.as_py() or "").encode(), l if l in m.cutoff and h <= m.cutoff[l] else None)
                score.append(s.astype(np.float32))
                pairs.append(n)
            yield pa.RecordBatch.from_arrays([*b.columns[3:], pa.array(score, pa.list_(pa.float32())), pa.array(pairs, pa.int64())], names=[*keep, "score", "pairs"])

    return base.select(F.col("text").alias("__text"), F.xxhash64("text", F.lit(model.seed)).alias("__h"), F.col("declared").alias("__l"), *keep).mapInArrow(run, schema)


def _softmax(logs: Column) -> Column:
    """Lambdas evaluate what they capture for every element, so maximum and sum are bound first."""
    use = lambda value, f: F.element_at(F.transform(F.array(value), f), 1)
    e = use(F.struct(logs.alias("l"), F.array_max(logs).alias("m")), lambda s: F.transform(s["l"], lambda x: F.exp(x - s["m"])))
    return use(e, lambda v: use(F.aggregate(v, F.lit(0.0), lambda a, y: a + y), lambda t: F.transform(v, lambda x: x / t)))


def posteriors(docs: DataFrame, key: str = "doc_id", text: str = "text", declared: str | None = "lang", host: str | None = "source", suffix: str | None = None, languages: tuple[str, ...] | None = None) -> DataFrame:
    """A row a document: key, language, confidence, kept, declared, text_language, likelihood.

    Every declared language is a class. One without a model (few texts declare it) is open to the documents that declare it,
    whose text is then as likely as any text: they are kept on their declaration unless a modelled language is far more
    likely. ``kept`` is false where no language is sure, where the bytes are unlike all modelled languages, and for texts
    without letters (null, empty). Of equally likely languages the first in the alphabet is named. Null declarations,
    hosts and suffixes are no evidence (a null host is smoothed as one host). Repeated rows are rows of their own. An
    empty table gives no rows; where nothing is declared languages are null and nothing is kept.
    """
    spark = docs.sparkSession
    none = F.lit(None).cast("string")
    base = docs.select(F.col(key).alias("key"), F.col(text).alias("text"), (label(declared) if declared else none).alias("declared"), (F.col(host).cast("string") if host else none).alias("host"), (F.lower(suffix) if suffix else none).alias("suffix"))
    model = fit(base, languages=languages)
    names, n = model.names, len(model.names) + 1  # the last class is what an unmodelled declaration says
    keep = ["key", "declared", "host", "suffix"]
    calm = F.least(F.lit(WEIGHT), F.lit(MOST) / F.greatest("pairs", F.lit(1)))
    other = F.col("declared").isNotNull() & ~F.col("declared").isin(*names) if languages is None else F.lit(False)
    flat = F.when(other, F.col("pairs") * float(np.log(1 / ALL_PAIRS)) * calm).otherwise(F.lit(NEVER))
    logs = F.concat(F.transform("score", lambda x: x.cast("double") * calm), F.array(flat))
    with small_batches(spark):
        marked = cut(text_scores(base, keep, model).withColumn("log", logs).withColumn("own", _softmax(F.col("log"))))
    sums = [F.sum(F.element_at("own", i + 1)).alias(f"p{i}") for i in range(n)]
    arr = F.array(*[F.col(f"p{i}") for i in range(n)])
    some = marked.where("pairs > 0")
    by_host = some.groupBy("host", "suffix").agg(*sums).select(F.col("host").alias("h"), F.col("suffix").alias("s"), arr.alias("in_host"))
    # wider levels are sums of the narrower ones' sums
    up = [F.sum(F.element_at("in_host", i + 1)).alias(f"p{i}") for i in range(n)]
    by_suffix = by_host.groupBy("s").agg(*up).select(F.col("s").alias("s2"), arr.alias("in_suffix"))
    whole = by_host.agg(*up).select(F.transform(arr, lambda x: F.coalesce(x, F.lit(0.0))).alias("in_all"))

    def smooth(counts: str, wider: Column) -> Column:
        total = F.aggregate(counts, F.lit(0.0), lambda a, y: a + y)
        return F.element_at(F.transform(F.array(total), lambda t: F.zip_with(counts, wider, lambda c, w: (c + F.lit(STRENGTH) * w) / (t + STRENGTH))), 1)

    even = F.array(*[F.lit(1.0 / n)] * n)
    priors = by_host.join(by_suffix, F.col("s").eqNullSafe(F.col("s2"))).join(F.broadcast(whole))  # one row
    priors = priors.withColumn("p_all", smooth("in_all", even)).withColumn("p_suffix", smooth("in_suffix", F.col("p_all"))).withColumn("prior", smooth("in_host", F.col("p_suffix"))).select("h", "s", "prior")
    out = marked.join(priors, F.col("host").eqNullSafe(F.col("h")) & F.col("suffix").eqNullSafe(F.col("s")), "left")

    def said(col: str, right: float) -> Column:
        """Log-evidence of a statement: it is right with this chance, else any other language; unknown ones say nothing."""
        true, false = float(np.log(right)), float(np.log((1 - right) / max(1, n - 1)))
        return F.when(F.col(f"__{col}") > 0, F.transform(F.sequence(F.lit(1), F.lit(n)), lambda i: F.when(i == F.col(f"__{col}"), true).otherwise(false))).otherwise(F.array_repeat(F.lit(0.0), n))

    place = F.create_map(*[F.lit(x) for i, name in enumerate(names) for x in (name, i + 1)]) if names else F.lit(None).cast("map<string,int>")
    out = out.withColumns({"__declared": F.when(other, n).otherwise(F.coalesce(F.element_at(place, F.col("declared")), F.lit(0))), "__suffix": F.coalesce(F.element_at(place, F.col("suffix")), F.lit(0))})
    logs = F.zip_with("log", F.transform(F.coalesce("prior", even), lambda x: F.log(x)), lambda a, b: a + b)
    for col, right in (("declared", DECLARED), ("suffix", SUFFIX)):
        logs = F.zip_with(logs, said(col, right), lambda a, b: a + b)
    out = out.withColumn("logs", logs).withColumn("post", _softmax(F.col("logs")))
    labels = F.array(*map(F.lit, names), F.when(other, F.col("declared")))
    at = lambda p: F.array_position(p, F.array_max(p)).cast("int")
    likely = F.array_max("score").cast("double") / F.when(F.col("pairs") > 0, F.col("pairs"))
    out = out.withColumn("likelihood", likely).withColumn("confidence", F.array_max("post"))
    letters = F.col("pairs") > 0
    fits = (F.col("likelihood") >= LIKELY) | (at(F.col("post")) == n)
    kept = F.coalesce(letters & (F.col("confidence") >= SURE) & fits & F.element_at(labels, at(F.col("post"))).isNotNull(), F.lit(False))
    return out.select(F.col("key").alias(key), F.when(letters, F.element_at(labels, at(F.col("post")))).alias("language"), "confidence", kept.alias("kept"), "declared", F.when(letters, F.element_at(labels, at(F.col("own")))).alias("text_language"), "likelihood")


def page_parts(pages: DataFrame) -> DataFrame:
    """Columns that raw pages offer: page_id, text (tags and scripts taken out), declared, host, suffix."""
    bare = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " "), r"<[^>]*+>", " ")
    host = F.lower(F.regexp_extract("url", r"^[a-zA-Z]+://([^/?#:]+)", 1))
    return pages.select("page_id", bare.alias("text"), F.nullif(F.regexp_extract("html", r"(?i)<html[^>]*\blang=[\"']?([a-z]+)", 1), F.lit("")).alias("declared"), host.alias("host"), F.substring_index(host, ".", -1).alias("suffix"))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return posteriors(documents(spark, sf_dir))


def language_of_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Raw pages with all four kinds of evidence: text, declared markup language, address suffix and host."""
    return posteriors(page_parts(spark.read.parquet(f"{sf_dir}/pages.parquet")), key="page_id", declared="declared", host="host", suffix="suffix")
