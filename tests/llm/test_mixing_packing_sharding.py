import random
import zlib

import duckdb
import numpy as np
import pandas as pd
import pytest

from worldfold.llm import common, mixing, packing, sharding

COLS = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, None, s, len(t or "")) for i, t, s in rows], COLS)


def some(n=300, seed=0):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcde") for _ in range(r.randint(1, 6)))
    rows = [(i, " ".join(word() for _ in range(r.choice([0, 1, 5, 40, 300]))), r.choice(["a", "b", "c", None, "hot", "hot", "hot"])) for i in range(n)]
    return rows + [(n, None, "a"), (n + 1, "", None), (n + 2, "x " * 5000, "b"), (n + 3, "same", "c"), (n + 3, "same", "c")]


def targets_by_hand(sizes, weights=(5, 2, 1)):
    total, names = sum(sizes.values()), sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    capped: set = set()
    while True:
        free = [s for s in names if s not in capped]
        rest = total - sum(3 * sizes[s] for s in capped)
        t = {s: 3 * sizes[s] if s in capped else rest * w[s] / sum(w[x] for x in free) for s in names}
        more = {s for s in free if t[s] > 3 * sizes[s]}
        if not more:
            return t
        capped |= more


def test_mix_meets_targets(spark):
    rows = some(900)
    got = mixing.mix(docs(spark, rows)).toPandas()
    assert len(got) == len(rows)
    sizes = {}
    for _, t, s in rows:
        sizes[s] = sizes.get(s, 0) + len((t or "").split())
    want = targets_by_hand(sizes)
    assert (got.taken <= 3 * got["size"]).all()
    for s, t in want.items():
        mine = got[got.source.isna()] if s is None else got[got.source == s]
        assert mine.target.iloc[0] == pytest.approx(t)
        assert mine["size"].sum() == mine.source_size.iloc[0] == sizes[s]
        assert mine.taken.sum() == pytest.approx(t, abs=64)
    again = mixing.mix(docs(spark, rows[::-1]).repartition(5)).toPandas()
    key = ["doc_id", "size", "taken"]
    assert got[key].sort_values(key, ignore_index=True).equals(again[key].sort_values(key, ignore_index=True))


def test_mix_equals_sql(spark):
    rows = [r for r in some(200) if r[0] != 203]
    con = duckdb.connect()
    documents = pd.DataFrame([(i, t, s) for i, t, s in rows], columns=["doc_id", "text", "source"])  # noqa: F841
    want = con.sql(mixing.ORACLE).df().sort_values("doc_id", ignore_index=True)
    got = mixing.mix(docs(spark, rows)).toPandas().sort_values("doc_id", ignore_index=True)
    assert (got.taken == want.taken).all() and (got.target == want.target).all()


def test_mix_of_nothing_and_of_no_words(spark):
    assert mixing.mix(docs(spark, [])).count() == 0
    got = mixing.mix(docs(spark, [(1, None, "a"), (2, " \n", None)])).toPandas()
    assert got.taken.tolist() == [0, 0] and got.target.tolist() == [0.0, 0.0]


def test_mixed_documents_repeat_whole_rows(spark):
    df = docs(spark, [(i, "w " * 50, "abc"[i % 3] if i < 90 else "a") for i in range(120)])
    out = mixing.mixed_documents(df)
    assert out.columns == df.columns
    by = out.toPandas().groupby("source").size().to_dict()
    assert by["a"] > by["b"] > by["c"]
    assert mixing.mixed_documents(docs(spark, [])).count() == 0


def test_schedule_is_even_at_every_length(spark):
    per = spark.createDataFrame([("a", 0, 700, 700.0), ("b", 1, 300, 300.0)], "source string, place int, source_size long, target double")
    s = mixing.schedule(spark, per, 1000, 1, 3).toPandas().sort_values("slot")
    share = (s.place == 0).cumsum() / range(1, len(s) + 1)
    assert abs(share.iloc[20:] - 0.7).max() < 0.1 and abs(share.iloc[-1] - 0.7) < 0.005


def test_word_count(spark):
    texts = [None, "", " ", "a", " a b ", "a\tb\nc\x0b\x0cd\re", "é ü", "a\xa0b", "x" * 100]
    df = spark.createDataFrame([(t,) for t in texts], "t string")
    assert [r[0] for r in df.select(common.word_count(df.t)).collect()] == [0, 0, 0, 1, 2, 5, 2, 1, 1]


def test_encoder_equals_the_other_library():
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    e = packing.encoder()
    for s in ["", "Hello world", " a  b ", "x\n y", "it's 1234 été ñ 日本", "<|endoftext|>", "a <|endoftext|> b", "  ", "\t\n", "€" * 50]:
        assert np.frombuffer(e(s), "<u4").tolist() == t.encode(s, add_special_tokens=False).ids, s


def _hold(packed, df, length=2048):
    e = packing.encoder()
    by_doc = {}
    for r in packed.itertuples():
        by_doc.setdefault(r.doc_id, []).append(r)
    texts = {}
    for r in df.collect():
        texts.setdefault(r["doc_id"], []).append(r["text"] or "")
    for k, ts in texts.items():
        raw = e(ts[0]) + (1).to_bytes(4, "little")
        ps = sorted(by_doc[k], key=lambda p: p.start)
        assert sum(p.length for p in ps) == len(ts) * len(raw) // 4
        for p in ps:
            assert p.doc_tokens == len(raw) // 4 and zlib.crc32(raw[4 * p.start : 4 * (p.start + p.length)]) == p.ids_crc32
    for _, g in packed.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == np.concatenate(([0], g.length.cumsum()[:-1])).tolist() and g.length.sum() <= length
    assert sorted(packed.sequence_id.unique()) == list(range(packed.sequence_id.nunique()))


def test_packing_holds(spark):
    df = docs(spark, some(400))
    packed = packing.pack(df)
    got = packed.toPandas()
    _hold(got, df)
    assert packing.padding(packed).collect()[0]["padding"] < 0.05
    assert packing.pack(docs(spark, [])).count() == 0


def test_patterns_place_every_piece_once():
    r = random.Random(1)
    for _ in range(30):
        h = {r.randint(1, 64): r.randint(1, 300) for _ in range(r.randint(1, 40))}
        found = packing.patterns(h, 64)
        used = {}
        for n, parts in found:
            assert sum(s * k for s, k in parts) <= 64
            for s, k in parts:
                used[s] = used.get(s, 0) + n * k
        assert used == h
        table, seen = packing.places(found), set()
        for s, n in h.items():
            seq, off = packing.locate(table, s, np.arange(n))
            for a, b in zip(seq.tolist(), off.tolist(), strict=True):
                cells = {(a, b + i) for i in range(s)}
                assert not cells & seen
                seen |= cells


def test_shards_are_near_equal_and_slots_gapless(spark):
    rows = some(3000) + [(10_000 + i, "the same text again and again", "hot") for i in range(1500)]
    df = docs(spark, rows)
    got = sharding.shard(df).toPandas()
    assert len(got) == len(rows) and set(got["law"]) == {"bytes"} and got.grown_shard.isna().all()
    size = got.groupby("shard")["size"].sum()
    assert set(size.index) == set(range(8)) and size.max() < 1.1 * size.min() + 20_000
    for _, g in got.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
    text = {i: t for i, t, _ in rows}
    for r in got.head(200).itertuples():
        raw = (text[r.doc_id] or "").encode()
        assert r.size == len(raw) + 1 and r.text_crc32 == zlib.crc32(raw)


def test_small_groups_stay_in_a_shard(spark):
    rows = [(i, f"text {i // 3} " * 20, "a") for i in range(3000)]
    got = sharding.shard(docs(spark, rows)).toPandas()
    got["group"] = got.doc_id // 3
    assert (got.groupby("group").shard.nunique() > 1).mean() < 0.01


def test_shards_of_few_rows(spark):
    assert sharding.shard(docs(spark, [])).count() == 0
    got = sharding.shard(docs(spark, [(1, None, "a"), (1, None, "a"), (2, "", None)])).toPandas()
    assert len(got) == 3 and got["size"].tolist() == [1, 1, 1]
    for _, g in got.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))


def test_small_sources_of_a_large_corpus_meet_their_targets(spark):
    # 20 million words; the weights ask for all of the small sources thrice
    rows = [(0, "w " * 500, "b"), (1, "w " * 7, "c"), *[(k, "w " * 400_000, "a") for k in range(2, 52)]]
    got = mixing.mix(docs(spark, rows).repartition(8), min_block=1).groupBy("source").agg({"taken": "sum", "target": "max"}).collect()
    assert len(got) == 3 and all(abs(x["sum(taken)"] - x["max(target)"]) <= 4 for x in got), got


def test_points_of_the_schedule_do_not_overflow(spark):
    # slots over 2**32 / golden ratio would overflow a long as one product
    n = 4_000_000_000
    point = f"((slot div 65536 % 65536 * {mixing.GOLDEN} % 65536) * 65536 + slot % 65536 * {mixing.GOLDEN}) % {2**32}"
    got = [x[1] for x in spark.range(n, n + 50).withColumnRenamed("id", "slot").selectExpr("slot", f"{point} AS point").orderBy("slot").collect()]
    assert got == [s * mixing.GOLDEN % 2**32 for s in range(n, n + 50)]
