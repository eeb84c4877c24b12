import hashlib
import random

import numpy as np
import pytest
import xxhash

from worldfold.llm import fingerprints as fp
from worldfold.llm import simhash

COLS = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, texts, ids=None):
    return spark.createDataFrame([(k, t, None, "s", None) for k, t in zip(ids or range(len(texts)), texts, strict=True)], COLS)


def prose(r, n):
    return " ".join("".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7))) for _ in range(n))


def shingles(t, k=5):
    w = t.encode().lower().split()
    return {b" ".join(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def edit(r, t, n):
    w = t.split()
    for _ in range(n):
        w[r.randrange(len(w))] = "edited" + str(r.randrange(10**6))
    return " ".join(w)


def test_likeness_estimates_jaccard():
    r = random.Random(0)
    errors = []
    for n in (0, 1, 3, 8, 20, 60):
        for _ in range(6):
            a = prose(r, 300)
            b = edit(r, a, n)
            low, some = fp.sketch([a.encode(), b.encode()])
            p = fp.pack(low, some)
            j = fp.likeness(p[:1], p[1:], some[:1], some[1:])[0]
            sa, sb = shingles(a), shingles(b)
            errors.append(j - len(sa & sb) / len(sa | sb))
    assert abs(np.mean(errors)) < 0.02 and np.std(errors) < 0.05


def test_texts_in_any_company_have_the_same_sketch():
    r = random.Random(1)
    texts = [prose(r, n) for n in (0, 1, 3, 4, 5, 6, 50)] + ["", " ", "A b  C\n\td", "x" * 5000]
    alone = [fp.hex_of(fp.pack(*fp.sketch([t.encode()])))[0] for t in texts]
    together = fp.hex_of(fp.pack(*fp.sketch([t.encode() for t in texts])))
    assert alone == together
    assert fp.hex_of(fp.pack(*fp.sketch([b"a B c d e f"]))) == fp.hex_of(fp.pack(*fp.sketch([b" A b\nc D e F "])))
    assert alone[0] == alone[7] == "0" * 256 and len(set(alone[1:7])) == 6


@pytest.mark.parametrize("step", [1, 7, 64])
def test_blocks_do_not_change_hashes(monkeypatch, step):
    r = random.Random(8)
    texts = [prose(r, 200), "x" * 500 + " y z", "", prose(r, 3)]
    raw = np.frombuffer("".join(texts).encode(), np.uint8)
    ends = np.cumsum([len(t) for t in texts])
    whole = fp.shingle_hashes(raw, ends)
    monkeypatch.setattr(fp, "_STEP", step)
    for a, b in zip(whole, fp.shingle_hashes(raw, ends), strict=True):
        assert (a == b).all()


def test_densification_fills_all_and_copies_only_filled_bins():
    least = np.full((3, 16), np.iinfo(np.uint64).max, np.uint64)
    least[0, 3], least[1, [0, 5]] = 7, (1, 2)
    empty = least == np.iinfo(np.uint64).max
    out = fp.densify(least.copy(), empty)
    assert set(out[0].tolist()) == {7} and set(out[1].tolist()) == {1, 2} and (out[2] == np.iinfo(np.uint64).max).all()


def brute_compare(rows):
    order = sorted(rows, key=lambda x: -x[0])
    for i, (k, t) in enumerate(order):
        nxt = order[(i + 1) % len(order)][1] or ""
        t = t or ""
        n = len(t) // 3
        yield k, len(t), hashlib.sha256((t[: len(t) - n] + nxt[:n]).encode()).hexdigest(), t, nxt


@pytest.mark.parametrize("parts", [1, 3, 16])
def test_edited_texts_follow_the_next_document(spark, parts):
    r = random.Random(2)
    rows = [(i * 3 - 50, prose(r, r.choice([0, 1, 4, 30, 200]))) for i in range(120)] + [(1000, None), (1001, "é" * 10), (1002, "short")]
    r.shuffle(rows)
    got = {x["doc_id"]: x for x in fp.compare_with_next(docs(spark, [t for _, t in rows], [k for k, _ in rows]).repartition(4), parts=parts).collect()}
    assert len(got) == len(rows)
    for k, n, sha, t, nxt in brute_compare(rows):
        assert (got[k]["n_chars"], got[k]["edited_sha256"]) == (n, sha)
        a, b = shingles(t), shingles(nxt)
        want = len(a & b) / len(a | b) if a and b else float(not a and not b)
        assert got[k]["near_next"] == pytest.approx(want, abs=0.15)


def test_alone_empty_and_null(spark):
    assert fp.compare_with_next(docs(spark, [])).count() == 0
    r = fp.compare_with_next(docs(spark, ["a b c d e f g"])).collect()
    assert len(r) == 1 and r[0]["near_next"] == 1.0
    two = fp.compare_with_next(docs(spark, [None, None], [5, 5])).collect()
    assert [x["near_edited"] for x in two] == [1.0, 1.0]


def test_fingerprint_column_keeps_others(spark):
    out = fp.fingerprint(docs(spark, ["a b c d e f", None]))
    assert out.columns[-1] == "fingerprint" and out.count() == 2


# ---- SimHash

def brute_simhash(t, k=3):
    w = t.encode().lower().split()
    if not w:
        return 0
    s = [b" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] or [b" ".join(w)]
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << j for j in range(64) if 2 * sum(x >> j & 1 for x in h) > len(h))


def brute_groups(fps, radius=2):
    parent = list(range(len(fps)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= radius:
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return [root(i) for i in range(len(fps))]


def test_groups_equal_brute_force(spark):
    r = random.Random(3)
    base = [prose(r, r.choice([1, 2, 3, 8, 60, 400])) for _ in range(60)]
    texts = base + [edit(r, t, 1) for t in base for _ in range(2)] + [None, "", " \n", "A B C", "a b c", *base[:5], "Ünï Ä ä x"]
    got = {x["doc_id"]: x for x in simhash.groups(docs(spark, texts)).collect()}
    fps = [brute_simhash(t or "") for t in texts]
    want = brute_groups(fps)
    for i in range(len(texts)):
        assert got[i]["fingerprint"] == f"{fps[i]:016x}" and got[i]["component_id"] == want[i]
    assert simhash.groups(docs(spark, [])).count() == 0


@pytest.mark.parametrize(("radius", "group"), [(1, 2000), (1, 3), (2, 2000), (2, 3), (3, 2000), (3, 3), (5, 3)])
def test_links_connect_what_is_close_also_in_large_groups(spark, radius, group):
    r = random.Random(4)
    fps = []
    for _ in range(25):
        x = r.getrandbits(64)
        fps.append(x)
        for _ in range(12):  # chains of one and two bits
            x ^= (1 << r.randrange(64)) | (1 << r.randrange(64))
            fps.append(x)
    fps = list(dict.fromkeys(fps))
    signed = [simhash._signed(x) for x in fps]
    df = spark.createDataFrame([(x,) for x in signed], "fp long")
    edges = simhash.links(df, radius, group)
    assert all(((a ^ b) & (2**64 - 1)).bit_count() <= radius and a < b for a, b in [tuple(e) for e in edges.collect()])
    root = {x["node"]: x["root"] for x in simhash.components(edges).collect()}
    want = brute_groups(fps, radius)
    mine = [root.get(x, x) for x in signed]
    assert len(set(mine)) == len(set(want)) == len(set(zip(mine, want, strict=True)))


def test_far_pairs_are_discarded_by_the_table_and_no_close_one_is():
    r = np.random.default_rng(3)
    u = r.integers(-(2**63), 2**63, 400)
    u = np.unique(np.concatenate((u, u[:100] ^ 5, u[:50] ^ (1 << 40))))
    seen = {}
    got = {tuple(sorted(p)) for p in simhash.close_pairs(u, 2, seen)}
    bits = u.view(np.uint64)
    d = np.bitwise_count(bits[:, None] ^ bits[None, :])
    assert got == {(i, j) for i, j in zip(*np.nonzero(d <= 2), strict=True) if i < j}
    pairs = len(u) * (len(u) - 1) // 2
    assert seen["in_reach"] < 0.5 * pairs and seen["left"] < 1.05 * seen["verified"] + 5


def test_radius_is_checked(spark):
    df = spark.createDataFrame([(1,), (3,)], "fp long")
    assert simhash.links(df, 0).count() == 0
    with pytest.raises(ValueError):
        simhash.links(df, 15)


def test_pivot_columns_bound_distances(spark):
    r = random.Random(5)
    a = r.getrandbits(64)
    b = a ^ (1 << 3) ^ (1 << 40)
    t = simhash.pivot_table(spark.createDataFrame([(simhash._signed(a),), (simhash._signed(b),)], "fp long")).collect()
    assert max(abs(x - y) for x, y in zip(t[0]["pivots"], t[1]["pivots"], strict=True)) <= 2


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 300)] + [(5000, 5001), (5001, 5000)]
    got = {x["node"]: x["root"] for x in simhash.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(201)) and all(got[1000 + i] == 1000 for i in range(300)) and got[5001] == 5000
    assert simhash.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_one_of_each_group_stays(spark):
    r = random.Random(6)
    base = [prose(r, 150) for _ in range(40)]
    near = [edit(r, t, 2) for t in base[:20]]
    far = [edit(r, t, 25) for t in base[20:30]]
    texts = base + near + far + base[:10] + [None, "", "one", "one"]
    df = docs(spark, texts)
    df = df.unionByName(df.where("doc_id = 3"))  # a repeated row
    kept = sorted(x["doc_id"] for x in simhash.keep_one(df).collect())
    sets = [shingles(t or "") for t in texts]
    parent = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            both = sets[i] | sets[j]
            if not both or len(sets[i] & sets[j]) / len(both) >= 0.8:
                a, b = i, j
                while parent[a] != a:
                    a = parent[a]
                while parent[b] != b:
                    b = parent[b]
                parent[max(a, b)] = min(a, b)
    assert kept == [i for i in range(len(texts)) if parent[i] == i]
    assert simhash.keep_one(docs(spark, [])).count() == 0


def test_large_groups_of_near_copies(spark, monkeypatch):
    monkeypatch.setattr(simhash, "GROUP", 10)
    r = random.Random(7)
    t = prose(r, 400)
    texts = [edit(r, t, 3) for _ in range(60)] + [prose(r, 100) for _ in range(20)]
    base = docs(spark, texts)
    nodes = simhash.wide_fingerprints(base, ["doc_id"]).selectExpr("doc_id AS id", "wide", "samples")
    root = {x["node"]: x["root"] for x in simhash.components(simhash.near_links(nodes, group=10)).collect()}
    assert {root.get(i) for i in range(60)} == {0} and not any(i in root for i in range(60, 80))


def first_of_groups(texts):
    """What brute force keeps: the first text of each group that pairs of Jaccard 0.8 or more connect."""
    sets = [shingles(t or "") for t in texts]
    parent = list(range(len(texts)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both >= 0.8 * (len(sets[i]) + len(sets[j]) - both):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return [i for i in range(len(texts)) if parent[i] == i]


def star(r, n, words=110):
    """A base text, and copies near to it but not to each other: two words changed in each."""
    base = prose(r, words).split()
    out = [" ".join(base)]
    for k in range(n):
        w = list(base)
        for i in r.sample(range(words), 2):
            w[i] = f"changed{k}x{i}"
        out.append(" ".join(w))
    return out


def kept_ids(df):
    return sorted(x["doc_id"] for x in simhash.keep_one(df).collect())


@pytest.mark.parametrize("n", [60, 500, 1500])
def test_stars_of_near_copies_equal_brute_force(spark, n):
    r = random.Random(11)
    texts = [prose(r, 110), *star(r, n)[::-1]]  # the base comes last
    assert kept_ids(docs(spark, texts)) == first_of_groups(texts) == [0, 1]


def test_groups_over_the_limit_equal_brute_force(spark, monkeypatch):
    for name, value in (("GROUP", 10), ("BLOCK", 40), ("BLOCK_SHINGLES", 3000)):
        monkeypatch.setattr(simhash, name, value, raising=False)
    r = random.Random(12)
    texts = [*star(r, 300)[::-1], *star(r, 80)[::-1], *[prose(r, 110) for _ in range(5)]]
    assert kept_ids(docs(spark, texts)) == first_of_groups(texts) == [0, 301, *range(382, 387)]


def test_different_texts_with_one_filler_word_stay(spark):
    r = random.Random(13)
    texts = [" ".join(["x"] * 300) + " " + prose(r, 200) for _ in range(8)]
    texts += [texts[0].upper(), texts[1] + " \n"]  # copies by their shingles
    assert kept_ids(docs(spark, texts)) == first_of_groups(texts) == list(range(8))


def test_repeated_lines_and_short_texts_equal_brute_force(spark):
    r = random.Random(14)
    texts = [prose(r, 150) for _ in range(6)]
    texts += [t + f" {line}" * n for t in texts[:6] for line in [prose(r, 10)] for n in (5, 10)]
    short = [prose(r, 8) for _ in range(60)]
    texts += [*short, *[f"{t} more" for t in short]]
    assert kept_ids(docs(spark, texts)) == first_of_groups(texts) == [*range(6), *range(18, 78)]


def test_wide_fingerprints_count_a_shingle_once(spark):
    r = random.Random(15)
    t, line = prose(r, 150), prose(r, 10)
    # five appended lines have all the shingles that fifty have
    rows = simhash.wide_fingerprints(docs(spark, [f"{t} {line} {line}" + f" {line}" * n for n in (3, 48)]), ["doc_id"]).collect()
    assert rows[0]["wide"] == rows[1]["wide"] and rows[0]["same"] == rows[1]["same"]
