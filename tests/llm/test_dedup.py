"""Near-duplicates, repeated passages and vectors against brute force."""

import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from wavefront.llm import bitmap, embeddings, minhash, suffix_dedup
from wavefront.llm.suffix_order import LENGTH, difference_cover, repeated_starts, shift_table, suffix_array
from wavefront.operators import components
from wavefront.operators.components import connected_components


def shingles(text):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def classes(texts, percent):
    """Least id reachable over links of rows with ids; rows of one id are one node."""
    own = [(i, shingles(t)) for i, t in texts if i is not None]
    root = {i: i for i, _ in own}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for k, (a, s) in enumerate(own):
        for b, o in own[:k]:
            if s and o and 100 * len(s & o) >= percent * len(s | o):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in root}


@pytest.mark.parametrize("percent", [80, 85])
def test_near_duplicates_match_brute_force(docs, texts, percent):
    want = classes(texts, percent)
    got = minhash.near_duplicates(docs, percent).collect()
    assert len(got) == len(texts)
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0, r["n_shingles"]) for r in got) == sorted((i is None, i or 0, len(shingles(t))) for i, t in texts)
    for r in got:
        assert r["component_id"] == want.get(r["doc_id"]) and r["kept"] == (r["doc_id"] == r["component_id"])
    assert want[4] == 1 and want[10] == 9 and want[6] == 6


def test_one_of_each_keeps_columns_and_one_of_a_class(docs):
    out = minhash.one_of_each(docs)
    assert out.columns == docs.columns
    ids = [r["doc_id"] for r in out.collect()]
    assert 1 in ids and 2 not in ids and 4 not in ids and ids.count(None) == 2


@pytest.mark.parametrize("stars", [minhash.STARS, 0, 2])
def test_original_in_the_middle_of_its_copies(spark, monkeypatch, stars):
    """Copies are near the original and not near each other; with no further stars the blocks alone must find it."""
    monkeypatch.setattr(minhash, "STARS", stars)
    monkeypatch.setattr(minhash, "BLOCK_BYTES", 8 * 8 * 400)
    r = random.Random(5)
    base = [f"w{r.randrange(10**6)}" for _ in range(404)]
    rows = []
    for n in range(51):
        own = list(base)
        for k in r.sample(range(5, 400), 4) if n != 25 else ():
            own[k] = f"x{n}y{k}"
        rows.append((n, " ".join(own)))
    want = classes(rows, 85)
    assert set(want.values()) == {0}
    got = {x["doc_id"]: x["component_id"] for x in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want


def test_similarity_near_the_threshold(spark):
    base = [f"w{k}" for k in range(300)]
    rows = [(0, " ".join(base))] + [(n, " ".join("x" if k in {11 * j for j in range(1, n + 1)} else w for k, w in enumerate(base))) for n in range(1, 12)]
    got = {r["doc_id"]: r["component_id"] for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == classes(rows, 85)


def test_tiny_sets_link_only_when_equal(spark):
    rows = [(0, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e g"), (3, "A  B c\td e f")]
    got = {r["doc_id"]: r["component_id"] for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {0: 0, 1: 0, 2: 2, 3: 0}


def removed(texts):
    """Brute force: (kept bytes, runs) of each text."""
    raw = [(t or "").encode() for _, t in texts]
    seen = Counter(t[k : k + LENGTH] for t in raw for k in range(len(t) - LENGTH + 1))
    out = []
    for t in raw:
        gone = np.zeros(len(t) + 1, bool)
        for k in range(len(t) - LENGTH + 1):
            if seen[t[k : k + LENGTH]] > 1:
                gone[k : k + LENGTH] = True
        out.append((bytes(b for b, g in zip(t, gone, strict=False) if not g), int((np.diff(gone.astype(int)) == 1).sum() + gone[0])))
    return out


def test_repeats_match_brute_force(docs, texts):
    want = sorted((i is None, i or 0, len((t or "").encode()), n, hashlib.sha256(k).hexdigest()) for (i, t), (k, n) in zip(texts, removed(texts), strict=True))
    got = suffix_dedup.remove_repeats(docs).collect()
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0, r["n_bytes"], r["n_spans"], r["kept_sha256"]) for r in got) == want
    assert all(hashlib.sha256(r["kept"]).hexdigest() == r["kept_sha256"] and r["n_removed"] == r["n_bytes"] - len(r["kept"]) for r in got)


def test_hot_buckets_give_the_same(docs, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "BUCKET_CLASSES", 1)
    a = suffix_dedup.remove_repeats(docs)
    assert sorted(r["kept_sha256"] for r in a.collect()) == sorted(hashlib.sha256(k).hexdigest() for k, _ in removed([(r["doc_id"], r["text"]) for r in docs.collect()]))


@pytest.mark.parametrize("in_task", [0, 10**6])
def test_hot_buckets_are_split_as_tables_or_in_their_task(docs, monkeypatch, in_task):
    monkeypatch.setattr(suffix_dedup, "BUCKET_CLASSES", 1)
    monkeypatch.setattr(suffix_dedup, "IN_TASK", in_task)
    steps, dealt_out = [], suffix_dedup._dealt_out
    monkeypatch.setattr(suffix_dedup, "_dealt_out", lambda large: steps.append(1) or dealt_out(large))
    a = suffix_dedup.remove_repeats(docs)
    assert sorted(r["kept_sha256"] for r in a.collect()) == sorted(hashlib.sha256(k).hexdigest() for k, _ in removed([(r["doc_id"], r["text"]) for r in docs.collect()]))
    assert bool(steps) == (not in_task)


def test_passages_of_51_words_go(spark):
    """Short words: 51 of them take far less than 400 bytes; blanks between words do not matter, 50 words stay."""
    r = random.Random(3)
    own = lambda n: [f"{r.randrange(10**5)}" for _ in range(n)]
    passage, less = [f"é{k}" for k in range(51)], [f"b{k}" for k in range(50)]
    assert len(" ".join(passage).encode()) < LENGTH
    parts = [(own(30), own(20)) for _ in range(4)]
    rows = [(k, " ".join([*a, *(passage if k < 2 else less), *b]) if k != 1 else " ".join(a) + "\n" + "  ".join(passage) + "\n" + " ".join(b)) for k, (a, b) in enumerate(parts)]
    got = {x["doc_id"]: x["text"].split() for x in suffix_dedup.without_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {k: [*a, *b] if k < 2 else [*a, *less, *b] for k, (a, b) in enumerate(parts)}


def test_without_repeats_keeps_columns(docs):
    out = suffix_dedup.without_repeats(docs)
    assert out.columns == docs.columns and out.count() == docs.count()
    assert out.where("doc_id = 13").first()["text"] == "" and out.where("doc_id = 13").first()["n_chars"] == 0


@pytest.mark.parametrize("text", [b"", b"a", b"banana", b"a" * 200, b"abracadabra" * 20, bytes(range(256)) * 2, b"\0\0a\0\0b\0\0"])
def test_suffix_array_is_sorted(text):
    assert suffix_array(text, 16).tolist() == sorted(range(len(text)), key=lambda i: text[i:])


@pytest.mark.parametrize("v", [8, 16, 32, 64])
def test_difference_cover(v):
    cover = difference_cover(v)
    assert {(a - b) % v for a in cover for b in cover} == set(range(v))
    t = shift_table(v)
    assert all((i + t[i, j]) % v in cover and (j + t[i, j]) % v in cover for i in range(v) for j in range(v))


def test_repeated_starts_by_counting():
    r = np.random.Generator(np.random.PCG64(1))
    common = bytes(r.integers(97, 100, 900, dtype=np.uint8))
    slices, bucket, anchor = [], [], []
    for k in range(6):
        a = int(r.integers(0, 200))
        piece = bytearray(common[300 - a : 300 + 420])
        if k % 2:
            piece[int(r.integers(0, len(piece)))] ^= 1
        slices.append(bytes(piece))
        bucket.append(k // 4)
        anchor.append(a)
    seen = Counter((b, s - a, t[s : s + LENGTH]) for t, b, a in zip(slices, bucket, anchor, strict=True) for s in range(len(t) - LENGTH + 1))
    got = repeated_starts(slices, np.array(bucket), np.array(anchor), np.ones(6, int))
    for t, b, a, flags in zip(slices, bucket, anchor, got, strict=True):
        assert flags.tolist() == [seen[b, s - a, t[s : s + LENGTH]] > 1 for s in range(len(t) - LENGTH + 1)]
    assert any(f.any() for f in got) and not all(f.all() for f in got)


def vectors(spark):
    r = np.random.Generator(np.random.PCG64(2))
    base = r.standard_normal((60, 16))
    rows = [(k, v.tolist()) for k, v in enumerate(base)] + [(100 + k, (base[k % 5] + 0.05 * r.standard_normal(16)).tolist()) for k in range(40)]
    odd = [(900, None), (901, [0.0] * 16), (902, [float("nan")] + [1.0] * 15), (903, []), (None, base[0].tolist()), (904, [None] + [1.0] * 15), (905, [1.0, 2.0]), (906, [2.0, 4.0])]
    return rows, odd, spark.createDataFrame(rows + odd, "vec_id long, embedding array<float>").selectExpr("*", "1 as n_links")


@pytest.mark.parametrize("chunk", [1024, 4])
def test_vectors_match_brute_force(spark, monkeypatch, chunk):
    monkeypatch.setattr(embeddings, "CHUNK", chunk)
    rows, odd, df = vectors(spark)
    x = np.array([np.array(v, np.float32) for _, v in rows], float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    near = x @ x.T >= 0.9
    np.fill_diagonal(near, False)
    label = np.array([i for i, _ in rows])
    for _ in range(50):
        label = np.minimum(label, np.where(near, label[None, :], 1 << 30).min(axis=1))
    want = {i: (int(near[k].sum()), int(label[k])) for k, (i, _) in enumerate(rows)} | {i: (0, i) for i, _ in odd} | {905: (1, 905), 906: (1, 905)}
    got = embeddings.near_vectors(df).collect()
    assert len(got) == len(rows) + len(odd)
    assert {r["vec_id"]: (r["n_links"], r["component_id"]) for r in got} == want
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in got)


def test_components_of_a_chain_and_a_star(spark):
    rows = [(k, k + 1) for k in range(40)] + [(100, k) for k in range(101, 160)] + [(7, 7), (None, 3)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(rows, "u long, v long")).collect()}
    assert got == {k: 0 for k in range(41)} | {k: 100 for k in range(100, 160)}


def test_few_edges_take_one_task_and_no_rounds(spark, monkeypatch):
    r = random.Random(4)
    edges = spark.createDataFrame([(r.randrange(-200, 400), r.randrange(400)) for _ in range(350)], "u long, v long")
    asked, cut = [], components.cut
    monkeypatch.setattr(components, "cut", lambda df: asked.append(1) or cut(df))
    once = sorted(map(tuple, connected_components(edges).collect()))
    assert len(asked) == 2
    monkeypatch.setattr(components, "ONE_TASK", 0)
    assert sorted(map(tuple, connected_components(edges).collect())) == once and len(asked) > 4


def test_bit_map_never_loses_a_key(spark):
    rows = spark.range(2000).selectExpr("id", "xxhash64(id) as k")
    hit = bitmap.marked(rows, bitmap.marks(rows.where("id % 7 = 0"), "k"), "k")
    assert hit.where("id % 7 = 0 and not hit").count() == 0 and hit.where("hit").count() < 400 and hit.count() == 2000


def test_empty_tables(spark, no_docs):
    assert minhash.near_duplicates(no_docs).count() == 0
    assert minhash.one_of_each(no_docs).count() == 0
    assert suffix_dedup.remove_repeats(no_docs).count() == 0
    assert suffix_dedup.without_repeats(no_docs).count() == 0
    assert embeddings.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0
