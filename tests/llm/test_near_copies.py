import random
import re

import numpy as np
import pytest

from corpusdedup.llm import near_copies
from corpusdedup.llm.near_copies import band_keys, keep_first_similar, shingle_set, similarity
from corpusdedup.operators.graph import DisjointSets


def shingles(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    return {tuple(words[i : i + 5]) for i in range(len(words) - 4)} or {tuple(words)}


def firsts(docs):
    sets = DisjointSets()
    own = {i: shingles(t) for i, t in docs}
    for i in own:
        for j in own:
            if i < j and len(own[i] & own[j]) >= 0.8 * len(own[i] | own[j]):
                sets.union(i, j)
    return {i for i in own if sets.find(i) == i}


def made(seed, groups=12, copies=12):
    random.seed(seed)
    out = []
    for _ in range(groups):
        base = [f"w{random.randrange(400)}" for _ in range(random.choice([6, 40, 150, 400]))]
        for _ in range(copies):
            words = list(base)
            for k in random.sample(range(len(words)), random.choice([0, 1, 2, 4, len(words) // 60])):
                words[k] = random.choice(["odd", "W1", "other"])
            out.append(" ".join(words))
    random.shuffle(out)
    return list(enumerate(out))


def test_sets_and_keys():
    for text in ("", " \n", "one", "a b c d e", "a b c d e f a b c d e f a", "Äb B c D e f"):
        assert len(shingle_set(text.encode())) == (len(shingles(text)) if text.split() else 0)
    a, b = (shingle_set(" ".join(map(str, range(k, 5000 + k))).encode()) for k in (0, 500))
    assert abs(similarity(a, b) - 4496 / 5496) < 1e-9 and similarity(a[:0], a[:0]) == 1 and similarity(a[:0], b) == 0
    assert 1 <= (band_keys(a) == band_keys(b)).sum() < 40 and len(set(band_keys(a).tolist())) == 40


def test_pairs_of_the_similarity_are_all_found(spark):
    docs = made(4) + [(1000, None), (1001, ""), (1002, "a b"), (1003, "A  b"), (1004, "a c")]
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 AS node", "2 AS _gone", "3 AS key")
    kept = keep_first_similar(df)
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} == firsts(docs)


def test_bounds_rule_out_no_similar_pair():
    random.seed(1)
    sets = [shingle_set(t.encode()) for _, t in made(9, 6, 10)]
    sizes, counts = np.array([len(s) for s in sets]), np.stack([np.bincount((s % np.uint64(near_copies.CELLS)).astype(int), minlength=near_copies.CELLS) for s in sets])
    apart = np.arange(len(sets)) // 2
    rows = np.arange(len(sets))
    want = {(i, j) for i in rows for j in rows if i < j and apart[i] != apart[j] and similarity(sets[i], sets[j]) >= 0.8}
    u, v = near_copies.may_be_similar(sizes, counts, apart, 0.8, rows, rows)
    assert want <= set(zip(u.tolist(), v.tolist())) and len(u) < 4 * len(want) + 200
    u, v = near_copies.may_be_similar(sizes, counts, apart, 0.8, rows[:20], rows[20:])
    assert {(i, j) for i, j in want if i < 20 <= j} <= set(zip(u.tolist(), v.tolist()))


@pytest.mark.parametrize("part", [1024, 16])
def test_a_band_of_unlike_texts_is_bounded(spark, monkeypatch, part):
    monkeypatch.setattr(near_copies, "PART", part)
    random.seed(part)
    base = [f"w{random.randrange(5000)}" for _ in range(200)]
    docs = []
    for _ in range(150):
        words = list(base)
        for k in random.sample(range(200), 10):
            words[k] = f"x{random.randrange(10**6)}"
        docs.append(" ".join(words))
        if random.random() < 0.3:
            words[random.randrange(200)] = "again"
            docs.append(" ".join(words))
    docs = list(enumerate(docs))
    kept = {r.doc_id for r in keep_first_similar(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert kept == firsts(docs) and 140 <= len(kept) < len(docs)


def test_the_stage_drops_near_copies_and_keeps_odd_rows(spark):
    import corpus_pipeline

    base = [f"w{i}" for i in range(300)]
    near = [(k, " ".join(base[:k] + ["odd"] * 8 + base[k + 8 :])) for k in range(0, 290, 10)]
    rows = near + [(1000, "x"), (1000, "y"), (1001, "y z"), (None, "x"), (None, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = [r.doc_id for r in dict(corpus_pipeline.STAGES)["near_duplicates"](spark, df, "").collect()]
    assert sorted(x for x in got if x is not None) == [0, 1000, 1001] and got.count(None) == 2
    assert keep_first_similar(df.limit(0)).count() == 0


def test_anchors_propose_what_is_then_compared(spark):
    from corpusdedup.llm.simhash import THRESHOLD, majority

    random.seed(12)
    docs, sets = [], DisjointSets()
    for _ in range(8):
        base = [f"w{random.randrange(400)}" for _ in range(1500)]
        docs.append(" ".join(base))
        for k in (3, 700, 1200):
            docs.append(" ".join([*base[:k], "odd", *base[k + 1 :]]))
    docs = list(enumerate(docs))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    own = near_copies._signed(df, 5)
    prints = {i: majority(shingle_set(t.encode())) for i, t in docs}
    assert {r.doc_id: r.fingerprint % (1 << 64) for r in own.collect()} == prints
    want = {(i, j) for i in prints for j in prints if i < j and i // 4 == j // 4 and (prints[i] ^ prints[j]).bit_count() <= THRESHOLD}
    found = {(r.u, r.v) for r in near_copies._anchored(own.selectExpr("doc_id AS node", "fingerprint"), df, 0.8, 5).collect()}
    assert found and all(i // 4 == j // 4 for i, j in found)
    for i, j in found:
        sets.union(i, j)
    assert all(sets.find(i) == sets.find(j) for i, j in want)
