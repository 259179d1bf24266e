import random
import re

import numpy as np
import xxhash

from corpusdedup.llm.simhash import crowded_anchors, fingerprint, fingerprints, home_anchors, keep_first, links, matches, near_duplicates, replicas
from corpusdedup.operators.graph import DisjointSets


def by_hand(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), text))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_fingerprints():
    for text in ("", " \n\t", "One", "one Two", "a b c", "ÄB äb\x0bX x y", "the cat sat on the mat the cat sat on"):
        assert fingerprint(text.encode()) == by_hand(text)


def test_near_pairs_meet_at_a_home():
    rng = np.random.default_rng(0)
    x = rng.integers(-(2**63), 2**63 - 1, 800)
    y = x.copy()
    for i in range(len(y)):
        for b in rng.choice(64, int(rng.integers(0, 3)), replace=False):
            y[i] ^= np.array(1 << int(b), np.uint64).view(np.int64)
    i, a, home = replicas(x)
    assert (np.bincount(i[home], minlength=len(x)) == 1).all()
    j, c, _ = replicas(y)
    at = set(zip(j.tolist(), c.tolist()))
    assert all((int(k), int(h)) in at for k, h in zip(i[home], a[home]))


def test_matches_are_brute_force_per_anchor():
    rng = np.random.default_rng(1)
    anchor = np.sort(rng.integers(0, 5, 60))
    fp = rng.integers(0, 32, 60)
    home = rng.random(60) < 0.3
    u, v = matches(anchor, fp, home, 2)
    want = sorted((int(fp[i]), int(fp[j])) for i in range(60) for j in range(60) if home[i] and anchor[i] == anchor[j] and 0 < int(fp[i] ^ fp[j]).bit_count() <= 2)
    assert sorted(zip(u.tolist(), v.tolist())) == want


def test_components_equal_all_pairs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = near_duplicates(docs).collect()
    texts = {r.doc_id: r.text for r in docs.collect()}
    fps = {i: by_hand(t) for i, t in texts.items()}
    sets = DisjointSets()
    ids = sorted(fps)
    for k, i in enumerate(ids):
        for j in ids[k:]:
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                sets.union(i, j)
    assert {r.doc_id: (r.fingerprint & (2**64 - 1), r.component_id) for r in rows} == {i: (fps[i], sets.find(i)) for i in ids}
    assert {r.doc_id for r in keep_first(docs).collect()} == {i for i in ids if sets.find(i) == i}


def test_a_dense_group_and_odd_rows(spark):
    random.seed(2)
    base = [f"w{i}" for i in range(300)]
    rows = [(1000 + k, " ".join(base[:k] + ["odd"] + base[k + 1 :])) for k in range(0, 300, 2)]
    rows += [(5, None), (4, ""), (6, " \n"), (7, "x"), (7, "x"), (None, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS anchor", "2 AS _gone", "3 AS fingerprint")
    got = near_duplicates(docs).collect()
    fps = [(r.doc_id, r.fingerprint & (2**64 - 1), r.component_id) for r in got]
    sets = DisjointSets()
    for i, f, _ in fps:
        for j, g, _ in fps:
            if i is not None and j is not None and (f ^ g).bit_count() <= 2:
                sets.union(i, j)
    assert len(got) == len(rows) and all(c == sets.find(i) for i, _, c in fps if i is not None)
    assert {c for i, _, c in fps if i in (4, 5, 6)} == {4} and {c for i, _, c in fps if i in (7, None)} == {7}
    kept = keep_first(docs)
    assert kept.columns == docs.columns and kept.where("doc_id = 7").count() == 1 and kept.where("doc_id is null").count() == 1
    assert near_duplicates(docs.limit(0)).count() == 0 and keep_first(docs.limit(0)).count() == 0 and fingerprints(docs.limit(0)).count() == 0


def test_home_anchors_are_the_home_replicas():
    x = np.random.default_rng(3).integers(-(2**63), 2**63 - 1, 500)
    i, a, home = replicas(x)
    assert (i[home] == np.arange(500)).all() and (home_anchors(x) == a[home]).all()


def test_crowded_anchors_lose_no_link(spark):
    rng = np.random.default_rng(4)
    low = int(rng.integers(0, 1 << 46))
    x = np.unique(np.concatenate((low | rng.integers(0, 1 << 17, 400) << 46, low | rng.integers(0, 1 << 17, 100) << 46 ^ 1 << rng.integers(0, 64, 100), rng.integers(0, 1 << 62, 50))))
    nodes = spark.createDataFrame([(int(v),) for v in x], "fingerprint long")
    want, got = DisjointSets(), DisjointSets()
    for k, u in enumerate(x.tolist()):
        for v in x[k:].tolist():
            if (u ^ v).bit_count() <= 2:
                want.union(u, v)
    for r in links(nodes, crowd=20).collect():
        got.union(r.u, r.v)
    assert crowded_anchors(nodes, crowd=20).count() > 0
    assert [got.find(v) for v in x.tolist()] == [want.find(v) for v in x.tolist()] and len({want.find(v) for v in x.tolist()}) < len(x)
