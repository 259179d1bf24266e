import numpy as np
import pytest

from corpusdedup.config import DedupConfig
from corpusdedup.operators.compare import all_pairs, candidates, compare, tile_matches, verify_pairs
from corpusdedup.operators.exact import exact_minhash_pairs
from corpusdedup.operators.signatures import band_rows, signatures
from corpusdedup.plans.store import HashStore, streamed_compare

CFG = DedupConfig()


def pairs_of(df):
    return {(r.u, r.v, r.matches) for r in df.collect()}


@pytest.fixture(scope="module")
def sig(spark, sf):
    own = spark.read.parquet(f"{sf}/documents.parquet").where("n_chars >= 200")
    return signatures(own, CFG, 55).cache()


def test_tiles_count_like_brute_force():
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 3, (70, 128)), rng.integers(0, 3, (50, 128))
    b[:20] = a[:20]
    b[5, :25], b[6, :26] = 9, 9
    want = {(i, j, int((a[i] == b[j]).sum())) for i in range(70) for j in range(50) if (a[i] == b[j]).sum() >= 103}
    for early in (True, False):
        assert set(zip(*(x.tolist() for x in tile_matches(a, b, 103, early)))) == want
    assert any(n == 103 for *_, n in want) or (5, 5, 103) in want


def test_all_pairs_over_tiles_and_units():
    rng = np.random.default_rng(2)
    s = np.repeat(rng.integers(0, 9, (40, 128)), 3, axis=0)
    ids = rng.permutation(120)
    u, v, n = all_pairs(ids, s, CFG, tile=16)
    assert len(u) == 40 * 3 and (u < v).all() and (n == 128).all()
    part = np.arange(120) % 2
    inside = [all_pairs(ids[part == p], s[part == p], CFG) for p in (0, 1)]
    across = all_pairs(ids, s, CFG, part)
    assert len(across[0]) + sum(len(x[0]) for x in inside) == len(u)


def test_the_sets_of_pairs_nest(sig):
    exact = pairs_of(exact_minhash_pairs(sig, CFG))
    assert exact == pairs_of(exact_minhash_pairs(sig, CFG, "tiles"))
    dense = pairs_of(compare(band_rows(sig, CFG), CFG, reduce=False).distinct())
    band = pairs_of(verify_pairs(candidates(band_rows(sig, CFG, "exact_band")), sig, CFG))
    anchor = pairs_of(compare(band_rows(sig, CFG, "exact_band"), CFG, "anchor", reduce=False).distinct())
    assert anchor <= band <= dense <= exact and exact


def test_one_bucket_is_exact_minhash(spark, sf, sig):
    own = spark.read.parquet(f"{sf}/documents.parquet").where("n_chars >= 200")
    one = signatures(own, CFG, 1)
    assert pairs_of(compare(band_rows(one, CFG), CFG, reduce=False).distinct()) == pairs_of(exact_minhash_pairs(sig, CFG))


def test_fewer_buckets_hold_the_pairs_of_more(spark, sf):
    own = spark.read.parquet(f"{sf}/documents.parquet").where("n_chars >= 200")
    few, more = (pairs_of(compare(band_rows(signatures(own, CFG, k), CFG), CFG, reduce=False).distinct()) for k in (20, 60))
    assert more <= few


def test_block_pairs_lose_nothing_and_sweeps_do_not_either(spark, sig):
    rows = band_rows(sig, CFG)
    whole = pairs_of(compare(rows, CFG, reduce=False).distinct())
    assert whole == pairs_of(compare(rows, CFG.but(d_max=3), reduce=False).distinct())
    assert pairs_of(compare(rows, CFG.but(d_max=3, oversize="independent"), reduce=False).distinct()) <= whole
    store = HashStore(spark).write(rows)
    for per_pass, workers in ((55, 1), (20, 3)):
        assert pairs_of(streamed_compare(store, CFG, 55, per_pass, workers, reduce=False)) == whole


def test_store_prunes(spark, sig):
    store = HashStore(spark).write(band_rows(sig, CFG))
    plan = store.scan([3], 10, 20)._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(band" in plan or "band#" in plan.split("PartitionFilters")[1][:60]
    assert "GreaterThanOrEqual(bucket,10)" in plan


def test_copies_in_one_bucket(spark):
    df = spark.createDataFrame([(i, "the same text in many copies, " * 10) for i in range(500)], "doc_id long, text string")
    found = compare(band_rows(signatures(df, CFG, 10), CFG), CFG.but(d_max=64))
    from corpusdedup.operators.graph import connected_components

    c = connected_components(found.select("u", "v"))
    assert c.count() == 500 and c.where("component <> 0").count() == 0


def crowd(spark, n, words=60):
    """Near copies: one word in a text of many differs, so that most bands agree; every seventh differs in all."""
    text = "concat(repeat('all the same words in every copy of this text ', 9), if(id % 7 = 0, repeat(md5(cast(id as string)), 30), concat('copy ', id)))"
    return spark.range(n).selectExpr("id AS doc_id", f"{text} AS text")


@pytest.mark.parametrize("plan,n", [("scale", 50_000), ("gpu_baseline", 20_000), ("dense", 2_000), ("stream", 2_000)])
def test_a_crowded_bucket_on_every_plan(spark, plan, n):
    from corpusdedup.plans.pipelines import dedup

    r = dedup(crowd(spark, n), CFG, plan)
    kept = r.kept
    likes = kept.where("doc_id % 7 <> 0").count()
    assert kept.where("doc_id % 7 = 0").count() == -(-n // 7) and 1 <= likes <= 0.01 * n + 2


def test_what_a_crowd_leaves_apart_is_compared(spark):
    from corpusdedup.operators.graph import connected_components
    from corpusdedup.plans.pipelines import keys_only_pairs

    rng = np.random.default_rng(6)
    base = rng.integers(0, 1000, 128)
    rows = []
    for k in range(300):
        s = base.copy()
        s[rng.choice(np.arange(8, 128), rng.integers(0, 60), replace=False)] = rng.integers(2000, 9000)
        rows.append((k, s.tolist()))
        t = s.copy()
        t[100] = -1
        rows.append((1000 + k, t.tolist()))
    sig = spark.createDataFrame(rows, "doc_id long, sig array<int>")
    parts = lambda cfg, reduce: {(r.node, r.component) for r in connected_components(keys_only_pairs(sig, cfg, reduce).select("u", "v")).collect()}
    want = parts(CFG, False)
    assert parts(CFG.but(d_max=32), True) == want == parts(CFG.but(d_max=32), False) and len({c for _, c in want}) > 20


def test_anchors_are_the_same_in_cut_buckets(spark, sig):
    rows = band_rows(sig, CFG)
    for verify in (True, False):
        assert pairs_of(compare(rows, CFG, "anchor", verify, reduce=False).distinct()) == pairs_of(compare(rows, CFG.but(d_max=3), "anchor", verify, reduce=False).distinct())


def test_entries_that_unlike_documents_share_bring_nobody_together(spark):
    from corpusdedup.operators.exact import agreeing

    rng = np.random.default_rng(8)
    sig = rng.integers(10_000, 4_000_000, (400, 128))
    sig[:, rng.choice(128, 60, replace=False)] = 7  # each pair meets at 60 positions
    own = spark.createDataFrame([(k, s.tolist()) for k, s in enumerate(sig)], "doc_id long, sig array<int>")
    # Some group of ten may be shared by chance in all but one entry; by position and value all 79,800 pairs would meet.
    assert agreeing(own, CFG).count() < 10 * 400
    near = []
    for k in range(300):
        s = sig[k].copy()
        s[rng.choice(128, 25, replace=False) if k % 2 else np.arange(k % 5, 128, 5)[:25]] += 1
        near.append((1000 + k, s.tolist()))
    t = sig[399].copy()
    t[rng.choice(128, 26, replace=False)] += 1
    rows = own.union(spark.createDataFrame([*near, (2000, t.tolist()), (3000, None)], "doc_id long, sig array<int>"))
    for method in ("join", "tiles"):
        assert {tuple(r) for r in exact_minhash_pairs(rows, CFG, method).collect()} == {(k, 1000 + k, 103) for k in range(300)}


def test_sub_units_that_fit_travel_together(spark, sig, monkeypatch):
    from corpusdedup.operators import compare as module

    rows = band_rows(sig, CFG)
    assert module.split_oversize(rows, CFG.but(d_max=3)).count() == rows.count()
    monkeypatch.setattr(module, "HELD_ROWS", 6)
    cut = module.split_oversize(rows, CFG.but(d_max=3))
    assert cut.count() > rows.count() and cut.where("unit not in (bi, bj)").count() == 0
    assert pairs_of(compare(rows, CFG.but(d_max=3), reduce=False).distinct()) == pairs_of(compare(rows, CFG, reduce=False).distinct())


def test_tiles_send_a_signature_once(spark, monkeypatch):
    """Three nearly equal signatures share most keys, by other sets of documents."""
    from corpusdedup.operators import exact

    base, sent, real = list(range(128)), [], exact.compare
    two, three = base[:64] + [900] + base[65:], base[:5] + [901] + base[6:]
    rows = spark.createDataFrame([(1, base), (2, two), (3, three), (4, list(range(5000, 5128)))], "doc_id long, sig array<int>")
    monkeypatch.setattr(exact, "compare", lambda rows, *a, **k: sent.append(rows.count()) or real(rows, *a, **k))
    assert {tuple(r) for r in exact.exact_minhash_pairs(rows, CFG, "tiles").collect()} == {(1, 2, 127), (1, 3, 127), (2, 3, 126)}
    assert sent == [3]


def test_exact_minhash_does_not_expand_copies(spark):
    """Copies and near copies are connected as by all their pairs, by about as many edges as there are documents."""
    from corpusdedup.operators.graph import connected_components

    rng = np.random.default_rng(9)
    base, rows = rng.integers(0, 1000, (3, 128)), []
    for k in range(600):
        s = base[k % 2].copy()
        if k % 2:  # near copies of the second, of which every tenth is too far from most
            s[rng.choice(128, 45 if k % 10 == 1 else rng.integers(0, 14), replace=False)] = rng.integers(2000, 9000)
        rows.append((k, s.tolist()))
    t = base[2].copy()
    t[:25] = -1
    rows += [(1000, base[2].tolist()), (1001, t.tolist()), (1002, None)]
    sig = spark.createDataFrame(rows, "doc_id long, sig array<int>").cache()
    parts = lambda pairs: {(r.node, r.component) for r in connected_components(pairs.select("u", "v")).collect()}
    every, few = exact_minhash_pairs(sig, CFG), exact_minhash_pairs(sig, CFG, reduce=True)
    assert parts(few) == parts(every) and {(1000, 1000), (1001, 1000)} <= parts(few)
    assert every.count() > 50_000 and few.select("u", "v").distinct().count() < 2 * 603


def test_exact_minhash_plan_does_not_expand_copies(spark):
    from corpusdedup.plans.pipelines import find_pairs

    own = spark.createDataFrame([(i, "the same text in many copies, " * 10) for i in range(400)], "doc_id long, text string")
    assert find_pairs(own, CFG, "exact_minhash").count() == 399 and find_pairs(own, CFG, "exact_minhash", reduce=False).count() == 400 * 399 // 2
