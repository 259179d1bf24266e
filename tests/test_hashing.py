import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.functions import hashing
from corpusdedup.functions.hashing import base_hash_column, base_hashes, codes_of, murmur_shingles, poly_direct, poly_prefix, poly_rolling, set_hashes, signature
from corpusdedup.operators.signatures import signatures

CFG = DedupConfig()
TEXT = st.text(st.characters(exclude_categories=["Cs"]), max_size=80)


@settings(deadline=None, max_examples=60)
@given(TEXT, st.integers(1, 8), st.sampled_from([4_294_967, 2**31 - 1]))
def test_evaluators_agree(text, k, p):
    codes = codes_of(text)
    one = poly_direct(codes, k, p, CFG.q)
    assert len(one) == max(0, len(text) - k + 1)
    assert ((0 <= one) & (one < p)).all()
    assert (one == poly_rolling(codes, k, p, CFG.q)).all() and (one == poly_prefix(codes, k, p, CFG.q)).all()
    by_hand = [sum(ord(c) * CFG.q**j for j, c in enumerate(text[i : i + k])) % p for i in range(len(text) - k + 1)]
    assert one.tolist() == by_hand


@settings(deadline=None, max_examples=40)
@given(TEXT, st.sampled_from([4_294_967, 2**31 - 1]))
def test_signature_is_the_minimum_of_every_function(text, p):
    cfg = CFG.but(p=p, n_hashes=8, bands=4, rows=2)
    h = set(poly_direct(codes_of(text), 5, p, cfg.q).tolist())
    s = signature(codes_of(text), cfg)
    if not h:
        assert s is None
    else:
        a, b = cfg.constants
        assert s.tolist() == [min((x * i + j) % p for x in h) for i, j in zip(a, b)]


def test_repeats_and_order_of_shingles_do_not_matter():
    a, b = signature(codes_of("abcdefgh" * 3), CFG), signature(codes_of("abcdefgh" * 9), CFG)
    assert (a == b).all()


def test_estimate_is_near_the_true_similarity():
    rng = np.random.default_rng(0)
    far = 0
    for _ in range(60):
        text = "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz"), 600))
        cut = int(rng.integers(100, 580))
        other = text[:cut] + "".join(rng.choice(list("0123456789"), 600 - cut))
        x, y = ({t[i : i + 5] for i in range(len(t) - 4)} for t in (text, other))
        true = len(x & y) / len(x | y)
        est = float((signature(codes_of(text), CFG) == signature(codes_of(other), CFG)).mean())
        far += abs(est - true) > 4 * (true * (1 - true) / 128) ** 0.5 + 1e-9
    assert far <= 1


def test_config_rejects_what_cannot_work():
    for bad in ({"bands": 15}, {"family": "none"}, {"q": 70_000}, {"p": 2**31}, {"unit": "line"}):
        with pytest.raises(ValueError):
            CFG.but(**bad)
    assert CFG.min_matches == 103
    ten = CFG.but(n_hashes=10, bands=5, rows=2)
    assert (ten.min_matches, ten.but(strict=True).min_matches) == (8, 9)


def test_engines_agree(spark):
    df = spark.createDataFrame([(1, "héllo wörld 😀 and more"), (2, "x" * 300), (3, "abcd"), (4, None), (5, "")], "doc_id long, text string")
    for family in ("affine", "murmur3", "sha1"):
        cfg = CFG.but(family=family)
        one = {r.doc_id: r for r in signatures(df, cfg, 50).collect()}
        two = {r.doc_id: r for r in signatures(df, cfg, 50, engine="sql").collect()}
        assert set(two) == {1, 2} and all(one[i].sig == two[i].sig and one[i].buckets == two[i].buckets for i in two)
        assert one[3].sig is None and one[4].sig is None and one[5].sig is None


def test_murmur_equals_spark(spark):
    text = "añb😀cde"
    got = spark.createDataFrame([(text[i : i + 5],) for i in range(len(text) - 4)], "g string").select(F.hash(*[F.ascii(F.substring("g", j + 1, 1)) for j in range(5)]).alias("h"))
    assert [r.h for r in got.collect()] == murmur_shingles(codes_of(text), 5).tolist()


def test_base_hash_columns(spark):
    df = spark.createDataFrame([("abcde",), ("ä😀xyz",)], "g string")
    got = [r[0] for r in df.select(base_hash_column(F.col("g"), CFG)).collect()]
    assert got == [poly_direct(codes_of(g), 5, CFG.p, CFG.q)[0] for g in ("abcde", "ä😀xyz")]


@pytest.mark.parametrize("family", ["sha1", "xxhash64"])
def test_a_shingle_met_before_is_not_hashed_again(monkeypatch, family):
    """Also where the shingles known are dropped all the time."""
    cfg, calls, real = CFG.but(family=family), [], hashing._gram_hash
    monkeypatch.setattr(hashing, "_known", {})
    monkeypatch.setattr(hashing, "_gram_hash", lambda cfg: lambda g: calls.append(g) or real(cfg)(g))
    for text in ("abcdefgh" * 50, "abcdefgh" * 9, "\ud800é😀 xyz", "abc"):
        assert set(set_hashes(codes_of(text), cfg).tolist()) == set(base_hashes(codes_of(text), cfg).tolist()), text
    assert len(calls) == 8 + 3 + (396 + 68 + 3)
    monkeypatch.setattr(hashing, "KNOWN", 2)
    for text in ("abcdefgh" * 50, "hgfedcba" * 9):
        assert set(set_hashes(codes_of(text), cfg).tolist()) == set(base_hashes(codes_of(text), cfg).tolist())
