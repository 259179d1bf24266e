import numpy as np
import pytest

from corpusdedup.operators import similar_sets
from corpusdedup.operators.similar_sets import jaccard_pairs, packed_grams


def grams(text, k):
    return {text[i : i + k] for i in range(len(text) - k + 1)}


@pytest.mark.parametrize("letters", ["ab", "abcdefgh é😀", "".join(map(chr, range(0x4E00, 0x9E00, 2)))])
def test_packed_grams_tell_grams_apart(letters):
    rng = np.random.default_rng(1)
    text = "".join(rng.choice(list(letters), 3000))
    for k in (1, 2, 5, 7):
        packed = packed_grams(np.array([ord(c) for c in text]), k).tolist()
        assert len(set(packed)) == len(grams(text, k)) == len({(p, text[i : i + k]) for i, p in enumerate(packed)})


@pytest.mark.parametrize("least, bytes_, chars", [(0.8, 1 << 19, 1 << 22), (0.8, 400, 3000), (0.5, 1 << 10, 1 << 22)])
def test_jaccard_pairs_by_brute_force(spark, monkeypatch, least, bytes_, chars):
    """Also with sub-units of a few rows, and where shingles that many documents share would bring all of them together."""
    monkeypatch.setattr(similar_sets, "UNIT_BYTES", bytes_)
    monkeypatch.setattr(similar_sets, "UNIT_CHARS", chars)
    rng = np.random.default_rng(2)
    texts = []
    for n in (6, 7, 8, 9, 12, 40, 60, 90, 200, 500):
        for _ in range(4):
            base = list(rng.choice(list("abcdé😀"), n))
            texts.append("".join(base))
            for edits in (1, n // 40 + 1, n // 20 + 1, n // 10):
                own = list(base)
                for at in rng.integers(0, n, edits):
                    own[at] = "z" if rng.random() < 0.5 else ""
                texts.append("".join(own) + texts[0][: rng.integers(0, 3)])
    texts += [texts[7], texts[7], texts[40], "", "abc", "abc", None]
    docs = [(3 * i + 1, t) for i, t in enumerate(texts)]
    sets, want = {i: grams(t or "", 5) for i, t in docs}, set()
    for u, a in sets.items():
        for v, b in sets.items():
            if u < v and a & b and len(a & b) / len(a | b) >= least:
                want.add((u, v, len(a & b), len(a | b), len(a & b) / len(a | b)))
    got = jaccard_pairs(spark.createDataFrame(docs, "doc_id long, text string"), least=least).collect()
    assert len(got) == len(want) > 30 and {tuple(r) for r in got} == want


def test_common_shingles_make_no_candidates(spark):
    """600 texts share 40 shingles of some 140: an inverted join has 7 million rows, the sketches leave no pair."""
    rng = np.random.default_rng(3)
    shared = "".join(rng.choice(list("abcdefgh"), 44))
    docs = spark.createDataFrame([(i, shared + "".join(rng.choice(list("abcdefgh"), 100))) for i in range(600)], "doc_id long, text string")
    sketches = similar_sets.materialise(similar_sets.parity_sketches(docs, 5, 0.8), "sketches")
    assert similar_sets.sketched_pairs(sketches, 0.8).count() == 0 and jaccard_pairs(docs).count() == 0
