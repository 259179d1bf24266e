import itertools
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusdedup.llm import language, line_quality, quality_model
from corpusdedup.llm.subword import BUCKETS, Features, tokens, word_numbers

SF = "/root/testdata/sf0.01"


def test_marginals_equal_enumeration():
    rng = np.random.default_rng(0)
    for _ in range(30):
        lengths = rng.integers(0, 5, 3)
        unary, move = rng.normal(size=(int(lengths.sum()), 3)), rng.normal(size=(3, 3))
        p, expected = language.marginals(unary, lengths, move)
        at, pairs = 0, np.zeros((3, 3))
        for n in lengths.tolist():
            if n:
                weight, own, two = 0.0, np.zeros((n, 3)), np.zeros((3, 3))
                for z in itertools.product(range(3), repeat=n):
                    w = np.exp(sum(unary[at + i, z[i]] for i in range(n)) + sum(move[z[i], z[i + 1]] for i in range(n - 1)))
                    weight += w
                    for i in range(n):
                        own[i, z[i]] += w
                    for i in range(n - 1):
                        two[z[i], z[i + 1]] += w
                assert np.allclose(p[at : at + n], own / weight)
                pairs += two / weight
            at += n
        assert np.allclose(expected, pairs)


def test_features_stay_inside_their_word():
    words = [b"a", b"the", "über".encode(), b"x" * 100]
    together = Features(words)
    w = np.random.default_rng(0).random(1 << 18)
    alone = [Features([x]).sums(w, w)[0] for x in words]
    assert np.allclose(together.sums(w, w), alone)
    assert together.number.tolist() == [1 + sum(max(0, len(x) + 3 - n) for n in (2, 3, 4)) for x in words]
    which, buckets = together.pairs()
    assert np.allclose(np.bincount(which, w[buckets], 4) + w[together.word], alone)
    ids, distinct, counts = tokens([b"a b\x0ba", b"", b" \n"])
    assert ids.tolist() == [0, 1, 0] and distinct == [b"a", b"b"] and counts.tolist() == [3, 0, 0]


def fold(i, n):
    return zlib.crc32(str(i).encode()) % n


@pytest.fixture(scope="module")
def tables(spark):
    return spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")


def test_language_on_held_out_documents(spark, tables):
    docs, _ = tables
    rows = {r.doc_id: r for r in language.identify(docs).collect()}
    lang = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    held = [i for i in rows if rows[i].held_out]
    assert all(rows[i].held_out == (fold(i, 5) == 0) for i in rows) and len(rows) == 1000
    assert np.mean([rows[i].lang_pred == lang[i] for i in held]) > 0.98


def test_code_switched_words(tables):
    docs, _ = tables
    rows = [(r.text.encode(), r.lang) for r in docs.where("n_chars between 1500 and 6000").orderBy("doc_id").limit(250).collect()]
    crf = language.train(*zip(*rows))
    text = {lang: t.split()[:30] for t, lang in rows}
    mixed = text["de"] + text["fr"] + text["en"]
    p, letters, _ = language.word_marginals(crf, [b" ".join(mixed)])
    want = [crf.labels.index(x) for x in ("de", "fr", "en") for _ in range(30)]
    assert (p.argmax(axis=1) == want)[letters].mean() > 0.9 and np.allclose(p.sum(axis=1), 1)
    assert (np.diag(crf.transitions) > crf.transitions.mean()).all()


def test_language_of_odd_rows(spark, tables):
    docs, _ = tables
    one = docs.where("lang = 'de'").select("text").first()[0]
    rows = [(10_001, None, None), (10_002, "", None), (10_003, "123 !!! |", None), (10_004, one, None), (10_004, one, None), (None, one, None), (10_005, "wort " * 3000, "de")]
    odd = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("score", F.lit("x")).withColumn("lang_pred", F.lit("y"))
    both = odd.unionByName(docs.select("doc_id", "text", "lang").withColumn("score", F.lit("x")).withColumn("lang_pred", F.lit("y")))
    got = language.identify(both).where("doc_id is null or doc_id > 10000").collect()
    by = {r.doc_id: (r.lang_pred, r.score) for r in got}
    assert len(got) == 7 and all(by[i] == ("und", 0.0) for i in (10_001, 10_002, 10_003)) and by[10_004][0] == by[None][0] == "de"
    assert language.identify(odd.limit(0)).count() == 0
    nothing = language.identify(odd.withColumn("lang", F.lit(None).cast("string")))
    assert {r.lang_pred for r in nothing.collect()} == {"und"}
    kept = language.keep_identified(both)
    assert kept.columns == both.columns and kept.where("doc_id in (10001, 10002, 10003)").count() == 0 and kept.where("doc_id = 10004").count() == 2
    # Neither labels nor ids move a prediction.
    crf = language.fit(docs, language.fold(5) != 0)
    changed = docs.select((F.col("doc_id") + 7).alias("doc_id"), "text", F.lit("zz").alias("lang"))
    assert [tuple(r)[1:] for r in language.predict(docs, crf).orderBy("doc_id").collect()] == [tuple(r)[1:] for r in language.predict(changed, crf).orderBy("doc_id").collect()]


def test_quality_on_held_out_documents(tables):
    docs, labels = tables
    rows = {r.doc_id: r for r in quality_model.classify(docs, labels).collect()}
    held = [(rows[r.doc_id].score, r.quality) for r in labels.collect() if fold(r.doc_id, 4) == 2]
    good, bad = ([s for s, q in held if q == k] for k in (1, 0))
    assert np.mean([g > b for g in good for b in bad]) > 0.95
    assert all(r.predicted == int(r.score >= 0.7) and 0 <= r.score <= 1 and r.held_out == (fold(r.doc_id, 4) == 2) for r in rows.values())


def test_scorer_equals_mean_of_vectors():
    random.seed(1)
    texts = [" ".join(random.choice(["good", "fine", "well"]) for _ in range(30)).encode() for _ in range(40)] + [" ".join(random.choice(["$$$", "!!!", "bad***"]) for _ in range(30)).encode() for _ in range(40)]
    scorer = quality_model.train(texts, [1] * 40 + [0] * 40, epochs=5)
    s = scorer.scores(texts)
    assert s[:40].min() > s[40:].max()
    t = b"good $$$ good good"
    words = t.split()
    feats = Features(words)
    each = feats.sums(scorer.grams, scorer.words) / feats.number
    both = [scorer.pairs[zlib.crc32(a) & (BUCKETS - 1) ^ zlib.crc32(b) & (BUCKETS - 1)] for a, b in zip(words, words[1:])]
    margin = each.mean() + np.mean(both) + scorer.bias
    assert np.isclose(scorer.scores([t])[0], 1 / (1 + np.exp(-margin)))
    assert np.isclose(scorer.scores([b""])[0], 1 / (1 + np.exp(-scorer.bias)))


def test_quality_of_odd_rows(spark, tables):
    docs, labels = tables
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "x " * 5000), (3, "x " * 5000)], "doc_id long, text string").withColumn("quality", F.lit("no"))
    assert quality_model.classify(odd, labels.limit(0)).select("score").distinct().count() == 1
    assert quality_model.classify(odd, labels).count() == 4 and quality_model.classify(odd.limit(0), labels).count() == 0
    ones = quality_model.classify(docs, labels.where("quality = 1")).agg(F.min("score")).first()[0]
    assert ones > 0.9
    assert line_quality.rate(odd, labels.limit(0)).where("n_words = 0").count() == 2 and line_quality.rate(odd.limit(0), labels).count() == 0


def test_viterbi_equals_enumeration():
    rng = np.random.default_rng(1)
    for _ in range(60):
        lengths = rng.integers(0, 6, 4)
        unary, move = rng.normal(size=(int(lengths.sum()), 3)), rng.normal(size=(3, 3))
        got, at = line_quality.viterbi(unary, lengths, move), 0
        for n in lengths.tolist():
            if n:
                best = max(itertools.product(range(3), repeat=n), key=lambda z: sum(unary[at + i, z[i]] for i in range(n)) + sum(move[z[i], z[i + 1]] for i in range(n - 1)))  # noqa: B023
                assert tuple(got[at : at + n]) == best
            at += n


def test_plain_counts_are_brute_force():
    random.seed(4)
    alphabet = ["a", "b", "é", "x|", "#y", "\n", " ", "\t", "a b c", "B b"]
    texts = ["".join(random.choice(alphabet) + random.choice([" ", ""]) for _ in range(random.randint(0, 40))) for _ in range(300)]
    got = line_quality.read_lines([t.encode() for t in texts])
    import re

    for k, t in enumerate(texts):
        words = re.findall(r"[^\x20\x09-\x0D]+", t)
        windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
        covered = {j for i, w in enumerate(windows) if windows.count(w) > 1 for j in (i, i + 1, i + 2)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        want = (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered))
        assert (got.n_words[k], got.word_chars[k], got.n_symbols[k], got.n_dup_lines[k], got.n_repeat_words[k]) == want
    ids = np.array([0, 1, 2, 0, 1, 2] * 2)
    assert line_quality.repeated_words(ids, np.array([12]), 1 << 40).tolist() == [12]


def test_line_labels_on_held_out_documents(tables):
    docs, labels = tables
    rows = {r.doc_id: r for r in line_quality.rate(docs, labels.where(language.fold(3) != 0)).collect()}
    held = [r for r in labels.collect() if fold(r.doc_id, 3) == 0]
    good, bad = ([rows[r.doc_id] for r in held if r.quality == q] for q in (1, 0))
    assert np.mean([r.kept for r in good if not r.base_failed]) > 0.97 and np.mean([r.kept for r in bad]) < 0.1
    assert not any(r.kept for r in rows.values() if r.base_failed)
    # Labels vary inside documents, good ones too.
    assert sum(0 < r.n_content_lines < r.n_lines for r in good) > 0.1 * len(good)


def test_verdicts_are_brute_force(spark, tables):
    """Features line by line in plain Python, all labellings of a document tried, on whole small documents."""
    docs, labels = tables
    crf = line_quality.fit(docs, labels)
    some = [r for r in docs.select("doc_id", "text").collect() if 0 < sum(bool(x.strip()) for x in r.text.split("\n")) <= 9]
    got = {r.doc_id: r for r in line_quality.judge(spark.createDataFrame([(r.doc_id, r.text) for r in some], "doc_id long, text string"), crf).collect()}
    recurrent = set(crf.recurrent.tolist())
    assert len(some) > 100
    for r in some:
        lines = [x for x in r.text.split("\n") if x.strip()]
        scores, sizes = [], []
        for i, x in enumerate(lines):
            words = x.split()
            n, raw = len(words), x.encode()
            upper, lower, digit = ([sum(map(of, w)) for w in words] for of in (lambda c: "A" <= c <= "Z", lambda c: "a" <= c <= "z", lambda c: "0" <= c <= "9"))
            symbols = sum(c in "#*$%&|<>" for w in words for c in w)
            own = [
                1, min(np.log2(n + 1) / 5, 2), n <= 2, min(symbols / n, 2), symbols > 0, sum(u > 1 and not v for u, v in zip(upper, lower)) / n, sum(d > 0 for d in digit) / n,
                sum(a == b for a, b in zip(words, words[1:])) / n, x in lines[:i], words[-1][-1] in ".!?:;\"')", min(sum(map(len, words)) / n / 10, 2), sum(u + v == 0 for u, v in zip(upper, lower)) / n,
                (zlib.crc32(raw) << 32 | zlib.adler32(raw)) in recurrent,
            ]
            scores.append(np.array(own, dtype=float) @ crf.weights), sizes.append(n)
        best = max(itertools.product((0, 1), repeat=len(lines)), key=lambda z: sum(s[k] for s, k in zip(scores, z)) + sum(crf.transitions[a, b] for a, b in zip(z, z[1:])))  # noqa: B023
        share = sum(n for n, k in zip(sizes, best) if k) / sum(sizes)
        assert got[r.doc_id].n_content_lines == sum(best) and np.isclose(got[r.doc_id].content_share, share)
        assert got[r.doc_id].kept == (not got[r.doc_id].base_failed and share >= 0.5)


def test_marks_bound_the_share_of_content():
    texts = [b"a b c\nd e f\nxx\n"] * 2
    lines = line_quality.read_lines(texts)
    unary = np.column_stack((np.zeros(6), np.array([1.0, 0.5, -2.0] * 2)))
    for marks in ([1, 0], [0, 1]):
        p, _ = line_quality.within_marks(unary, lines, np.array(marks), np.zeros((2, 2)))
        share = [(p[3 * d : 3 * d + 3, 1] * lines.words[:3]).sum() / lines.words[:3].sum() for d in (0, 1)]
        assert all(s >= 0.6 if m else s <= 0.2 + 1e-3 for s, m in zip(share, marks))
    other = line_quality.read_lines([f"start {k}\nthe banner\nend {k}".encode() for k in range(4)] + [b"one\ntwo\nthree"] * 5)
    assert set(line_quality.recurrent_lines(other).tolist()) == {zlib.crc32(b"the banner") << 32 | zlib.adler32(b"the banner")}


def test_lines_of_any_length_are_decoded_whole():
    rng = np.random.default_rng(2)
    for lengths in ([1, 700, 0, 5, 129], [3000], [128, 256, 1]):
        lengths = np.array(lengths)
        unary, move = 3 * rng.normal(size=(int(lengths.sum()), 3)), 2 * rng.normal(size=(3, 3))
        want, _ = language.marginals(unary, lengths, move)
        for block, at_once in ((4, 16), (128, 128), (128, 1 << 15)):
            parts = list(language.distributions(lambda a, b: unary[a:b], lengths, move, block, at_once))  # noqa: B023
            assert np.allclose(np.concatenate([p for *_, p in parts]), want) and parts[0][0] == 0 and parts[-1][1] == len(unary)


def test_letters_are_letters():
    crf = language.train(["das ist der text".encode(), b"this is the text"], ["de", "en"])
    assert language.guess(crf, ["\u00bd \u2461 12 \u2167".encode(), b"\xff\xfe", "\u00fc".encode()])[0][:2] == ["und", "und"]
    assert language.has_letter("\u4f60".encode()) and language.has_letter(b"x1") and not language.has_letter("\u0661_".encode())


def test_a_long_text_takes_bounded_memory(spark, tables):
    docs, _ = tables
    rows = [(r.text.encode(), r.lang) for r in docs.where("n_chars between 1500 and 6000").orderBy("doc_id").limit(250).collect()]
    crf = language.train(*zip(*rows))
    one = b" ".join(t.replace(b"\n", b" ") for t, _ in rows)
    line = (one + b" ") * (20_000_000 // len(one))
    import tracemalloc

    tracemalloc.start()
    (name,), score = language.guess(crf, [line])
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 150e6, peak
    # The same as without cutting it.
    known: dict[bytes, int] = {}
    ids = word_numbers(line, known)
    letters = np.array([language.has_letter(w) for w in known])
    unary = crf.unary(list(known)).astype(np.float32).astype(np.float64)
    unary[~letters] = 0
    p, _ = language.marginals(unary[ids[:200_000]], np.array([200_000]), crf.transitions, count=False)
    cut = np.concatenate([p for *_, p in language.distributions(lambda a, b: unary[ids[a:b]], np.array([200_000]), crf.transitions)])
    assert np.allclose(p, cut) and name == crf.labels[p[letters[ids[:200_000]]].sum(axis=0).argmax()] and 0 < score[0] <= 1


def test_runs_of_languages(spark, tables):
    docs, _ = tables
    rows = [(r.text.encode(), r.lang) for r in docs.where("n_chars between 1500 and 6000").orderBy("doc_id").limit(250).collect()]
    crf = language.train(*zip(*rows))
    text = {lang: b" ".join(t.split()[:40]).decode() for t, lang in rows}
    mixed = spark.createDataFrame([(1, text["de"] + " " + text["fr"]), (2, None), (3, "12 !"), (4, text["es"])], "doc_id long, text string")
    runs = language.label_words(mixed, crf).orderBy("doc_id", "first_word").collect()
    assert {r.doc_id for r in runs} == {1, 4}
    for i, n in ((1, 80), (4, 40)):
        own = [r for r in runs if r.doc_id == i]
        assert own[0].first_word == 0 and sum(r.n_words for r in own) == n and all(a.first_word + a.n_words == b.first_word and a.lang != b.lang for a, b in zip(own, own[1:]))
    spoken = {}
    for r in runs:
        if r.doc_id == 1:
            spoken[r.lang] = spoken.get(r.lang, 0) + r.n_words
    assert spoken["de"] > 30 and spoken["fr"] > 30
    # Switching between known languages is no reason to go.
    three = spark.createDataFrame([(9, text["de"] + " " + text["fr"] + " " + text["en"], None)], "doc_id long, text string, lang string")
    both = three.unionByName(docs.select("doc_id", "text", "lang"))
    assert language.keep_identified(both).where("text is not null").join(three.select("text"), "text").count() == 1
    nothing = language.keep_identified(spark.createDataFrame([(1, "some words", None), (2, "12 3", None), (3, None, None)], "doc_id long, TEXT string, lang string"))
    assert [r.doc_id for r in nothing.collect()] == [1]


def test_draws_are_bounded(spark):
    from corpusdedup.llm.common import bounded_draw, marked_draw

    same = spark.createDataFrame([(7, "a", b"x" * 100)] * 500 + [(k, "b", b"y" * k) for k in range(50)], "doc_id long, label string, text binary")
    got = bounded_draw(same, 20, 1000, "t")
    assert sum(r[1] == "a" for r in got) in (0, 10) and 0 < sum(r[1] == "b" for r in got) <= 20 and sum(len(r[2]) for r in got if r[1] == "b") <= 1000
    marks = spark.createDataFrame([(k, k % 2) for k in range(100)] + [(5, 1)], "doc_id long, label int")
    texts = spark.createDataFrame([(k, f"text {k}") for k in range(90)] + [(95, None)], "doc_id long, text string")
    got = marked_draw(texts, marks, 1000, 1 << 20, "t")
    assert sorted(r[0] for r in got) == sorted([*range(90), 5])
