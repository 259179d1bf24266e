import collections
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from corpusdedup.llm import language
from corpusdedup.llm.entries import tokenizer_path
from corpusdedup.llm.packing import cut
from tests.llm.test_lines import brute_force
from tests.llm.test_near_copies import firsts
from tests.llm.test_others import hits
from tests.llm.test_packing import best_fit_decreasing

STAGES = dict(corpus_pipeline.STAGES)


def by_hand(spark, sf):
    """The pipeline in one process: code of the tests where there is any, one text at a time."""
    from tokenizers import Tokenizer

    table = spark.read.parquet(f"{sf}/documents.parquet")
    crf = language.fit(table, language.fold(5) != 0)
    docs = {}
    for r in table.select("doc_id", "text").collect():
        p, letters, _ = language.word_marginals(crf, [r.text.encode()])
        if letters.any() and p[letters].max(axis=1).mean() >= 0.5:
            docs[r.doc_id] = r.text
    drops = brute_force(list(docs.items()))
    docs = {i: "\n".join(x for n, x in enumerate(t.split("\n")) if n not in drops[i]) for i, t in docs.items()}
    drops = {i: d for i, d in drops.items() if d}
    docs = {i: t for i, t in docs.items() if t.split() or i not in drops}
    first = firsts(list(docs.items()))
    docs = {i: t for i, t in docs.items() if i in first}
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert all(len(t.split()) >= 10 for _, t in items)  # so that any hit is one of a window of full length
    docs = {i: docs[i] for i, (_, n, _) in hits(list(docs.items()), items).items() if not n}
    tokens, pieces = Tokenizer.from_file(tokenizer_path()), set()
    for i, t in docs.items():
        ids = np.array([*tokens.encode(t, add_special_tokens=False).ids, 2], dtype="<u4")
        pieces |= {(i, k, s, n, zlib.crc32(ids[s : s + n].tobytes())) for k, (s, n) in enumerate(cut(len(ids), 1024))}
    return pieces


def test_the_whole_pipeline_by_hand(spark, sf):
    want = by_hand(spark, sf)
    rows = corpus_pipeline.run(spark, sf).collect()
    assert {(r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows} == want and len(rows) == len(want) > 100
    places = collections.defaultdict(list)
    for r in rows:
        places[r.sequence_id].append((r.offset, r.length))
    assert len(places) == best_fit_decreasing([n for *_, n, _ in want], 1024)
    for own in places.values():
        ends = np.cumsum([n for _, n in sorted(own)])
        assert [o for o, _ in sorted(own)] == [0, *ends[:-1].tolist()] and ends[-1] <= 1024


ROWS = [
    (1, "the and attion to thanedble the", "en"), (1, "the and attion to thanedble the", "en"), (2, None, "en"), (3, "", None), (4, "12 ! 3", "de"), (None, "the and attion to thanedble", "en"), (None, None, None),
    (5, "word " * 60_000, "en"), (6, "x" * 300_000, None), (7, "le la des et enmentai", "fr"), (7, "a different text with the same id as another", "fr"), (8, "\n\n \t", "de"),
]
CLASHES = ("_doc", "_dropped", "_lines", "_gone", "_hit", "node", "digest", "key", "component", "fingerprint", "hits", "items", "row", "piece", "length", "sequence_id", "offset", "score", "dropped_lines", "a.b")


@pytest.mark.parametrize("name", list(STAGES)[:-1])
def test_a_stage_on_odd_rows(spark, sf, name):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string, lang string").select("*", F.lit("s").alias("source"), F.length("text").cast("long").alias("n_chars"), *[F.lit(k).alias(c) for k, c in enumerate(CLASHES)])
    got = STAGES[name](spark, docs, sf)
    passed = [c for c in docs.columns if not (name == "lines" and c == "dropped_lines")]
    assert got.columns == passed
    rows = got.collect()
    ids = collections.Counter(r.doc_id for r in rows)
    if name == "language":
        assert not set(ids) & {2, 3, 4, 8} and ids[1] == 2 and all(r.text for r in rows)
    elif name == "lines":
        assert ids[2] == ids[3] == 1 and ids[None] == 2 and ids[5] == 1
    elif name == "near_duplicates":
        # 2, 3 and 8 are without words: one group; of equal ids one row stays.
        assert ids == {1: 1, 2: 1, 4: 1, 5: 1, 6: 1, 7: 1, None: 2}
    else:
        assert ids == collections.Counter(r[0] for r in ROWS)
    nothing = STAGES[name](spark, docs.limit(0), sf)
    assert nothing.columns == passed and nothing.count() == 0


def test_packing_of_odd_rows(spark, sf):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string, lang string").select("*", *[F.lit(k).alias(c) for k, c in enumerate(CLASHES)])
    rows = STAGES["packing"](spark, docs, sf).collect()
    assert sum(r.piece == 0 for r in rows) == len(ROWS) and sum(r.length == 1 for r in rows) == 3
    assert STAGES["packing"](spark, docs.limit(0), sf).count() == 0


def test_nothing_is_left_behind(spark, sf):
    from corpusdedup.plans import shared

    before = len(shared._written)
    corpus_pipeline.run(spark, sf).count()
    left = [p.rpartition("/")[2].rsplit("-", 1)[0] for p in shared._written[before:]]
    assert sorted(left) == ["pack-ranks", "pieces", "stage-decontamination"]
