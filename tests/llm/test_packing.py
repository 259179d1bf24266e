import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from corpusdedup.llm.entries import tokenizer_path
from corpusdedup.llm.packing import cut, encode, pack, pack_documents, plan, sequences


def best_fit_decreasing(lengths, capacity):
    rooms = []
    for n in sorted(lengths, reverse=True):
        fits = [i for i, r in enumerate(rooms) if r >= n]
        if fits:
            i = min(fits, key=lambda i: rooms[i])
            rooms[i] -= n
        else:
            rooms.append(capacity - n)
    return len(rooms)


@pytest.mark.parametrize("seed", range(20))
def test_plan_equals_best_fit_on_documents(seed):
    random.seed(seed)
    capacity = random.choice([7, 50, 100])
    lengths = [random.randint(1, capacity) for _ in range(random.randint(0, 250))]
    rows, n = plan(dict(Counter(lengths)), capacity)
    slots, ranks = defaultdict(list), Counter()
    for length, a, b, first, offset in rows:
        ranks[length] += b - a
        for k in range(b - a):
            slots[first + k].append((offset, length))
    assert ranks == Counter(lengths) and n == best_fit_decreasing(lengths, capacity) == len(slots)
    for own in slots.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= capacity


def test_cut():
    assert cut(0, 10) == [(0, 0)] and cut(10, 10) == [(0, 10)]
    assert cut(25, 10) == [(0, 5), (5, 10), (15, 10)] and cut(20, 10) == [(0, 10), (10, 10)]
    with pytest.raises(ValueError):
        plan({11: 1}, 10)


def test_ids_are_those_of_the_tokenizer_file():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    for text in ("", "Hello  world\n\n é😀 it's 123", " \t x", "a" * 500, "über ñandú"):
        assert encode(text, tokenizer_path()).tolist() == t.encode(text, add_special_tokens=False).ids


def test_added_tokens_and_long_white_space_have_the_ids_of_the_file():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    for text in ("a <|endoftext|> b", "<|endoftext|>", "x  <|endoftext|>  \n y<|endoftext|><|endoftext|>'s", "<|endoftext| >", " " * 1_500_000 + "x", "a\n" + "\t" * 1_200_000 + "<|endoftext|> é"):
        assert encode(text, tokenizer_path()).tolist() == t.encode(text, add_special_tokens=False).ids


def test_round_trip_and_odd_rows(spark):
    rows = [(1, "word " * 3000, "x"), (2, None, "y"), (3, "", "z"), (4, "short text", "p"), (4, "short text", "p"), (5, "word " * 900, None), (None, "no id", "q")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, piece string").selectExpr("*", "1 AS length", "2 AS sequence_id", "3 AS `a.b`")
    packed = pack_documents(docs, tokenizer_path(), capacity=64)
    got = packed.collect()
    by_doc = defaultdict(list)
    for r in got:
        by_doc[r.doc_id].append(r)
        assert r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes()) and len(r.ids) == r.length
    for i, text in ((1, "word " * 3000), (2, ""), (3, ""), (5, "word " * 900)):
        own = sorted(by_doc[i], key=lambda r: r.piece)
        assert sum((r.ids for r in own), []) == encode(text, tokenizer_path()).tolist() + [2]
        assert all(r.length == 64 for r in own[1:])
    assert len(by_doc[4]) == 2
    seqs = {r.sequence_id: r.ids for r in sequences(packed).collect()}
    assert all(len(s) <= 64 for s in seqs.values())
    assert all(seqs[r.sequence_id][r.offset : r.offset + r.length] == r.ids for r in got)
    assert pack_documents(docs.limit(0), tokenizer_path()).count() == 0


def test_a_hot_length_is_ranked_in_parts(spark):
    items = spark.range(3000).selectExpr("id AS doc_id", "0 AS piece", "CAST(if(id % 3 = 0, 400, 1 + id % 700) AS LONG) AS length")
    items.write.parquet(path := f"{spark.conf.get('spark.checkpoint.dir')}/hot")
    got = pack(spark.read.parquet(path), 1024, per_part=150).toPandas().sort_values(["sequence_id", "offset"])
    assert len(got) == 3000 and (got.offset == got.groupby("sequence_id").length.cumsum() - got.length).all()
    assert got.groupby("sequence_id").length.sum().max() <= 1024
