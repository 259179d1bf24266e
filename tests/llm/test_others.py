import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash

from corpusdedup.llm import decontaminate as D
from corpusdedup.llm import pii as P
from corpusdedup.llm.quotations import conversations, order_replies
from corpusdedup.llm.sharding import shard, splitters

LOW = lambda t: re.sub("[A-Z]", lambda m: m.group().lower(), t)


def hits(docs, items):
    words = lambda t: re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", LOW(t or ""))
    windows = {}
    for i, t in items:
        w = words(t)
        n = min(10, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            windows.setdefault(tuple(w[k : k + n]), set()).add(i)
    out = {}
    for d, t in docs:
        w, hit, own = words(t), set(), set()
        for n in {len(x) for x in windows}:
            for k in range(len(w) - n + 1):
                if (found := windows.get(tuple(w[k : k + n]))) is not None:
                    hit.update(range(k, k + n))
                    own |= found
        out[d] = (len(w), len(hit), sorted(own))
    return out


@pytest.mark.parametrize("query_bytes", [1 << 20, 300])
def test_decontamination_is_brute_force(spark, query_bytes):
    random.seed(7)
    vocabulary = [f"w{i}" for i in range(5)] + ["É", "the"]
    text = lambda n: " ".join(random.choice(vocabulary).replace("w1", random.choice(["w1", "W1", "w1,"])) for _ in range(n))
    items = [(k, text(random.choice([1, 4, 9, 10, 11, 14]))) for k in range(12)] + [(50, None), (51, ""), (52, "..."), (0, "w0 w0 w0 w0 w0 w0 w0 w0 w0 w0 w0")]
    docs = [(k, text(random.choice([0, 3, 9, 60, 200]))) for k in range(30)] + [(100, None), (101, ""), (102, items[0][1] + " x"), (103, items[5][1])]
    ds = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 AS items", "2 AS _hit")
    bs = spark.createDataFrame(items, "item_id long, text string").selectExpr("*", "1 AS doc_id")
    got = D.decontaminate(ds, bs, query_bytes=query_bytes).select("doc_id", "n_words", D.n_hit("hits").alias("n"), "items", "near_items", "full", D.items_digest("items").alias("s")).collect()
    want = hits(docs, items)
    assert {r.doc_id: (r.n_words, r.n, sorted(r["items"])) for r in got} == want and len(got) == len(docs)
    for r in got:
        assert r.s == hashlib.sha256(",".join(sorted(map(str, r["items"]))).encode()).hexdigest() and set(r["items"]) <= set(r.near_items)
    long = hits(docs, [(i, t) for i, t in items if len(re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", t or "")) >= 10])
    assert {r.doc_id: r.full for r in got} == {d: n > 0 for d, (_, n, _) in long.items()}
    gone = {d for d, (words, n, _) in want.items() if long[d][1] or (n and 2 * n >= words)}
    assert {r.doc_id for r in D.drop_contaminated(ds, bs).collect()} == set(want) - gone and 0 < len(gone) < len(want)


@pytest.mark.parametrize("query_bytes", [1 << 20, 40])
def test_repeated_and_null_ids_keep_their_rows(spark, query_bytes):
    items = [(k, " ".join(f"i{k}w{j}" for j in range(12))) for k in range(4)]
    docs = [(1, items[0][1]), (1, items[1][1] + " x"), (1, "clean"), (None, items[2][1] + " y z"), (None, "clean too"), (None, None), (2, items[3][1]), (2, items[3][1])]
    ds = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 AS row")
    got = D.decontaminate(ds, spark.createDataFrame(items, "item_id long, text string"), query_bytes=query_bytes)
    rows = [(r.doc_id, r.n_words, r.n, r["items"]) for r in got.select("doc_id", "n_words", D.n_hit("hits").alias("n"), "items").collect()]
    want = [(1, 12, 12, [0]), (1, 13, 12, [1]), (1, 1, 0, []), (None, 14, 12, [2]), (None, 2, 0, []), (None, 0, 0, []), (2, 12, 12, [3]), (2, 12, 12, [3])]
    assert sorted(rows, key=str) == sorted(want, key=str)


def test_proximity_and_the_whole_index(spark):
    item = "one two three four five six seven eight nine ten"
    near = item.replace("four five", "four extra five")
    far = item.replace("four five", "four a b c five")
    docs = spark.createDataFrame([(1, item), (2, near), (3, far), (4, "one two three"), (5, "four five six seven eight nine ten")], "doc_id long, text string")
    index = D.build_index(docs)
    rows = {r.doc_id: r for r in D.search(index, [(9, item.encode())]).collect()}
    assert rows[1]["items"] == [9] and rows[2]["items"] == [] and rows[2].near_items == [9] and rows[3].near_items == []
    assert rows[4].near_items == rows[5].near_items == [] and rows[1].hits == [0, 10]
    with pytest.raises(Exception, match="gap"):
        D.search(D.build_index(docs, gap=3), [(9, item.encode())]).collect()
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert D.decontaminate(docs.limit(0), bench).count() == 0
    assert D.decontaminate(docs, bench.limit(0)).where("size(items) > 0").count() == 0


def test_merged_runs():
    assert D.merged_runs([[0, 3, 8, 9], [2, 5], [], [5, 6]]) == [0, 6, 8, 9]


def base(t):
    out = [(0, *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(1, *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m.group())
        if 16 <= len(d) <= 19 and P.luhn(d):
            out.append((2, *m.span()))
    return out + [(3, *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 8 <= len(re.sub("[^0-9]", "", m.group())) <= 15]


def test_base_spans():
    random.seed(3)
    for alphabet in ("a@.-1", "0123.. ", "0123456789 -", "+1234567890 ().-@\nxé", "a@b.c%_- "):
        for _ in range(4000):
            t = "".join(random.choice(alphabet) for _ in range(random.randint(0, 40)))
            assert base(t) == P.base_spans(t)
    for t in ("4111 1111 1111 1111", "x4111-1111-1111-1111y", "1.2.3.4.5.6.7.8", "999.1.1.1", "0000000255.1.1.1", "a@b.c@d.e", "+49 (30) 1234-5678."):
        assert base(t) == P.base_spans(t)
    P.base_spans("1" * 200_000 + " " + "a" * 200_000 + "@ " + "1.1." * 50_000 + "+1" * 50_000)


def test_labelers_are_weighed_and_spans_added(spark):
    rows = [(i, f"write to user{i}@mail{i % 7}.example.com or call +1 (555) 555-{1000 + i} from 10.1.{i % 200}.7") for i in range(200)]
    rows += [(1000, "mail me: joe (at) mail.example.com, call (030) 555-1234"), (1001, None), (1002, ""), (1003, "card 4111.1111.1111.1111 pay"), (1004, "+1 (826) 555-4081 190.137.223.204"), (1004, "+1 (826) 555-4081 190.137.223.204")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS spans", "2 AS base", "3 AS _spans")
    found = P.find(docs)
    got = {r.doc_id: r for r in found.select("doc_id", P.joined("base").alias("b"), P.joined("spans").alias("s")).collect()}
    assert found.count() == len(rows) and all(set(filter(None, r.b.split(","))) <= set(r.s.split(",")) for r in got.values())
    assert got[0].b == "email:9:34,ip:65:73,phone:43:59" or got[0].b.count(":") == 6
    assert got[1000].b == "" and "email:9:" in got[1000].s and "phone:" in got[1000].s
    assert got[1004].b.startswith("ip:") and "phone:0:17" in got[1004].s and got[1001].s == got[1002].s == ""
    text = {r.doc_id: r.text for r in P.masked(docs, found).collect()}
    assert text[1004] == "<phone> <ip>" and text[1001] is None and "@" not in text[3] and P.masked(docs, found).columns == docs.columns
    assert P.find(docs.limit(0)).count() == 0
    truth, chance = P.reliabilities({P.pattern(k, P.votes(t, k, a, b)): 5 for _, t in rows[:50] for k, a, b in P.base_spans(t)})
    assert min(truth.values()) > 0.9 and (chance[P.EMAIL, :, 1, 2] > 0.5).all()


def test_found_spans_are_those_of_one_process(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = {r.doc_id: (r.b, r.s) for r in P.find(docs, per_pattern=1 << 20).select("doc_id", P.joined("base").alias("b"), P.joined("spans").alias("s")).collect()}
    own, drawn, counts = {}, [], {}
    for r in docs.select("doc_id", "text").collect():
        base = P.base_spans(r.text)
        spans = base + P.wider_spans(r.text, base)
        codes = [P.pattern(s[0], P.votes(r.text, *s)) for s in spans]
        seen = [P.features(r.text, *s) for s in spans]
        own[r.doc_id] = (base, spans[len(base) :], seen[len(base) :])
        drawn += zip(codes, seen)
        for c in codes:
            counts[c] = counts.get(c, 0) + 1
    weights = P.train(sorted(drawn), counts)
    text = lambda spans: ",".join(f"{P.KINDS[k]}:{a}:{b}" for k, a, b in spans)
    want = {i: (text(b), text(sorted(b + P.chosen(w, [P.probability(weights, f) for f in x], P.ACCEPT)))) for i, (b, w, x) in own.items()}
    assert got == want and len(want) == 1000


def test_recall_of_planted_spans(spark):
    rng = random.Random(8)
    plain = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("doc_id % 4 = 1").select("doc_id", "text").collect()
    key = lambda n, of: "".join(rng.choice(of) for _ in range(n))
    hexes, mixed, digits = "0123456789abcdef", "ABCDEFGHJKMNPQRSTUVWXYZabcdefghjkmnpqrstuvwxyz23456789", "0123456789"

    def card(n):
        body = "4" + key(n - 2, digits)
        return next(body + c for c in digits if P.luhn(body + c))

    planted = {
        "email": lambda: rng.choice(["jo{0}@mail{0}.example.com", "jo{0} (at) mail.example.com", "write to jo{0} [at] host{0} [dot] org"]).format(rng.randint(1, 99)),
        "ip": lambda: rng.choice([".".join(str(rng.randint(1, 220)) for _ in range(4)), ":".join(key(4, hexes) for _ in range(8))]),
        "card": lambda: rng.choice([card(16), "card " + " ".join(re.findall("....", card(16))), ".".join(re.findall("....", card(16)))]),
        "phone": lambda: rng.choice([f"+1 ({rng.randint(200, 999)}) 555-{rng.randint(1000, 9999)}", f"call (0{rng.randint(20, 99)}) 555-{rng.randint(1000, 9999)}", f"tel +49 30 {rng.randint(100000, 999999)}"]),
        "secret": lambda: rng.choice([f'token = "{key(40, hexes)}"', f"password: {key(14, mixed)}7", f"AKIA{key(16, 'ABCDEFGHIJKLMNOP234567')}", f"api_key={key(32, mixed)}"]),
    }
    rows, want, planted_as = [], {}, {}
    for k, r in enumerate(plain):
        rows.append((r.doc_id, r.text))
        if k % 2:
            kind = rng.choice(list(planted))
            words = r.text.split(" ")
            planted_as[10_000 + k] = planted[kind]()
            words.insert(rng.randint(0, len(words)), planted_as[10_000 + k])
            rows.append((10_000 + k, " ".join(words)))
            want[10_000 + k] = kind
    rows += [(20_000 + k, f"order {key(16, '13579')} of part {key(8, digits)}, version {k}.2.1, sha {'c' * 7}") for k in range(60)]
    found = P.find(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    got = {r.doc_id: [s.kind for s in r.spans] for r in found}
    before = {r.doc_id: len(got[r.doc_id]) for r in plain}
    caught = [k in got[i] for i, k in want.items()]
    missed = [(k, planted_as[i]) for i, k in want.items() if k not in got[i]]
    assert sum(caught) / len(caught) >= 0.95, missed
    assert all(r.spans == r.base for r in found if r.doc_id >= 20_000)
    assert sum(n > 0 for n in before.values()) < 0.12 * len(before)


def check_shards(rows, docs, shards):
    texts = dict(docs)
    assert len(rows) == len(docs)
    for r in rows:
        t = texts[r.doc_id] or ""
        assert (r.size, r.text_crc32) == (len(t.encode()) + 1, zlib.crc32(t.encode()))
    for k in {r.shard for r in rows}:
        assert 0 <= k < shards and sorted(r.slot for r in rows if r.shard == k) == list(range(sum(r.shard == k for r in rows)))
    share = sum(r.size for r in rows) / shards
    most = max((r.size for r in rows), default=0)
    for k in range(shards):
        assert abs(sum(r.size for r in rows if r.shard == k) - share) <= 2 * most + 0.02 * share


def test_shards(spark):
    random.seed(6)
    docs = [(i, "é" * random.randint(0, 300)) for i in range(600)] + [(i, "the hot text " * 8) for i in range(600, 1000)] + [(2000, None), (2001, "")]
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 AS key", "2 AS size", "3 AS range_id")
    rows = shard(df, 16).collect()
    check_shards(rows, docs, 16)
    assert len({r.shard for r in rows if 600 <= r.doc_id < 1000}) > 3  # a third of the rows in one text is spread
    few = {}
    for r in rows:
        few.setdefault(r.text_crc32, set()).add(r.shard)
    assert sum(len(s) > 1 for s in few.values()) <= 16
    check_shards(shard(df, 3).collect(), docs, 3)
    assert shard(df.limit(0), 16).count() == 0
    one = shard(df.where("doc_id = 5"), 16).collect()
    assert len(one) == 1 and one[0].slot == 0


def test_shards_by_brute_force(spark):
    """All rows in one sorted list, cut where the bytes before reach a multiple of the total over the shards."""
    random.seed(9)
    texts = [f"text {k} " + "é" * random.randint(0, 200) for k in range(900)]
    docs = [(k, t) for k, t in enumerate(texts)] + [(2000 + k, random.choice(texts)) for k in range(150)] + [(5000, None), (5001, ""), (5002, texts[0]), (5002, texts[0])]
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    rows = sorted((signed(xxhash.xxh64_intdigest(t or "", 42)), i, zlib.crc32((t or "").encode()), len((t or "").encode()) + 1) for i, t in docs)
    total = sum(r[3] for r in rows)
    share, before, want, at = total / 8, 0, [], 0
    while at < len(rows):
        same = [r for r in rows[at:] if r[0] == rows[at][0]]
        held = sum(r[3] for r in same)
        for r in same:
            middle = held / 2 if held <= max(1.0, 0.05 * share) else sum(x[3] for x in same[: same.index(r)]) + r[3] / 2
            want.append((r[1], r[3], r[2], min(7, int((before + middle) // share))))
        before, at = before + held, at + len(same)
    got = shard(spark.createDataFrame(docs, "doc_id long, text string"), 8, ranges=4, range_rows=300, together=0.05).collect()
    assert sorted((r.doc_id, r.size, r.text_crc32, r.shard) for r in got) == sorted(want)
    slots = {}
    for n, (*_, s) in enumerate(want):
        slots.setdefault(s, []).append(want[n][0])
    assert {s: [r.doc_id for r in sorted((r for r in got if r.shard == s), key=lambda r: r.slot)] for s in slots} == slots


def test_splitters_weigh_by_size(spark):
    items = spark.range(20_000).selectExpr("id AS doc_id", "id AS key", "CAST(if(id < 2000, 900, 1) AS LONG) AS size")
    cuts = splitters(items, 4000, 100)
    inside = sum(c < 2000 for c in cuts) / len(cuts)
    assert 0.97 < inside <= 1 and cuts == sorted(set(cuts))


CHAT = [
    (1, 0, "a", "Hello there my friends.\nShall we meet tomorrow?"),
    (1, 1, "b", "Other topic is the weather today."),
    (1, 2, "c", "On Monday a wrote:\n> Hello there my friends.\n> Shall we meet   tomorrow?\nYes, at noon please."),
    (1, 3, "d", "> Other topic is the\n> weather today.\nIt rains all day long."),
    (1, 4, "a", "> > Shall we meet tomorrow?\n> Yes, at noon please.\nGood, see you then all."),
    (1, 5, "b", "No quotes at all here."),
    (1, 6, "c", ">> Yes, at noon please.\n\nI quote a level two only"),
    (1, 7, "d", "> words that nobody in here wrote\nStill mine"),
    (2, 0, "x", None), (None, 0, "x", "t"), (2, None, "y", "> q"), (3, 0, "x", ""), (3, 0, "x", ""), (4, 0, "z", "Hello there my friends."), (5, 3, "z", "> Hello there my friends.\nwrong conversation"),
]


def test_quotations(spark):
    df = spark.createDataFrame(CHAT, "conv_id long, turn long, role string, text string").selectExpr("*", "1 AS _conv", "2 AS depth", "3 AS reply_no")
    rows = order_replies(df).collect()
    assert len(rows) == len(CHAT)
    one = sorted((r for r in rows if r.conv_id == 1), key=lambda r: r.reply_no)
    assert [(r.turn, r.parent_turn, r.depth, r.quote_levels) for r in one] == [(0, None, 0, 0), (2, 0, 1, 1), (4, 2, 2, 2), (6, 2, 2, 2), (1, None, 0, 0), (3, 1, 1, 1), (5, None, 0, 0), (7, None, 0, 1)]
    assert [r.text for r in one][1:4] == ["Yes, at noon please.", "Good, see you then all.", "I quote a level two only"] and one[-1].text == "Still mine"
    assert sorted(r.reply_no for r in rows if r.conv_id == 3) == [0, 1]
    assert all(r.reply_no is None for r in rows if r.conv_id is None or r.turn is None)
    assert next(r for r in rows if r.conv_id == 5).parent_turn is None
    assert order_replies(df.limit(0)).count() == 0


def test_short_quotes_and_scripts_without_spaces(spark):
    said = ["Shall we go?", "Yes.", "sounds good\nat nine", "我们明天在图书馆见面", "行", "今日は雨です。\n傘を持って行きます", "👍 !", "no\nYes.\nwell then"]
    quotes = [("> Yes.\nwhy", 1), ("> sounds good\nok", 2), ("> 我们明天在图书馆见面\n好的", 3), ("> 行\n好", 4), ("> 傘を持って行きます\nはい", 5), ("> 👍 !\nthanks", 6), ("> no\n> nobody said this here\nso", None), (">\n> ...\nempty", None)]
    rows = [(1, k, "a", t) for k, t in enumerate(said)] + [(1, 10 + k, "b", t) for k, (t, _) in enumerate(quotes)]
    got = {r.turn: (r.parent_turn, r.depth) for r in order_replies(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert [got[10 + k] for k in range(len(quotes))] == [(p, int(p is not None)) for _, p in quotes]


def test_a_long_conversation_is_cut_in_parts(spark):
    df = spark.range(700).selectExpr("CAST(1 AS LONG) AS conv_id", "id AS turn", "'u' AS role", "if(id % 10 = 9, concat('> message number ', id - 5, ' of this long talk\\nanswer'), concat('message number ', id, ' of this long talk')) AS text")
    got = order_replies(df)
    assert got.where("parent_turn = turn - 5").count() == 70 and sorted(r.reply_no for r in got.collect()) == list(range(700))
    parts = conversations(got, 100).orderBy("part").collect()
    assert [p.n_messages for p in parts] == [100] * 7 and ">" not in "".join(p.text for p in parts)
    assert parts[0].text.index("answer") > parts[0].text.index("message number 4 ")


def threads(seed):
    """Conversations whose messages quote one another at several levels, with and without a line of introduction."""
    rng = random.Random(seed)
    said = ["Shall we go?", "Yes.", "see you at nine\n\nbring the maps", "行", "no\nnot today\nmaybe later", "...", "Über alles gut!", "a line of words that is long enough"]
    rows = []
    for conv in range(12):
        texts = []
        for turn in range(rng.randint(1, 12)):
            text = rng.choice(said) if rng.random() < 0.7 else f"message {rng.randint(0, 99)} here\nand more of it"
            for _ in range(rng.choice([0, 0, 1, 1, 2])):
                if texts:
                    old = rng.choice(texts)
                    lines = old.split("\n")
                    lines = lines if rng.random() < 0.7 else lines[: rng.randint(1, len(lines))]
                    quote = "\n".join(rng.choice(["> ", ">", " > "]) + x for x in lines)
                    head = rng.choice(["", "", "On Monday x wrote:\n", "Am Dienstag:\n"])
                    text = f"{head}{quote}\n{text}" if rng.random() < 0.8 else f"{text}\n{head}{quote}"
            texts.append(text)
            rows.append((conv, rng.choice([turn, turn, turn, max(0, turn - 1)]), rng.choice(["a", "b", None]), text if rng.random() < 0.97 else None))
    return rows + [(None, 1, "a", "> x"), (3, None, "b", "> Yes."), (40, 0, "a", ""), (40, 0, "a", "")]


@pytest.mark.parametrize("seed", range(4))
def test_threads_equal_sql(spark, seed):
    import duckdb

    from corpusdedup.llm.entries import CONVERSATIONS_SQL, OP5_SQL

    rows = threads(seed) if seed else CHAT
    got = order_replies(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    c = duckdb.connect()
    c.execute("CREATE TABLE conversations (conv_id BIGINT, turn BIGINT, role VARCHAR, text VARCHAR)")
    c.executemany("INSERT INTO conversations VALUES (?, ?, ?, ?)", rows)
    assert sorted(map(repr, (tuple(r) for r in got.collect()))) == sorted(map(repr, c.execute(OP5_SQL).fetchall()))
    assert got.where("parent_turn is not null").count() > 2
    whole = conversations(got).selectExpr("conv_id", "part", "n_messages", "md5(text)").collect()
    assert sorted(map(repr, (tuple(r) for r in whole))) == sorted(map(repr, c.execute(CONVERSATIONS_SQL).fetchall()))


def test_native_plans(spark, sf):
    plan = order_replies(spark.read.parquet(f"{sf}/conversations.parquet"))._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_all_windows_of_a_block_are_looked_up_side_by_side():
    from corpusdedup.llm.decontaminate import Block

    rng = np.random.default_rng(3)
    text = rng.integers(0, 12, 4000)
    text[1500:1520] = -1  # a gap
    lists = {w: np.flatnonzero(text == w) for w in range(12)}
    block = Block([b"%d" % w for w in lists], np.cumsum([len(x) for x in lists.values()]), np.concatenate(list(lists.values())).astype("<i4").tobytes(), {b"%d" % w: 10 - w for w in range(11)})
    for n in (1, 2, 5):
        starts = rng.integers(0, 1400, 30)
        words = np.unique(np.stack([text[a : a + n] for a in starts if 11 not in text[a : a + n]]), axis=0)
        row, at, exact = block.find(10 - words, 1)
        for i, w in enumerate(words):
            counts = [len(lists[x]) for x in w]
            k = int(np.argsort(counts, kind="stable")[0])
            near = [p - k for p in lists[int(w[k])] if all(j == k or np.isin(np.arange(p - k + j - 1, p - k + j + 2), lists[int(x)]).any() for j, x in enumerate(w))]
            assert at[row == i].tolist() == near
            assert at[(row == i) & exact].tolist() == [p for p in range(4001 - n) if (text[p : p + n] == w).all()]
