import random

import duckdb
import pyarrow as pa

from corpusdedup.llm.entries import OP10_SQL
from corpusdedup.llm.line_dedup import MIN_WORDS, dedup_lines, drop_repeated_lines


def one_word_apart(a, b):
    if len(a) > len(b):
        a, b = b, a
    if len(a) == len(b):
        return sum(x != y for x, y in zip(a, b)) <= 1
    return len(b) == len(a) + 1 and any(b[:i] + b[i + 1 :] == a for i in range(len(b)))


def brute_force(docs, least=MIN_WORDS):
    seen, out = [], {}
    for i, text in sorted(docs):
        drop = []
        for n, line in enumerate((text or "").split("\n")):
            words = line.lower().split()
            if not words:
                continue
            if any(words == w or (len(words) >= least <= len(w) and one_word_apart(words, w)) for w in seen):
                drop.append(n)
            seen.append(words)
        out[i] = drop
    return out


def made(seed, docs=40):
    """Lines in which an edit hits every place, so that all ways to differ occur."""
    random.seed(seed)
    vocabulary = [f"w{i}" for i in range(6)]
    bases = [[random.choice(vocabulary) for _ in range(n)] for n in (1, 3, 4, 5, 6, 8, 9, 10, 16, 17, 18, 33, 34, 70)]
    rows = []
    for i in range(docs):
        lines = []
        for _ in range(4):
            x = list(random.choice(bases))
            for _ in range(random.choice([0, 1, 1, 2])):
                k = random.randrange(len(x))
                how = random.choice("rid")
                x[k : k + (how != "i")] = [] if how == "d" and len(x) > 1 else [random.choice(vocabulary + ["odd"])]
            lines.append(random.choice([" ", "  ", " \t"]).join(x).replace("w1", random.choice(["w1", "W1"])))
        rows.append((i, "\n".join(lines + random.choice([[], [""], [" "]]))))
    return rows


def test_every_way_to_differ_by_a_word(spark):
    rows = made(1) + [(100, None), (101, ""), (102, "\n\n")]
    got = {r.doc_id: (r.text, r.dropped_lines) for r in dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    want = brute_force(rows)
    assert {i: d for i, (_, d) in got.items()} == want and sum(map(len, want.values())) > 60
    for i, text in rows:
        assert got[i][0] == (None if text is None else "\n".join(x for n, x in enumerate(text.split("\n")) if n not in want[i]))


def test_shorter_lines_if_asked_for(spark):
    rows = made(3)
    for least in (3, 4):
        got = {r.doc_id: r.dropped_lines for r in dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), least).collect()}
        assert got == brute_force(rows, least) and sum(map(len, got.values())) > sum(map(len, brute_force(rows).values()))


def test_sql_says_the_same(spark):
    rows = made(2)
    documents = pa.table({"doc_id": [i for i, _ in rows], "text": [t for _, t in rows]})  # noqa: F841
    want = {r[0]: r[2] for r in duckdb.sql(OP10_SQL).fetchall()}
    got = {r.doc_id: ",".join(map(str, r.dropped_lines)) for r in dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want


def test_a_template_in_many_copies(spark):
    docs = spark.range(3000).selectExpr("id AS doc_id", "concat('page number ', id, ' of the long report on bridges\nonly ', id) AS text")
    assert dedup_lines(docs).where("size(dropped_lines) = 1").count() == 2999


def test_odd_columns_rows_and_tables(spark):
    rows = [(1, "a line of five words\nb", 9, "k"), (1, "a line of five words\nb", 9, "k"), (None, "a line of five words", 1, None), (2, "A line of five words", 2, None), (3, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_chars long, _doc string").selectExpr("*", "1 AS _dropped", "2 AS dropped_lines", "3 AS _lines", "4 AS `a.b`")
    got = dedup_lines(docs)
    assert got.columns == [c for c in docs.columns if c != "dropped_lines"] + ["dropped_lines"] and got.count() == 5
    kept = drop_repeated_lines(docs)
    assert sorted((r.doc_id or 0) for r in kept.collect()) == [0, 1, 1, 3] and kept.where("n_chars = 9").count() == 2
    assert dedup_lines(docs.limit(0)).count() == 0 and drop_repeated_lines(docs.limit(0)).count() == 0


def test_main_path_has_no_python(spark, sf):
    plan = dedup_lines(spark.read.parquet(f"{sf}/documents.parquet"))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan
