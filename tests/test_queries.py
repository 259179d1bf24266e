"""Every query that has SQL against DuckDB on the smallest tables, the others against brute force."""

import os

import duckdb
import pytest
import xxhash

from corpusdedup.queries import experiments, methods, relational, streams

QUERIES = {**methods.QUERIES, **experiments.QUERIES, **relational.QUERIES, **streams.QUERIES}
SQL = {**methods.SQL, **experiments.SQL, **relational.SQL, **streams.SQL}


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{sf}/{f}'")
    return c


def canonical(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return [columns[i] for i in order], sorted(repr([round(r[i], 6) if isinstance(r[i], float) else r[i] for i in order]) for r in rows)


@pytest.mark.parametrize("name", SQL)
def test_equals_sql(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    got = canonical(df.columns, [tuple(r) for r in df.collect()])
    r = duck.execute(SQL[name])
    assert got == canonical([x[0] for x in r.description], r.fetchall())


def xxh64(text, seed=42):
    return xxhash.xxh64_intdigest(text.encode(), seed)


def test_xxhash_signatures(spark, sf):
    got = {r.doc_id: r.checksum for r in QUERIES["signature_xxhash64_checksum"](spark, sf).collect()}
    a, b = methods.CFG.constants
    some = methods.docs(spark, sf).select("doc_id", "text").collect()
    assert set(got) == {r.doc_id for r in some}
    for r in some[::25]:
        h = {xxh64(r.text[i : i + 5]) % methods.CFG.p for i in range(len(r.text) - 4)}
        assert got[r.doc_id] == sum(min((x * m + c) % methods.CFG.p for x in h) for m, c in zip(a, b))


def test_engine_hashes(spark, sf):
    signed = lambda x, n: x - (1 << n) if x >> (n - 1) else x
    rows = QUERIES["op_str_hashes_spark"](spark, sf).collect()
    text = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert {r.doc_id: r.xxhash64 for r in rows} == {i: signed(xxh64(t), 64) for i, t in text.items()}
    assert all(r.murmur3 == murmur(text[r.doc_id].encode()) for r in rows)


def murmur(data, seed=42):
    """Murmur3 of four-byte blocks, then of the bytes that are left, each as a signed number in a block of its own."""
    low, h = 0xFFFFFFFF, seed
    turn = lambda x, n: (x << n | x >> (32 - n)) & low
    whole = len(data) // 4 * 4
    blocks = [int.from_bytes(data[i : i + 4], "little") for i in range(0, whole, 4)] + [(c - 256 if c > 127 else c) & low for c in data[whole:]]
    for x in blocks:
        h = (turn(h ^ (turn(x * 0xCC9E2D51 & low, 15) * 0x1B873593 & low), 13) * 5 + 0xE6546B64) & low
    h ^= len(data)
    for shift, factor in ((16, 0x85EBCA6B), (13, 0xC2B2AE35)):
        h = (h ^ h >> shift) * factor & low
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


def test_independent_units_by_brute_force(spark, sf):
    own = methods.docs(spark, sf)
    sig = {r.doc_id: (r.sig, r.buckets) for r in methods.sigs(spark, sf).collect()}
    unit = {r.doc_id: r.h for r in own.selectExpr("doc_id", "xxhash64(doc_id) AS h").collect()}
    buckets = {}
    for i, (_, bs) in sig.items():
        for band, b in enumerate(bs):
            buckets.setdefault((band, b), []).append(i)
    want = set()
    for ids in buckets.values():
        units = -(-len(ids) // 5)
        for i in ids:
            for j in ids:
                n = sum(x == y for x, y in zip(sig[i][0], sig[j][0])) if i < j and unit[i] % units == unit[j] % units else 0
                if n >= 103:
                    want.add((i, j, n))
    assert {tuple(r) for r in QUERIES["dup_pairs_dense_independent"](spark, sf).collect()} == want and want


def test_costs(spark, sf):
    """What is measured can't be compared, what goes with it can."""
    rows = lambda name: QUERIES[name](spark, sf).collect()
    kernels = {r.kernel: r for r in rows("hash_kernel_seconds")}
    assert len({r.shingles for k, r in kernels.items() if k != "polynomial_8_bases"}) == 1 and all(r.seconds > 0 for r in kernels.values())
    assert kernels["sha1"].seconds > kernels["polynomial_direct"].seconds
    ablation = {r.variant: r.removed for r in rows("ablation_seconds")}
    assert ablation["whole"] == ablation["sequential"] > 0 and abs(ablation["murmur3"] - ablation["whole"]) <= 2
    by_plan = {r.plan: r for r in rows("communication")}
    assert by_plan["gpu_baseline"].shuffled_bytes > by_plan["scale"].shuffled_bytes > 0
    sweeps = sorted(rows("c_sweep_cost"), key=lambda r: r.per_pass)
    assert len({r.pairs for r in sweeps}) == 1 and [r.sweeps for r in sweeps] == sorted((r.sweeps for r in sweeps), reverse=True)
    assert sweeps[0].input_bytes > sweeps[-1].input_bytes
    sizes = rows("k_sweep_cost")
    assert len({r.removed for r in sizes}) == 1 and len(sizes) == 5
    pages = {r.method: (r.members, r.clusters, r.removed) for r in rows("pages_methods")}
    assert pages["dense"] == pages["exact_minhash"] == pages["scale"]


def test_entry_point(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).columns == ["doc_id", "cluster", "keep"]
    assert set(QUERIES) <= set(entry.queries()) and set(entry.oracle_sql()) <= set(entry.queries())


def test_every_query_is_held_against_something():
    here = {"signature_xxhash64_checksum", "op_str_hashes_spark", "dup_pairs_dense_independent", "hash_kernel_seconds", "ablation_seconds", "communication", "c_sweep_cost", "k_sweep_cost", "pages_methods"}
    assert set(QUERIES) - set(SQL) == here


@pytest.mark.parametrize("name", ["lsh_curve", "op_math_mod_sqrt", "tuning_dmax"])
def test_spark_reads_a_given_table(spark, sf, name):
    assert any("documents.parquet" in f for f in QUERIES[name](spark, sf).inputFiles())
