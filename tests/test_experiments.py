import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.functions.hashing import poly_direct, poly_prefix, poly_rolling
from corpusdedup.operators.contamination import contained_items, gram_set
from corpusdedup.operators.kernels import KERNELS, hash_kernels, in_parts
from corpusdedup.operators.metrics import fidelity, with_f1
from corpusdedup.operators.select import sample_clusters
from corpusdedup.plans import shared
from corpusdedup.plans.metering import measure
from corpusdedup.plans.pipelines import dedup
from corpusdedup.plans.scaling import enlarged, growth_exponent, parallel_efficiency

CFG = DedupConfig()


def test_rolling_hash_at_every_length():
    rng = np.random.default_rng(0)
    for n in (0, 4, 5, 6, 63, 64, 67, 68, 69, 70, 132, 133, 1000):
        codes = rng.integers(0, 0x110000, n)
        for k in (1, 5, 9):
            want = poly_direct(codes, k, CFG.p, CFG.q)
            assert (poly_rolling(codes, k, CFG.p, CFG.q) == want).all() and (poly_prefix(codes, k, CFG.p, CFG.q) == want).all()


def test_kernels_count_and_time(spark):
    docs = spark.createDataFrame([("abcdefg",), ("ab",), (None,), ("x" * 100,)], "text string")
    rows = {r.kernel: r for r in hash_kernels(docs).collect()}
    assert set(rows) == set(KERNELS) and all(r.shingles == (99 if k != "polynomial_8_bases" else 8 * 99) and r.seconds > 0 for k, r in rows.items())
    assert hash_kernels(docs.limit(0)).count() in (0, len(KERNELS))


def test_kernels_hold_a_bounded_number_of_characters():
    texts = ["x" * 10, None, "", *["y" * 10] * 5, "z" * 100, "w"]
    parts = list(in_parts(texts, 25))
    assert [t for p in parts for t in p] == [t for t in texts if t is not None]
    assert all(len(p) == 1 or sum(map(len, p)) <= 25 for p in parts) and len(parts) == 5


def test_the_meter_sees_shuffles(spark):
    cost = measure(spark, lambda: spark.range(100_000).groupBy((F.col("id") % 1000).alias("k")).count().collect())
    assert cost["shuffle_write_bytes"] > 0 and cost["stages"] >= 2 and cost["seconds"] > 0
    assert measure(spark, lambda: None)["stages"] == 0


def test_turned_copies_multiply_the_clusters(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    one, three = (dedup(enlarged(docs, n, 10**6), CFG, "scale") for n in (1, 3))
    assert three.corpus.count() == 3 * one.corpus.count() and three.drop.count() == 3 * one.drop.count()
    with pytest.raises(ValueError):
        enlarged(docs, 27, 10**6)
    assert math.isclose(growth_exponent([1, 2, 4, 8], [3 * x**1.5 for x in (1, 2, 4, 8)]), 1.5)
    assert parallel_efficiency([1, 2, 4], [8.0, 4.0, 4.0]) == [1.0, 1.0, 0.5]


@pytest.mark.parametrize("plan", ["dense", "scale"])
def test_results_do_not_depend_on_the_number_of_tasks(spark, sf, plan):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    was = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        found = []
        for n in (1, 3, 13):
            spark.conf.set("spark.sql.shuffle.partitions", str(n))
            found.append({(r.doc_id, r.cluster) for r in dedup(docs.repartition(n), CFG, plan).decisions.collect()})
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)
    assert found[0] == found[1] == found[2] and found[0]


@pytest.mark.parametrize("setting", ["spark.sql.adaptive.enabled", "spark.sql.codegen.wholeStage"])
def test_results_do_not_depend_on_the_engine(spark, sf, setting):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    found = []
    try:
        for on in ("true", "false"):
            spark.conf.set(setting, on)
            found.append({tuple(r) for plan in ("dense", "scale") for r in dedup(docs, CFG, plan).decisions.collect()})
    finally:
        spark.conf.set(setting, "true")
    assert found[0] == found[1] and found[0]


def test_a_sequential_run_finds_the_same(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    a, b = (dedup(docs, CFG, "stream", pipelined=p) for p in (True, False))
    assert {tuple(r) for r in a.decisions.collect()} == {tuple(r) for r in b.decisions.collect()}


def test_samples_keep_clusters_whole(spark):
    docs = spark.range(2000).selectExpr("id AS doc_id", "if(id % 3 = 0, 'a', 'b') AS lang")
    clusters = spark.range(900).selectExpr("id AS node", "id - id % 9 AS component")
    drawn = sample_clusters(docs, clusters, 0.5, {"a": 0.2}).collect()
    whole = {}
    for r in drawn:
        whole.setdefault(r.cluster, []).append(r.doc_id)
    assert all(len(m) == 9 and min(m) == c for c, m in whole.items() if c < 900) and all(m == [c] for c, m in whole.items() if c >= 900)
    single = {"a": [c for c in whole if c >= 900 and c % 3 == 0], "b": [c for c in whole if c >= 900 and c % 3]}
    assert 0.13 < len(single["a"]) / 367 < 0.27 and 0.43 < len(single["b"]) / 733 < 0.57
    assert sample_clusters(docs.limit(0), clusters, 0.5).count() == 0


def test_f1(spark):
    pairs = lambda rows: spark.createDataFrame(rows, "u long, v long")
    one = with_f1(fidelity(pairs([(1, 2), (3, 4), (5, 6)]), pairs([(1, 2), (7, 8)]), ["u", "v"], "pair", "x")).first()
    assert math.isclose(one.f1, 0.4) and with_f1(fidelity(pairs([(1, 2)]), pairs([(3, 4)]), ["u", "v"], "pair", "x")).first().f1 == 0


@pytest.mark.parametrize("probes", [1 << 21, 60])
def test_contained_items_by_brute_force(spark, probes):
    rng = np.random.default_rng(3)
    word = lambda: "".join(rng.choice(list("abcdeé😀"), rng.integers(1, 5)))
    items = [(k, " ".join(word() for _ in range(rng.integers(1, 9)))) for k in range(12)] + [(50, ""), (51, None), (52, "abc")]
    docs = []
    for k in range(60):
        t = [word() for _ in range(rng.integers(0, 20))]
        if rng.random() < 0.6:
            own = list(items[int(rng.integers(0, 12))][1])
            for _ in range(int(rng.integers(0, 4))):
                own[int(rng.integers(0, len(own)))] = "z"
            t.append("".join(own))
        docs.append((k, " ".join(t)))
    docs += [(100, None), (101, "")]
    want = set()
    for d, t in docs:
        for i, x in items:
            own = gram_set(x or "", 5)
            both = own & gram_set(t or "", 5)
            if own and len(both) / len(own) >= 0.8:
                want.add((d, i, len(both), len(own)))
    got = contained_items(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), probes=probes)
    assert {tuple(r)[:4] for r in got.collect()} == want and len(want) > 5


def test_shared_tables_are_deleted(spark):
    import os

    path = lambda p: p.removeprefix("file:")
    with shared.releasing(spark) as keep:
        a, b = (shared.materialise(spark.range(5).toDF("x"), n) for n in ("a", "b"))
        keep(b)
        ((pa,), (pb,)) = (tuple(shared.paths_of(t)) for t in (a, b))
        assert os.path.exists(path(pa))
    assert not os.path.exists(path(pa)) and b.count() == 5
    shared.delete(spark, b)
    assert not os.path.exists(path(pb))


def test_a_cluster_must_name_its_shared_folder():
    from types import SimpleNamespace as Fake

    session = lambda master, app="a": Fake(conf=Fake(get=lambda *_: None), sparkContext=Fake(master=master, applicationId=app))
    assert shared.shared_dir(session("local[4]")) == shared.shared_dir(session("local[4]")) != shared.shared_dir(session("local", "b"))
    for master in ("spark://host:7077", "local-cluster[2,1,1024]", "yarn"):
        with pytest.raises(ValueError, match="spark.checkpoint.dir"):
            shared.shared_dir(session(master))


def test_pages_methods_leave_no_shuffle_and_no_table(spark, sf, tmp_path):
    """Pages in copies: all plans find the same, and what one of them wrote and exchanged is gone before the next."""
    import os

    from corpusdedup.queries.experiments import pages_methods

    pages = spark.read.parquet(f"{sf}/pages.parquet").limit(6)
    pages.crossJoin(spark.range(20)).selectExpr("page_id * 1000 + id AS page_id", "url", "html").write.parquet(f"{tmp_path}/pages.parquet")
    at = spark.conf.get("spark.checkpoint.dir")
    files = lambda: {f.getName() for f in spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()) if f.getName().startswith("shuffle_")}
    shuffles, tables = files(), set(os.listdir(at)) if os.path.isdir(at) else set()
    found = {r.method: (r.members, r.clusters, r.removed) for r in pages_methods(spark, str(tmp_path)).collect()}
    assert set(found.values()) == {(100, 5, 95)}  # one of the six pages is too short
    assert len(files() - shuffles) == 0 and set(os.listdir(at)) == tables
