"""The experiment workloads beyond the methods themselves: kernels, ablations, errors, samples, a second corpus, scaling, communication."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusdedup.operators.bucketing import buckets_for
from corpusdedup.operators.compare import compare
from corpusdedup.operators.exact import exact_minhash_pairs
from corpusdedup.operators.kernels import hash_kernels
from corpusdedup.operators.metrics import cluster_counts, fidelity, with_f1
from corpusdedup.operators.select import sample_clusters
from corpusdedup.operators.signatures import band_rows
from corpusdedup.operators.similar_sets import jaccard_pairs
from corpusdedup.plans.metering import measure
from corpusdedup.plans.pipelines import dedup, find_pairs
from corpusdedup.plans.scaling import enlarged
from corpusdedup.plans.shared import delete, dropping_shuffles
from corpusdedup.plans.store import HashStore, streamed_compare
from corpusdedup.plans.tuning import comm_bytes, fit_cost_model, k_opt
from corpusdedup.queries.methods import CFG, CLUSTERS, DENSE_PAIRS, DOCS, GRAMS, SIG, base_sql, docs, murmur_sql, sigs, table, with_
from corpusdedup.sources.corpus import pages_as_documents

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


# Hash kernels alone

_ALL = lambda base: base.replace("SELECT DISTINCT", "SELECT")
_HASHED = ", ".join(
    (
        DOCS, GRAMS, _ALL(base_sql(name="poly")), murmur_sql("murmur", distinct=False),
        *[f"{name} AS (SELECT CAST(('0x' || substr({name}(g), {at}, 8)) AS BIGINT) % {CFG.p} AS h FROM grams)" for name, at in (("sha1", 33), ("md5", 25))],
    )
)
_KERNELS = (("polynomial_direct", "poly"), ("polynomial_rolling", "poly"), ("polynomial_prefix", "poly"), ("murmur3", "murmur"), ("sha1", "sha1"), ("md5", "md5"))


@query("hash_kernels", with_(_HASHED, " UNION ALL ".join(f"SELECT '{k}' AS kernel, count(*) AS shingles, CAST(sum(h) AS BIGINT) AS checksum FROM {t}" for k, t in _KERNELS)))
def kernel_checksums(spark, sf):
    return hash_kernels(docs(spark, sf), CFG, [k for k, _ in _KERNELS]).drop("seconds")


@query("hash_kernel_seconds")
def kernel_seconds(spark, sf):
    """Seconds inside the tasks, summed, and millions of shingles a second: the order of the kernels is what tells."""
    return hash_kernels(docs(spark, sf), CFG).select("kernel", "shingles", F.round("seconds", 4).alias("seconds"), F.round(F.col("shingles") / F.col("seconds") / 1e6, 3).alias("millions_a_second"))


# Ablations: another hash, no overlap of reading and computing


def _removed(found: DataFrame, variant: str) -> DataFrame:
    from corpusdedup.operators.graph import connected_components

    c = connected_components(found.select("u", "v"))
    return c.agg(F.count("*").alias("members"), F.coalesce(F.sum((F.col("node") != F.col("component")).cast("long")), F.lit(0)).alias("removed")).select(F.lit(variant).alias("variant"), "members", "removed")


_VARIANT = "SELECT {} AS variant, (SELECT count(*) FROM comp) AS members, (SELECT count(*) FROM comp WHERE doc_id <> cluster) AS removed"


@query("ablation_results", with_(CLUSTERS, " UNION ALL ".join(_VARIANT.format(f"'{v}'") for v in ("whole", "sequential")), True))
def ablation_results(spark, sf):
    own = docs(spark, sf)
    return _removed(find_pairs(own, CFG, "stream"), "whole").union(_removed(find_pairs(own, CFG, "stream", pipelined=False), "sequential"))


@query("ablation_seconds")
def ablation_seconds(spark, sf):
    """variant, removed, seconds by phase of the streamed plan as a whole, without overlap, and with Murmur3."""
    own, rows = table(spark, sf, "documents"), []
    for variant, cfg, pipelined in (("whole", CFG, True), ("sequential", CFG, False), ("murmur3", CFG.but(family="murmur3"), True)):
        r = dedup(own, cfg, "stream", pipelined=pipelined)
        rows.append((variant, r.drop.count(), *[round(r.seconds[x], 3) for x in ("generation", "comparison", "union")]))
    return spark.createDataFrame(rows, "variant string, removed long, generation double, comparison double, union_seconds double")


# Errors against the true similarity

_TRUE = "g AS (SELECT DISTINCT doc_id, g FROM grams), n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY 1), truth AS (SELECT u, v FROM (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS common FROM g a JOIN g b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2) JOIN n x ON u = x.doc_id JOIN n y ON v = y.doc_id WHERE common / (x.n + y.n - common) >= 0.8)"
_ERRORS = """SELECT '{m}' AS method, n_a, n_b, n_both, n_a - n_both AS false_positives, n_b - n_both AS false_negatives, round(n_both / n_a, 9) AS precision, round(n_both / n_b, 9) AS recall, round(2 * (n_both / n_a) * (n_both / n_b) / (n_both / n_a + n_both / n_b), 9) AS f1
FROM (SELECT (SELECT count(*) FROM {t}) AS n_a, (SELECT count(*) FROM truth) AS n_b, (SELECT count(*) FROM {t} JOIN truth USING (u, v)) AS n_both)"""


@query("errors_vs_true_similarity", with_(f"{DENSE_PAIRS}, {_TRUE}", " UNION ALL ".join(_ERRORS.format(m=m, t=t) for m, t in (("dense", "found"), ("exact_minhash", "pairs")))))
def errors_vs_true_similarity(spark, sf):
    truth, s = jaccard_pairs(docs(spark, sf)), sigs(spark, sf)
    out = None
    for plan, found in (("dense", compare(band_rows(s, CFG), CFG, reduce=False)), ("exact_minhash", exact_minhash_pairs(s, CFG))):
        one = with_f1(fidelity(found, truth, ["u", "v"], "pair", plan))
        one = one.select("method", "n_a", "n_b", "n_both", (F.col("n_a") - F.col("n_both")).alias("false_positives"), (F.col("n_b") - F.col("n_both")).alias("false_negatives"), *[F.round(c, 9).alias(c) for c in ("precision", "recall", "f1")])
        out = one if out is None else out.union(one)
    return out


# A sample that keeps clusters whole


@query(
    "cluster_sample",
    with_(
        CLUSTERS + ", own AS (SELECT doc_id, lang, coalesce(cluster, doc_id) AS cluster FROM docs LEFT JOIN comp USING (doc_id)), heads AS (SELECT cluster, lang AS stratum FROM own WHERE doc_id = cluster)",
        "SELECT doc_id, cluster, stratum FROM own JOIN heads USING (cluster) WHERE CAST(('0x' || substr(md5(CAST(cluster AS VARCHAR)), 1, 8)) AS BIGINT) / 4294967296.0 < CASE WHEN stratum = 'en' THEN 0.25 ELSE 0.5 END",
        True,
    ),
)
def cluster_sample(spark, sf):
    r = dedup(table(spark, sf, "documents"), CFG, "dense")
    return sample_clusters(r.corpus, r.clusters, 0.5, {"en": 0.25})


# Raw pages as a second corpus

_PAGES = "trim(regexp_replace(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<[^>]+>', ' ', 'g'), '\\s+', ' ', 'g'))"
_PAGE_DOCS = f"docs AS (SELECT page_id AS doc_id, nfc_normalize(text) AS text FROM (SELECT page_id, {_PAGES} AS text FROM pages) WHERE length(nfc_normalize(text)) >= 200)"


@query("pages_clusters", with_(CLUSTERS.replace(DOCS, _PAGE_DOCS), "SELECT doc_id, cluster FROM comp", True))
def pages_clusters(spark, sf):
    return dedup(pages_as_documents(table(spark, sf, "pages")), CFG, "dense").decisions.select("doc_id", "cluster")


@query("pages_methods")
def pages_methods(spark, sf):
    """method, members, clusters, removed and seconds of every plan on the pages."""
    own, rows = pages_as_documents(table(spark, sf, "pages")), []
    for plan in ("scale", "dense", "gpu_baseline", "cpu_baseline", "exact_minhash"):
        with dropping_shuffles(spark):
            r = dedup(own, CFG, plan)
            n = cluster_counts(r.decisions).first()
        delete(spark, r.pairs, r.clusters)
        rows.append((plan, n["members"], n["clusters"], n["removed"], *[round(r.seconds[x], 3) for x in ("generation", "comparison", "union")]))
    return spark.createDataFrame(rows, "method string, members long, clusters long, removed long, generation double, comparison double, union_seconds double")


# A larger corpus of the same structure

_TURNED = "docs AS (SELECT doc_id + copy * 1000000000 AS doc_id, nfc_normalize(CASE copy WHEN 0 THEN text ELSE translate(text, 'abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ', 'bcdefghijklmnopqrstuvwxyzaBCDEFGHIJKLMNOPQRSTUVWXYZA') END) AS text FROM documents, unnest([0, 1]) AS t(copy) WHERE length(nfc_normalize(text)) >= 200)"


@query("enlarged_clusters", with_(CLUSTERS.replace(DOCS, _TURNED), "SELECT doc_id // 1000000000 AS copy, count(*) AS members, count(DISTINCT cluster) AS clusters FROM comp GROUP BY 1", True))
def enlarged_clusters(spark, sf):
    r = dedup(enlarged(table(spark, sf, "documents"), 2, 10**9), CFG, "dense")
    return r.decisions.groupBy(F.expr("doc_id div 1000000000").alias("copy")).agg(F.count("*").alias("members"), F.countDistinct("cluster").alias("clusters"))


# Communication, sweeps and bucket sizes with what they cost


@query("communication")
def communication(spark, sf):
    """plan, bytes that its comparison exchanged, read and waited for, and what the formula says of the exchange."""
    own = docs(spark, sf)
    s, n, rows = sigs(spark, sf), own.count(), []
    for plan, kind in (("gpu_baseline", "shuffle"), ("scale", "keys"), ("stream", "stream")):
        c = measure(spark, lambda plan=plan: find_pairs(own, CFG, plan))
        rows.append((plan, int(c["shuffle_write_bytes"]), int(c["shuffle_read_bytes"]), int(c["fetch_wait_ms"]), int(c["input_bytes"]), int(comm_bytes(kind, n, CFG, 2 * n))))
    del s
    return spark.createDataFrame(rows, "plan string, shuffled_bytes long, fetched_bytes long, fetch_wait_ms long, scanned_bytes long, formula_bytes long")


@query("c_sweep_cost")
def c_sweep_cost(spark, sf):
    """Buckets a sweep, sweeps, pairs, bytes read from the store and seconds."""
    own = docs(spark, sf)
    k = buckets_for(own, CFG)
    store, rows = HashStore(spark).write(band_rows(sigs(spark, sf, k=k), CFG)), []
    for part in (16, 8, 4, 2, 1):
        c, held = max(1, k // part), []
        cost = measure(spark, lambda c=c, held=held: held.append(streamed_compare(store, CFG, k, c, reduce=False).count()))
        rows.append((c, -(-k // c), held[0], int(cost["input_bytes"]), round(cost["seconds"], 3)))
    return spark.createDataFrame(rows, "per_pass long, sweeps long, pairs long, input_bytes long, seconds double")


@query("k_sweep_cost")
def k_sweep_cost(spark, sf):
    """Buckets, seconds of comparing and of all, removed documents, and the cost model fitted to the seconds of comparing."""
    own, seen = table(spark, sf, "documents"), []
    n = docs(spark, sf).count()
    for m in (1, 2, 4, 6, 8):
        cfg = CFG.but(k_mult=float(m))
        r = dedup(own, cfg, "dense")
        seen.append((m, buckets_for(r.corpus, cfg), r.drop.count(), r.seconds["comparison"], sum(r.seconds.values())))
    a, b = fit_cost_model([(n, k, t) for _, k, _, t, _ in seen])
    best = k_opt(n, a, b) if a > 0 and b > 0 else None
    return spark.createDataFrame([(*row[:3], round(row[3], 3), round(row[4], 3), a, b, best) for row in seen], "k_mult int, n_buckets long, removed long, comparison double, total double, a double, b double, best_k double")


@query("engine_matrix", with_(SIG, " UNION ALL ".join(f"SELECT '{e}' AS engine, count(*) AS docs, CAST(sum(list_sum(s)) AS BIGINT) AS checksum FROM sig" for e in ("arrow", "arrow_rolling", "sql"))))
def engine_matrix(spark, sf):
    """The same signatures by every engine: the fused kernel, the kernel on rolling hashes, and relational operators."""
    from corpusdedup.operators.signatures import signatures

    own, out = docs(spark, sf), None
    for name, engine, method in (("arrow", "arrow", "direct"), ("arrow_rolling", "arrow", "rolling"), ("sql", "sql", "direct")):
        s = signatures(own, CFG, engine=engine, method=method)
        one = s.agg(F.count("*").alias("docs"), F.sum(F.aggregate("sig", F.lit(0).cast("long"), lambda a, x: a + x)).alias("checksum")).select(F.lit(name).alias("engine"), "docs", "checksum")
        out = one if out is None else out.union(one)
    return out
