"""Methods, variants, baselines and measures as queries over the given tables, with SQL written independently of them."""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.functions.hashing import base_hash_column, char_grams
from corpusdedup.functions.shingles import char_shingles, jaccard, lsh_probability, shingle_set, word_shingles
from corpusdedup.operators.bucketing import buckets_for
from corpusdedup.operators.compare import candidates, compare, verify_pairs
from corpusdedup.operators.contamination import contained_items
from corpusdedup.operators.exact import exact_duplicates, exact_minhash_pairs, signature_copies
from corpusdedup.operators.graph import connected_components
from corpusdedup.operators.metrics import bucket_balance, cluster_counts, fidelity, hash_quality, rank_balance, token_savings
from corpusdedup.operators.normalize import clean
from corpusdedup.operators.select import select_survivors
from corpusdedup.operators.signatures import band_rows, signature_long, signatures
from corpusdedup.operators.similar_sets import jaccard_pairs
from corpusdedup.plans.pipelines import dedup, find_pairs, keys_only_pairs
from corpusdedup.plans.shared import materialise, releasing
from corpusdedup.plans.store import HashStore, streamed_compare
from corpusdedup.plans.tuning import choose_c, choose_d_max, choose_storage, k_opt, predict_time

CFG = DedupConfig()
SMALL = DedupConfig(n_hashes=8, bands=4, rows=2, family="multibase")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def docs(spark: SparkSession, sf: str) -> DataFrame:
    return clean(table(spark, sf, "documents"), CFG)


def sigs(spark: SparkSession, sf: str, cfg: DedupConfig = CFG, k: int | None = None) -> DataFrame:
    """Signatures, written once: their columns are read more than once below."""
    own = docs(spark, sf)
    return materialise(signatures(own, cfg, k or buckets_for(own, cfg)), "signatures")


# Pieces of SQL, each a common table expression that needs those before it.
DOCS = "docs AS (SELECT doc_id, nfc_normalize(text) AS text, lang, source FROM documents WHERE length(nfc_normalize(text)) >= 200)"


def grams_sql(source: str, key: str, name: str) -> str:
    """All 5-grams of characters, from shifted lists of characters side by side."""
    shifted = ", ".join(f"unnest(c[{j}:greatest({j - 1}, len(c) - {5 - j})]) AS c{j}" for j in range(1, 6))
    return f"{name} AS (SELECT {key}, c1 || c2 || c3 || c4 || c5 AS g FROM (SELECT {key}, {shifted} FROM (SELECT {key}, string_split(text, '') AS c FROM {source})))"


GRAMS = grams_sql("docs", "doc_id", "grams")


def base_sql(q: int = CFG.q, p: int = CFG.p, name: str = "base") -> str:
    power, terms = 1, []
    for j in range(5):
        terms.append(f"CAST(unicode(substr(g, {j + 1}, 1)) AS BIGINT) * {power}")
        power = power * q % p
    return f"{name} AS (SELECT DISTINCT doc_id, ({' + '.join(terms)}) % {p} AS h FROM grams)"


def murmur_sql(name: str = "base", distinct: bool = True) -> str:
    """Murmur3 of the five characters of each gram, chained as Spark's hash chains integers, by 64-bit arithmetic on 32-bit numbers."""
    word, low = "4294967296", "CAST(4294967296 AS UBIGINT)"
    keep = "doc_id, g"
    sub = f"SELECT {keep}, CAST({CFG.seed} AS UBIGINT) AS h FROM grams"
    turned = lambda x, n: f"({x} * {1 << n} % {word}) + ({x} // {1 << (32 - n)})"
    for j in range(5):
        sub = f"SELECT {keep}, h, CAST(unicode(substr(g, {j + 1}, 1)) AS UBIGINT) * 3432918353 % {low} AS x FROM ({sub})"
        sub = f"SELECT {keep}, h, ({turned('x', 15)}) * 461845907 % {low} AS x FROM ({sub})"
        sub = f"SELECT {keep}, xor(h, x) AS h FROM ({sub})"
        sub = f"SELECT {keep}, xor((({turned('h', 13)}) * 5 + 3864292196) % {low}, CAST(4 AS UBIGINT)) AS h FROM ({sub})"
        sub = f"SELECT {keep}, xor(h, h // 65536) * 2246822507 % {low} AS h FROM ({sub})"
        sub = f"SELECT {keep}, xor(h, h // 8192) * 3266489909 % {low} AS h FROM ({sub})"
        sub = f"SELECT {keep}, xor(h, h // 65536) AS h FROM ({sub})"
    signed = f"CASE WHEN h >= 2147483648 THEN CAST(h AS BIGINT) - {word} ELSE CAST(h AS BIGINT) END"
    return f"{name} AS (SELECT {'DISTINCT ' if distinct else ''}doc_id, (({signed}) % {CFG.p} + {CFG.p}) % {CFG.p} AS h FROM ({sub}))"


def sig_sql(cfg: DedupConfig = CFG, base: str = "base") -> str:
    least = ", ".join(f"min((h * {a} + {b}) % {cfg.p})" for a, b in zip(*cfg.constants))
    return f"sig AS (SELECT doc_id, [{least}] AS s FROM {base} GROUP BY doc_id)"


LONG = "long AS (SELECT doc_id, unnest(range(0, 128)) AS pos, unnest(s) AS val FROM sig)"
PAIRS = "pairs AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS matches FROM long a JOIN long b ON a.pos = b.pos AND a.val = b.val AND a.doc_id < b.doc_id GROUP BY 1, 2 HAVING count(*) >= 103)"
SIG = ", ".join((DOCS, GRAMS, base_sql(), sig_sql()))
EXACT = ", ".join((SIG, LONG, PAIRS))


def kk(mult: str = "4") -> str:
    return f"kk AS (SELECT greatest(1, CAST(floor({mult} * sqrt(count(*))) AS BIGINT)) AS k, count(*) AS n FROM docs)"


DENSE = "bands AS (SELECT doc_id, j AS band, CAST(list_sum(s[j * 8 + 1:j * 8 + 8]) AS BIGINT) % k AS bucket FROM sig, kk, unnest(range(0, 16)) AS t(j))"
EXACT_BAND = "bands AS (SELECT doc_id, j AS band, s[j * 8 + 1:j * 8 + 8] AS bucket FROM sig, unnest(range(0, 16)) AS t(j))"
CANDIDATES = "cand AS (SELECT DISTINCT a.doc_id AS u, b.doc_id AS v FROM bands a JOIN bands b ON a.band = b.band AND a.bucket = b.bucket AND a.doc_id < b.doc_id)"
VERIFIED = "found AS (SELECT u, v, matches FROM pairs JOIN cand USING (u, v))"
DENSE_PAIRS = ", ".join((EXACT, kk(), DENSE, CANDIDATES, VERIFIED))
CC = """reach(node, root) AS (SELECT u, u FROM found UNION SELECT v, v FROM found UNION
  SELECT CASE WHEN r.node = f.u THEN f.v ELSE f.u END, r.root FROM reach r JOIN found f ON r.node IN (f.u, f.v)),
comp AS (SELECT node AS doc_id, min(root) AS cluster FROM reach GROUP BY node)"""
CLUSTERS = ", ".join((DENSE_PAIRS, CC))


def with_(parts: str, select: str, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}{parts} {select}"


@query("nfc_filter", with_(DOCS, "SELECT doc_id, length(text) AS chars, md5(text) AS digest FROM docs"))
def nfc_filter(spark, sf):
    return docs(spark, sf).select("doc_id", F.char_length("text").cast("long").alias("chars"), F.md5("text").alias("digest"))


@query("shingle_counts", with_(f"{DOCS}, {GRAMS}", "SELECT doc_id, count(*) AS shingles, count(DISTINCT g) AS distinct_shingles FROM grams GROUP BY 1"))
def shingle_counts(spark, sf):
    own = docs(spark, sf).select("doc_id", char_shingles(F.col("text")).alias("g"))
    return own.select("doc_id", F.size("g").cast("long").alias("shingles"), F.size(shingle_set(F.col("g"))).cast("long").alias("distinct_shingles"))


@query(
    "word_shingle_counts",
    with_(
        f"{DOCS}, w AS (SELECT doc_id, list_filter(string_split_regex(text, '\\s+'), lambda x: x <> '') AS w FROM docs)",
        "SELECT doc_id, CAST(greatest(0, len(w) - 4) AS BIGINT) AS shingles, (SELECT count(DISTINCT array_to_string(w[i:i + 4], ' ')) FROM unnest(range(1, len(w) - 3)) AS t(i)) AS distinct_shingles FROM w",
    ),
)
def word_shingle_counts(spark, sf):
    own = docs(spark, sf).select("doc_id", F.explode(F.array(word_shingles(F.col("text")))).alias("g"))
    return own.select("doc_id", F.size("g").cast("long").alias("shingles"), F.size(F.array_distinct("g")).cast("long").alias("distinct_shingles"))


@query("base_hash_stats", with_(", ".join((DOCS, GRAMS, base_sql())), "SELECT doc_id, count(*) AS n, min(h) AS least, max(h) AS most, CAST(sum(h) AS BIGINT) AS total FROM base GROUP BY 1"))
def base_hash_stats(spark, sf):
    own = docs(spark, sf).select("doc_id", F.explode(char_grams(F.col("text"), 5)).alias("g")).select("doc_id", base_hash_column(F.col("g"), CFG).alias("h")).distinct()
    return own.groupBy("doc_id").agg(F.count("*").alias("n"), F.min("h").alias("least"), F.max("h").alias("most"), F.sum("h").alias("total"))


@query("signature_affine_long", with_(f"{SIG}, {LONG}", "SELECT doc_id, CAST(pos AS INTEGER) AS pos, CAST(val AS INTEGER) AS val FROM long"))
def signature_affine_long(spark, sf):
    return signature_long(signatures(docs(spark, sf), CFG))


def _multibase_sql() -> str:
    bases = ", ".join(base_sql(q, name=f"base{i}") for i, q in enumerate(SMALL.bases))
    rows = " UNION ALL ".join(f"SELECT doc_id, {i} AS pos, CAST(min(h) AS INTEGER) AS val FROM base{i} GROUP BY 1" for i in range(8))
    return with_(f"{DOCS}, {GRAMS}, {bases}", rows)


@query("signature_multibase_long", _multibase_sql())
def signature_multibase_long(spark, sf):
    return signature_long(signatures(docs(spark, sf), SMALL))


@query("signature_checksum", with_(SIG, "SELECT doc_id, CAST(list_sum(s) AS BIGINT) AS checksum FROM sig"))
def signature_checksum(spark, sf):
    own = signatures(docs(spark, sf), CFG, engine="sql")
    return own.select("doc_id", F.aggregate("sig", F.lit(0).cast("long"), lambda a, x: a + x).alias("checksum"))


def _family_sql(expression: str) -> str:
    return with_(f"{DOCS}, {GRAMS}, base AS (SELECT DISTINCT doc_id, ({expression}) % {CFG.p} AS h FROM grams), {sig_sql()}", "SELECT doc_id, CAST(list_sum(s) AS BIGINT) AS checksum FROM sig")


def _checksum(spark, sf, family: str):
    own = signatures(docs(spark, sf), CFG.but(family=family))
    return own.select("doc_id", F.aggregate("sig", F.lit(0).cast("long"), lambda a, x: a + x).alias("checksum"))


@query("signature_sha1_checksum", _family_sql("CAST(('0x' || substr(sha1(g), 33, 8)) AS BIGINT)"))
def signature_sha1(spark, sf):
    return _checksum(spark, sf, "sha1")


_MURMUR_SIG = ", ".join((DOCS, GRAMS, murmur_sql(), sig_sql()))


@query("signature_murmur3_checksum", with_(_MURMUR_SIG, "SELECT doc_id, CAST(list_sum(s) AS BIGINT) AS checksum FROM sig"))
def signature_murmur3(spark, sf):
    return _checksum(spark, sf, "murmur3")


@query("signature_xxhash64_checksum")
def signature_xxhash64(spark, sf):
    return _checksum(spark, sf, "xxhash64")


_WORDS = "list_filter(string_split_regex(text, '\\s+'), lambda x: x <> '')"
_WORD_SIG = ", ".join(
    (
        DOCS, f"codes AS (SELECT doc_id, list_transform({_WORDS}, lambda x: CAST(('0x' || substr(md5(x), 1, 8)) AS BIGINT) // 2) AS c FROM docs)",
        f"base AS (SELECT DISTINCT doc_id, ({' + '.join(f'c[i + {j}] * {pow(CFG.q, j, CFG.p)}' for j in range(5))}) % {CFG.p} AS h FROM codes, unnest(range(1, len(c) - 3)) AS t(i))", sig_sql(),
    )
)


@query("signature_word_checksum", with_(_WORD_SIG, "SELECT doc_id, CAST(list_sum(s) AS BIGINT) AS checksum FROM sig"))
def signature_word(spark, sf):
    own = signatures(docs(spark, sf), CFG.but(unit="word"))
    return own.select("doc_id", F.aggregate("sig", F.lit(0).cast("long"), lambda a, x: a + x).alias("checksum"))


@query("band_sums", with_(SIG, "SELECT doc_id, CAST(j AS INTEGER) AS band, CAST(list_sum(s[j * 8 + 1:j * 8 + 8]) AS BIGINT) AS total FROM sig, unnest(range(0, 16)) AS t(j)"))
def band_sums(spark, sf):
    own = signatures(docs(spark, sf), CFG)
    sums = [F.aggregate(F.slice("sig", 8 * j + 1, 8), F.lit(0).cast("long"), lambda a, x: a + x) for j in range(16)]
    return own.select("doc_id", F.posexplode(F.array(*sums)).alias("band", "total"))


@query("dense_buckets", with_(", ".join((SIG, kk(), DENSE)), "SELECT doc_id, CAST(band AS INTEGER) AS band, bucket FROM bands"))
def dense_bucket_ids(spark, sf):
    own = docs(spark, sf)
    return band_rows(signatures(own, CFG, buckets_for(own, CFG)), CFG).select("doc_id", "band", "bucket")


@query("exact_band_keys", with_(f"{SIG}, {EXACT_BAND}", "SELECT CAST(band AS INTEGER) AS band, count(*) AS docs, count(DISTINCT bucket) AS keys FROM bands GROUP BY 1"))
def exact_band_keys(spark, sf):
    rows = band_rows(signatures(docs(spark, sf), CFG), CFG, "exact_band")
    return rows.groupBy("band").agg(F.count("*").alias("docs"), F.countDistinct("bucket").alias("keys"))


@query("md5_band_keys", with_(f"{SIG}, {EXACT_BAND}", "SELECT CAST(band AS INTEGER) AS band, count(*) AS docs, count(DISTINCT md5(array_to_string(bucket, ','))) AS keys FROM bands GROUP BY 1"))
def md5_band_keys(spark, sf):
    rows = band_rows(signatures(docs(spark, sf), CFG), CFG, "md5")
    return rows.groupBy("band").agg(F.count("*").alias("docs"), F.countDistinct("bucket").alias("keys"))


_BALANCE = ", ".join(
    (
        SIG, kk(), DENSE,
        "sizes AS (SELECT band, bucket, count(*) AS n FROM bands GROUP BY 1, 2)",
        "per AS (SELECT band, sum(s.n) / any_value(k) AS mean, sqrt(greatest(sum(s.n * s.n) / any_value(k) - (sum(s.n) / any_value(k)) * (sum(s.n) / any_value(k)), 0)) AS sd, CAST(sum(s.n * (s.n - 1) // 2) AS BIGINT) AS comparisons FROM sizes s, kk GROUP BY 1)",
        "outs AS (SELECT s.band, count(*) AS outliers, CAST(sum(n * (n - 1) // 2) AS BIGINT) AS oc FROM sizes s JOIN per p ON s.band = p.band AND n > mean + 2 * sd GROUP BY 1)",
    )
)


@query(
    "bucket_stats_per_band",
    with_(
        _BALANCE,
        "SELECT CAST(p.band AS INTEGER) AS band, k AS n_buckets, round(mean, 6) AS mean, round(sd, 6) AS stddev, comparisons, coalesce(outliers, 0) AS outliers, round(100.0 * coalesce(outliers, 0) / k, 6) AS pct_out, coalesce(oc, 0) AS out_comparisons, round(100.0 * coalesce(oc, 0) / comparisons, 6) AS pct_out_comparisons FROM per p LEFT JOIN outs o USING (band), kk",
    ),
)
def bucket_stats_per_band(spark, sf):
    own = docs(spark, sf)
    n = own.count()
    k = buckets_for(own, CFG)
    b = bucket_balance(band_rows(sigs(spark, sf, k=k), CFG), k, n)
    r = lambda c: F.round(c, 6).alias(c)
    return b.select("band", "n_buckets", r("mean"), r("stddev"), "comparisons", "outliers", r("pct_out"), "out_comparisons", r("pct_out_comparisons"))


@query(
    "expected_vs_actual",
    with_(
        _BALANCE + ", e AS (SELECT k * (CAST(n AS DOUBLE) / k) * ((CAST(n AS DOUBLE) / k) - 1) / 2 AS expected FROM kk)",
        "SELECT CAST(band AS INTEGER) AS band, comparisons, round(expected, 6) AS expected, round(comparisons - expected, 6) AS delta, round(100 * (comparisons - expected) / expected, 6) AS rel_err_expected_pct, round(100 * (comparisons - expected) / comparisons, 6) AS rel_err_actual_pct FROM per, e",
    ),
)
def expected_vs_actual(spark, sf):
    own = docs(spark, sf)
    n = own.count()
    k = buckets_for(own, CFG)
    b = bucket_balance(band_rows(sigs(spark, sf, k=k), CFG), k, n)
    r = lambda c: F.round(c, 6).alias(c)
    return b.select("band", "comparisons", r("expected"), r("delta"), r("rel_err_expected_pct"), r("rel_err_actual_pct"))


@query("band_imbalance", with_(_BALANCE, "SELECT max(comparisons) AS most, round(avg(comparisons), 6) AS mean, round(max(comparisons) / avg(comparisons), 6) AS imbalance FROM per"))
def band_imbalance(spark, sf):
    own = docs(spark, sf)
    n = own.count()
    k = buckets_for(own, CFG)
    b = rank_balance(bucket_balance(band_rows(sigs(spark, sf, k=k), CFG), k, n))
    return b.select("most", F.round("mean", 6).alias("mean"), F.round("imbalance", 6).alias("imbalance"))


@query("candidate_counts_dense", with_(", ".join((SIG, kk(), DENSE, CANDIDATES)), "SELECT count(*) AS candidates FROM cand"))
def candidate_counts_dense(spark, sf):
    return candidates(band_rows(sigs(spark, sf), CFG)).agg(F.count("*").alias("candidates"))


@query("candidate_counts_exact_band", with_(", ".join((SIG, EXACT_BAND, CANDIDATES)), "SELECT count(*) AS candidates FROM cand"))
def candidate_counts_exact_band(spark, sf):
    return candidates(band_rows(sigs(spark, sf), CFG, "exact_band")).agg(F.count("*").alias("candidates"))


_P = "SELECT u, v, CAST(matches AS INTEGER) AS matches FROM found"


def _pairs(found: DataFrame) -> DataFrame:
    return found.groupBy("u", "v").agg(F.max("matches").alias("matches"))


@query("dup_pairs_exact_minhash", with_(EXACT, _P.replace("found", "pairs")))
def dup_pairs_exact_minhash(spark, sf):
    return exact_minhash_pairs(sigs(spark, sf), CFG)


@query("dup_pairs_exact_minhash_tiles", with_(EXACT, _P.replace("found", "pairs")))
def dup_pairs_exact_minhash_tiles(spark, sf):
    return exact_minhash_pairs(sigs(spark, sf), CFG, "tiles")


@query("dup_pairs_dense", with_(DENSE_PAIRS, _P))
def dup_pairs_dense(spark, sf):
    return _pairs(compare(band_rows(sigs(spark, sf), CFG), CFG, reduce=False))


@query("dup_pairs_dense_no_early_exit", with_(DENSE_PAIRS, _P))
def dup_pairs_dense_no_early_exit(spark, sf):
    return _pairs(compare(band_rows(sigs(spark, sf), CFG), CFG, reduce=False, early_exit=False))


@query("dup_pairs_dense_block_pairs", with_(DENSE_PAIRS, _P))
def dup_pairs_dense_block_pairs(spark, sf):
    return _pairs(compare(band_rows(sigs(spark, sf), CFG), CFG.but(d_max=5), reduce=False))


@query("dup_pairs_dense_independent")
def dup_pairs_dense_independent(spark, sf):
    return _pairs(compare(band_rows(sigs(spark, sf), CFG), CFG.but(d_max=5, oversize="independent"), reduce=False))


@query("dup_pairs_streamed", with_(DENSE_PAIRS, _P))
def dup_pairs_streamed(spark, sf):
    own = docs(spark, sf)
    k = buckets_for(own, CFG)
    return streamed_compare(HashStore(spark).write(band_rows(sigs(spark, sf, k=k), CFG)), CFG, k, max(1, k // 2), reduce=False)


@query("dup_pairs_exact_band", with_(", ".join((EXACT, EXACT_BAND, CANDIDATES, VERIFIED)), _P))
def dup_pairs_exact_band(spark, sf):
    s = sigs(spark, sf)
    return verify_pairs(candidates(band_rows(s, CFG, "exact_band")), s, CFG)


@query("dup_pairs_keys_only", with_(", ".join((EXACT, EXACT_BAND, CANDIDATES, VERIFIED)), _P))
def dup_pairs_keys_only(spark, sf):
    return _pairs(keys_only_pairs(sigs(spark, sf), CFG, reduce=False))


_ANCHOR = "heads AS (SELECT band, bucket, min(doc_id) AS u FROM bands GROUP BY 1, 2), cand AS (SELECT DISTINCT u, doc_id AS v FROM bands JOIN heads USING (band, bucket) WHERE doc_id <> u)"


@query("dup_pairs_anchor", with_(", ".join((EXACT, EXACT_BAND, _ANCHOR, VERIFIED)), _P))
def dup_pairs_anchor(spark, sf):
    return _pairs(compare(band_rows(sigs(spark, sf), CFG, "exact_band"), CFG, "anchor", reduce=False))


@query("dup_pairs_anchor_unverified", with_(", ".join((SIG, EXACT_BAND, _ANCHOR)), "SELECT u, v FROM cand"))
def dup_pairs_anchor_unverified(spark, sf):
    return compare(band_rows(sigs(spark, sf), CFG, "exact_band"), CFG, "anchor", verify=False, reduce=False).select("u", "v").distinct()


@query("dup_pairs_dense_anchor", with_(", ".join((EXACT, kk(), DENSE, _ANCHOR, VERIFIED)), _P))
def dup_pairs_dense_anchor(spark, sf):
    return _pairs(compare(band_rows(sigs(spark, sf), CFG), CFG, "anchor", reduce=False))


_SHA_BASE = f"base AS (SELECT DISTINCT doc_id, CAST(('0x' || substr(sha1(g), 33, 8)) AS BIGINT) % {CFG.p} AS h FROM grams)"
_SHA = ", ".join((DOCS, GRAMS, _SHA_BASE, sig_sql(), LONG, PAIRS))


@query("dup_pairs_cpu_baseline", with_(", ".join((_SHA, EXACT_BAND, _ANCHOR, VERIFIED)), _P))
def dup_pairs_cpu_baseline(spark, sf):
    return find_pairs(docs(spark, sf), CFG, "cpu_baseline")


_MURMUR = f"{_MURMUR_SIG}, {LONG}, {PAIRS}"


@query("dup_pairs_gpu_baseline", with_(", ".join((_MURMUR, EXACT_BAND, _ANCHOR, VERIFIED)), _P))
def dup_pairs_gpu_baseline(spark, sf):
    return find_pairs(docs(spark, sf), CFG, "gpu_baseline")


@query("dup_pairs_murmur3_ablation", with_(", ".join((_MURMUR, kk(), DENSE, CANDIDATES, VERIFIED)), _P))
def dup_pairs_murmur3_ablation(spark, sf):
    return find_pairs(docs(spark, sf), CFG.but(family="murmur3"), "dense", reduce=False)


_REPS = "reps AS (SELECT min(doc_id) AS doc_id, text FROM docs GROUP BY text)"


@query(
    "dup_pairs_scale_plan",
    with_(
        ", ".join((EXACT, _REPS, EXACT_BAND, CANDIDATES, VERIFIED)),
        _P + " WHERE u IN (SELECT doc_id FROM reps) AND v IN (SELECT doc_id FROM reps) UNION ALL SELECT r.doc_id, d.doc_id, 128 FROM docs d JOIN reps r USING (text) WHERE d.doc_id <> r.doc_id",
    ),
)
def dup_pairs_scale_plan(spark, sf):
    return find_pairs(docs(spark, sf), CFG, "scale", reduce=False)


def _clusters(spark, sf, method: str = "contract", keep: str = "min_id"):
    pairs = find_pairs(docs(spark, sf), CFG, "dense")
    return materialise(connected_components(pairs.select("u", "v"), method), "clusters")


_C = with_(CLUSTERS, "SELECT doc_id, cluster FROM comp", True)


def _named(c: DataFrame) -> DataFrame:
    return c.select(F.col("node").alias("doc_id"), F.col("component").alias("cluster"))


@query("clusters", _C)
def clusters(spark, sf):
    return _named(_clusters(spark, sf))


@query("clusters_star", _C)
def clusters_star(spark, sf):
    return _named(_clusters(spark, sf, "star"))


@query("clusters_label", _C)
def clusters_label(spark, sf):
    return _named(_clusters(spark, sf, "label"))


@query("clusters_driver", _C)
def clusters_driver(spark, sf):
    return _named(_clusters(spark, sf, "driver"))


@query("survivors", with_(CLUSTERS, "SELECT doc_id, cluster, doc_id = cluster AS keep FROM comp", True))
def survivors(spark, sf):
    return select_survivors(_clusters(spark, sf))


@query("survivors_longest", with_(CLUSTERS, "SELECT doc_id, cluster, row_number() OVER (PARTITION BY cluster ORDER BY length(text) DESC, doc_id) = 1 AS keep FROM comp JOIN docs USING (doc_id)", True))
def survivors_longest(spark, sf):
    return select_survivors(_clusters(spark, sf), "longest", docs(spark, sf))


@query("survivors_best_quality", with_(CLUSTERS + ", l AS (SELECT doc_id, max(quality) AS q FROM labels GROUP BY 1)", "SELECT doc_id, cluster, row_number() OVER (PARTITION BY cluster ORDER BY coalesce(q, -1) DESC, doc_id) = 1 AS keep FROM comp LEFT JOIN l USING (doc_id)", True))
def survivors_best_quality(spark, sf):
    return select_survivors(_clusters(spark, sf), "best_quality", labels=table(spark, sf, "labels"))


@query("removed_ids", with_(CLUSTERS, "SELECT doc_id FROM comp WHERE doc_id <> cluster", True))
def removed_ids(spark, sf):
    return dedup(table(spark, sf, "documents"), CFG, "dense").drop


@query("kept_corpus", with_(CLUSTERS, "SELECT doc_id, md5(text) AS digest FROM docs WHERE doc_id NOT IN (SELECT doc_id FROM comp WHERE doc_id <> cluster)", True))
def kept_corpus(spark, sf):
    return dedup(table(spark, sf, "documents"), CFG, "dense").kept.select("doc_id", F.md5("text").alias("digest"))


@query("cluster_counts", with_(CLUSTERS, "SELECT count(*) AS members, count(DISTINCT cluster) AS clusters, count(*) FILTER (WHERE doc_id <> cluster) AS removed FROM comp", True))
def cluster_count_row(spark, sf):
    return cluster_counts(dedup(table(spark, sf, "documents"), CFG, "dense").decisions)


_FID = """m AS (SELECT u AS doc_id FROM found UNION SELECT v FROM found), e AS (SELECT u AS doc_id FROM pairs UNION SELECT v FROM pairs),
t AS (SELECT (SELECT count(*) FROM m) AS n_a, (SELECT count(*) FROM e) AS n_b, (SELECT count(*) FROM m JOIN e USING (doc_id)) AS n_both)"""


@query("fidelity_vs_exact", with_(f"{DENSE_PAIRS}, {_FID}", "SELECT 'dense' AS method, 'member' AS level, n_a, n_b, n_both, round(n_both / (n_a + n_b - n_both), 9) AS jaccard, round(n_both / n_a, 9) AS precision, round(n_both / n_b, 9) AS recall FROM t"))
def fidelity_vs_exact(spark, sf):
    """Members only, so copies of a signature, which both methods find, need no pairs of their own."""
    members = lambda p: p.select(F.explode(F.array("u", "v")).alias("doc_id"))
    with releasing(spark) as keep:
        copies, single = signature_copies(sigs(spark, sf))
        dense, exact = (materialise(members(p.select("u", "v").union(copies)).distinct(), "members") for p in (compare(band_rows(single, CFG), CFG), exact_minhash_pairs(single, CFG, reduce=True)))
        keep(dense, exact)
    f = fidelity(dense, exact, ["doc_id"], "member", "dense")
    return f.select("method", "level", "n_a", "n_b", "n_both", *[F.round(c, 9).alias(c) for c in ("jaccard", "precision", "recall")])


_NAMES = re.compile(r"\b(base|sig|long|pairs|bands|heads|cand|found|reach|comp)\b")


def suffixed(parts: str, suffix: str) -> str:
    """The same common table expressions under names of their own."""
    return _NAMES.sub(lambda m: f"{m.group()}_{suffix}", parts)


_PLANS_SQL = ", ".join(
    (
        DOCS, GRAMS, kk(),
        suffixed(", ".join((base_sql(), sig_sql(), LONG, PAIRS, "found AS (SELECT * FROM pairs)", CC)), "exact"),
        suffixed(", ".join((base_sql(), sig_sql(), LONG, PAIRS, DENSE, CANDIDATES, VERIFIED, CC)), "dense"),
        suffixed(", ".join((_SHA_BASE, sig_sql(), LONG, PAIRS, EXACT_BAND, _ANCHOR, VERIFIED, CC)), "cpu_baseline"),
        suffixed(", ".join((murmur_sql(), sig_sql(), LONG, PAIRS, EXACT_BAND, _ANCHOR, VERIFIED, CC)), "gpu_baseline"),
    )
)


def _fidelity_sql(a: str, b: str, level: str, label: str) -> str:
    """One row of measures of what plan ``a`` found against plan ``b``."""
    ids = lambda p: {"pair": f"SELECT u, v FROM found_{p}", "member": f"SELECT doc_id FROM comp_{p}", "removed": f"SELECT doc_id FROM comp_{p} WHERE doc_id <> cluster"}[level]
    counts = f"SELECT (SELECT count(*) FROM ({ids(a)})) AS n_a, (SELECT count(*) FROM ({ids(b)})) AS n_b, (SELECT count(*) FROM ({ids(a)} INTERSECT {ids(b)})) AS n_both"
    return f"SELECT '{label}' AS method, '{level}' AS level, n_a, n_b, n_both, round(n_both / (n_a + n_b - n_both), 9) AS jaccard, round(n_both / n_a, 9) AS precision, round(n_both / n_b, 9) AS recall, round(100 * (n_both / n_b), 9) AS overlap_pct FROM ({counts})"


def _rounded(f: DataFrame) -> DataFrame:
    return f.select("method", "level", "n_a", "n_b", "n_both", *[F.round(c, 9).alias(c) for c in ("jaccard", "precision", "recall", "overlap_pct")])


@query("fidelity_all_levels", with_(_PLANS_SQL, " UNION ALL ".join(_fidelity_sql(p, "exact", level, p) for p in ("dense", "cpu_baseline", "gpu_baseline") for level in ("pair", "member", "removed")), True))
def fidelity_all_levels(spark, sf):
    own = table(spark, sf, "documents")
    exact = dedup(own, CFG, "exact_minhash", reduce=False)
    out = None
    for plan in ("dense", "cpu_baseline", "gpu_baseline"):
        r = dedup(own, CFG, plan, reduce=False)
        rows = fidelity(r.pairs, exact.pairs, ["u", "v"], "pair", plan).union(fidelity(r.decisions, exact.decisions, ["doc_id"], "member", plan)).union(fidelity(r.drop, exact.drop, ["doc_id"], "removed", plan))
        out = rows if out is None else out.union(rows)
    return _rounded(out)


@query("overlap_vs_shuffle", with_(_PLANS_SQL, _fidelity_sql("dense", "gpu_baseline", "member", "dense_vs_gpu_baseline"), True))
def overlap_vs_shuffle(spark, sf):
    own = table(spark, sf, "documents")
    return _rounded(fidelity(dedup(own, CFG, "dense").decisions, dedup(own, CFG, "gpu_baseline").decisions, ["doc_id"], "member", "dense_vs_gpu_baseline"))


def _k_sweep_sql() -> str:
    parts = []
    for m in (1, 2, 4, 6, 8):
        pre = ", ".join((kk(str(m)).replace("kk AS", f"kk{m} AS"), DENSE.replace("bands AS", f"bands{m} AS").replace(", kk,", f", kk{m},"), CANDIDATES.replace("cand AS", f"cand{m} AS").replace("bands ", f"bands{m} "), f"found{m} AS (SELECT u, v FROM pairs JOIN cand{m} USING (u, v))", CC.replace("reach", f"reach{m}").replace("comp", f"comp{m}").replace("found", f"found{m}")))
        parts.append(pre)
    rows = " UNION ALL ".join(f"SELECT {m} AS k_mult, k AS n_buckets, (SELECT CAST(sum(n * (n - 1) // 2) AS BIGINT) FROM (SELECT count(*) AS n FROM bands{m} GROUP BY band, bucket)) AS comparisons, (SELECT count(*) FROM comp{m} WHERE doc_id <> cluster) AS removed FROM kk{m}" for m in (1, 2, 4, 6, 8))
    return with_(f"{EXACT}, {', '.join(parts)}", rows, True)


@query("k_sweep", _k_sweep_sql())
def k_sweep(spark, sf):
    own = docs(spark, sf)
    out = None
    for m in (1, 2, 4, 6, 8):
        cfg = CFG.but(k_mult=float(m))
        k = buckets_for(own, cfg)
        rows = band_rows(materialise(signatures(own, cfg, k), "signatures"), cfg)
        done = connected_components(compare(rows, cfg).select("u", "v"))
        work = rows.groupBy("band", "bucket").agg(F.count("*").alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("comparisons"))
        one = done.agg(F.coalesce(F.sum((F.col("node") != F.col("component")).cast("long")), F.lit(0)).alias("removed")).crossJoin(work).select(F.lit(m).alias("k_mult"), F.lit(k).cast("long").alias("n_buckets"), "comparisons", "removed")
        out = one if out is None else out.union(one)
    return out


@query("c_sweep", with_(", ".join((DENSE_PAIRS, "cs AS (SELECT greatest(1, k // unnest([16, 8, 4, 2, 1])) AS per_pass, k FROM kk)")), "SELECT per_pass, CAST(ceil(k / per_pass) AS BIGINT) AS sweeps, (SELECT count(*) FROM found) AS pairs FROM cs"))
def c_sweep(spark, sf):
    own = docs(spark, sf)
    k = buckets_for(own, CFG)
    store = HashStore(spark).write(band_rows(sigs(spark, sf, k=k), CFG))
    out = None
    for part in (16, 8, 4, 2, 1):
        c = max(1, k // part)
        one = streamed_compare(store, CFG, k, c, reduce=False).agg(F.count("*").alias("pairs")).select(F.lit(c).cast("long").alias("per_pass"), F.lit(-(-k // c)).cast("long").alias("sweeps"), "pairs")
        out = one if out is None else out.union(one)
    return out


@query("exact_hash_dups", "SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS cluster, count(*) OVER (PARTITION BY text) AS copies FROM documents QUALIFY count(*) OVER (PARTITION BY text) > 1")
def exact_hash_dups(spark, sf):
    return exact_duplicates(table(spark, sf, "documents"))


_SETS = f"{DOCS}, {GRAMS}, g AS (SELECT DISTINCT doc_id, g FROM grams), n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY 1)"


@query(
    "jaccard_true_pairs",
    with_(
        _SETS + ", c AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS common FROM g a JOIN g b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2)",
        "SELECT u, v, common, x.n + y.n - common AS total, round(common / (x.n + y.n - common), 9) AS jaccard FROM c JOIN n x ON u = x.doc_id JOIN n y ON v = y.doc_id WHERE common / (x.n + y.n - common) >= 0.8",
    ),
)
def jaccard_true_pairs(spark, sf):
    return jaccard_pairs(docs(spark, sf)).withColumn("jaccard", F.round("jaccard", 9))


_HALVES = "h AS (SELECT doc_id, list_distinct(w[1:len(w) // 2]) AS a, list_distinct(w[len(w) // 2 + 1:]) AS b FROM (SELECT doc_id, string_split(text, ' ') AS w FROM docs)), c AS (SELECT doc_id, len(list_intersect(a, b)) AS common, len(a) + len(b) AS n FROM h), s AS (SELECT doc_id, common / (n - common) AS s FROM c)"


@query("lsh_curve", with_(f"{DOCS}, {_HALVES}", "SELECT doc_id, round(s, 9) AS similarity, round(1 - pow(1 - pow(s, 8), 16), 9) AS probability FROM s"))
def lsh_curve(spark, sf):
    """The curve at the similarity of each document's two halves, as sets of words."""
    words = docs(spark, sf).select("doc_id", F.split("text", " ").alias("w"))
    half = F.floor(F.size("w") / 2).cast("int")
    halves = words.select("doc_id", F.array_distinct(F.slice("w", F.lit(1), half)).alias("a"), F.array_distinct(F.slice("w", half + 1, F.size("w"))).alias("b"))
    s = halves.select("doc_id", jaccard(F.col("a"), F.col("b")).alias("s"))
    return s.select("doc_id", F.round("s", 9).alias("similarity"), F.round(lsh_probability(F.col("s"), 16, 8), 9).alias("probability"))


_MEM = (1 << 20, 1 << 24, 1 << 30)


@query("tuning_storage", with_(DOCS, f"SELECT m AS memory, count(*) * 129 * 4 * 4 AS required, CASE WHEN count(*) * 129 * 4 * 4 <= 0.2 * m THEN 'memory' ELSE 'parquet' END AS mode FROM docs, unnest([{', '.join(map(str, _MEM))}]) AS t(m) GROUP BY m"))
def tuning_storage(spark, sf):
    n = docs(spark, sf).count()
    rows = [(m, (s := choose_storage(n, 128, 4, m)).required_bytes, s.mode) for m in _MEM]
    return spark.createDataFrame(rows, "memory long, required long, mode string")


@query("tuning_c", with_(f"{DOCS}, {kk()}", f"SELECT m AS memory, least(k, greatest(1, CAST(floor(0.2 * m * k / (4 * n * 128 * 4)) AS BIGINT))) AS per_pass FROM kk, unnest([{', '.join(map(str, _MEM))}]) AS t(m)"))
def tuning_c(spark, sf):
    own = docs(spark, sf)
    n, k = own.count(), buckets_for(own, CFG)
    return spark.createDataFrame([(m, choose_c(n, k, 128, 4, m)) for m in _MEM], "memory long, per_pass long")


@query("tuning_dmax", with_(f"{DOCS}, d AS (SELECT m, greatest(1, CAST(ceil(0.5 * m / (128 * 4)) AS BIGINT) - 1) AS d_max FROM unnest([{', '.join(map(str, _MEM))}]) AS t(m))", "SELECT m AS memory, d_max, CAST(ceil((SELECT count(*) FROM docs) / d_max) AS BIGINT) AS units FROM d"))
def tuning_dmax(spark, sf):
    """The largest bucket that each memory holds, and the sub-units of a bucket of all documents."""
    sizes = spark.createDataFrame([(m, choose_d_max(128, m)) for m in _MEM], "memory long, d_max long")
    return sizes.crossJoin(docs(spark, sf).agg(F.count("*").alias("n"))).select("memory", "d_max", F.ceil(F.col("n") / F.col("d_max")).alias("units"))


@query("cost_model", with_(f"{DOCS}, n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM docs)", "SELECT k, round(1e-6 * n * k + 1e-5 * n * n / k, 9) AS predicted, round(sqrt(1e-5 * n / 1e-6), 6) AS best_k FROM n, unnest([16, 64, 256, 1024]) AS t(k)"))
def cost_model(spark, sf):
    n = docs(spark, sf).count()
    rows = [(k, round(predict_time(n, k, 1e-6, 1e-5), 9), round(k_opt(n, 1e-6, 1e-5), 6)) for k in (16, 64, 256, 1024)]
    return spark.createDataFrame(rows, "k int, predicted double, best_k double")


@query(
    "contamination_hits",
    with_(
        f"{grams_sql('benchmark', 'item_id', 'bgs')}, bg AS (SELECT DISTINCT item_id, g FROM bgs), bn AS (SELECT item_id, count(*) AS total FROM bg GROUP BY 1), "
        f"{grams_sql('documents', 'doc_id', 'dgs')}, dg AS (SELECT DISTINCT doc_id, g FROM dgs), c AS (SELECT doc_id, item_id, count(*) AS common FROM dg JOIN bg USING (g) GROUP BY 1, 2)",
        "SELECT doc_id, item_id, common, total, round(common / total, 9) AS containment FROM c JOIN bn USING (item_id) WHERE common / total >= 0.8",
    ),
)
def contamination_hits(spark, sf):
    return contained_items(table(spark, sf, "documents"), table(spark, sf, "benchmark")).withColumn("containment", F.round("containment", 9))


_KEPT = CLUSTERS + ", gone AS (SELECT doc_id FROM comp WHERE doc_id <> cluster)"


@query(
    "quality_before_after",
    with_(_KEPT, "SELECT quality, toxic, count(*) AS before_n, count(*) FILTER (WHERE doc_id NOT IN (SELECT doc_id FROM gone)) AS after_n FROM docs JOIN labels USING (doc_id) GROUP BY 1, 2", True),
)
def quality_before_after(spark, sf):
    r = dedup(table(spark, sf, "documents"), CFG, "dense")
    own = r.corpus.select("doc_id").join(table(spark, sf, "labels"), "doc_id").join(r.drop.withColumn("_gone", F.lit(True)), "doc_id", "left")
    return own.groupBy("quality", "toxic").agg(F.count("*").alias("before_n"), F.sum(F.col("_gone").isNull().cast("long")).alias("after_n"))


@query(
    "token_savings",
    with_(_KEPT + ", t AS (SELECT doc_id, len(list_filter(string_split_regex(text, '\\s+'), lambda x: x <> '')) AS t FROM docs)", "SELECT CAST(sum(t) AS BIGINT) AS tokens_raw, CAST(sum(t) FILTER (WHERE doc_id NOT IN (SELECT doc_id FROM gone)) AS BIGINT) AS tokens_kept FROM t", True),
)
def token_savings_row(spark, sf):
    r = dedup(table(spark, sf, "documents"), CFG, "dense")
    return token_savings(r.corpus, r.drop).select("tokens_raw", "tokens_kept")


def _rate(spark, sf, by: str):
    r = dedup(table(spark, sf, "documents"), CFG, "dense")
    own = r.corpus.select("doc_id", by).join(r.drop.withColumn("_gone", F.lit(1)), "doc_id", "left")
    return own.groupBy(by).agg(F.count("*").alias("docs"), F.count("_gone").alias("removed"))


def _rate_sql(by: str) -> str:
    return with_(_KEPT, f"SELECT {by}, count(*) AS docs, count(*) FILTER (WHERE doc_id IN (SELECT doc_id FROM gone)) AS removed FROM docs GROUP BY 1", True)


@query("dup_rate_by_lang", _rate_sql("lang"))
def dup_rate_by_lang(spark, sf):
    return _rate(spark, sf, "lang")


@query("dup_rate_by_source", _rate_sql("source"))
def dup_rate_by_source(spark, sf):
    return _rate(spark, sf, "source")


@query(
    "hash_quality",
    with_(
        f"{DOCS}, {GRAMS}, u AS (SELECT DISTINCT g FROM grams), h AS (SELECT ({' + '.join(f'CAST(unicode(substr(g, {j + 1}, 1)) AS BIGINT) * {pow(CFG.q, j, CFG.p)}' for j in range(5))}) % {CFG.p} AS h FROM u), v AS (SELECT h, count(*) AS c FROM h GROUP BY 1)",
        "SELECT (SELECT count(*) FROM h) AS shingles, count(*) AS \"values\", CAST(sum(c * (c - 1) // 2) AS BIGINT) AS colliding_pairs FROM v",
    ),
)
def hash_quality_row(spark, sf):
    q = hash_quality(docs(spark, sf), CFG)
    return q.select("shingles", "values", F.round(F.col("collision_rate") * F.col("shingles") * (F.col("shingles") - 1) / 2).cast("long").alias("colliding_pairs"))
