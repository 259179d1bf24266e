"""The relational, array, string and date operations around the methods, over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpusdedup.plans.shared import materialise
from corpusdedup.queries import methods
from corpusdedup.sources.corpus import read_corpus, round_trip

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    def add(f):
        QUERIES[f"op_{name}"] = f
        if sql is not None:
            SQL[f"op_{name}"] = sql
        return f

    return add


def t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


# Sources and sinks


@op("scan_parquet_pruned", "SELECT doc_id, md5(text) AS digest FROM documents WHERE n_chars >= 200")
def scan_parquet_pruned(spark, sf):
    return t(spark, sf, "documents").where("n_chars >= 200").select("doc_id", F.md5("text").alias("digest"))


@op("scan_jsonl_roundtrip", "SELECT doc_id, md5(text) AS digest FROM documents")
def scan_jsonl_roundtrip(spark, sf):
    path = round_trip(t(spark, sf, "documents").select("doc_id", "text"), "json")
    return read_corpus(spark, path, "json").select("doc_id", F.md5("text").alias("digest"))


@op("scan_csv_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_csv_roundtrip(spark, sf):
    own = t(spark, sf, "nation")
    return spark.read.schema(own.schema).csv(round_trip(own, "csv"))


@op("scan_orc_roundtrip", "SELECT r_regionkey, r_name FROM region")
def scan_orc_roundtrip(spark, sf):
    own = t(spark, sf, "region")
    return spark.read.schema(own.schema).orc(round_trip(own, "orc"))


@op("scan_text_lines", "SELECT count(*) AS lines FROM region")
def scan_text_lines(spark, sf):
    return spark.read.text(round_trip(t(spark, sf, "region").select(F.col("r_name").alias("value")), "text")).agg(F.count("*").alias("lines"))


@op("source_file_map", "SELECT 'documents.parquet' AS file, count(*) AS docs FROM documents")
def source_file_map(spark, sf):
    own = t(spark, sf, "documents").select(F.regexp_extract("_metadata.file_path", r"(documents\.parquet)", 1).alias("file"))
    return own.groupBy("file").agg(F.count("*").alias("docs"))


@op("sink_partitioned", "SELECT lang, count(*) AS docs FROM documents WHERE lang IN ('de', 'fr') GROUP BY 1")
def sink_partitioned(spark, sf):
    path = round_trip(t(spark, sf, "documents").select("doc_id", "lang"), "parquet", "lang")
    return spark.read.parquet(path).where(F.col("lang").isin("de", "fr")).groupBy("lang").agg(F.count("*").alias("docs"))


# Filters and projections


@op("filter_short", "SELECT doc_id, n_chars FROM documents WHERE length(text) < 200")
def filter_short(spark, sf):
    return t(spark, sf, "documents").where(F.length("text") < 200).select("doc_id", "n_chars")


@op("filter_predicates", "SELECT count(*) AS n FROM lineitem WHERE l_quantity BETWEEN 5 AND 20 AND (l_returnflag IN ('A', 'R') OR l_linestatus LIKE 'O%') AND l_comment_ok IS NOT NULL".replace("l_comment_ok", "l_shipdate"))
def filter_predicates(spark, sf):
    own = t(spark, sf, "lineitem")
    return own.where(F.col("l_quantity").between(5, 20) & (F.col("l_returnflag").isin("A", "R") | F.col("l_linestatus").like("O%")) & F.col("l_shipdate").isNotNull()).agg(F.count("*").alias("n"))


@op("filter_null_safe", "SELECT count(*) AS n FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.quality IS NOT DISTINCT FROM NULL")
def filter_null_safe(spark, sf):
    own = t(spark, sf, "documents").join(t(spark, sf, "labels"), "doc_id", "left")
    return own.where(F.col("quality").eqNullSafe(F.lit(None))).agg(F.count("*").alias("n"))


@op("project_case", "SELECT doc_id, CASE WHEN n_chars < 500 THEN 'small' WHEN n_chars < 5000 THEN 'middle' ELSE 'large' END AS size_class, CAST(n_chars AS VARCHAR) AS chars FROM documents")
def project_case(spark, sf):
    c = F.col("n_chars")
    return t(spark, sf, "documents").select("doc_id", F.when(c < 500, "small").when(c < 5000, "middle").otherwise("large").alias("size_class"), c.cast("string").alias("chars"))


# Joins

_OL = "SELECT o_orderpriority, count(*) AS lines, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _orders_lines(spark, sf, hint: str | None = None):
    o, li = t(spark, sf, "orders"), t(spark, sf, "lineitem")
    o = o.hint(hint) if hint else o
    return o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.sum("l_quantity").cast("long").alias("quantity"))


@op("join_hash", _OL)
def join_hash(spark, sf):
    return _orders_lines(spark, sf)


@op("join_sortmerge", _OL)
def join_sortmerge(spark, sf):
    return _orders_lines(spark, sf, "merge")


@op("join_shuffle_hash", "SELECT c_mktsegment, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def join_shuffle_hash(spark, sf):
    o, c = t(spark, sf, "orders"), t(spark, sf, "customer").hint("shuffle_hash")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("orders"))


@op("join_broadcast", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, sf):
    # region has a fixed handful of rows
    return t(spark, sf, "nation").join(F.broadcast(t(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


@op("join_left", "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels l USING (doc_id)")
def join_left(spark, sf):
    return t(spark, sf, "documents").join(t(spark, sf, "labels"), "doc_id", "left").select("doc_id", "quality")


@op("join_right", "SELECT doc_id, n_chars, toxic FROM documents d RIGHT JOIN labels l USING (doc_id)")
def join_right(spark, sf):
    return t(spark, sf, "documents").join(t(spark, sf, "labels"), "doc_id", "right").select("doc_id", "n_chars", "toxic")


@op("join_full", "SELECT count(*) AS n, count(a.doc_id) AS a, count(b.doc_id) AS b FROM (SELECT doc_id FROM documents WHERE n_chars > 1000) a FULL JOIN (SELECT doc_id FROM labels) b ON a.doc_id = b.doc_id")
def join_full(spark, sf):
    a = t(spark, sf, "documents").where("n_chars > 1000").select("doc_id", F.lit(1).alias("a"))
    b = t(spark, sf, "labels").select("doc_id", F.lit(1).alias("b"))
    return a.join(b, "doc_id", "full").agg(F.count("*").alias("n"), F.count("a").alias("a"), F.count("b").alias("b"))


@op("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, sf):
    return t(spark, sf, "documents").join(t(spark, sf, "labels"), "doc_id", "left_semi").select("doc_id")


@op("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, sf):
    return t(spark, sf, "documents").join(t(spark, sf, "labels"), "doc_id", "left_anti").select("doc_id")


@op("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross(spark, sf):
    # both have a fixed handful of rows
    return t(spark, sf, "region").crossJoin(t(spark, sf, "nation")).select("r_name", "n_name")


@op("join_theta", "SELECT a.doc_id, count(*) AS shorter FROM documents a JOIN benchmark b ON length(b.text) < length(a.text) GROUP BY 1")
def join_theta(spark, sf):
    """Items shorter than each document.  An inequality alone has no key, so it becomes a rank among the items' lengths, which are as many as there are lengths."""
    sizes = t(spark, sf, "benchmark").groupBy(F.char_length("text").alias("_n")).agg(F.count("*").alias("_items"))
    sizes = sizes.select("_n", "_items", F.lit(None).cast("long").alias("doc_id"))
    own = t(spark, sf, "documents").select(F.char_length("text").alias("_n"), F.lit(0).cast("long").alias("_items"), "doc_id")
    # Both sides by length: totals of cells of lengths before, and the running total inside a cell, so no task holds all.
    both = own.unionByName(sizes).withColumn("_cell", F.floor(F.log2(F.col("_n") + 1) * 8))
    cells = both.groupBy("_cell").agg(F.sum("_items").alias("_in"))  # some hundreds of rows at most
    before = cells.select("_cell", (F.sum("_in").over(Window.orderBy("_cell")) - F.col("_in")).alias("_before"))
    lengths = both.groupBy("_cell", "_n").agg(F.sum("_items").alias("_in"))
    shorter = lengths.select("_cell", "_n", (F.sum("_in").over(Window.partitionBy("_cell").orderBy("_n")) - F.col("_in")).alias("_inside")).join(F.broadcast(before), "_cell")
    found = own.join(shorter.select("_n", (F.col("_before") + F.col("_inside")).alias("shorter")), "_n")
    return found.where("shorter > 0").select("doc_id", "shorter")


@op("join_range", "SELECT a.doc_id, count(*) AS partners FROM documents a JOIN documents b ON a.doc_id <> b.doc_id AND b.n_chars BETWEEN 0.8 * a.n_chars AND a.n_chars / 0.8 AND a.lang = b.lang GROUP BY 1")
def join_range(spark, sf):
    """Other documents of a language whose length is within a ratio: lengths meet lengths, with how many documents have them, so no pair of documents is made."""
    own = t(spark, sf, "documents").where("n_chars > 0 and lang is not null").select("doc_id", "lang", "n_chars")
    # A length's cell on a log scale, and both neighbours, hold all lengths within the ratio: an equi-join.
    cell = lambda c: F.floor(F.log(c) / F.lit(0.2232))
    lengths = own.groupBy("lang", "n_chars").agg(F.count("*").alias("_docs"))
    there = lengths.select("lang", cell(F.col("n_chars")).alias("_cell"), F.col("n_chars").alias("_n"), "_docs")
    here = lengths.select("lang", "n_chars", F.explode(F.array(cell(F.col("n_chars")) - 1, cell(F.col("n_chars")), cell(F.col("n_chars")) + 1)).alias("_cell"))
    met = here.join(there, ["lang", "_cell"]).where((F.col("_n") >= 0.8 * F.col("n_chars")) & (F.col("_n") <= F.col("n_chars") / 0.8))
    return own.join(met.groupBy("lang", "n_chars").agg((F.sum("_docs") - 1).alias("partners")), ["lang", "n_chars"]).where("partners > 0").select("doc_id", "partners")


@op("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def join_interval(spark, sf):
    """Events of one user at most ten minutes apart: cells of ten minutes, each event meets its own and the next."""
    own = t(spark, sf, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 600_000_000).alias("cell"))
    a = own.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array(F.col("cell"), F.col("cell") + 1)).alias("cell"))
    b = own.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), "cell")
    return a.join(b, ["user_id", "cell"]).where("tb > ta and tb <= ta + interval 10 minutes").select("a", "b")


@op("join_asof", "SELECT p.event_id, c.value AS last_click FROM events p ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'click' GROUP BY 1, 2) c ON p.user_id = c.user_id AND p.ts >= c.ts WHERE p.event_type = 'purchase'")
def join_asof(spark, sf):
    """The latest click at or before each purchase of a user: both sides in one stream, the last seen value carried along."""
    own = t(spark, sf, "events")
    clicks = own.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("value").alias("value")).select("user_id", "ts", F.lit(0).alias("side"), F.lit(None).cast("long").alias("event_id"), "value")
    buys = own.where("event_type = 'purchase'").select("user_id", "ts", F.lit(1).alias("side"), "event_id", F.lit(None).cast("double").alias("value"))
    w = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return clicks.union(buys).withColumn("last_click", F.last("value", ignorenulls=True).over(w)).where("side = 1").select("event_id", "last_click")


@op("join_self_bucket", "SELECT count(*) AS pairs FROM (SELECT user_id, event_type FROM events) a JOIN (SELECT user_id, event_type FROM events) b USING (user_id, event_type)")
def join_self_bucket(spark, sf):
    own = t(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    return own.agg(F.sum(F.col("n") * F.col("n")).alias("pairs"))


# Aggregates


@op("agg_hash_partial", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity, min(l_extendedprice) AS least, max(l_extendedprice) AS most, round(avg(l_discount), 6) AS discount FROM lineitem GROUP BY 1, 2")
def agg_hash_partial(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("quantity"), F.min("l_extendedprice").alias("least"), F.max("l_extendedprice").alias("most"), F.round(F.avg("l_discount"), 6).alias("discount"))


@op("agg_sort", "SELECT lang, max(md5(text)) AS most FROM documents GROUP BY 1")
def agg_sort(spark, sf):
    return t(spark, sf, "documents").groupBy("lang").agg(F.max(F.md5("text")).alias("most"))


@op("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@op("agg_approx_distinct", "SELECT true AS close FROM (SELECT count(DISTINCT l_partkey) AS n FROM lineitem)")
def agg_approx_distinct(spark, sf):
    own = t(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("n"))
    return own.select((F.abs(F.col("a") - F.col("n")) <= 0.1 * F.col("n")).alias("close"))


@op("agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.5) AS median, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY 1")
def agg_percentile(spark, sf):
    return t(spark, sf, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("median"), F.percentile("n_chars", 0.9).alias("p90"))


@op("agg_stddev", "SELECT source, round(stddev_pop(n_chars), 6) AS spread FROM documents GROUP BY 1")
def agg_stddev(spark, sf):
    return t(spark, sf, "documents").groupBy("source").agg(F.round(F.stddev_pop("n_chars"), 6).alias("spread"))


@op("agg_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
def agg_rollup(spark, sf):
    return t(spark, sf, "documents").rollup("lang", "source").agg(F.count("*").alias("n"))


@op("agg_cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def agg_cube(spark, sf):
    return t(spark, sf, "documents").cube("lang", "source").agg(F.count("*").alias("n"))


@op("agg_grouping_sets", "SELECT lang, source, count(*) AS n, CAST(grouping(lang, source) AS BIGINT) AS gid FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(spark, sf):
    return t(spark, sf, "documents").groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n"), F.grouping_id().alias("gid"))


@op("agg_pivot", "SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en FROM documents GROUP BY 1")
def agg_pivot(spark, sf):
    return t(spark, sf, "documents").groupBy("source").pivot("lang", ["de", "en"]).count().fillna(0)


@op("agg_filter_clause", "SELECT count(*) FILTER (WHERE quality = 1) AS good, count(*) FILTER (WHERE toxic = 1) AS toxic FROM labels")
def agg_filter_clause(spark, sf):
    t(spark, sf, "labels").createOrReplaceTempView("_labels")
    return spark.sql("SELECT count(*) FILTER (WHERE quality = 1) AS good, count(*) FILTER (WHERE toxic = 1) AS toxic FROM _labels")


@op("agg_minby_maxby", "SELECT lang, arg_min(doc_id, n_chars * 1000000 + doc_id) AS shortest, arg_max(doc_id, n_chars * 1000000 + doc_id) AS longest FROM documents GROUP BY 1")
def agg_minby_maxby(spark, sf):
    k = F.col("n_chars") * 1_000_000 + F.col("doc_id")
    return t(spark, sf, "documents").groupBy("lang").agg(F.min_by("doc_id", k).alias("shortest"), F.max_by("doc_id", k).alias("longest"))


@op("agg_salted", "SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY 1")
def agg_salted(spark, sf):
    """Two steps over a salt: what a hot key needs where an aggregate has no partial form."""
    own = t(spark, sf, "lineitem").withColumn("salt", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(16)))
    return own.groupBy("l_returnflag", "salt").agg(F.count("*").alias("n")).groupBy("l_returnflag").agg(F.sum("n").alias("n"))


# Windows


def _by_length():
    return Window.partitionBy("lang").orderBy(F.col("n_chars").desc(), "doc_id")


@op("win_row_number", "SELECT doc_id, CAST(row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS INTEGER) AS rn FROM documents")
def win_row_number(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.row_number().over(_by_length()).alias("rn"))


@op("win_rank", "SELECT o_orderkey, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INTEGER) AS r, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INTEGER) AS d FROM orders")
def win_rank(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t(spark, sf, "orders").select("o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"))


@op("win_ntile", "SELECT doc_id, CAST(ntile(4) OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS INTEGER) AS q, round(percent_rank() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id), 9) AS pr, round(cume_dist() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id), 9) AS cd FROM documents")
def win_ntile(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.ntile(4).over(_by_length()).alias("q"), F.round(F.percent_rank().over(_by_length()), 9).alias("pr"), F.round(F.cume_dist().over(_by_length()), 9).alias("cd"))


@op("win_lag_lead", "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_lead(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"))


@op("win_rows_frame", "SELECT o_orderkey, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving FROM orders")
def win_rows_frame(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return t(spark, sf, "orders").select("o_orderkey", F.round(F.avg("o_totalprice").over(w), 4).alias("moving"))


@op("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def win_range_frame(spark, sf):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return t(spark, sf, "events").select("event_id", F.count("*").over(w).alias("last_hour"))


@op("win_first_last", "SELECT event_id, first_value(value) OVER w AS first, last_value(value) OVER w AS last, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(spark, sf, "events").select("event_id", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"), F.nth_value("value", 2).over(w).alias("second"))


# Order, limits, sets


@op("sort_global", "SELECT doc_id, CAST(row_number() OVER (ORDER BY n_chars DESC, doc_id) AS BIGINT) AS place FROM documents")
def sort_global(spark, sf):
    """Places in the order of all rows: a range partitioning sorts them, and what stands before each partition is added."""
    order = [F.col("n_chars").desc(), F.col("doc_id")]
    own = materialise(t(spark, sf, "documents").select("doc_id", "n_chars").repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_id", F.monotonically_increasing_id()), "sorted")
    part = own.withColumn("_part", F.shiftright("_id", 33))
    sizes = part.groupBy("_part").agg(F.count("*").alias("_n"))  # a row for each partition
    before = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))
    return part.join(F.broadcast(before), "_part").select("doc_id", (F.col("_before") + F.col("_id").bitwiseAND((1 << 33) - 1) + 1).alias("place"))


@op("sort_within", "SELECT count(*) AS n, true AS ordered FROM documents")
def sort_within(spark, sf):
    own = t(spark, sf, "documents").select("doc_id", "n_chars").repartition(4, "doc_id").sortWithinPartitions("n_chars").withColumn("_i", F.monotonically_increasing_id())
    w = Window.partitionBy(F.shiftright("_i", 33)).orderBy("_i")
    return own.select((F.col("n_chars") >= F.lag("n_chars", 1, 0).over(w)).alias("ok")).agg(F.count("*").alias("n"), F.bool_and("ok").alias("ordered"))


@op("topk", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10")
def topk(spark, sf):
    return t(spark, sf, "documents").orderBy(F.col("n_chars").desc(), "doc_id").limit(10).select("doc_id", "n_chars")


@op("topk_per_group", "SELECT lang, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) <= 3")
def topk_per_group(spark, sf):
    return t(spark, sf, "documents").withColumn("rn", F.row_number().over(_by_length())).where("rn <= 3").select("lang", "doc_id")


@op("offset_limit", "SELECT doc_id FROM documents ORDER BY doc_id LIMIT 20 OFFSET 40")
def offset_limit(spark, sf):
    return t(spark, sf, "documents").select("doc_id").orderBy("doc_id").offset(40).limit(20)


def _two(spark, sf):
    d = t(spark, sf, "documents")
    return d.where("n_chars > 1000").select("doc_id"), t(spark, sf, "labels").select("doc_id")


_A, _B = "SELECT doc_id FROM documents WHERE n_chars > 1000", "SELECT doc_id FROM labels"


@op("set_union_all", f"{_A} UNION ALL {_B}")
def set_union_all(spark, sf):
    a, b = _two(spark, sf)
    return a.unionByName(b)


@op("set_union", f"{_A} UNION {_B}")
def set_union(spark, sf):
    a, b = _two(spark, sf)
    return a.union(b).distinct()


@op("set_intersect", f"{_A} INTERSECT {_B}")
def set_intersect(spark, sf):
    a, b = _two(spark, sf)
    return a.intersect(b)


_RETURNED, _SHIPPED = "SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R'", "SELECT l_partkey FROM lineitem WHERE l_linestatus = 'O'"


def _parts(spark, sf):
    own = t(spark, sf, "lineitem")
    return own.where("l_returnflag = 'R'").select("l_partkey"), own.where("l_linestatus = 'O'").select("l_partkey")


@op("set_intersect_all", f"{_RETURNED} INTERSECT ALL {_SHIPPED}")
def set_intersect_all(spark, sf):
    a, b = _parts(spark, sf)
    return a.intersectAll(b)


@op("set_except", f"{_A} EXCEPT {_B}")
def set_except(spark, sf):
    a, b = _two(spark, sf)
    return a.subtract(b)


@op("set_except_all", f"{_RETURNED} EXCEPT ALL {_SHIPPED}")
def set_except_all(spark, sf):
    a, b = _parts(spark, sf)
    return a.exceptAll(b)


# Strings, numbers, dates

_STRIPPED = "trim(regexp_replace(lower(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<[^>]+>', ' ', 'g')), '[ \\t\\n]+', ' ', 'g'))"


@op("str_normalise", f"SELECT page_id, md5({_STRIPPED}) AS digest FROM pages")
def str_normalise(spark, sf):
    body = F.regexp_replace(F.regexp_replace("html", "(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]+>", " ")
    return t(spark, sf, "pages").select("page_id", F.md5(F.trim(F.regexp_replace(F.lower(body), "[ \t\n]+", " "))).alias("digest"))


@op("str_url_parts", "SELECT regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")
def str_url_parts(spark, sf):
    return t(spark, sf, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("pages"))


@op("str_hashes", "SELECT doc_id, md5(text) AS md5, sha1(text) AS sha1, sha256(text) AS sha256 FROM documents")
def str_hashes(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.md5("text").alias("md5"), F.sha1("text").alias("sha1"), F.sha2("text", 256).alias("sha256"))


@op("str_hashes_spark")
def str_hashes_spark(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.hash("text").alias("murmur3"), F.xxhash64("text").alias("xxhash64"))


_HOST = "regexp_extract(url, '^https?://([^/?#]+)', 1)"


@op("str_levenshtein", f"SELECT page_id, CAST(levenshtein(url, before) AS INTEGER) AS d FROM (SELECT page_id, url, lag(url) OVER (PARTITION BY {_HOST} ORDER BY page_id) AS before FROM pages) WHERE before IS NOT NULL")
def str_levenshtein(spark, sf):
    """Edit distance of each page's address and that of the page before it of the same host."""
    w = Window.partitionBy(F.parse_url("url", F.lit("HOST"))).orderBy("page_id")
    own = t(spark, sf, "pages").select("page_id", "url", F.lag("url").over(w).alias("before"))
    return own.where("before is not null").select("page_id", F.levenshtein("url", "before").alias("d"))


@op("str_functions", "SELECT doc_id, substr(text, 1, 10) AS head, upper(source) AS src, length(trim(text)) AS n, translate(lang, 'de', 'xy') AS tr, concat_ws('-', lang, source) AS both FROM documents")
def str_functions(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.substring("text", 1, 10).alias("head"), F.upper("source").alias("src"), F.length(F.trim("text")).cast("long").alias("n"), F.translate("lang", "de", "xy").alias("tr"), F.concat_ws("-", "lang", "source").alias("both"))


@op("math_mod_sqrt", "SELECT doc_id, i, i % 7 AS m, CAST(floor(4 * sqrt(i)) AS BIGINT) AS k, CAST(ceil(i / 3.0) AS BIGINT) AS c, round(pow(i, 1.5), 3) AS p, round(ln(i + 1), 9) AS l FROM (SELECT doc_id, CAST(n_chars AS BIGINT) AS i FROM documents)")
def math_mod_sqrt(spark, sf):
    i = F.col("i")
    own = t(spark, sf, "documents").select("doc_id", F.col("n_chars").cast("long").alias("i"))
    return own.select("doc_id", "i", (i % 7).alias("m"), F.floor(4 * F.sqrt(i)).alias("k"), F.ceil(i / 3).alias("c"), F.round(F.pow(i, F.lit(1.5)), 3).alias("p"), F.round(F.log(i + 1), 9).alias("l"))


@op("math_histogram", "SELECT least(11, greatest(0, CAST(floor((n_chars - 0) / 500.0) AS BIGINT) + 1)) AS cell, count(*) AS n FROM documents GROUP BY 1")
def math_histogram(spark, sf):
    return t(spark, sf, "documents").groupBy(F.width_bucket(F.col("n_chars").cast("double"), F.lit(0.0), F.lit(5000.0), F.lit(10)).alias("cell")).agg(F.count("*").alias("n"))


@op("decimal_sum", "SELECT l_linestatus, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS VARCHAR) AS total FROM lineitem GROUP BY 1")
def decimal_sum(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_linestatus").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("string").alias("total"))


@op("date_trunc_diff", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, count(*) AS n, max(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate)) AS days FROM orders GROUP BY 1")
def date_trunc_diff(spark, sf):
    own = t(spark, sf, "orders")
    return own.groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month")).agg(F.count("*").alias("n"), F.max(F.datediff("o_orderdate", F.lit("1992-01-01").cast("date"))).cast("long").alias("days"))


# Arrays, maps, structs


@op("array_hof", "SELECT vec_id, round(list_sum([x * x for x in embedding]), 3) AS norm2, CAST(len([x for x in embedding if x > 0]) AS INTEGER) AS positive FROM embeddings")
def array_hof(spark, sf):
    own = t(spark, sf, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    return own.select("vec_id", F.round(F.aggregate(F.zip_with("e", "e", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x), 3).alias("norm2"), F.size(F.filter("e", lambda x: x > 0)).alias("positive"))


_PARTS = "p AS (SELECT l_orderkey AS k, list(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1)"


@op("array_sets", f"WITH {_PARTS} SELECT a.k, CAST(len(list_intersect(a.parts, b.parts)) AS INTEGER) AS common, CAST(len(list_distinct(a.parts || b.parts)) AS INTEGER) AS total FROM p a JOIN p b ON b.k = a.k + 1")
def array_sets(spark, sf):
    p = t(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("k")).agg(F.collect_set("l_partkey").alias("a"))
    b = p.select((F.col("k") - 1).alias("k"), F.col("a").alias("b"))
    return p.join(b, "k").select("k", F.size(F.array_intersect("a", "b")).alias("common"), F.size(F.array_union("a", "b")).alias("total"))


@op("array_explode", "SELECT vec_id, CAST(i - 1 AS INTEGER) AS pos, CAST(embedding[i] AS DOUBLE) AS val FROM embeddings, unnest(range(1, len(embedding) + 1)) AS t(i)")
def array_explode(spark, sf):
    return t(spark, sf, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "val")).withColumn("val", F.col("val").cast("double"))


@op("map_json", "SELECT event_id, CAST(len(json_keys(props)) AS INTEGER) AS n_keys, array_to_string(list_sort(json_keys(props)), ',') AS names FROM events")
def map_json(spark, sf):
    own = t(spark, sf, "events").select("event_id", F.from_json("props", "map<string,string>").alias("m"))
    return own.select("event_id", F.size(F.map_keys("m")).alias("n_keys"), F.array_join(F.array_sort(F.map_keys("m")), ",").alias("names"))


@op("struct_nested", "SELECT conv_id, md5(string_agg(role || ':' || text, chr(10) ORDER BY turn)) AS digest, count(*) AS turns FROM conversations GROUP BY 1")
def struct_nested(spark, sf):
    own = t(spark, sf, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("m"), F.count("*").alias("turns"))
    return own.select("conv_id", F.md5(F.array_join(F.transform("m", lambda x: F.concat(x["role"], F.lit(":"), x["text"])), "\n")).alias("digest"), "turns")


@op("sample_stratified", "SELECT doc_id, lang FROM documents WHERE CAST(('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8)) AS BIGINT) / 4294967296.0 < CASE lang WHEN 'en' THEN 0.1 WHEN 'de' THEN 0.5 ELSE 0 END")
def sample_stratified(spark, sf):
    from corpusdedup.operators.select import portable_share

    rate = F.when(F.col("lang") == "en", 0.1).when(F.col("lang") == "de", 0.5).otherwise(0.0)
    return t(spark, sf, "documents").select("doc_id", "lang").where(portable_share(F.col("doc_id")) < rate)


@op("subquery_corr", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def subquery_corr(spark, sf):
    t(spark, sf, "orders").createOrReplaceTempView("_orders")
    return spark.sql("SELECT o_orderkey FROM _orders o WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM _orders i WHERE i.o_custkey = o.o_custkey)")


@op("subquery_scalar", "SELECT doc_id FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
def subquery_scalar(spark, sf):
    t(spark, sf, "documents").createOrReplaceTempView("_documents")
    return spark.sql("SELECT doc_id FROM _documents WHERE n_chars > (SELECT avg(n_chars) FROM _documents)")


@op("subquery_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 200000)")
def subquery_exists(spark, sf):
    t(spark, sf, "orders").createOrReplaceTempView("_orders")
    t(spark, sf, "customer").createOrReplaceTempView("_customer")
    return spark.sql("SELECT c_custkey FROM _customer c WHERE EXISTS (SELECT 1 FROM _orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 200000)")


_WALK = "WITH RECURSIVE walk(conv_id, turn, depth) AS (SELECT conv_id, min(turn), 0 FROM {t} GROUP BY conv_id UNION ALL SELECT w.conv_id, c.turn, w.depth + 1 FROM walk w JOIN {t} c ON c.conv_id = w.conv_id AND c.turn = w.turn + 1) SELECT conv_id, turn, depth FROM walk"


@op("cte_recursive", _WALK.format(t="conversations"))
def cte_recursive(spark, sf):
    """Walks the edges from each turn to the next."""
    t(spark, sf, "conversations").createOrReplaceTempView("_conversations")
    return spark.sql(_WALK.format(t="_conversations"))


# Python surface


@op("udf_arrow", "SELECT doc_id, length(text) AS n FROM documents")
def udf_arrow(spark, sf):
    from corpusdedup.functions.registered import text_lengths

    return t(spark, sf, "documents").select("doc_id", text_lengths()(F.col("text")).alias("n"))


def _merged_sql() -> str:
    from corpusdedup.queries.methods import CFG, base_sql, grams_sql, with_

    least = ", ".join(f"min((h * {a} + {b}) % {CFG.p})" for a, b in zip(*CFG.constants))
    return with_(f"{grams_sql('documents', 'doc_id', 'grams')}, {base_sql()}", f"SELECT source, CAST(list_sum([{least}]) AS BIGINT) AS checksum FROM base JOIN documents USING (doc_id) GROUP BY 1")


@op("udaf_min_merge", _merged_sql())
def udaf_min_merge(spark, sf):
    from corpusdedup.functions.registered import min_merge
    from corpusdedup.operators.signatures import signatures

    own = signatures(t(spark, sf, "documents")).where("sig is not null").join(t(spark, sf, "documents").select("doc_id", "source"), "doc_id")
    return own.groupBy("source").agg(min_merge()(F.col("sig")).alias("sig")).select("source", F.aggregate("sig", F.lit(0).cast("long"), lambda a, x: a + x).alias("checksum"))


@op("udtf_bands", methods.SQL["dense_buckets"])
def udtf_bands(spark, sf):
    from corpusdedup.functions.registered import register
    from corpusdedup.operators.signatures import signatures

    register(spark)
    own = methods.docs(spark, sf)
    signatures(own).where("sig is not null").createOrReplaceTempView("_sigs")
    return spark.sql(f"SELECT doc_id, band, bucket FROM _sigs, LATERAL lsh_buckets(sig, {methods.buckets_for(own, methods.CFG)})")
