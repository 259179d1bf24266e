"""Line deduplication over a deletion neighbourhood, with DataFrame operations only.

Two lines are alike if at most one word was put in, left out or replaced.  A line's neighbourhood is the line itself and its
variants with one word deleted, each as a hash that knows the order of its words; alike lines share a variant.  Of the lines
that share one, all but the earliest are compared with the earliest, word by word, so a group costs as much as it has members.

A variant per word of the whole corpus would be shuffled for nothing where a line has no partner.  One edit leaves the first
or the last words of a line as they were, so only lines that share such an end with another distinct line emit variants;
this loses no partner.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusdedup.llm.common import quoted, unused
from corpusdedup.plans.shared import fitted, materialise

#: Lines of fewer words are compared for equality only by default: one word of four would be a similarity below 0.8.
MIN_WORDS = 5
#: The least that ``min_words`` may be: any two lines of a word or two are a word apart or near it.
LEAST_WORDS = 3


def normalised(line: Column) -> Column:
    """Lower case, runs of white space as one space, none at the ends."""
    odd = line.contains("  ") | line.contains("\t") | line.contains("\r") | line.contains("\f") | line.contains("\v")
    return F.lower(F.trim(F.when(odd, F.regexp_replace(line, "[ \t\r\f\x0b]+", " ")).otherwise(line)))


def _line_rows(docs: DataFrame) -> DataFrame:
    """_doc, _line, _norm of every line that has a word."""
    own = docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long").alias("_doc"), "text")
    lines = own.select("_doc", F.posexplode(F.split("text", "\n")).alias("_line", "_raw"))
    return lines.select("_doc", "_line", normalised(F.col("_raw")).alias("_norm")).where("_norm <> ''")


def _end_keys(norm: Column, words: Column, min_words: int) -> Column:
    """Hashes of a line's first and last h words, for the power of two h that leaves at least one word between; where the next shorter line has half that h, those of that too."""
    half = F.floor(F.log2((words - 1) / 2)).cast("int")
    end = lambda h: F.call_function("substring_index", norm, F.lit(" "), h)
    key = lambda h: F.array(F.xxhash64(end(h), F.lit("first"), h), F.xxhash64(end(-h), F.lit("last"), h))
    h = F.pow(F.lit(2), half).cast("int")
    both = F.when(words - 1 == 2 * h, F.concat(key(h), F.when(words > min_words, key((h / 2).cast("int"))).otherwise(F.array().cast("array<bigint>"))))
    return F.when(words >= min_words, F.coalesce(both, key(h))).otherwise(F.array().cast("array<bigint>"))


def find_repeats(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """_doc and _dropped (array of line numbers from 0): the lines that repeat an earlier line, exactly or but for a word.

    Earlier is by doc_id, then line number.
    """
    if min_words < LEAST_WORDS:
        raise ValueError(f"lines of fewer than {LEAST_WORDS} words can only be equal")
    rows = _line_rows(docs)
    words = F.length("_norm") - F.length(F.translate("_norm", " ", "")) + 1
    rows = rows.select("_doc", "_line", F.xxhash64("_norm").alias("_h"), F.hash("_norm").alias("_g"), words.alias("_n"), "_norm")
    lines = materialise(rows.select("_doc", "_line", "_h", "_g", "_n", _end_keys(F.col("_norm"), F.col("_n"), min_words).alias("_ends")), "lines")

    # Distinct lines, each with its earliest document.
    distinct = materialise(lines.groupBy("_h", "_g").agg(F.min("_doc").alias("_doc"), F.count("*").alias("_copies"), F.min("_n").alias("_n")), "line-texts")
    ends = lines.where(F.col("_n") >= min_words).select("_h", "_g", F.explode("_ends").alias("_end"))
    # An end shared by two distinct lines shows two different hashes; both extremes are kept by partial aggregation.
    shared = ends.groupBy("_end").agg(F.min("_h").alias("_lo"), F.max("_h").alias("_hi")).where("_lo <> _hi").select("_end")
    shared = materialise(shared, "line-ends")
    partners = materialise(ends.join(fitted(shared, 8), "_end", "left_semi").select("_h", "_g").distinct(), "line-partners")

    near = _near_repeats(docs, lines, distinct, partners)
    affected = distinct.where("_copies > 1").select("_h", "_g", F.col("_doc").alias("_first"), F.lit(False).alias("_near"))
    affected = affected.join(near, ["_h", "_g"], "left_anti").union(near.select("_h", "_g", F.lit(None).cast("long"), F.lit(True)))
    affected = materialise(affected, "line-affected")
    hit = lines.select("_doc", "_line", "_h", "_g").join(fitted(affected, 29), ["_h", "_g"])
    by_text = hit.groupBy("_doc", "_h", "_g").agg(F.min("_line").alias("_keep"), F.collect_list("_line").alias("_all"), F.max("_first").alias("_first"), F.max("_near").alias("_near"))
    drop = F.when(F.col("_near") | (F.col("_doc") != F.col("_first")), F.col("_all")).otherwise(F.array_remove("_all", F.col("_keep")))
    return by_text.select("_doc", drop.alias("_drop")).where(F.size("_drop") > 0).groupBy("_doc").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("_drop")))).alias("_dropped"))


def _near_repeats(docs: DataFrame, lines: DataFrame, distinct: DataFrame, partners: DataFrame) -> DataFrame:
    """_h, _g of the distinct lines that have an earlier one within one word."""
    # The earliest place of each line that has a possible partner, and its text from there.
    first = distinct.select("_h", "_g", "_doc").join(fitted(partners, 12), ["_h", "_g"], "left_semi")
    first = materialise(first, "line-first")
    places = lines.select("_doc", "_line", "_h", "_g").join(fitted(first, 20), ["_h", "_g", "_doc"]).groupBy("_doc", "_h", "_g").agg(F.min("_line").alias("_line"))
    wanted = materialise(places.groupBy("_doc").agg(F.collect_list(F.struct("_line", "_h", "_g")).alias("_want")), "line-places")
    own = docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long").alias("_doc"), "text").join(fitted(wanted, 120), "_doc")
    # explode(array(x)) makes x a column of its own, which is split once, not once for each line taken from it.
    own = own.select("_doc", "_want", F.explode(F.array(F.split("text", "\n"))).alias("_lines")).select("_doc", F.explode("_want").alias("_w"), "_lines")
    texts = own.select("_doc", F.col("_w._line").alias("_line"), F.col("_w._h").alias("_h"), F.col("_w._g").alias("_g"), normalised(F.get("_lines", F.col("_w._line"))).alias("_norm"))
    texts = materialise(texts.dropDuplicates(["_h", "_g"]), "line-candidates")

    variants = _variants(texts)
    met = materialise(variants.groupBy("_key").count().where("count > 1").select("_key"), "variants-met")
    group = materialise(variants.join(fitted(met, 8), "_key", "left_semi"), "variants")
    me = F.struct("_doc", "_line", "_h", "_g")
    gone = group.where("_at >= 0").select("_key", "_at", me.alias("_me"))
    # Replaced: both lack the same word.
    least = gone.groupBy("_key", "_at").agg(F.min("_me").alias("_head"))
    replaced = gone.join(least, ["_key", "_at"]).where("_me > _head").select(F.col("_me").alias("_late"), F.col("_head").alias("_early"), "_at", F.lit("replaced").alias("_how"))
    # Put in or left out: one is whole, the other lacks a word.
    whole = group.where("_at < 0").select("_key", me.alias("_whole"))
    pair = gone.join(whole, "_key").where("_me <> _whole")
    late = pair.where("_whole < _me").select(F.col("_me").alias("_late"), F.col("_whole").alias("_early"), "_at", F.lit("late lacks").alias("_how"))
    early = pair.where("_me < _whole").groupBy("_whole").agg(F.min(F.struct("_me", "_at")).alias("_m")).select(F.col("_whole").alias("_late"), F.col("_m._me").alias("_early"), F.col("_m._at").alias("_at"), F.lit("early lacks").alias("_how"))
    candidates = replaced.union(late).union(early)
    # Verify the edit on the words themselves.
    text = lambda side: texts.select(F.col("_h").alias(f"{side}_h"), F.col("_g").alias(f"{side}_g"), F.split("_norm", " ").alias(f"{side}_words"))
    both = candidates.select("_at", "_how", F.col("_late._h").alias("l_h"), F.col("_late._g").alias("l_g"), F.col("_early._h").alias("e_h"), F.col("_early._g").alias("e_g"))
    both = both.join(text("l"), ["l_h", "l_g"]).join(text("e"), ["e_h", "e_g"])
    lacks = lambda c: F.concat(F.slice(c, F.lit(1), F.col("_at")), F.slice(c, F.col("_at") + 2, F.size(c)))
    left = F.when(F.col("_how") == "early lacks", F.col("l_words")).otherwise(lacks("l_words"))
    right = F.when(F.col("_how") == "late lacks", F.col("e_words")).otherwise(lacks("e_words"))
    return materialise(both.where(left == right).select(F.col("l_h").alias("_h"), F.col("l_g").alias("_g")).distinct(), "line-near")


def _variants(texts: DataFrame) -> DataFrame:
    """A row for each line without its word at _at, and one (_at = -1) for the whole line; _key hashes what is left, in order.

    Words hash with their place, so a variant's hash is the exclusive or of the words before, and of the words after as if one
    place earlier: one running aggregate along the line instead of a string for each variant.
    """
    own = texts.repartition("_h", "_g").select("_h", "_g", "_doc", "_line", F.posexplode(F.split("_norm", " ")).alias("_at", "_word"))
    own = own.select("_h", "_g", "_doc", "_line", "_at", F.xxhash64("_word", "_at").alias("_a"), F.xxhash64("_word", F.col("_at") - 1).alias("_b"))
    along = Window.partitionBy("_h", "_g").orderBy("_at").rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("_h", "_g").orderBy("_at").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    own = own.select("*", F.bit_xor("_a").over(along).alias("_pa"), F.bit_xor("_b").over(along).alias("_pb"), F.bit_xor("_a").over(whole).alias("_ta"), F.bit_xor("_b").over(whole).alias("_tb"), F.count("_a").over(whole).alias("_n"))
    without = F.col("_pa").bitwiseXOR(F.col("_a")).bitwiseXOR(F.col("_tb")).bitwiseXOR(F.col("_pb"))
    row = lambda key, n, at: F.struct(F.xxhash64(key, n).alias("_key"), at.cast("int").alias("_at"))
    one = row(without, F.col("_n") - 1, F.col("_at"))
    made = F.when(F.col("_at") == 0, F.array(one, row(F.col("_ta"), F.col("_n"), F.lit(-1)))).otherwise(F.array(one))
    return own.select("_h", "_g", "_doc", "_line", F.explode(made).alias("_v")).select("_h", "_g", "_doc", "_line", "_v._key", "_v._at")


def dedup_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """``docs`` without the lines that repeat an earlier line, with ``dropped_lines`` (their numbers from 0, ascending) as last column.

    A line is dropped if an earlier one (by doc_id, then line number) equals it after normalisation or, from ``min_words``
    words on, differs by one word.  Lines without words stay.  Null texts and rows without doc_id stay as they are; rows of
    equal doc_id are one document, and lose the same line numbers; other columns stay, and a column named dropped_lines is
    replaced; an empty table gives an empty result.
    """
    columns = [c for c in docs.columns if c.lower() != "dropped_lines"]
    key, gone, lines = unused(columns, "_doc", "_dropped", "_lines")
    drops = materialise(find_repeats(docs, min_words), "line-drops").withColumnsRenamed({"_doc": key, "_dropped": gone})
    own = [quoted(c) for c in columns]
    joined = docs.select(own).join(fitted(drops, 80), F.col("doc_id").cast("long") == F.col(key), "left")
    split = joined.select(*own, gone, F.explode(F.array(F.when(F.col(gone).isNotNull(), F.split("text", "\n")))).alias(lines))
    kept = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col(gone))
    text = F.when(F.col(gone).isNull(), F.col("text")).otherwise(F.array_join(F.transform(kept, lambda i: F.get(lines, i)), "\n"))
    return split.select(*[text.alias(c) if c.lower() == "text" else quoted(c) for c in columns], F.coalesce(gone, F.array().cast("array<int>")).alias("dropped_lines"))


def drop_repeated_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """``docs`` with the text that ``dedup_lines`` leaves, n_chars brought up to date, and without the documents of which no word is left.

    A column named dropped_lines does not pass.
    """
    left = dedup_lines(docs, min_words)
    touched = F.size("dropped_lines") > 0
    emptied = touched & ~F.col("text").rlike(r"[^ \t\n\x0b\f\r]")
    kept = left.where(~F.coalesce(emptied, F.lit(False)))
    n_chars = F.when(touched, F.length("text").cast("long"))
    return kept.select(*[F.coalesce(n_chars, quoted(c)).alias(c) if c.lower() == "n_chars" else quoted(c) for c in left.columns if c != "dropped_lines"])
