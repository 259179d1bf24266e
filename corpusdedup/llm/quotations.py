"""Quotation linking for message threads, with DataFrame operations only.

Quote marks at the start of lines give nested levels.  Quoted passages, their paragraphs and their lines are normalised and
hashed, and joined to the earliest message of the conversation that wrote them itself.  A message answers the message that its
shallowest linked quotes come from.  Conversations are then put in reply order: threads by their first message, and inside a
thread by turn, with all quotes removed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusdedup.plans.shared import fitted, materialise

#: Characters that a paragraph or line inside a longer passage needs to be looked up: shorter ones occur by chance.
MIN_CHARS = 5
#: Messages of a conversation that are joined into one text.
PART = 256

_MARKS = r"^[ \t]*((?:>[ \t]?)+)"
#: How a line that introduces a quote begins in some languages; it ends with a colon.
_INTRODUCES = r"(?:^|\n)[ \t]*(?:On|Am|Le|El|Il|Op)\b[^\n]*:\s*$"


def normalised(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def _units(text: Column, least: int = 0) -> Column:
    """The whole passage, its paragraphs and its lines, normalised, with their number of characters.

    Paragraphs and lines of fewer than ``least`` characters are left out unless they are the whole.  Where normalising leaves
    nothing (signs only), the text itself counts, with single spaces.
    """

    def unit(x: Column) -> Column:
        plain = normalised(x)
        kept = F.when(plain != "", plain).otherwise(F.trim(F.regexp_replace(F.lower(x), r"\s+", " ")))
        return F.struct(F.md5(kept).alias("hash"), F.length(kept).cast("long").alias("chars"), (F.length(plain) >= least).alias("long"))

    parts = F.transform(F.concat(F.array(text), F.split(text, r"\n[ \t]*\n"), F.split(text, "\n")), unit)
    return F.array_distinct(F.filter(parts, lambda u: (u["chars"] > 0) & (u["long"] | (u["hash"] == parts[0]["hash"]))))


def quote_runs(messages: DataFrame) -> DataFrame:
    """_conv, _turn, _text (hash), _run, _level, _body: each message that quotes, as runs of lines of one level, marks removed."""
    own = messages.where(F.col("text").rlike(r"(?m)" + _MARKS)).select(F.col("conv_id").alias("_conv"), F.col("turn").alias("_turn"), F.xxhash64("text").alias("_text"), "text").dropDuplicates(["_conv", "_turn", "_text"])
    lines = own.select("_conv", "_turn", "_text", F.posexplode(F.split("text", "\n")).alias("_no", "_raw"))
    level = F.length(F.regexp_replace(F.regexp_extract("_raw", _MARKS, 1), "[^>]", ""))
    lines = lines.select("_conv", "_turn", "_text", "_no", level.alias("_level"), F.regexp_replace("_raw", _MARKS, "").alias("_line"))
    along = Window.partitionBy("_conv", "_turn", "_text").orderBy("_no")
    changed = (F.col("_level") != F.lag("_level", 1, -1).over(along)).cast("int")
    lines = lines.withColumn("_changed", changed).withColumn("_run", F.sum("_changed").over(along))
    own = lines.groupBy("_conv", "_turn", "_text", "_run", "_level").agg(F.array_sort(F.collect_list(F.struct("_no", "_line"))).alias("_l"))
    own = own.withColumn("_body", F.array_join(F.transform("_l", lambda x: x["_line"]), "\n"))
    follows = F.lead("_level", 1, 0).over(Window.partitionBy("_conv", "_turn", "_text").orderBy("_run"))
    bare = F.when((F.col("_level") == 0) & (F.col("_next") > 0), F.regexp_replace("_body", _INTRODUCES, "")).otherwise(F.col("_body"))
    return own.withColumn("_next", follows).select("_conv", "_turn", "_text", "_run", "_level", bare.alias("_body"))


def link(messages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(own words of the messages that quote: _conv, _turn, _text, _clean, _levels; answers: _conv, _turn, _parent)."""
    runs = materialise(quote_runs(messages), "quote-runs")
    said = F.array_sort(F.collect_list(F.when(F.col("_level") == 0, F.struct("_run", "_body"))))
    clean = runs.groupBy("_conv", "_turn", "_text").agg(F.regexp_replace(F.array_join(F.transform(said, lambda x: x["_body"]), "\n"), r"^\s+|\s+$", "").alias("_clean"), F.max("_level").cast("int").alias("_levels"))
    clean = materialise(clean, "quote-free")
    quoted = runs.where("_level > 0").select("_conv", "_turn", "_level", F.explode(_units(F.col("_body"), MIN_CHARS)).alias("_u")).select("_conv", "_turn", "_level", "_u.hash", "_u.chars").distinct()
    quoted = materialise(quoted, "quoted")
    wanted = materialise(quoted.select("_conv", "hash").distinct(), "quoted-hashes")
    whole = messages.where("text is not null").select(F.col("conv_id").alias("_conv"), F.col("turn").alias("_turn"), F.xxhash64("text").alias("_text"), "text")
    told = whole.join(fitted(clean, 400), ["_conv", "_turn", "_text"], "left").select("_conv", "_turn", F.coalesce("_clean", "text").alias("_own"))
    told = told.join(fitted(materialise(wanted.select("_conv").distinct(), "quoting-conversations"), 8), "_conv", "left_semi")
    units = told.select("_conv", "_turn", F.explode(_units(F.col("_own"))).alias("_u")).select("_conv", "_turn", "_u.hash")
    source = units.join(fitted(wanted, 60), ["_conv", "hash"], "left_semi").groupBy("_conv", "hash").agg(F.min("_turn").alias("_source"))
    met = quoted.join(source, ["_conv", "hash"]).where("_source < _turn")
    weighed = met.groupBy("_conv", "_turn", "_level", "_source").agg(F.sum("chars").alias("_w"))
    best = weighed.groupBy("_conv", "_turn").agg(F.min(F.struct("_level", -F.col("_w"), -F.col("_source"))).alias("_b"))
    return clean, materialise(best.select("_conv", "_turn", (-F.col("_b.col3")).alias("_parent")), "answers")


def threads(answers: DataFrame) -> DataFrame:
    """_conv, _turn, _root, _depth of every message that answers another, by doubling: as many rounds as the depth has binary digits."""
    now = materialise(answers.select("_conv", "_turn", F.col("_parent").alias("_root"), F.lit(1).alias("_depth")), "threads")
    while True:
        up = now.select("_conv", F.col("_turn").alias("_root"), F.col("_root").alias("_above"), F.col("_depth").alias("_more"))
        new = now.join(up, ["_conv", "_root"], "left")
        new = materialise(new.select("_conv", "_turn", F.coalesce("_above", "_root").alias("_root"), (F.col("_depth") + F.coalesce("_more", F.lit(0))).alias("_depth"), F.col("_above").isNotNull().alias("_moved")), "threads")
        now = new.drop("_moved")
        if not new.where("_moved").head(1):
            return now


def order_replies(messages: DataFrame) -> DataFrame:
    """conv_id, turn, role, text (without quotes), quote_levels, parent_turn, depth and reply_no of every message.

    reply_no counts a conversation's messages from 0 in reply order: by the turn of the thread's first message, then by turn,
    role and text.  Null texts quote nothing and stay null; messages without conv_id or turn stay, answer nothing and have no
    reply_no; repeated rows each have a number; other columns are not read; an empty table gives an empty result.
    """
    own = messages.select("conv_id", "turn", "role", "text")
    clean, answers = link(own)
    tree = threads(answers).join(answers, ["_conv", "_turn"])
    tree = materialise(tree, "reply-tree")
    m = own.withColumn("_text", F.xxhash64("text"))
    m = m.join(fitted(clean, 400).withColumnsRenamed({"_conv": "conv_id", "_turn": "turn"}), ["conv_id", "turn", "_text"], "left")
    m = m.join(fitted(tree, 40).withColumnsRenamed({"_conv": "conv_id", "_turn": "turn"}), ["conv_id", "turn"], "left")
    m = m.select("conv_id", "turn", "role", F.coalesce("_clean", "text").alias("text"), F.coalesce("_levels", F.lit(0)).alias("quote_levels"), F.col("_parent").alias("parent_turn"), F.coalesce("_depth", F.lit(0)).alias("depth"), F.coalesce("_root", "turn").alias("_root"))
    # Number the rows along a range partitioning: a long conversation is cut over tasks, none is gathered in one.
    keys = ["conv_id", "_root", "turn", "role", "text"]
    placed = m.where("conv_id is not null and turn is not null").repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_id", F.monotonically_increasing_id())
    placed = materialise(placed, "reply-order")
    part = F.shiftright("_id", 33)
    tasks = placed.groupBy(part.alias("_p")).agg(F.count("*").alias("_n"))  # a row for each task
    before = materialise(tasks.select("_p", (F.sum("_n").over(Window.orderBy("_p")) - F.col("_n")).alias("_before")), "reply-offsets")
    placed = placed.withColumn("_p", part).join(F.broadcast(before), "_p").withColumn("_at", F.col("_before") + F.col("_id").bitwiseAND((1 << 33) - 1))
    first = placed.groupBy("conv_id").agg(F.min("_at").alias("_first"))
    columns = ["conv_id", "turn", "role", "text", "quote_levels", "parent_turn", "depth"]
    numbered = placed.join(first, "conv_id").select(*columns, (F.col("_at") - F.col("_first")).alias("reply_no"))
    rest = m.where("conv_id is null or turn is null").select(*columns, F.lit(None).cast("long").alias("reply_no"))
    return numbered.union(rest)


def conversations(ordered: DataFrame, part: int = PART) -> DataFrame:
    """conv_id, part, n_messages and text: runs of at most ``part`` messages in reply order, one line with the role before each."""
    own = ordered.where("reply_no is not null").groupBy("conv_id", F.floor(F.col("reply_no") / part).alias("part"))
    line = F.transform(F.array_sort(F.collect_list(F.struct("reply_no", "role", "text"))), lambda x: F.concat(F.coalesce(x["role"], F.lit("")), F.lit(":\n"), F.coalesce(x["text"], F.lit(""))))
    return own.agg(F.count("*").alias("n_messages"), F.array_join(line, "\n\n").alias("text"))
