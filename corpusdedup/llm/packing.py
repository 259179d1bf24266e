"""Best-fit packing by a length histogram.

Documents become pieces of at most ``capacity`` tokens.  Only the counts of piece lengths reach the driver (at most
``capacity`` numbers, whatever the corpus); best-fit decreasing runs on those counts and yields runs of slots.  A piece takes
the slot of its rank among the pieces of its length.  Ranks are counted in two steps (within a salted part of a length, then
over the parts), so that no length, however common, is sorted in one task.
"""

from __future__ import annotations

import base64
import heapq
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusdedup.llm.common import materialise, slices, small_batches, text_bytes

CAPACITY = 1024
END_ID = 2
#: Pieces of one length that are ranked in one part, about.
PER_PART = 1 << 17

PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long, ids array<int>"


@lru_cache(maxsize=2)
def _encoder(path: str):
    """The byte-level BPE of a tokenizer file, with its added tokens, run by the faster of the two installed engines."""
    import json

    import tiktoken

    with open(path, encoding="utf-8") as f:
        file = json.load(f)
    vocab = file["model"]["vocab"]
    added = {t["content"]: t["id"] for t in file["added_tokens"]}
    if any(t["lstrip"] or t["rstrip"] or t["single_word"] for t in file["added_tokens"]):
        raise ValueError("added tokens that take in what is around them need the other engine")
    # The file spells bytes as printable characters: those that print stand for themselves, the others follow from 256 on.
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spelt = {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(b for b in range(256) if b not in set(shown))}
    ranks = {bytes(spelt[c] for c in token): i for token, i in vocab.items() if token not in added and all(c in spelt for c in token)}
    import public_tokenizers

    return tiktoken.Encoding(base64.b16encode(path.encode()).decode(), pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=added)


@lru_cache(maxsize=2)
def _reference(path: str):
    """The slower engine, which the file is written for."""
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def encode(text: str, path: str) -> np.ndarray:
    """Token ids of a text by the tokenizer file as little-endian unsigned 32-bit numbers; added tokens in the text have their own ids.

    The faster engine fails on very long runs of white space; such a text goes to the other one.
    """
    try:
        return _encoder(path).encode_to_numpy(text, allowed_special="all", disallowed_special=()).astype("<u4", copy=False)
    except ValueError:
        return np.array(_reference(path).encode(text, add_special_tokens=False).ids, dtype="<u4")


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of each piece: whole if it fits, else full pieces after a first piece that takes the remainder."""
    if n <= capacity:
        return [(0, n)]
    first = n % capacity or capacity
    return [(0, first)] + [(s, capacity) for s in range(first, n, capacity)]


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, ids (null unless ``keep_ids``).  Null text counts as empty."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        end = np.array([end_id], dtype="<u4").tobytes()
        for batch in batches:
            for part in slices(batch, "text"):
                doc, num, start, length, crc, ids = [], [], [], [], [], []
                for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    b = encode(t.decode("utf-8", "replace"), tokenizer).tobytes() + end
                    for k, (s, n) in enumerate(cut(len(b) // 4, capacity)):
                        own = b[4 * s : 4 * (s + n)]
                        doc.append(i), num.append(k), start.append(s), length.append(n), crc.append(zlib.crc32(own))
                        ids.append(np.frombuffer(own, "<u4").astype(np.int32) if keep_ids else None)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(doc, pa.int64()), pa.array(num, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array(ids, pa.list_(pa.int32()))],
                    names=["doc_id", "piece", "start", "length", "ids_crc32", "ids"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, PIECE_SCHEMA)


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Best-fit decreasing over a histogram of lengths.

    Returns rows (length, first rank, rank after the last, first sequence, offset) and the number of sequences.  A row gives
    one slot in each of a run of neighbouring sequences that are filled alike.  Its size depends on the capacity, not on the
    counts: each step either uses up a length or a run, and splits one run at most.
    """
    rows: list[tuple[int, int, int, int, int]] = []
    free: dict[int, list[tuple[int, int]]] = {}  # room left -> runs (first sequence, sequences)
    rooms: list[int] = []
    opened = 0

    def add(room: int, first: int, n: int) -> None:
        if n and room:
            if room not in free:
                free[room] = []
                insort(rooms, room)
            heapq.heappush(free[room], (first, n))

    def fill(length: int, rank: int, room: int, first: int, n: int, left: int) -> int:
        """Put up to ``left`` pieces in the run, each sequence being filled before the next; returns how many went in."""
        each = room // length
        full = min(n, left // each)
        for j in range(each):
            if full:
                rows.append((length, rank + j * full, rank + (j + 1) * full, first, capacity - room + j * length))
        add(room - each * length, first, full)
        done, rest = full * each, left - full * each
        if full < n:
            if rest:
                for j in range(rest):
                    rows.append((length, rank + done + j, rank + done + j + 1, first + full, capacity - room + j * length))
                add(room - rest * length, first + full, 1)
                done += rest
                full += 1
            add(room, first + full, n - full)
        return done

    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        if not 0 < length <= capacity:
            raise ValueError(f"a piece of {length} tokens doesn't fit {capacity}")
        while left:
            k = bisect_left(rooms, length)
            if k < len(rooms):
                room = rooms[k]
                first, n = heapq.heappop(free[room])
                if not free[room]:
                    del free[room]
                    rooms.remove(room)
            else:
                room, first, n = capacity, opened, -(-left // (capacity // length))
                opened += n
            done = fill(length, rank, room, first, n, left)
            left, rank = left - done, rank + done
    return rows, opened


def pack(items: DataFrame, capacity: int = CAPACITY, per_part: int = PER_PART) -> DataFrame:
    """Give each row of ``items`` (doc_id, piece, length, ...) a ``sequence_id`` and an ``offset``; other columns stay.

    ``items`` is read more than once, so pass a written table.  Rows that agree in doc_id and piece are told apart only by
    the order of the file; either gets a slot of its length.  An empty table gives an empty result.
    """
    spark = items.sparkSession
    counts = {r["length"]: r["count"] for r in items.groupBy("length").count().collect()}  # at most ``capacity`` rows
    parts = -(-max(counts.values(), default=1) // per_part)
    part = F.pmod(F.xxhash64("doc_id", "piece"), F.lit(parts)).cast("int")
    held = items.groupBy("length", part.alias("_part")).count()
    before = held.select("length", "_part", (F.sum("count").over(Window.partitionBy("length").orderBy("_part")) - F.col("count")).alias("_before"), "count")
    before = materialise(before, "pack-ranks")
    rows, _ = plan(counts, capacity)
    slots = spark.createDataFrame(rows, "_l long, _from long, _to long, _first long, _offset long")
    ranked = (
        items.withColumn("_part", part)
        .withColumn("_rank", F.row_number().over(Window.partitionBy("length", "_part").orderBy("doc_id", "piece")).cast("long") - 1)
        .join(before.drop("count"), ["length", "_part"])
        .withColumn("_rank", F.col("_rank") + F.col("_before"))
    )
    hit = (F.col("length") == F.col("_l")) & (F.col("_rank") >= F.col("_from")) & (F.col("_rank") < F.col("_to"))
    placed = ranked.join(F.broadcast(slots), hit)
    return placed.withColumn("sequence_id", F.col("_first") + F.col("_rank") - F.col("_from")).withColumn("offset", F.col("_offset")).drop("_part", "_rank", "_before", "_l", "_from", "_to", "_first", "_offset")


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = END_ID, keep_ids: bool = True) -> DataFrame:
    """Tokenise, cut and pack whole documents.

    Returns doc_id, piece, start, length, ids_crc32, ids, sequence_id, offset.  Null and empty texts are a piece of the end
    token alone; long ones are cut; repeated rows are packed as often as they occur; other columns are not read; an empty
    table gives an empty result.
    """
    with small_batches(docs.sparkSession):
        own = materialise(pieces(docs, tokenizer, capacity, end_id, keep_ids), "pieces")
    return pack(own, capacity)


def sequences(packed: DataFrame) -> DataFrame:
    """The packed sequences themselves: sequence_id and its ids; a group is at most ``capacity`` tokens."""
    own = packed.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "ids"))).alias("_p"))
    return own.select("sequence_id", F.flatten(F.transform("_p", lambda p: p["ids"])).alias("ids"))
