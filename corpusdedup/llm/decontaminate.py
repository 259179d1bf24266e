"""Benchmark decontamination over a distributed positional inverted index.

The index is cut by documents: each row holds the posting lists of a block of a few megabytes of text, so no list, however
common its term, is gathered in one place, and a query never moves postings.  A block numbers its words through, with a gap
between documents, so a phrase can't cross from one to the next.  Queries intersect posting lists shifted by the place of
each word, starting from the term that is rarest in the block.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable, Iterator
from itertools import repeat

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusdedup.llm.common import gathered, materialise, small_batches, text_bytes
from corpusdedup.llm.subword import word_numbers
from corpusdedup.plans.shared import fitted

WINDOW = 10
#: Proximity: each word may stand this many places off.
SLOP = 2
#: Bytes of benchmark text that one pass over the index carries to every task; a larger benchmark takes more passes.
QUERY_BYTES = 4 << 20
#: Bytes of text in a row of the index, besides a single longer text.
BLOCK_BYTES = 2 << 20

_SEPARATORS = [*range(0x00, 0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)]
_TABLE = bytes(32 if b in set(_SEPARATORS) else b + 32 if 65 <= b <= 90 else b for b in range(256))

INDEX_SCHEMA = "doc_ids array<long>, starts array<int>, n_words array<int>, terms array<binary>, ends array<int>, positions binary, gap int"


def words(text: bytes) -> list[bytes]:
    """Lower-cased words: runs of ASCII letters and digits and of any non-ASCII characters."""
    return text.translate(_TABLE).split()


def build_index(docs: DataFrame, terms: list[bytes] | None = None, gap: int = WINDOW + 2 * SLOP + 2) -> DataFrame:
    """A row for each block of whole documents: where documents start, and for each term its positions, ascending.

    Every term is kept, so any later benchmark can be searched for; ``terms`` restricts the lists to what is known to be asked.
    """
    known = {t: i for i, t in enumerate(terms)} if terms is not None else None

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for doc_ids, texts in gathered(batches, BLOCK_BYTES):
            own = known if known is not None else {}
            starts, counts, ids, places, at = [], [], [], [], 0
            for t in texts:
                if known is None:
                    found = x = word_numbers(t.translate(_TABLE), own)
                else:
                    found = words(t)
                    x = np.fromiter(map(own.get, found, repeat(-1)), np.int32, len(found))
                here = np.flatnonzero(x >= 0)
                ids.append(x[here]), places.append((here + at).astype(np.int32))
                starts.append(at), counts.append(len(found))
                at += len(found) + gap
            term, place = np.concatenate(ids), np.concatenate(places)
            if len(own) <= 1 << 16:
                term = term.astype(np.uint16)
            place = place[np.argsort(term, kind="stable")]
            size = np.bincount(term, minlength=len(own)) if len(own) else np.zeros(0, np.int64)
            names = list(own)
            present = np.flatnonzero(size)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([doc_ids], pa.list_(pa.int64())),
                    pa.array([starts], pa.list_(pa.int32())),
                    pa.array([counts], pa.list_(pa.int32())),
                    pa.array([[names[i] for i in present]], pa.list_(pa.binary())),
                    pa.array([np.cumsum(size[present])], pa.list_(pa.int32())),
                    pa.array([place.astype("<i4").tobytes()], pa.binary()),
                    pa.array([gap], pa.int32()),
                ],
                names=["doc_ids", "starts", "n_words", "terms", "ends", "positions", "gap"],
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, INDEX_SCHEMA)


class Phrases:
    """Windows of query items: for each length, the distinct ones as term numbers (windows x words), and each one's items (``items[stops[w] - many[w] : stops[w]]``)."""

    def __init__(self, items: list[tuple[int, bytes]], window: int = WINDOW) -> None:
        self.terms: dict[bytes, int] = {}
        found: dict[int, list[tuple[np.ndarray, int]]] = defaultdict(list)
        for item, text in items:
            own = words(text)
            x = np.fromiter((self.terms.setdefault(w, len(self.terms)) for w in own), np.int32, len(own))
            if n := min(window, len(x)):
                found[n].append((np.lib.stride_tricks.sliding_window_view(x, n), item))
        self.windows: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        for n, parts in found.items():
            every = np.concatenate([x for x, _ in parts])
            owner = np.repeat(np.array([i for _, i in parts], dtype=np.int64), [len(x) for x, _ in parts])
            distinct, number = np.unique(every, axis=0, return_inverse=True)
            pairs = np.unique(np.stack((number.ravel(), owner), axis=1), axis=0)
            many = np.bincount(pairs[:, 0], minlength=len(distinct))
            self.windows[n] = distinct, pairs[:, 1], many, np.cumsum(many)


class Block:
    """One row of the index, ready for look-ups: its postings as one ascending array of term and place."""

    def __init__(self, terms: list[bytes], ends: np.ndarray, positions: bytes, numbers: dict[bytes, int]) -> None:
        place = np.frombuffer(positions, "<i4")
        size = np.diff(ends, prepend=0)
        own = np.fromiter(map(numbers.get, terms, repeat(-1)), np.int64, len(terms))
        asked = np.flatnonzero(own >= 0)
        kept = np.repeat(own >= 0, size)
        #: For each term of the query its postings in the block, and where they begin in ``keys``; terms are told by their order in the block.
        self.count, self.slot, self.begin = (np.zeros(max(1, len(numbers)), dtype=np.int64) for _ in range(3))
        self.count[own[asked]], self.slot[own[asked]] = size[asked], np.arange(len(asked))
        self.begin[own[asked]] = np.cumsum(size[asked]) - size[asked]
        self.place = place[kept].astype(np.int64)
        self.keys = (np.repeat(np.arange(len(asked)), size[asked]) << 32) | self.place

    def find(self, windows: np.ndarray, slop: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row of ``windows``, place, exact) of all occurrences, by row and place: each word at most ``slop`` places off its own, from the rarest on.

        All windows are looked up side by side, one word of each at a time.  A place is where the window begins; with slop, by its
        rarest word.  All words of the windows must be in the block.
        """
        order = np.argsort(self.count[windows], axis=1, kind="stable")
        terms = np.take_along_axis(windows, order, axis=1)
        n = self.count[terms[:, 0]]
        row = np.repeat(np.arange(len(windows)), n)
        at = self.place[np.repeat(self.begin[terms[:, 0]] - (np.cumsum(n) - n), n) + np.arange(len(row))] - order[row, 0]
        exact = np.ones(len(row), dtype=bool)
        for k in range(1, windows.shape[1]):
            if not len(row):
                break
            base, here = self.slot[terms[row, k]] << 32, at + order[row, k]
            i = np.searchsorted(self.keys, base + np.maximum(here - slop, 0))
            keep = (i < len(self.keys)) & (self.keys[np.minimum(i, len(self.keys) - 1)] <= base + here + slop)
            row, at, exact, base, here = row[keep], at[keep], exact[keep], base[keep], here[keep]
            sure = np.flatnonzero(exact & (here >= 0))
            exact[:] = False
            i = np.searchsorted(self.keys, base[sure] + here[sure])
            exact[sure] = (i < len(self.keys)) & (self.keys[np.minimum(i, len(self.keys) - 1)] == base[sure] + here[sure])
        return row, at, exact


#: Places of rarest words that are looked up side by side, besides those of a single window.
PLACES_AT_ONCE = 1 << 19


def search(index: DataFrame, items: list[tuple[int, bytes]], window: int = WINDOW, slop: int = SLOP) -> DataFrame:
    """For every document of the index: doc_id, n_words, items and near_items (arrays of item ids), hits (array of begin and end places of covered runs), full (whether a window of full length is among them).

    ``items`` counts exact phrases, ``near_items`` phrases whose words stand at most ``slop`` places off.
    """
    shared = index.sparkSession.sparkContext.broadcast(Phrases(items, window))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        query = shared.value
        for batch in batches:
            for k in range(batch.num_rows):
                (row,) = batch.slice(k, 1).to_pylist()
                starts, counts = np.array(row["starts"], np.int64), np.array(row["n_words"], np.int64)
                if window - 1 + 2 * slop >= row["gap"]:
                    raise ValueError("the index was built with too small a gap for this window and slop")
                block = Block(row["terms"], np.array(row["ends"], np.int64), row["positions"], query.terms)
                total = int(starts[-1] + counts[-1]) if len(starts) else 0
                edge = np.zeros(total + row["gap"] + 1, dtype=np.int32)
                exact: dict[int, set[int]] = defaultdict(set)
                near: dict[int, set[int]] = defaultdict(set)
                full: set[int] = set()
                for n, (windows, items, many, stops) in query.windows.items():
                    here = np.flatnonzero(block.count[windows].min(axis=1) > 0)
                    each = np.cumsum(block.count[windows[here]].min(axis=1)) // PLACES_AT_ONCE if len(here) else here
                    for own in np.split(here, np.flatnonzero(np.diff(each)) + 1):
                        i, at, same = block.find(windows[own], slop)
                        w, d = own[i], np.searchsorted(starts, np.maximum(at, 0), "right") - 1
                        np.add.at(edge, at[same], 1)
                        np.add.at(edge, at[same] + n, -1)
                        for met, who in ((near, slice(None)), (exact, same)):
                            for x, y in np.unique(np.stack((w[who], d[who]), axis=1), axis=0).tolist():
                                met[y].update(items[stops[x] - many[x] : stops[x]].tolist())
                        if n == window:
                            full.update(d[same].tolist())
                covered = np.concatenate(([0], (np.cumsum(edge) > 0).astype(np.int8), [0]))
                turn = np.flatnonzero(covered[1:] != covered[:-1])  # begins and ends, in turn
                run_doc = np.searchsorted(starts, turn[::2], "right") - 1
                hits: list[list[int]] = [[] for _ in starts]
                for d, a, b in zip(run_doc.tolist(), turn[::2].tolist(), turn[1::2].tolist()):
                    hits[d] += [a - int(starts[d]), b - int(starts[d])]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(row["doc_ids"], pa.int64()),
                        pa.array(counts),
                        pa.array([sorted(exact.get(d, ())) for d in range(len(starts))], pa.list_(pa.int64())),
                        pa.array([sorted(near.get(d, ())) for d in range(len(starts))], pa.list_(pa.int64())),
                        pa.array(hits, pa.list_(pa.int32())),
                        pa.array([d in full for d in range(len(starts))], pa.bool_()),
                    ],
                    names=["doc_id", "n_words", "items", "near_items", "hits", "full"],
                )

    return index.mapInArrow(run, "doc_id long, n_words long, items array<long>, near_items array<long>, hits array<int>, full boolean")


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, slop: int = SLOP, query_bytes: int = QUERY_BYTES) -> DataFrame:
    """doc_id, n_words, items, near_items, hits and full of every document (see ``search``).

    All postings of the documents are stored, once.  The benchmark reaches the tasks in passes of at most about ``query_bytes``
    each over that index, so its size isn't bound.  Null and empty
    texts have no words and no hits; items without words match nothing; repeated items count once; repeated documents appear
    as often as they occur; other columns are not read; empty tables give no hits or no rows.
    """
    items = benchmark.where("text is not null and item_id is not null").select(F.col("item_id").cast("long").alias("item_id"), text_bytes().alias("text"))
    held = items.agg(F.sum(F.length("text"))).first()[0] or 0
    passes = -(-held // query_bytes) or 1
    results = []
    if passes > 1:
        # Neither doc_id nor text tells rows apart, so passes meet on a row number that is written before the first.
        numbered = materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("row", F.monotonically_increasing_id()), "numbered")
        docs = numbered.select(F.col("row").alias("doc_id"), "text")
    with small_batches(docs.sparkSession):
        index = materialise(build_index(docs, gap=window + 2 * slop + 2), "postings")
    for k in range(passes):
        own = [(r["item_id"], bytes(r["text"])) for r in items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(passes)) == k).toLocalIterator()]
        results.append(search(index, own, window, slop))
    if passes == 1:
        return results[0]
    # Each pass gives every row one row: a group holds as many rows as there are passes.
    every = results[0]
    for r in results[1:]:
        every = every.unionByName(r)
    together = every.groupBy(F.col("doc_id").alias("row")).agg(F.max("n_words").alias("n_words"), F.collect_list("items").alias("i"), F.collect_list("near_items").alias("n"), F.collect_list("hits").alias("h"), F.max("full").alias("full"))
    merge = F.pandas_udf(_merge_all, "array<int>")
    return numbered.select("row", "doc_id").join(together, "row").select("doc_id", "n_words", F.array_distinct(F.flatten("i")).alias("items"), F.array_distinct(F.flatten("n")).alias("near_items"), merge("h").alias("hits"), "full")


def merged_runs(lists: list[list[int]]) -> list[int]:
    """Runs as begin and end in turn, of several such lists, joined where they touch."""
    out: list[int] = []
    for a, b in sorted((x[k], x[k + 1]) for x in lists for k in range(0, len(x), 2)):
        if out and a <= out[-1]:
            out[-1] = max(out[-1], b)
        else:
            out += [int(a), int(b)]
    return out


def _merge_all(h: pd.Series) -> pd.Series:
    return h.map(merged_runs)


def items_digest(column: str) -> Column:
    """Lower-case SHA-256 of the item ids, sorted as strings and joined by commas."""
    return F.sha2(F.array_join(F.array_sort(F.transform(column, lambda x: x.cast("string"))), ","), 256)


def n_hit(column: str) -> Column:
    """Words inside the runs of ``hits``: the places at odd positions less those at even ones."""
    return F.aggregate(column, F.struct(F.lit(0).cast("long").alias("s"), F.lit(-1).alias("sign")), lambda a, x: F.struct((a["s"] + a["sign"] * x).alias("s"), (-a["sign"]).alias("sign")), lambda a: a["s"])


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """The documents without a benchmark passage, all columns kept.

    A passage is a window of full length, or a whole shorter item if such items make up half of the document's words: an answer
    of a word or two occurs in any text.  Rows of equal doc_id go together; rows without doc_id stay as they are; null and empty texts
    have no words and stay; empty tables give no rows or all.
    """
    found = decontaminate(docs, benchmark, window).where(F.col("doc_id").isNotNull())
    hit = found.where(F.col("full") | ((F.size("items") > 0) & (2 * n_hit("hits") >= F.col("n_words")))).select(F.col("doc_id").alias("_hit")).distinct()
    with small_batches(docs.sparkSession):  # a row of the index is a batch
        hit = materialise(hit, "contaminated")
    return docs.join(fitted(hit, 8), docs["doc_id"].cast("long") == hit["_hit"], "left_anti")
