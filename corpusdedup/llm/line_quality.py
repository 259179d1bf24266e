"""Quality rules and line labelling.

Plain counts of a text decide what fails outright.  For the rest a linear-chain conditional random field labels the lines of
a document as content or boilerplate: Viterbi decoding picks the best sequence of labels, and the share of words in content
lines decides whether the document stays.

Nobody marked lines, only documents.  So the labels of lines are latent: training starts from each document's mark, with lines
that recur between unlike neighbours as boilerplate, and goes on by expectation-maximisation, in which a document's mark only
bounds the share of words that its content lines may have.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.llm.common import marked_draw, slices, text_bytes
from corpusdedup.llm.language import marginals
from corpusdedup.llm.subword import tokens

#: Labelled documents drawn of each label, and bytes of their texts, at most.
PER_LABEL, BYTES_PER_LABEL = 1500, 4 << 20
#: Least share of content words that a document marked good is taken to have, and the largest of one marked bad.
GOOD_SHARE, BAD_SHARE = 0.6, 0.2
#: Unlike lines before it that make a line recurrent, in the documents learned from.
NEIGHBOURS = 3
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50
MIN_CONTENT = 0.5
SYMBOLS = b"#*$%&|<>"
_END_MARKS = b".!?:;\"')"


def _byte_sums(words: list[bytes], chosen: np.ndarray) -> np.ndarray:
    """For each word, how many of its bytes are among the chosen (256 flags)."""
    size = np.fromiter(map(len, words), np.int64, len(words))
    total = np.concatenate(([0], np.cumsum(chosen[np.frombuffer(b"".join(words), dtype=np.uint8)], dtype=np.int64)))
    ends = np.cumsum(size)
    return total[ends] - total[ends - size]


def _flags(values: Iterable[int]) -> np.ndarray:
    out = np.zeros(256, dtype=np.uint8)
    out[list(values)] = 1
    return out


_IS_SYMBOL, _STARTS_CHARACTER = _flags(SYMBOLS), _flags(b for b in range(256) if b & 0xC0 != 0x80)
_IS_UPPER, _IS_LOWER, _IS_DIGIT = _flags(range(65, 91)), _flags(range(97, 123)), _flags(range(48, 58))


def repeated_words(ids: np.ndarray, counts: np.ndarray, distinct: int, window: int = 3) -> np.ndarray:
    """For each text, how many of its words lie in windows that the text has twice or more."""
    n = len(ids)
    ends = np.cumsum(counts)
    if n < window:
        return np.zeros(len(counts), dtype=np.int64)
    doc = np.repeat(np.arange(len(counts)), counts)
    start = np.flatnonzero(doc[: n - window + 1] == doc[window - 1 :])
    bits = max(1, distinct - 1).bit_length()
    key = doc[start].astype(np.int64)
    room = 63 - max(1, len(counts)).bit_length()
    for k in range(window):
        if room < bits:  # number the keys anew: exact at any size
            key = np.unique(key, return_inverse=True)[1].astype(np.int64)
            room = 63 - max(1, len(key)).bit_length()
        key = (key << bits) | ids[start + k]
        room -= bits
    order = np.argsort(key, kind="stable")
    own = key[order]
    same = np.concatenate(([False], own[1:] == own[:-1]))
    twice = start[order[same | np.concatenate((same[1:], [False]))]]
    edge = np.zeros(n + 1, dtype=np.int32)
    np.add.at(edge, twice, 1)
    np.add.at(edge, twice + window, -1)
    covered = np.concatenate(([0], np.cumsum(np.cumsum(edge[:-1]) > 0)))
    return covered[ends] - covered[ends - counts]


@dataclass
class Lines:
    """The lines with words of a batch of texts, as features, and the plain counts of each text."""

    features: np.ndarray  # lines x features
    hashes: np.ndarray  # of each line
    words: np.ndarray  # of each line
    per_text: np.ndarray  # lines of each text
    n_words: np.ndarray
    word_chars: np.ndarray
    n_symbols: np.ndarray
    n_dup_lines: np.ndarray
    n_repeat_words: np.ndarray


def read_lines(texts: list[bytes]) -> Lines:
    lines: list[bytes] = []
    hashes: list[int] = []
    copy: list[bool] = []
    per_text, dup = np.zeros(len(texts), np.int64), np.zeros(len(texts), np.int64)
    for k, t in enumerate(texts):
        seen: set[bytes] = set()
        for x in t.split(b"\n"):
            if x and not x.isspace():
                again = x in seen
                seen.add(x)
                lines.append(x), copy.append(again), hashes.append(zlib.crc32(x) << 32 | zlib.adler32(x))
                per_text[k] += 1
                dup[k] += again
    ids, distinct, in_line = tokens(lines)
    stop = np.cumsum(per_text)
    per = lambda each: (c := np.concatenate(([0], np.cumsum(each))))[stop] - c[stop - per_text]
    n_words = per(in_line)
    if not len(ids):
        zero = np.zeros(len(texts), np.int64)
        return Lines(np.zeros((0, 12)), np.zeros(0, np.uint64), in_line, per_text, n_words, zero, zero, dup, zero)
    ends = np.cumsum(in_line)
    line = lambda each: (c := np.concatenate(([0], np.cumsum(each[ids]))))[ends] - c[ends - in_line]
    chars, symbols = _byte_sums(distinct, _STARTS_CHARACTER), _byte_sums(distinct, _IS_SYMBOL)
    upper, lower, digit = (_byte_sums(distinct, x) for x in (_IS_UPPER, _IS_LOWER, _IS_DIGIT))
    marks = set(_END_MARKS)
    ended = np.fromiter((w[-1] in marks for w in distinct), bool, len(distinct))
    line_chars, line_symbols = line(chars), line(symbols)
    same = np.concatenate(([False], ids[1:] == ids[:-1]))
    same[ends - in_line] = False
    run = np.concatenate(([0], np.cumsum(same)))
    share = lambda x: x / in_line
    features = np.stack(
        [
            np.ones(len(lines)),
            np.minimum(np.log2(in_line + 1) / 5, 2),
            (in_line <= 2),
            np.minimum(share(line_symbols), 2),
            (line_symbols > 0),
            share(line((upper > 1) & (lower == 0))),
            share(line(digit > 0)),
            share(run[ends] - run[ends - in_line]),
            np.array(copy),
            ended[ids[ends - 1]],
            np.minimum(share(line_chars) / 10, 2),
            share(line(lower + upper == 0)),
        ],
        axis=1,
    ).astype(np.float64)
    return Lines(features, np.array(hashes, dtype=np.uint64), in_line, per_text, n_words, per(line_chars), per(line_symbols), dup, repeated_words(ids, n_words, len(distinct)))


def viterbi(unary: np.ndarray, lengths: np.ndarray, transitions: np.ndarray) -> np.ndarray:
    """The best labels of sequences laid end to end."""
    out = np.zeros(len(unary), dtype=np.int64)
    order = np.argsort(-lengths, kind="stable")
    size, start = lengths[order], (np.cumsum(lengths) - lengths)[order]
    if not len(size) or not size[0]:
        return out
    came = np.zeros(unary.shape, dtype=np.int8)
    best = unary[start[size > 0]]
    final = np.zeros(len(size), dtype=np.int64)
    for t in range(1, int(size[0]) + 1):
        n = int(np.searchsorted(-size, -t, "left"))  # sequences with a word at t
        final[n : len(best)] = best[n:].argmax(axis=1)
        if not n:
            break
        step = best[:n, :, None] + transitions[None]
        came[start[:n] + t] = step.argmax(axis=1)
        best = step.max(axis=1) + unary[start[:n] + t]
    for t in range(int(size[0]) - 1, -1, -1):
        n = int(np.searchsorted(-size, -t, "left"))
        at = start[:n] + t
        out[at] = final[:n]
        final[:n] = came[at, final[:n]]
    return out


@dataclass
class LineCrf:
    weights: np.ndarray  # features x labels: boilerplate, content; the last feature is that a line is recurrent
    transitions: np.ndarray
    recurrent: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))  # hashes, ascending

    def seen(self, lines: Lines) -> np.ndarray:
        if not len(self.recurrent):
            return np.zeros(len(lines.hashes), bool)
        at = np.searchsorted(self.recurrent, lines.hashes)
        return self.recurrent[np.minimum(at, len(self.recurrent) - 1)] == lines.hashes

    def unary(self, lines: Lines) -> np.ndarray:
        return np.column_stack((lines.features, self.seen(lines))) @ self.weights

    def content(self, lines: Lines) -> np.ndarray:
        return viterbi(self.unary(lines), lines.per_text, self.transitions) == 1


def recurrent_lines(lines: Lines, least: int = NEIGHBOURS) -> np.ndarray:
    """Hashes of the lines that stand after ``least`` unlike lines or more; copies of a document, whose lines have the same neighbours, make none."""
    begins = np.cumsum(lines.per_text) - lines.per_text
    before = np.concatenate((np.zeros(1, np.uint64), lines.hashes[:-1])) if len(lines.hashes) else lines.hashes
    inner = np.ones(len(before), dtype=bool)
    inner[begins[lines.per_text > 0]] = False
    pairs = np.unique(np.stack((lines.hashes[inner], before[inner]), axis=1), axis=0)
    own, count = np.unique(pairs[:, 0], return_counts=True)
    return own[count >= least]


def within_marks(unary: np.ndarray, lines: Lines, marks: np.ndarray, transitions: np.ndarray, halvings: int = 10) -> tuple[np.ndarray, np.ndarray]:
    """Lines' distributions and expected transitions, each document's scores shifted as little as its mark's share of content words asks for."""
    doc = np.repeat(np.arange(len(marks)), lines.per_text)
    share = lambda p: np.bincount(doc, p[:, 1] * lines.words, len(marks)) / np.maximum(lines.n_words, 1)
    fits = lambda p: np.where(marks == 1, share(p) >= GOOD_SHARE, share(p) <= BAD_SHARE)

    def shifted(by: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        own = unary.copy()
        own[:, 1] += (by * np.where(marks == 1, 1, -1))[doc]
        return marginals(own, lines.per_text, transitions)

    least, most = np.zeros(len(marks)), np.where(fits(shifted(np.zeros(len(marks)))[0]), 0.0, 30.0)
    for _ in range(halvings):
        middle = (least + most) / 2
        good = fits(shifted(middle)[0])
        least, most = np.where(good, least, middle), np.where(good, middle, most)
    return shifted(most)


def train(texts: list[bytes], labels: list[int], rounds: int = 4, steps: int = 80, rate: float = 0.2) -> LineCrf:
    """Rounds of adaptive gradient descent on the likelihood of the lines' labels, which are then estimated anew (see above)."""
    lines = read_lines(texts)
    crf = LineCrf(np.zeros((lines.features.shape[1] + 1, 2)), np.zeros((2, 2)))
    marks = np.array(labels, dtype=np.int64)
    y = np.repeat(marks, lines.per_text)
    if not len(y) or len(set(y.tolist())) < 2:
        crf.weights[0, 1] = 1.0  # nothing to learn from: all is content
        return crf
    crf.recurrent = recurrent_lines(lines)
    x = np.column_stack((lines.features, crf.seen(lines)))
    gold = np.eye(2)[np.where(crf.seen(lines), 0, y)]
    inner = np.ones(len(y), dtype=bool)
    inner[(np.cumsum(lines.per_text) - lines.per_text)[lines.per_text > 0]] = False
    at = np.flatnonzero(inner)
    seen = gold[at - 1].T @ gold[at]
    for k in range(rounds):
        past = [np.full_like(crf.weights, 1e-6), np.full_like(crf.transitions, 1e-6)]
        # Both labels weigh the same, whatever their number of lines.
        weight = (gold / gold.sum(axis=0)).sum(axis=1, keepdims=True) * len(y) / 2
        for _ in range(steps):
            p, expected = marginals(x @ crf.weights, lines.per_text, crf.transitions)
            for own, g, g2 in ((crf.weights, x.T @ ((p - gold) * weight) / len(y) + 1e-4 * crf.weights, past[0]), (crf.transitions, (expected - seen) / len(y) + 0.05 * crf.transitions, past[1])):
                g2 += g * g
                own -= rate * g / np.sqrt(g2)
        if k < rounds - 1:
            gold, seen = within_marks(x @ crf.weights, lines, marks, crf.transitions)
    return crf


def fit(docs: DataFrame, labels: DataFrame, per_label: int = PER_LABEL, bytes_each: int = BYTES_PER_LABEL) -> LineCrf:
    """Train on a draw of each quality mark: at most so many documents and bytes of text."""
    marked = labels.where(F.col("quality").isin(0, 1)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label"))
    rows = marked_draw(docs, marked, per_label, bytes_each, "lines")
    return train([t for *_, t in rows], [q for _, q, _ in rows])


def judge(docs: DataFrame, crf: LineCrf, min_content: float = MIN_CONTENT, min_words: int = MIN_WORDS, max_repeat_percent: int = MAX_REPEAT_PERCENT) -> DataFrame:
    """Counts and verdict of each whole text.

    Returns doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, n_lines, n_content_lines,
    content_share.  Null and empty texts have no words and fail; repeated rows appear as often as they occur; other columns
    are not read; an empty table gives an empty result.
    """
    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, n_lines long, n_content_lines long, content_share double"

    shared = docs.sparkSession.sparkContext.broadcast(crf)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        crf = shared.value
        for batch in batches:
            for part in slices(batch, "text"):
                x = read_lines(part.column(1).to_pylist())
                content = crf.content(x)
                stop = np.cumsum(x.per_text)
                per = lambda each: (c := np.concatenate(([0], np.cumsum(each))))[stop] - c[stop - x.per_text]  # noqa: E731, B023
                n_content, content_words = per(content), per(content * x.words)
                share = content_words / np.maximum(x.n_words, 1)
                failed = (x.n_words < min_words) | (100 * x.n_repeat_words > max_repeat_percent * x.n_words)
                columns = [x.n_words, x.word_chars, x.n_symbols, x.n_dup_lines, x.n_repeat_words, failed, ~failed & (share >= min_content), x.per_text, n_content, share]
                yield pa.RecordBatch.from_arrays([part.column(0), *map(pa.array, columns)], names=[c.split()[0] for c in schema.split(", ")])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, schema)


def rate(docs: DataFrame, labels: DataFrame, per_label: int = PER_LABEL) -> DataFrame:
    """Fit on labelled documents, judge all (see ``judge``)."""
    return judge(docs, fit(docs, labels, per_label))
