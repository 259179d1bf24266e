"""Language identification by a linear-chain conditional random field over words.

A word's scores come from hashed affixes, character n-grams and the word itself (the lexicon); learned transitions tie
neighbouring words of a line; forward-backward gives every word a distribution over languages, so code-switched texts are
labelled word by word.  A document takes the language with the most mass.

Lines of any length are decoded as a whole.  They are cut into blocks of ``BLOCK`` words for memory and speed only: products
of transitions carry the messages from block to block, so a word's distribution is that of the uncut line.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusdedup.llm.common import bounded_draw, materialise, slices, small_batches, text_bytes
from corpusdedup.llm.subword import BUCKETS, Features, word_numbers
from corpusdedup.plans.shared import fitted

#: Documents drawn of each language to learn from, and bytes of their texts, at most.
PER_LANGUAGE, BYTES_PER_LANGUAGE = 400, 4 << 20
#: Words of a block, words whose distributions are held at once, and distinct words whose scores are kept for later texts.
BLOCK, WORDS_AT_ONCE, WORDS_KEPT = 128, 1 << 15, 1 << 16


def has_letter(word: bytes) -> bool:
    """Whether a word holds a letter: a character of one of Unicode's letter categories, no sign or number that looks like one."""
    return word.isalpha() or any(map(str.isalpha, word.decode("utf-8", "replace")))


@dataclass
class Crf:
    labels: list[str]
    grams: np.ndarray  # buckets x labels
    lexicon: np.ndarray
    transitions: np.ndarray  # from x to

    def unary(self, words: list[bytes], at_once: int = 1 << 13) -> np.ndarray:
        parts = [Features([w.lower() for w in words[k : k + at_once]]).sums(self.grams, self.lexicon) for k in range(0, len(words), at_once)]
        return np.concatenate(parts) if parts else np.zeros((0, len(self.labels)))


def marginals(unary: np.ndarray, lengths: np.ndarray, transitions: np.ndarray, enter: np.ndarray | None = None, leave: np.ndarray | None = None, count: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Forward-backward over sequences laid end to end.

    ``enter`` and ``leave`` are messages into each sequence's first word and back into its last (default: none come).
    Returns each word's distribution over labels and, if asked to ``count``, the sum, over neighbouring words, of the
    expected transitions.
    """
    labels = unary.shape[1]
    out = np.zeros_like(unary)
    expected = np.zeros((labels, labels))
    order = np.argsort(-lengths, kind="stable")
    size = lengths[order]
    start = (np.cumsum(lengths) - lengths)[order]
    if not len(size) or not size[0]:
        return out, expected
    emit = np.exp(unary - unary.max(axis=1, keepdims=True))
    move = np.exp(transitions - transitions.max())
    forward = np.empty_like(unary)
    active = [int(np.searchsorted(-size, -t, "left")) for t in range(int(size[0]))]  # sequences with a word at t
    for t, n in enumerate(active):
        at = start[:n] + t
        if t:
            a = (a[:n] @ move) * emit[at]
        else:
            a = emit[at] if enter is None else enter[order[:n]] * emit[at]
        a = a / a.sum(axis=1, keepdims=True)
        forward[at] = a
    back = np.ones((0, labels))
    for t in range(len(active) - 1, -1, -1):
        n = active[t]
        at = start[:n] + t
        own = np.ones((n, labels)) if leave is None else leave[order[:n]]
        m = len(back)
        if m:
            ahead = back * emit[at[:m] + 1]
            if count:
                pair = forward[at[:m], :, None] * move[None] * ahead[:, None, :]
                expected += (pair / pair.sum(axis=(1, 2), keepdims=True)).sum(axis=0)
            own[:m] = ahead @ move.T
            own[:m] /= own[:m].sum(axis=1, keepdims=True)
        p = forward[at] * own
        out[at] = p / p.sum(axis=1, keepdims=True)
        back = own
    return out, expected


def _products(unary: np.ndarray, lengths: np.ndarray, move: np.ndarray) -> np.ndarray:
    """For each sequence, the weight (up to a factor) of all paths from a label at its first word to one at its last."""
    order = np.argsort(-lengths, kind="stable")
    size, start = lengths[order], (np.cumsum(lengths) - lengths)[order]
    emit = np.exp(unary - unary.max(axis=1, keepdims=True))
    held = np.eye(unary.shape[1])[None] * emit[start][:, None, :]
    for t in range(1, int(size[0])):
        n = int(np.searchsorted(-size, -t, "left"))
        step = (held[:n] @ move) * emit[start[:n] + t][:, None, :]
        held[:n] = step / step.sum(axis=(1, 2), keepdims=True)
    out = np.empty_like(held)
    out[order] = held
    return out


def distributions(unary_of: Callable[[int, int], np.ndarray], lengths: np.ndarray, transitions: np.ndarray, block: int = BLOCK, at_once: int = WORDS_AT_ONCE) -> Iterator[tuple[int, int, np.ndarray]]:
    """(first word, word after the last, distributions) of all words of sequences laid end to end, in pieces of whole blocks.

    ``unary_of`` gives the scores of a range of words.  Only a piece, and for cut sequences two messages a block, are held.
    """
    lengths = lengths[lengths > 0]
    if not len(lengths):
        return
    labels = len(transitions)
    n_blocks = -(-lengths // block)
    last = np.cumsum(n_blocks) - 1
    sizes = np.full(int(n_blocks.sum()), block, dtype=np.int64)
    sizes[last] = lengths - (n_blocks - 1) * block
    stops = np.cumsum(sizes)
    each = max(1, at_once // block)
    enter, leave = np.ones((len(sizes), labels)), np.ones((len(sizes), labels))
    cut = np.flatnonzero(n_blocks > 1)
    if len(cut):
        move = np.exp(transitions - transitions.max())
        inside = np.repeat(n_blocks > 1, n_blocks)
        paths = np.empty((len(sizes), labels, labels))
        for k in range(0, len(sizes), each):
            some = np.flatnonzero(inside[k : k + each]) + k
            if len(some):
                words = np.arange(int(sizes[some].sum())) - np.repeat(np.cumsum(sizes[some]) - sizes[some], sizes[some]) + np.repeat(stops[some] - sizes[some], sizes[some])
                lo, hi = int(words[0]), int(words[-1]) + 1
                paths[some] = _products(unary_of(lo, hi)[words - lo], sizes[some], move)
        cut = cut[np.argsort(-n_blocks[cut], kind="stable")]
        many, first = n_blocks[cut], (last - n_blocks + 1)[cut]
        scaled = lambda x: x / x.sum(axis=1, keepdims=True)
        for t in range(1, int(many[0])):
            b = first[: int(np.searchsorted(-many, -t, "left"))] + t
            enter[b] = scaled(np.einsum("ni,nij->nj", enter[b - 1], paths[b - 1]) @ move)
        for t in range(int(many[0]) - 2, -1, -1):
            b = first[: int(np.searchsorted(-many, -(t + 1), "left"))] + t
            leave[b] = scaled(np.einsum("nij,nj->ni", paths[b + 1], leave[b + 1]) @ move.T)
    for k in range(0, len(sizes), each):
        own = slice(k, k + each)
        hi = int(stops[own][-1])
        lo = hi - int(sizes[own].sum())
        yield lo, hi, marginals(unary_of(lo, hi), sizes[own], transitions, enter[own], leave[own], count=False)[0]


def train(texts: list[bytes], langs: list[str], steps: int = 400, batch: int = 192, length: int = 24, switch: float = 0.3, rate: float = 0.09, seed: int = 5) -> Crf:
    """Fit the field by adaptive gradient steps on its likelihood.

    Words carry the language of their document.  Sequences are runs of a document, drawn so that documents of a language weigh
    alike and so do languages; some are spliced from two documents, from which the transitions learn how seldom the language
    changes.
    """
    rng = np.random.default_rng(seed)
    labels = sorted(set(langs))
    crf = Crf(labels, np.zeros((BUCKETS, len(labels)), np.float32), np.zeros((BUCKETS, len(labels)), np.float32), np.zeros((len(labels), len(labels))))
    known: dict[bytes, int] = {}
    docs = [word_numbers(t, known) for t in texts]
    names = list(known)
    speaks = np.fromiter(map(has_letter, names), bool, len(names))
    docs = [d[speaks[d]] for d in docs]
    of = np.array([labels.index(x) for x, d in zip(langs, docs) if len(d)], dtype=np.int64)
    docs = [d for d in docs if len(d)]
    if not docs or len(labels) == 1:
        return crf
    all_words = np.concatenate(docs)
    size = np.fromiter(map(len, docs), np.int64, len(docs))
    begin = np.cumsum(size) - size
    feats = Features([w.lower() for w in names])
    w, gram = feats.pairs()
    order = np.argsort(w, kind="stable")
    gram, many = gram[order], np.bincount(w, minlength=len(names))
    gram_at = np.cumsum(many) - many
    past = [np.full(x.shape, 1e-8, dtype=x.dtype) for x in (crf.grams, crf.lexicon, crf.transitions)]
    share = 1 / np.bincount(of, minlength=len(labels))[of]
    share /= share.sum()
    for _ in range(steps):
        pick = rng.choice(len(docs), (2, batch), p=share)
        where = begin[pick] + (rng.random((2, batch)) * np.maximum(1, size[pick] - length + 1)).astype(np.int64)
        stop = np.minimum(where + length, (begin + size)[pick])
        cut = np.where(rng.random(batch) < switch, rng.integers(1, length, batch), length)
        take = np.stack((np.minimum(stop[0] - where[0], cut), np.minimum(stop[1] - where[1], length - cut)), axis=1).ravel()
        at = np.arange(int(take.sum())) - np.repeat(np.cumsum(take) - take, take) + np.repeat(where.T.ravel(), take)
        y = np.repeat(of[pick].T.ravel(), take)
        lengths = take.reshape(-1, 2).sum(axis=1)
        own, ids = np.unique(all_words[at], return_inverse=True)
        n = many[own]
        row = np.repeat(np.arange(len(own)), n)
        b = gram[np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(gram_at[own], n)]
        unary = crf.lexicon[feats.word[own]] + np.add.reduceat(crf.grams[b], np.cumsum(n) - n, axis=0).astype(np.float64)
        p, expected = marginals(unary[ids], lengths, crf.transitions)
        grad = p
        grad[np.arange(len(y)), y] -= 1
        inner = np.ones(len(y), dtype=bool)
        inner[np.cumsum(lengths) - lengths] = False
        step = np.flatnonzero(inner)
        seen = np.zeros_like(expected)
        np.add.at(seen, (y[step - 1], y[step]), 1)
        by_word = np.stack([np.bincount(ids, grad[:, k], len(own)) for k in range(len(labels))], axis=1)
        for x, g2, slot, each in ((crf.grams, past[0], b, by_word[row]), (crf.lexicon, past[1], feats.word[own], by_word)):
            touched, to = np.unique(slot, return_inverse=True)
            g = np.stack([np.bincount(to, each[:, k], len(touched)) for k in range(len(labels))], axis=1)
            g2[touched] += g * g
            x[touched] -= rate * g / np.sqrt(g2[touched])
        past[2] += (expected - seen) ** 2
        crf.transitions -= rate * (expected - seen) / np.sqrt(past[2])
    return crf


def fold(n: int) -> Column:
    """crc32 of doc_id as text, modulo n."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def fit(docs: DataFrame, learn: Column, per_language: int = PER_LANGUAGE, bytes_each: int = BYTES_PER_LANGUAGE) -> Crf:
    """Train on a draw of each language among the rows for which ``learn`` holds: at most so many documents and bytes of text.

    Every language found is learned; memory grows by 8 MB with each.
    """
    own = docs.where(learn & F.col("lang").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("label"), text_bytes().alias("text"))
    rows = bounded_draw(own, per_language, bytes_each, "language")
    return train([t for *_, t in rows], [x for _, x, _ in rows])


class Speaker:
    """Distributions of the words of texts; scores of distinct words are kept from text to text, up to a bound."""

    def __init__(self, crf: Crf, kept: int = WORDS_KEPT) -> None:
        self.crf, self.kept = crf, kept
        self._forget()

    def _forget(self) -> None:
        self.known: dict[bytes, int] = {}
        self.scores, self.letters = np.zeros((0, len(self.crf.labels)), np.float32), np.zeros(0, bool)

    def _read(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(number of each word, words of each line, lines of each text)."""
        if len(self.known) > self.kept:
            self._forget()
        ids, in_line, per_text = [], [], np.zeros(len(texts), np.int64)
        for k, t in enumerate(texts):
            begin = 0
            while begin <= len(t):
                end = t.find(b"\n", begin)
                end = len(t) if end < 0 else end
                found = word_numbers(t[begin:end], self.known)
                if len(found):
                    ids.append(found), in_line.append(len(found))
                    per_text[k] += 1
                begin = end + 1
        new = list(self.known)[len(self.letters) :]
        letters = np.fromiter(map(has_letter, new), bool, len(new))
        scores = self.crf.unary(new).astype(np.float32)
        scores[~letters] = 0
        self.letters, self.scores = np.concatenate((self.letters, letters)), np.concatenate((self.scores, scores))
        return (np.concatenate(ids) if ids else np.zeros(0, np.int32)), np.array(in_line, dtype=np.int64), per_text

    def words(self, texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(text of each word, does it hold a letter, its distribution), piece by piece, in order."""
        ids, in_line, per_text = self._read(texts)
        text_of_line = np.repeat(np.arange(len(texts)), per_text)
        stops = np.cumsum(in_line)
        for lo, hi, p in distributions(lambda a, b: self.scores[ids[a:b]].astype(np.float64), in_line, self.crf.transitions):
            line = np.searchsorted(stops, np.arange(lo, hi), "right")
            yield text_of_line[line], self.letters[ids[lo:hi]], p

    def masses(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of each text: the mass of its words with a letter in each language, their number, and the sum of each one's largest share."""
        labels = len(self.crf.labels)
        mass, total, sure = np.zeros((len(texts), labels)), np.zeros(len(texts)), np.zeros(len(texts))
        for of, letter, p in self.words(texts):
            of, p = of[letter], p[letter]
            total += np.bincount(of, minlength=len(texts))
            sure += np.bincount(of, p.max(axis=1), len(texts))
            for k in range(labels):
                mass[:, k] += np.bincount(of, p[:, k], len(texts))
        return mass, total, sure

    def guess(self, texts: list[bytes]) -> tuple[list[str], np.ndarray]:
        """Language and score (share of the mass of words with a letter) of each text; ``und`` and 0 without any letter."""
        if not self.crf.labels:
            return ["und"] * len(texts), np.zeros(len(texts))
        mass, total, _ = self.masses(texts)
        names = [self.crf.labels[b] if n else "und" for b, n in zip(mass.argmax(axis=1).tolist(), total.tolist())]
        return names, np.where(total > 0, np.clip(mass.max(axis=1) / np.maximum(total, 1), 0, 1), 0.0)


def guess(crf: Crf, texts: list[bytes]) -> tuple[list[str], np.ndarray]:
    """Language and score of each text (see ``Speaker``)."""
    return Speaker(crf).guess(texts)


def word_marginals(crf: Crf, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distribution of each word, does it hold a letter, words in each text)."""
    found = list(Speaker(crf).words(texts))
    if not found:
        return np.zeros((0, len(crf.labels))), np.zeros(0, bool), np.zeros(len(texts), np.int64)
    of, letters, p = (np.concatenate([x[k] for x in found]) for k in range(3))
    return p, letters, np.bincount(of, minlength=len(texts))


def predict(docs: DataFrame, crf: Crf) -> DataFrame:
    """doc_id, lang_pred and score (share of the words' mass) of each whole text; ``und`` and 0 without any letter."""
    shared = docs.sparkSession.sparkContext.broadcast(crf)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        speaker = Speaker(shared.value)
        for batch in batches:
            for part in slices(batch, "text"):
                names, score = speaker.guess(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(names, pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, "doc_id long, lang_pred string, score double")


def label_words(docs: DataFrame, crf: Crf) -> DataFrame:
    """doc_id, lang, first_word and n_words: the runs of words of one language in each whole text, in order.

    Words are counted over the text from 0.  Words without a letter join the run before them, or the first.  Null texts and
    those without a letter have no rows.
    """
    shared = docs.sparkSession.sparkContext.broadcast(crf)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            for part in slices(batch, "text"):
                ids, langs, firsts, sizes = [], [], [], []
                for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    p, letters, _ = word_marginals(own, [t])
                    at = np.flatnonzero(letters)
                    best = p[at].argmax(axis=1)
                    turn = np.flatnonzero(np.concatenate(([True], best[1:] != best[:-1]))) if len(at) else at
                    first = at[turn]
                    first[:1] = 0
                    ids += [i] * len(turn)
                    langs += [own.labels[k] for k in best[turn].tolist()]
                    firsts += first.tolist()
                    sizes += np.diff(np.append(first, len(p))).tolist()
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(langs, pa.string()), pa.array(firsts, pa.int64()), pa.array(sizes, pa.int64())], names=["doc_id", "lang", "first_word", "n_words"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, "doc_id long, lang string, first_word long, n_words long")


def identify(docs: DataFrame, learn: Column | None = None, per_language: int = PER_LANGUAGE) -> DataFrame:
    """Fit on the labelled rows of ``docs`` for which ``learn`` holds (default: doc_id's fold of five isn't 0), predict all rows.

    Returns doc_id, held_out, lang_pred, score.  Null texts and texts without a letter are ``und`` with score 0; rows without
    a lang are not learned from; repeated rows appear as often as they occur; other columns are not read; an empty table
    gives an empty result, and where nothing can be learned from, every text is ``und``.
    """
    crf = fit(docs, fold(5) != 0 if learn is None else learn, per_language)
    return predict(docs, crf).select("doc_id", F.coalesce(fold(5) == 0, F.lit(False)).alias("held_out"), "lang_pred", "score")


def keep_identified(docs: DataFrame, learn: Column | None = None, per_language: int = PER_LANGUAGE, least: float = 0.5) -> DataFrame:
    """The documents whose words are told with a mean certainty of ``least`` or more, all columns kept.

    A word's certainty is the share of its likeliest language, so a text that switches between known languages stays.  Null
    texts and those without a letter go.  Where nothing can be learned, no document is rejected for its language, and only
    those go.  Repeated rows stay or go together; rows without doc_id are judged like any other; an empty table gives an
    empty result.
    """
    crf = fit(docs, fold(5) != 0 if learn is None else learn, per_language)
    shared = docs.sparkSession.sparkContext.broadcast(crf)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        speaker = Speaker(shared.value)
        for batch in batches:
            for part in slices(batch, "text"):
                texts = part.column(0).to_pylist()
                if speaker.crf.labels:
                    _, total, sure = speaker.masses(texts)
                    keep = (total > 0) & (sure >= least * total)
                else:
                    keep = [any(map(has_letter, t.split())) for t in texts]
                yield pa.RecordBatch.from_arrays([pa.array([hashlib.sha256(t).hexdigest() for t, k in zip(texts, keep) if not k], pa.string())], names=["_gone"])

    # A verdict hangs on the text alone, so what goes is told by its digest and no text comes back from Python.
    with small_batches(docs.sparkSession):
        gone = materialise(docs.select(text_bytes().alias("text")).mapInArrow(run, "_gone string").distinct(), "unidentified")
    return docs.join(fitted(gone, 64), F.sha2(text_bytes(), 256) == gone["_gone"], "left_anti")
