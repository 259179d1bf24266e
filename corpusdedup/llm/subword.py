"""Words of a batch of texts and their hashed subword features, computed for each distinct word of the batch at once."""

from __future__ import annotations

import re
import zlib

import numpy as np

#: Hash buckets of the n-grams and of the whole words.
BUCKETS = 1 << 18
SIZES = (2, 3, 4)
_MIX = {2: 0x9E3779B1, 3: 0x85EBCA77, 4: 0xC2B2AE3D}


def tokens(texts: list[bytes]) -> tuple[np.ndarray, list[bytes], np.ndarray]:
    """(number of each word, the distinct words, words in each text): words are what ASCII white space separates."""
    known: dict[bytes, int] = {}
    parts = [word_numbers(t, known) for t in texts]
    return (np.concatenate(parts) if parts else np.zeros(0, np.int32)), list(known), np.fromiter(map(len, parts), np.int64, len(parts))


#: Bytes of a text that are split at once.
PIECE = 1 << 18
_BLANK = re.compile(rb"[ \t\n\x0b\x0c\r]")


def word_numbers(text: bytes, known: dict[bytes, int]) -> np.ndarray:
    """The number of each word of a text; ``known`` numbers the distinct words and takes in new ones.

    Long texts are split piece by piece between words, so that their words are never all held as objects.
    """
    parts, begin = [], 0
    while begin < len(text):
        end = min(len(text), begin + PIECE)
        if end < len(text):
            blank = _BLANK.search(text, end)
            end = blank.start() if blank else len(text)
        found = text[begin:end].split()
        parts.append(np.fromiter((known.setdefault(w, len(known)) for w in found), np.int32, len(found)))
        begin = end
    return np.concatenate(parts) if len(parts) > 1 else parts[0] if parts else np.zeros(0, np.int32)


class Features:
    """Hash buckets of all n-grams of some words (a space before and after each), and of the words themselves.

    ``lo[n]`` and ``hi[n]`` bound each word's n-grams in ``grams[n]``; an n-gram that holds a word's edge is its affix.
    """

    def __init__(self, words: list[bytes], buckets: int = BUCKETS) -> None:
        flat = np.frombuffer(b" " + b" ".join(words) + b"    ", dtype=np.uint8).astype(np.uint32)
        size = np.fromiter(map(len, words), np.int64, len(words))
        first = np.cumsum(size + 1) - size  # after the space before
        self.grams, self.lo, self.hi = {}, {}, {}
        code = flat[: len(flat) - 3].copy()
        for n in SIZES:
            code = code | (flat[n - 1 : len(flat) - 4 + n] << np.uint32(8 * (n - 1)))
            h = (code * np.uint32(_MIX[n])) ^ (code >> np.uint32(15))
            self.grams[n] = ((h * np.uint32(0x27D4EB2F)) >> np.uint32(32 - (buckets.bit_length() - 1))).astype(np.int32)
            self.lo[n] = first - 1
            self.hi[n] = np.maximum(first - 1, first + size - n + 2)
        self.word = np.fromiter((zlib.crc32(w) & (buckets - 1) for w in words), np.int32, len(words))
        self.number = 1 + sum(self.hi[n] - self.lo[n] for n in SIZES)

    def sums(self, gram_weights: np.ndarray, word_weights: np.ndarray) -> np.ndarray:
        """Each word's sum of the weights of its features; weights are (buckets,) or (buckets, labels)."""
        out = word_weights[self.word].astype(np.float64)
        for n in SIZES:
            total = np.zeros((len(self.grams[n]) + 1, *gram_weights.shape[1:]))
            np.cumsum(gram_weights[self.grams[n]], axis=0, dtype=np.float64, out=total[1:])
            out += total[self.hi[n]] - total[self.lo[n]]
        return out

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """(word, bucket) of every n-gram of every word."""
        words, buckets = [], []
        for n in SIZES:
            each = self.hi[n] - self.lo[n]
            w = np.repeat(np.arange(len(each)), each)
            words.append(w)
            buckets.append(self.grams[n][np.arange(len(w)) - np.repeat(np.cumsum(each) - each, each) + np.repeat(self.lo[n], each)])
        return np.concatenate(words), np.concatenate(buckets)
