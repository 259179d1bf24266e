"""Hash kernels on their own: no input or output, no minima, timed inside the tasks."""

from __future__ import annotations

import hashlib
import time
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig
from corpusdedup.functions.hashing import base_hashes, codes_of, poly_direct, rolling_hashes


def _md5(codes: np.ndarray, cfg: DedupConfig) -> np.ndarray:
    text = codes.astype("<u4").tobytes().decode("utf-32-le", "surrogatepass")
    grams = (text[i : i + cfg.k].encode("utf-8", "surrogatepass") for i in range(len(text) - cfg.k + 1))
    return np.array([int.from_bytes(hashlib.md5(g).digest()[-4:], "big") % cfg.p for g in grams], dtype=np.int64)


#: Hashes in [0, p) of all shingles of a code sequence.
KERNELS: dict[str, Callable[[np.ndarray, DedupConfig], np.ndarray]] = {
    "polynomial_direct": lambda c, cfg: rolling_hashes(c, cfg, "direct"),
    "polynomial_rolling": lambda c, cfg: rolling_hashes(c, cfg, "rolling"),
    "polynomial_prefix": lambda c, cfg: rolling_hashes(c, cfg, "prefix"),
    "polynomial_8_bases": lambda c, cfg: np.concatenate([poly_direct(c, cfg.k, cfg.p, q) for q in cfg.bases[:8]]),
    "murmur3": lambda c, cfg: base_hashes(c, cfg.but(family="murmur3")),
    "sha1": lambda c, cfg: base_hashes(c, cfg.but(family="sha1")),
    "xxhash64": lambda c, cfg: base_hashes(c, cfg.but(family="xxhash64")),
    "md5": _md5,
}


#: Characters of the texts whose hashes a task holds at once, besides a single longer text.
CHARS_AT_ONCE = 1 << 18


def in_parts(texts: Iterable[str | None], limit: int = CHARS_AT_ONCE) -> Iterator[list[str]]:
    """The texts that aren't null, in lists of at most ``limit`` characters or one text."""
    part, held = [], 0
    for t in texts:
        if t is None:
            continue
        if part and held + len(t) > limit:
            yield part
            part, held = [], 0
        part.append(t)
        held += len(t)
    if part:
        yield part


def hash_kernels(docs: DataFrame, cfg: DedupConfig = DedupConfig(), kernels: Iterable[str] = tuple(KERNELS)) -> DataFrame:
    """kernel, shingles, checksum (sum of all hashes), seconds: summed over the tasks, each kernel on the same texts in memory.

    Null texts have no shingles; texts are hashed one by one, as in the plans.
    """
    names = list(kernels)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sums = {name: [0, 0, 0.0] for name in names}
            for k in range(0, batch.num_rows, 256):
                for part in in_parts(batch.column(0).slice(k, 256).to_pylist()):
                    codes = [codes_of(t) for t in part]
                    for name, own in sums.items():
                        kernel = KERNELS[name]
                        began = time.perf_counter()
                        found = [kernel(c, cfg) for c in codes]
                        own[2] += time.perf_counter() - began
                        own[0] += sum(map(len, found))
                        own[1] += sum(int(h.sum()) for h in found)
            rows = [(name, *own) for name, own in sums.items()]
            cells = list(zip(*rows))
            yield pa.RecordBatch.from_arrays([pa.array(cells[0], pa.string()), pa.array(cells[1], pa.int64()), pa.array(cells[2], pa.int64()), pa.array(cells[3], pa.float64())], names=["kernel", "shingles", "checksum", "seconds"])

    each = docs.select("text").mapInArrow(run, "kernel string, shingles long, checksum long, seconds double")
    return each.groupBy("kernel").agg(F.sum("shingles").alias("shingles"), F.sum("checksum").alias("checksum"), F.sum("seconds").alias("seconds"))
