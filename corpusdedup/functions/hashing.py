"""Polynomial shingle hashes and the hash families, as numpy kernels and as SQL expressions.

A shingle c_1 .. c_k has the value sum c_i q^(i-1) mod p.  Three evaluators give the same numbers: ``direct`` sums k shifted
products, ``rolling`` goes from one shingle to the next by the inverse of q, ``prefix`` takes differences of a running sum.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from corpusdedup.config import DedupConfig

#: Rows of the table of hashes that is held at once.
CHUNK = 256
#: Steps that the rolling hash takes from each of its starting points, which advance side by side.
STRIDE = 64


def codes_of(text: str) -> np.ndarray:
    """Code points of a text."""
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.int64)


def poly_direct(codes: np.ndarray, k: int, p: int, q: int) -> np.ndarray:
    n = len(codes) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=np.int64)
    out, power = np.zeros(n, dtype=np.int64), 1
    small = int(codes.max()) * p * k < 1 << 63  # then the plain sum fits
    for j in range(k):
        out += codes[j : j + n] * power if small else (codes[j : j + n] % p) * power % p
        power = power * q % p
    return out % p


def poly_rolling(codes: np.ndarray, k: int, p: int, q: int) -> np.ndarray:
    """Each value from the one before: drop the first character, divide by q (multiply by its inverse), add the new one.

    Every ``STRIDE``-th value is summed directly; from these the others follow side by side, one step of all at a time.
    """
    n = len(codes) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=np.int64)
    inverse, top = pow(q, -1, p), pow(q, k - 1, p)
    lanes = -(-n // STRIDE)
    c = np.zeros(lanes * STRIDE + k, dtype=np.int64)
    c[: len(codes)] = codes % p
    starts = np.arange(lanes) * STRIDE
    h = np.zeros(lanes, dtype=np.int64)
    for j in range(k):
        h = (h + c[starts + j] * pow(q, j, p)) % p
    out = np.empty((STRIDE, lanes), dtype=np.int64)
    out[0] = h
    gone, new = c[: lanes * STRIDE].reshape(lanes, STRIDE).T, c[k : lanes * STRIDE + k].reshape(lanes, STRIDE).T
    for i in range(1, STRIDE):
        h = ((h - gone[i - 1]) % p * inverse + new[i - 1] * top) % p
        out[i] = h
    return out.T.ravel()[:n]


def poly_prefix(codes: np.ndarray, k: int, p: int, q: int) -> np.ndarray:
    """Differences of sum c_i q^i mod p, shifted back by the inverse power."""
    n = len(codes) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=np.int64)
    powers, backs, inverse = [1], [1], pow(q, -1, p)
    for _ in range(len(codes) - 1):
        powers.append(powers[-1] * q % p)
        backs.append(backs[-1] * inverse % p)
    total = np.concatenate(([0], np.cumsum((codes % p) * np.array(powers) % p)))
    return (total[k:] - total[:-k]) % p * np.array(backs[:n]) % p


EVALUATORS = {"direct": poly_direct, "rolling": poly_rolling, "prefix": poly_prefix}


def rolling_hashes(codes: np.ndarray, cfg: DedupConfig, method: str = "direct", q: int | None = None) -> np.ndarray:
    """Hash of every shingle of a code sequence, in order."""
    return EVALUATORS[method](codes, cfg.k, cfg.p, q or cfg.q)


def _murmur_round(x: np.ndarray, h: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = x * np.uint32(0xCC9E2D51)
        x = (x << np.uint32(15)) | (x >> np.uint32(17))
        x = x * np.uint32(0x1B873593)
        h = h ^ x
        h = (h << np.uint32(13)) | (h >> np.uint32(19))
        h = h * np.uint32(5) + np.uint32(0xE6546B64)
        h = h ^ np.uint32(4)
        h ^= h >> np.uint32(16)
        h = h * np.uint32(0x85EBCA6B)
        h ^= h >> np.uint32(13)
        h = h * np.uint32(0xC2B2AE35)
        return h ^ (h >> np.uint32(16))


def murmur_shingles(codes: np.ndarray, k: int, seed: int = 42) -> np.ndarray:
    """Murmur3 of each shingle's code points, one 4-byte block after the other, as Spark's ``hash`` chains integer columns."""
    n = len(codes) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=np.int64)
    x = codes.astype(np.uint32)
    h = np.full(n, seed, dtype=np.uint32)
    for j in range(k):
        h = _murmur_round(x[j : j + n], h)
    return h.view(np.int32).astype(np.int64)


def base_hashes(codes: np.ndarray, cfg: DedupConfig, method: str = "direct") -> np.ndarray:
    """The one hash in [0, p) of each shingle that the remixing starts from."""
    if cfg.family in ("affine", "multibase"):
        return rolling_hashes(codes, cfg, method)
    if cfg.family == "murmur3":
        return murmur_shingles(codes, cfg.k) % cfg.p
    n = len(codes) - cfg.k + 1
    raw = codes.astype("<u4").tobytes()
    grams = [raw[4 * i : 4 * (i + cfg.k)].decode("utf-32-le", "surrogatepass").encode("utf-8", "surrogatepass") for i in range(max(0, n))]
    one = _gram_hash(cfg)
    return np.array([one(g) for g in grams], dtype=np.int64)


def _gram_hash(cfg: DedupConfig) -> Callable[[bytes], int]:
    if cfg.family == "sha1":
        return lambda g: int.from_bytes(hashlib.sha1(g).digest()[-4:], "big") % cfg.p
    import xxhash

    return lambda g: xxhash.xxh64_intdigest(g, 42) % cfg.p


#: Hashes of shingles met lately, of each family and modulus, and how many of them are held.
_known: dict[tuple[str, int], dict[str, int]] = {}
KNOWN = 1 << 17


def set_hashes(codes: np.ndarray, cfg: DedupConfig) -> np.ndarray:
    """The base hashes of the distinct shingles, in no order: SHA-1 and xxHash64 are called for those only that were not met lately."""
    if cfg.family not in ("sha1", "xxhash64"):
        raise ValueError(f"no hash of shingles one by one: {cfg.family}")
    known, one = _known.setdefault((cfg.family, cfg.p), {}), _gram_hash(cfg)
    if len(known) >= KNOWN:
        known.clear()
    text, out = codes.astype("<u4").tobytes().decode("utf-32-le", "surrogatepass"), []
    for g in {text[i : i + cfg.k] for i in range(len(text) - cfg.k + 1)}:
        h = known.get(g)
        if h is None:
            h = one(g.encode("utf-8", "surrogatepass"))
            if len(known) < KNOWN:
                known[g] = h
        out.append(h)
    return np.array(out, dtype=np.int64)


@functools.lru_cache(maxsize=8)
def _fractions(cfg: DedupConfig) -> tuple[np.ndarray, np.ndarray]:
    """a / p and (b + 1/2) / p of every hash function, in units of 2^-64."""
    p = cfg.p
    scale = [((a << 64) + p // 2) // p for a in map(int, cfg.constants[0])]
    shift = [((2 * b + 1) << 63) // p for b in map(int, cfg.constants[1])]
    return np.array(scale, dtype=np.uint64), np.array(shift, dtype=np.uint64)


def fixed_point_minima(h: np.ndarray, cfg: DedupConfig) -> np.ndarray:
    """The minimum of (a h + b) mod p over h for every hash function; p is below 2^31.

    Products that wrap at 2^64 leave the fraction of (a h + b + 1/2) / p, with an error below (p + 1) / 2 units where values
    lie 2^64 / p apart, so order and value are exact.  No division is done, and one buffer of a cache's size is used again.
    """
    scale, shift = _fractions(cfg)
    least = np.full(cfg.n_hashes, np.iinfo(np.uint64).max, dtype=np.uint64)
    x, buffer = h.astype(np.uint64), np.empty((CHUNK, cfg.n_hashes), dtype=np.uint64)
    for i in range(0, len(x), CHUNK):
        own = x[i : i + CHUNK, None]
        u = buffer[: len(own)]
        np.multiply(own, scale, out=u)
        np.add(u, shift, out=u)
        np.minimum(least, u.min(axis=0), out=least)
    p, half = np.uint64(cfg.p), np.uint64(32)
    low = (least & np.uint64(0xFFFFFFFF)) * p >> half
    return ((least >> half) * p + low >> half).astype(np.int64)


def signature(codes: np.ndarray, cfg: DedupConfig, method: str = "direct") -> np.ndarray | None:
    """The minima of all hash functions over the shingles; None for a text without a shingle."""
    if len(codes) < cfg.k:
        return None
    if cfg.family == "multibase":
        return np.array([rolling_hashes(codes, cfg, method, q).min() for q in cfg.bases], dtype=np.int64)
    own = set_hashes(codes, cfg) if cfg.family in ("sha1", "xxhash64") else base_hashes(codes, cfg, method)
    h = np.sort(own.astype(np.uint32))
    return fixed_point_minima(h[np.concatenate(([True], h[1:] != h[:-1]))], cfg)


# SQL forms: the same numbers inside whole-stage code.


def char_grams(text: Column, k: int) -> Column:
    """All k-grams of characters, overlapping, in order.

    Each match takes one character after looking ahead, so none starts inside a character that the JVM holds as two units.
    """
    return F.regexp_extract_all(text, F.lit(f"(?s)(?=(.{{{k}}}))."), F.lit(1))


def poly_hash(gram: Column, k: int, p: int, q: int) -> Column:
    """The polynomial value of a k-gram."""
    power, terms = 1, []
    for j in range(k):
        terms.append(F.ascii(F.substring(gram, j + 1, 1)).cast("long") * F.lit(power))
        power = power * q % p
    total = terms[0]
    for t in terms[1:]:
        total = total + t
    return total % F.lit(p)


def base_hash_column(gram: Column, cfg: DedupConfig) -> Column:
    if cfg.family in ("affine", "multibase"):
        return poly_hash(gram, cfg.k, cfg.p, cfg.q)
    if cfg.family == "murmur3":
        return F.pmod(F.hash(*[F.ascii(F.substring(gram, j + 1, 1)) for j in range(cfg.k)]).cast("long"), F.lit(cfg.p))
    if cfg.family == "sha1":
        return F.conv(F.substring(F.sha1(gram.cast("binary")), 33, 8), 16, 10).cast("long") % F.lit(cfg.p)
    raise ValueError(f"the {cfg.family} family has no SQL form")


def remixed(h: Column, cfg: DedupConfig) -> list[Column]:
    return [(h * F.lit(a) + F.lit(b)) % F.lit(cfg.p) for a, b in zip(*cfg.constants)]
