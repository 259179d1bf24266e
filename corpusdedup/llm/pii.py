"""Personal data and secrets by weak supervision.

Labelers of four sorts (form, gazetteer, context, check) vote on candidate spans.  Expectation-maximisation over the counts of
vote patterns in the whole corpus estimates how reliable each is for each kind.  The posteriors are the targets of a logistic
span classifier over hashed features of a span's characters and of the words around it; it is trained on a bounded draw of
candidates and decides on those that the fixed base patterns don't already hold.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusdedup.llm.common import map_rows, materialise, quoted, slices, text_bytes, unused

#: The base patterns know the first four.
KINDS = ("email", "ip", "card", "phone", "secret")
EMAIL, IP, CARD, PHONE, SECRET = range(len(KINDS))
#: Probability from which a candidate counts as personal data.
ACCEPT = 0.9
#: Characters before and after a candidate that the context labeler and the classifier read.
AROUND = 40
#: Candidates of each vote pattern drawn to train the classifier, at most, and its hashed features.
PER_PATTERN, DIMENSIONS = 100, 1 << 14
#: Share of card numbers that fail the check digit.
MISTYPED = 0.001

# Base patterns, matched leftmost and without overlap, each kind for itself.
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_RUN = re.compile(r"[+0-9][0-9 .()+\-]*")
_DIGITS = re.compile(r"[0-9]+")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")

# Wider patterns: what a candidate may look like.
_SPELT_AT = re.compile(r"\(at\)|\[at\]|\{at\}| at | @ ?|@ ", re.IGNORECASE)
_SPELT_EMAIL = re.compile(
    r"[A-Za-z0-9._%+-]{1,64}(?: ?(?:\(at\)|\[at\]|\{at\}) ?| at | ?@ ?)[A-Za-z0-9-]{1,63}(?:(?: ?(?:\(dot\)|\[dot\]|\{dot\}) ?| dot |\.)[A-Za-z0-9-]{1,63}){1,8}", re.IGNORECASE
)
_LONG_ADDRESS = re.compile(r"(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{1,4}:){2,7}(?::?[0-9A-Fa-f]{1,4}){1,6}(?![0-9A-Za-z:])")
_LOCAL_PHONE = re.compile(r"(?<![0-9+.(-])(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\) ?|[0-9]{2,4}[ .-])[0-9]{3,4}[ .-][0-9]{3,4}(?![0-9.-])")
_ABROAD_PHONE = re.compile(r"(?<![0-9])00[1-9][0-9]{0,2}[ (-][0-9 ()-]{5,14}[0-9]")
_WIDE_RUN = re.compile(r"[+(0-9][0-9 .()+\-]{8,}")
_LOOSE_CARD = re.compile(r"(?<![0-9.])[0-9]{4}(?:[ .-]?[0-9]{4}){2,3}[0-9]{0,3}(?![0-9.])")
_OPAQUE = re.compile(r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/=-]{16,512}(?![A-Za-z0-9_+/=-])")
_PEM = re.compile(r"-----BEGIN [A-Z ]{0,30}PRIVATE KEY-----")
_GIVEN = re.compile(r"""(?i)(?:pass(?:word|wd|phrase)?|pwd|secret|token|credential|api[_ -]?key|access[_ -]?key|private[_ -]?key|contrase\u00f1a|passwort|kennwort|mot de passe)["']? ?(?:=|:|:=) ?["']?([^\s"',;]{6,512})""")

#: Gazetteers.  Fixed values.  Domain endings that aren't two-letter country codes, which all count.
ENDINGS = frozenset("com org net edu gov mil int info biz name pro aero coop museum jobs mobi travel tel cat asia post xxx app dev io ai cloud online site store tech blog news shop".split())
#: First numbers of addresses that no single host has: own network, loopback, groups, reserved.
NO_HOST = frozenset([0, 127, *range(224, 256)])
#: First digits of card issuers, as ranges of four digits.
ISSUERS = ((2014, 2014), (2149, 2149), (2221, 2720), (3000, 3059), (3400, 3499), (3528, 3589), (3600, 3999), (4000, 4999), (5000, 5999), (6011, 6011), (6200, 6299), (6304, 6304), (6440, 6599), (6759, 6763))
#: Country calling codes of one and two digits; all others have three.
CALLING = frozenset("1 7 20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split())
THREE_DIGIT_ZONES = frozenset("21 22 23 24 25 26 29 35 37 38 42 50 59 67 68 69 80 85 87 88 96 97 99".split())
#: How keys of well-known services begin.
KEY_STARTS = ("AKIA", "ASIA", "AIza", "ghp_", "gho_", "ghs_", "github_pat_", "glpat-", "sk-", "sk_live_", "rk_live_", "xoxb-", "xoxp-", "eyJ", "SG.", "ya29.", "npm_", "pypi-", "hf_")
#: Context.  Fixed values: how words begin that speak for a kind, and words that speak against it.
CUES = {
    "email": ("mail", "e-mail", "contact", "write", "address", "reach", "correo", "escrib", "courriel", "adresse", "kontakt", "schreib", "envoy"),
    "ip": ("ip", "host", "server", "login", "address", "from", "client", "connect", "adresse", "servidor", "serveur", "remote", "ssh"),
    "card": ("card", "visa", "master", "credit", "debit", "payment", "pay", "amex", "carte", "tarjeta", "karte", "kredit", "paiement", "pago"),
    "phone": ("phone", "tel", "call", "fax", "mobil", "cell", "ring", "whatsapp", "sms", "appel", "llam", "anruf", "ruf", "handy"),
    "secret": ("token", "secret", "key", "passw", "pass", "pwd", "api", "auth", "bearer", "credential", "contrase", "kennwort", "geheim", "clave", "clef", "mot"),
}
AGAINST = {
    "email": ("example",),
    "ip": ("version", "release", "section", "chapter"),
    "card": ("isbn", "issn", "order", "invoice", "serial", "tracking", "ean", "sku", "part"),
    "phone": ("isbn", "issn", "order", "invoice", "serial", "version", "page", "pages"),
    "secret": ("sha", "md5", "commit", "checksum", "digest", "integrity", "hash", "uuid", "build", "revision"),
}
_WORD = re.compile(r"[^\W\d_]+")

VOTES = 3**4
PATTERNS = len(KINDS) * VOTES


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if k & 1:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _only_digits(s: str) -> str:
    return "".join(_DIGITS.findall(s))


def emails(text: str) -> list[tuple[int, int]]:
    out, done = [], 0
    at = text.find("@")
    while at >= 0:
        a = at
        while a > done and text[a - 1] in _LOCAL:
            a -= 1
        m = _DOMAIN.match(text, at + 1) if a < at else None
        if m:
            out.append((a, m.end()))
            done = m.end()
        at = text.find("@", max(at + 1, done))
    return out


def addresses(text: str, a: int, b: int) -> Iterator[tuple[int, int]]:
    """Four groups of digits joined by single dots: the pattern, group by group, so that long runs of digits cost no more than their length."""
    if text.count(".", a, b) < 3:
        return
    groups = [m.span() for m in _DIGITS.finditer(text, a, b)]
    joined = [groups[i + 1][0] == groups[i][1] + 1 and text[groups[i][1]] == "." for i in range(len(groups) - 1)]
    i = 0
    while i + 3 < len(groups):
        if joined[i] and joined[i + 1] and joined[i + 2]:
            yield groups[i][0], groups[i + 3][1]
            i += 4
        else:
            i += 1


def _valid_address(s: str) -> bool:
    return all(int(p.lstrip("0")[:4] or 0) <= 255 for p in s.split("."))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind, start, end) by kind, then start; code points, end exclusive."""
    found: list[list[tuple[int, int]]] = [emails(text), [], [], []]
    for run in _RUN.finditer(text):
        a, b = run.span()
        if b - a < 2:
            continue
        found[1] += [(i, j) for i, j in addresses(text, a, b) if _valid_address(text[i:j])]
        for m in _CARD.finditer(text, a, b):
            d = _only_digits(m.group())
            if 16 <= len(d) <= 19 and luhn(d):
                found[2].append(m.span())
        if "+" in run.group():
            found[3] += [m.span() for m in _PHONE.finditer(text, a, b) if 8 <= len(_only_digits(m.group())) <= 15]
    return [(k, a, b) for k, own in enumerate(found) for a, b in own]


def _opaque(value: str) -> bool:
    """Whether a run of characters looks drawn at random: letters and digits mixed, or one of the two at a key's length."""
    digits, letters = sum(map(str.isdigit, value)), sum(map(str.isalpha, value))
    return digits > 1 and letters > 1


def wider_spans(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Candidates that no base span overlaps: whatever might be personal data or a secret, most of it perhaps not."""
    found: list[tuple[int, int, int]] = []
    if _SPELT_AT.search(text) and ("." in text or "dot" in text.lower()):
        found += [(EMAIL, *m.span()) for m in _SPELT_EMAIL.finditer(text)]
    if text.count(":") > 2:
        found += [(IP, *m.span()) for m in _LONG_ADDRESS.finditer(text)]
    for run in _WIDE_RUN.finditer(text):
        a, b = run.span()
        found += [(IP, *x) for x in addresses(text, a, b)]
        found += [(PHONE, *m.span()) for m in _LOCAL_PHONE.finditer(text, a, b)]
        found += [(PHONE, *m.span()) for m in _ABROAD_PHONE.finditer(text, a, b)]
        found += [(CARD, *m.span()) for m in _LOOSE_CARD.finditer(text, a, b)]
    found += [(SECRET, *m.span()) for m in _OPAQUE.finditer(text) if _opaque(m.group()) or m.group().startswith(KEY_STARTS)]
    low = text.lower() if "=" in text or ":" in text else ""
    if any(w in low for w in ("pass", "pwd", "secret", "token", "credential", "key", "contrase", "kennwort")):
        found += [(SECRET, *m.span(1)) for m in _GIVEN.finditer(text)]
    if "-----BEGIN" in text:
        found += [(SECRET, *m.span()) for m in _PEM.finditer(text)]
    if not found:
        return []
    taken = np.zeros(len(text) + 1, dtype=bool) if base else None
    for _, a, b in base:
        taken[a:b] = True
    return sorted({x for x in found if taken is None or not taken[x[1] : x[2]].any()})


def _words_around(text: str, a: int, b: int) -> tuple[list[str], list[str]]:
    """The words before and after a span, those next to it first."""
    before = [w.lower() for w in _WORD.findall(text, max(0, a - AROUND), a)][::-1]
    return before, [w.lower() for w in _WORD.findall(text, b, min(len(text), b + AROUND))]


def _entropy(s: str) -> float:
    return -sum(n / len(s) * math.log2(n / len(s)) for n in Counter(s).values())


def votes(text: str, kind: int, a: int, b: int) -> tuple[int, int, int, int]:
    """Form, gazetteer, context, check: 1 for, -1 against, 0 no opinion."""
    s = text[a:b]
    d = _only_digits(s)
    before, after = _words_around(text, a, b)
    name = KINDS[kind]
    for_it = any(w.startswith(c) for w in before + after for c in CUES[name])
    context = 1 if for_it else -1 if any(w in AGAINST[name] for w in before + after) else 0
    if kind == EMAIL:
        ending = re.split(r"[.)\]} ]+", s.rstrip(".)]} "))[-1].lower()
        plain = "@" in s and " " not in s
        form = 1 if plain and not s.startswith((".", "-")) else 1 if re.search(r"(?i)[(\[{]at", s) else 0 if "@" in s or re.search(r"(?i) dot ", s) else -1
        gaz = 1 if ending in ENDINGS or (len(ending) == 2 and ending.isalpha()) else 0 if ending.isalpha() and len(ending) < 7 else -1
        check = 1 if ".." not in s and ending.isalpha() else -1
    elif kind == IP:
        if ":" in s:
            groups = s.split(":")
            form = 1 if len(groups) == 8 or "::" in s else -1
            gaz, check = (1 if len(d) and any(len(g) > 2 for g in groups) else -1), (1 if s.count("::") <= 1 and ":::" not in s and len(groups) <= 8 else -1)
        else:
            parts = [int(p[:9]) for p in s.split(".")]
            form = 1 if all(p == "0" or p[0] != "0" for p in s.split(".")) else -1
            gaz = -1 if parts[0] in NO_HOST else 1
            check = 1 if max(parts) <= 255 else -1
    elif kind == CARD:
        form = 1 if "." not in s and len({c for c in s if not c.isdigit()}) <= 1 else 0
        gaz = 1 if any(lo <= int(d[:4]) <= hi for lo, hi in ISSUERS) else -1
        check = 1 if 13 <= len(d) <= 19 and luhn(d) else -1
    elif kind == PHONE:
        abroad = s[1:] if s[0] == "+" else s[2:] if s.startswith("00") else ""
        own = _only_digits(abroad)
        form = 1 if s[0] == "+" else 0 if s.startswith("00") or "(" in s else -1 if len({c for c in s if c in " .-"}) > 1 else 0
        gaz = 0 if not own else 1 if own[:1] in CALLING or own[:2] in CALLING or own[:2] in THREE_DIGIT_ZONES else -1
        check = 1 if 8 <= len(own or d) <= 15 else -1
    else:
        hexes = re.fullmatch(r"[0-9A-Fa-f]+", s)
        form = 1 if s.startswith("-----") or (hexes and len(s) in (32, 40, 48, 64, 96, 128)) or re.search(r"[=:] ?[\"']?$", text[max(0, a - 3) : a]) else 0 if _opaque(s) else -1
        gaz = 1 if s.startswith(KEY_STARTS) or s.startswith("-----") else 0
        check = 1 if s.startswith("-----") or (_entropy(s) >= 2.8 and len(s) >= 16) else 0 if _opaque(s) else -1
    return form, gaz, context, check


def pattern(kind: int, own: tuple[int, int, int, int]) -> int:
    """A candidate's kind and votes as one number below ``PATTERNS``."""
    code = 0
    for v in own:
        code = 3 * code + v + 1
    return kind * VOTES + code


def _unpacked(code: int) -> tuple[int, list[int]]:
    kind, v = divmod(code, VOTES)
    return kind, [v // 3 ** (3 - j) % 3 - 1 for j in range(4)]


_RUNS = re.compile(r"9+|a+|A+")


def features(text: str, kind: int, a: int, b: int) -> list[int]:
    """Hashes of what a span looks like (its shape, runs of it, its first and last characters, its length) and of what stands around it."""
    s = text[a : min(b, a + 256)]
    shape = "".join("9" if c.isdigit() else "A" if c.isupper() else "a" if c.isalpha() else c for c in s)
    runs = _RUNS.sub(lambda m: f"{m.group()[0]}{min(len(m.group()), 20)}", shape)
    short = "^" + _RUNS.sub(lambda m: m.group()[0], shape) + "$"
    before, after = _words_around(text, a, b)
    own = [f"run {runs}", f"first {s[:2]}", f"last {s[-2:]}", f"length {(b - a).bit_length()}", f"entropy {int(2 * _entropy(s))}", f"left {text[max(0, a - 2):a]}", f"right {text[b:b + 1]}"]
    own += [f"gram {short[i:i + 3]}" for i in range(min(len(short) - 2, 24))]
    own += [f"near {w}" for w in before[:2]] + [f"before {w}" for w in before[:6]] + [f"after {w}" for w in after[:3]]
    return sorted({zlib.crc32(f"{kind} {x}".encode("utf-8", "surrogatepass")) & (DIMENSIONS - 1) for x in [*own, "kind"]})


def reliabilities(counts: dict[int, int], rounds: int = 60) -> tuple[dict[int, float], np.ndarray]:
    """Expectation-maximisation: each pattern's posterior, and each labeler's chances of its votes given the truth (kind, labeler, truth, vote)."""
    codes = sorted(counts)
    kinds = np.array([_unpacked(c)[0] for c in codes], dtype=np.int64)
    vote = np.array([_unpacked(c)[1] for c in codes], dtype=np.int64).reshape(-1, 4) + 1
    n = np.array([counts[c] for c in codes], dtype=np.float64)
    post = 1 / (1 + np.exp(-1.5 * (vote - 1).sum(axis=1)))
    chance = np.full((len(KINDS), 4, 2, 3), 1.0)
    # Labelers are taken to be better than chance: votes as told count as some observations.  An abstention tells nothing.
    prior = np.array([[4.0, 0.0, 1.0], [1.0, 0.0, 4.0]])
    for _ in range(rounds):
        share = np.full(len(KINDS), 0.5)
        for k in range(len(KINDS)):
            here = kinds == k
            for j in range(4):
                for y, p in ((0, 1 - post), (1, post)):
                    own = np.bincount(vote[here, j], n[here] * p[here], 3) + prior[y]
                    chance[k, j, y, [0, 2]] = own[[0, 2]] / own[[0, 2]].sum()
            if k == CARD:
                chance[k, 3, 1, [0, 2]] = MISTYPED, 1 - MISTYPED  # known, not estimated: numbers of cards pass their check
            share[k] = (np.sum((n * post)[here]) + 1) / (np.sum(n[here]) + 2)
        log = np.log(share[kinds]) - np.log(1 - share[kinds]) + sum(np.log(chance[kinds, j, 1, vote[:, j]]) - np.log(chance[kinds, j, 0, vote[:, j]]) for j in range(4))
        post = 1 / (1 + np.exp(-np.clip(log, -500, 500)))
    return dict(zip(codes, post.tolist())), chance


def train(rows: list[tuple[int, list[int]]], counts: dict[int, int], steps: int = 300, rate: float = 0.3, decay: float = 1e-5) -> np.ndarray:
    """Weights of a logistic regression on the posteriors of drawn candidates (pattern, features), the last one for the bias.

    A pattern weighs as the root of how often it occurs, so that rare ones count.
    """
    weights = np.zeros(DIMENSIONS + 1)
    if not rows:
        return weights
    truth, _ = reliabilities(counts)
    drawn = Counter(p for p, _ in rows)
    y = np.array([truth[p] for p, _ in rows])
    w = np.array([math.sqrt(counts[p]) / drawn[p] for p, _ in rows])
    w /= w.sum()
    size = np.fromiter((len(f) + 1 for _, f in rows), np.int64, len(rows))
    row = np.repeat(np.arange(len(rows)), size)
    which = np.fromiter((x for _, f in rows for x in (*f, DIMENSIONS)), np.int64, len(row))
    past = np.full(DIMENSIONS + 1, 1e-8)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(row, weights[which], len(rows)), -500, 500)))
        g = np.bincount(which, (w * (p - y))[row], DIMENSIONS + 1) + decay * weights
        past += g * g
        weights -= rate * g / np.sqrt(past)
    return weights


def probability(weights: np.ndarray, own: list[int]) -> float:
    return 1 / (1 + math.exp(-max(-500.0, min(500.0, float(weights[own].sum() + weights[-1])))))


def extract(docs: DataFrame) -> DataFrame:
    """doc_id, base and wider spans of each whole text as flat arrays (kind, start, end in turn), and a pattern and features for each span, base ones first."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ints, lists = pa.list_(pa.int64()), pa.list_(pa.list_(pa.int32()))
        for batch in batches:
            for part in slices(batch, "text"):
                base, wider, codes, seen = [], [], [], []
                for t in part.column(1).to_pylist():
                    text = t.decode("utf-8", "replace")
                    own = base_spans(text)
                    more = wider_spans(text, own)
                    base.append([x for s in own for x in s]), wider.append([x for s in more for x in s])
                    codes.append([pattern(s[0], votes(text, *s)) for s in own + more])
                    seen.append([features(text, *s) for s in own + more])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(base, ints), pa.array(wider, ints), pa.array(codes, pa.list_(pa.int32())), pa.array(seen, lists)], names=["doc_id", "base", "wider", "patterns", "features"])

    schema = "doc_id long, base array<long>, wider array<long>, patterns array<int>, features array<array<int>>"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text")).mapInArrow(run, schema)


def learn(found: DataFrame, per_pattern: int = PER_PATTERN) -> tuple[np.ndarray, dict[int, int]]:
    """The classifier's weights, and how often each vote pattern occurs, from what ``extract`` found.

    The counts are of the whole corpus, at most ``PATTERNS`` of them; of each pattern at most ``per_pattern`` candidates, drawn
    by a hash, are looked at one by one.
    """
    each = found.select("doc_id", F.explode(F.arrays_zip("patterns", "features")).alias("c")).select("doc_id", F.col("c.patterns").alias("p"), F.col("c.features").alias("f"))
    counts = {r["p"]: r["count"] for r in found.select(F.explode("patterns").alias("p")).groupBy("p").count().collect()}
    at = F.pmod(F.xxhash64("doc_id", "f"), F.lit(1 << 30))
    # Twice as many as asked for, of which the first by hash are taken.
    least = F.create_map(*[F.lit(x) for p, n in counts.items() for x in (p, int((1 << 30) * min(1.0, 2 * per_pattern / n)) + 1)]) if counts else F.lit(None)
    drawn = each.withColumn("at", at).where(F.col("at") < least[F.col("p")]) if counts else each.withColumn("at", at).limit(0)
    first = Window.partitionBy("p").orderBy("at", "doc_id")
    rows = drawn.withColumn("n", F.row_number().over(first)).where(F.col("n") <= per_pattern).select("p", "f").collect()
    return train(sorted((r["p"], list(r["f"])) for r in rows), counts), counts


def chosen(spans: list[tuple[int, int, int]], chances: list[float], accept: float) -> list[tuple[int, int, int]]:
    """The likeliest of the accepted spans, none overlapping one before it."""
    out: list[tuple[int, int, int]] = []
    for p, s in sorted(((p, s) for p, s in zip(chances, spans) if p >= accept), key=lambda x: (-x[0], x[1][1] - x[1][2], x[1])):
        if not any(s[1] < b and a < s[2] for _, a, b in out):
            out.append(s)
    return out


def find(docs: DataFrame, accept: float = ACCEPT, per_pattern: int = PER_PATTERN) -> DataFrame:
    """doc_id, base (array of kind, start, end) and spans (the same with what the classifier adds) of each row.

    Both are ordered by kind as in ``KINDS``, then start.  Null and empty texts have no spans; repeated rows appear as often as
    they occur; other columns are not read; an empty table gives an empty result.
    """
    own = materialise(extract(docs), "pii-candidates")
    weights, _ = learn(own, per_pattern)
    span = "array<struct<kind:string,start:long,end:long>>"

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        named = lambda spans: [{"kind": KINDS[k], "start": a, "end": b} for k, a, b in spans]
        triples = lambda x: list(zip(x[::3], x[1::3], x[2::3]))
        for batch in batches:
            base, spans = [], []
            for b, w, f in zip(*(batch.column(k).to_pylist() for k in (1, 2, 4))):
                b, w = triples(b), triples(w)
                base.append(named(b))
                spans.append(named(sorted(b + chosen(w, [probability(weights, x) for x in f[len(b) :]], accept))))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(base, of), pa.array(spans, of)], names=["doc_id", "base", "spans"])

    return own.mapInArrow(run, f"doc_id long, base {span}, spans {span}")


def joined(column: str) -> Column:
    """kind:start:end of each span, joined by commas."""
    return F.array_join(F.transform(column, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def masked(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """The documents with each span replaced by its kind in angle brackets; of overlapping spans the first counts.

    Rows of equal doc_id are masked by the spans of the first, so repeated ids must have equal texts.
    """
    key, found = unused(docs.columns, "_doc", "_spans")
    at = [c.lower() for c in docs.columns].index("text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, own in zip(batch.column(at).to_pylist(), batch.column(batch.num_columns - 1).to_pylist()):
                out, done = [], 0
                for s in sorted(own or [], key=lambda s: (s["start"], s["end"])):
                    if s["start"] >= done:
                        out += [text[done : s["start"]], f"<{s['kind']}>"]
                        done = s["end"]
                texts.append("".join([*out, text[done:]]) if text is not None else None)
            columns = [pa.array(texts, batch.column(k).type) if k == at else batch.column(k) for k in range(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names[:-1])

    own = spans.select(F.col("doc_id").alias(key), F.col("spans").alias(found)).dropDuplicates([key])
    both = docs.join(own, F.col("doc_id").cast("long") == F.col(key), "left").select(*map(quoted, docs.columns), found)
    return map_rows(both, run, len(docs.columns))
