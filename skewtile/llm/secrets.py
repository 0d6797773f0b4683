"""Secret scans: fixed patterns, and random-looking tokens found by a battery of tests.

A token is a run of 20 or more characters of the base64 and URL alphabets that holds a digit or mixes
cases. Its encoding is inferred (hex, base32, base64), its characters become numbers of that alphabet,
and three tests ask whether they look uniform and independent: chi-squared over alphabet bins, runs
above and below the middle, serial correlation. The smallest of the three p-values, times three, is the
evidence for randomness. Ordinary tokens give the null: for each length class, the share of words made
of letters alone, of that or a shorter class, that score as high, joined with what the score alone tells. That p-value is weighed by length (a longer token
can show more) and a false discovery rate is held over all candidates of the corpus by the
step-up rule, on a table of score bins of fixed size. Tokens within base spans are candidates like others: they add no span, but
how many of them look random is told.

Cases: null and empty texts have no spans; repeated rows are scanned alike; a tie of spans goes by the
kind as listed; an empty table gives no rows; of the input only doc_id and text are read.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.llm.scratch import settle

# The base patterns and their least lengths.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "random")
_HINT = re.compile(r"[:=]")

TOKEN = re.compile(r"[A-Za-z0-9+/_-]{20,}")
ALPHABETS = {
    "hex": "0123456789abcdef",
    "base32": "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567",
    "base64": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/",
}
_CODE = {name: {ord(c): i for i, c in enumerate(s)} for name, s in ALPHABETS.items()}
_CODE["base64"] |= {ord("-"): 62, ord("_"): 63}
_CODE["hex"] |= {ord(c.upper()): i for i, c in enumerate(ALPHABETS["hex"])}
_SETS = {name: frozenset(map(chr, codes)) for name, codes in _CODE.items()}
BINS = 64
"""Score bins of the null and candidate tables, for each length class: their size does not grow with the corpus."""
PRIOR = 20
"""Ordinary tokens that the score alone stands for beside those counted."""


def base_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    if _HINT.search(text):
        found += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    found += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def encoding(token: str) -> str:
    seen = set(token)
    if seen <= _SETS["hex"] and (token.islower() or token.isupper() or token.isdigit()):
        return "hex"
    return "base32" if seen <= _SETS["base32"] else "base64"


def _normal_tail(z: float) -> float:
    return math.erfc(abs(z) / math.sqrt(2))


def _chi2_tail(x: float, dof: int) -> float:
    """The upper tail by a cube-root normal approximation."""
    if x <= 0:
        return 1.0
    z = ((x / dof) ** (1 / 3) - (1 - 2 / (9 * dof))) / math.sqrt(2 / (9 * dof))
    return 0.5 * math.erfc(z / math.sqrt(2))


def battery(token: str, kind: str) -> tuple[float, float, float]:
    """p-values of uniformity, runs and serial correlation under the hypothesis of independent uniform characters."""
    size, codes = len(ALPHABETS[kind]), _CODE[kind]
    values = [codes[ord(c)] for c in token]
    n = len(values)
    bins = min(size, max(8, 1 << int(math.log2(n / 2.5))))
    counts = Counter(v * bins // size for v in values)
    fair = n / bins
    chi = sum((counts.get(b, 0) - fair) ** 2 for b in range(bins)) / fair
    high = [2 * v >= size for v in values]
    up = sum(high)
    runs = 1 + sum(a != b for a, b in zip(high, high[1:]))
    if 0 < up < n:
        mean = 1 + 2 * up * (n - up) / n
        var = (mean - 1) * (mean - 2) / (n - 1)
        p_runs = _normal_tail((runs - mean) / math.sqrt(var)) if var > 0 else 0.0
    else:
        p_runs = 0.0
    m = sum(values) / n
    var = sum((v - m) ** 2 for v in values)
    r = sum((a - m) * (b - m) for a, b in zip(values, values[1:])) / var if var else 1.0
    p_serial = _normal_tail((r + 1 / n) * math.sqrt(n)) if var else 0.0
    return _chi2_tail(chi, bins - 1), p_runs, p_serial


def score(token: str) -> tuple[str, int, int, bool]:
    """(encoding, length class, score bin, ordinary). A higher bin looks more random."""
    kind = encoding(token)
    p = min(1.0, 3 * min(battery(token, kind)))
    at = BINS - 1 - min(BINS - 1, int(-4 * math.log2(max(p, 2**-16))))
    return kind, min(7, int(4 * math.log2(len(token) / 20))), at, token.isalpha() and token[1:].islower()


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        for text in b.column("text").to_pylist():
            text = text or ""
            base = base_spans(text)
            tokens = []
            for m in TOKEN.finditer(text):
                kind, size, at, plain = score(m.group())
                known = any(s < m.end() and m.start() < e for s, e, _ in base)
                tokens.append({"start": m.start(), "end": m.end(), "encoding": kind, "size": size, "score": at, "plain": plain, "known": known})
            rows.append(([{"start": s, "end": e, "kind": k} for s, e, k in base], tokens))
        yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array([r[0] for r in rows], _BASE), pa.array([r[1] for r in rows], _TOKENS)], ["doc_id", "base", "tokens"])


_BASE = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.string())]))
_TOKENS = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("encoding", pa.string()), ("size", pa.int32()), ("score", pa.int32()), ("plain", pa.bool_()), ("known", pa.bool_())]))
SCAN = "doc_id long, base array<struct<start:int,end:int,kind:string>>, tokens array<struct<start:int,end:int,encoding:string,size:int,score:int,plain:boolean,known:boolean>>"


def accepted_bins(scanned: DataFrame, rate: float) -> dict[tuple[int, int], bool]:
    """Which (length class, score bin) cells are secrets at the false discovery rate, over all tokens of the corpus."""
    cells = scanned.select(F.explode("tokens").alias("t")).groupBy("t.size", "t.score", "t.plain").agg(F.count(F.lit(1)).alias("n"))
    null, seen = np.zeros((8, BINS)), np.zeros((8, BINS))
    for r in cells.collect():  # 8 length classes x BINS scores x 2 at most
        (null if r["plain"] else seen)[r["size"], r["score"]] += r["n"]
    return accepted_cells(null, seen, rate)


def accepted_cells(null: np.ndarray, seen: np.ndarray, rate: float) -> dict[tuple[int, int], bool]:
    """null, seen: ordinary and other tokens in each (length class, score bin).

    p of a cell: the share of ordinary tokens of this or a shorter class (which score higher) that score as high, together
    with PRIOR tokens more that are spread as the score alone tells. At every count of ordinary tokens it is above 0 and, in
    the top bin, below 1 / (count + 1) until one of them scores as high."""
    tail = np.cumsum(np.cumsum(null, axis=0)[:, ::-1], axis=1)[:, ::-1]
    alone = np.minimum(1.0, 0.0025 * 2.0 ** (np.arange(BINS)[::-1] / 4.0))
    p = (tail + PRIOR * alone) / (tail[:, :1] + PRIOR)
    weight = (1 + np.arange(8))[:, None] * np.ones((1, BINS))
    total = seen.sum()
    if not total:
        return {}
    weight *= total / (weight * seen).sum()
    q = np.minimum(1.0, p / weight)
    order = np.argsort(q, axis=None)
    passed, best = 0.0, -1.0
    for cell in order:
        passed += seen.flat[cell]
        if passed and q.flat[cell] <= rate * passed / total:
            best = q.flat[cell]
    return {(i, j): bool(q[i, j] <= best) for i in range(8) for j in range(BINS)}


def find_secrets(docs: DataFrame, rate: float = 0.01) -> DataFrame:
    """doc_id, base and found: arrays of (start, end, kind) in code points, end exclusive; found has the base spans too. n_confirmed:
    tokens within base spans that the battery accepts."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    scanned = settle(rows.mapInArrow(_scan, SCAN), "scanned")
    yes = [size * BINS + at for (size, at), ok in accepted_bins(scanned, rate).items() if ok]
    cell = lambda t: t["size"] * BINS + t["score"]
    accepted = F.filter("tokens", lambda t: (~t["plain"]) & F.array_contains(F.array(*(F.lit(x) for x in yes)).cast("array<int>"), cell(t)))
    scanned = scanned.withColumn("accepted", accepted)
    random = F.transform(F.filter("accepted", lambda t: ~t["known"]), lambda t: F.struct(t["start"], t["end"], F.lit("random").alias("kind")))
    confirmed = F.size(F.filter("accepted", lambda t: t["known"])).cast("long").alias("n_confirmed")
    return scanned.select("doc_id", "base", F.array_sort(F.concat("base", random), _by_start).alias("found"), confirmed)


def _by_start(a, b):
    rank = lambda s: F.array_position(F.array(*(F.lit(k) for k in KINDS)), s["kind"])
    less = (a["start"] < b["start"]) | ((a["start"] == b["start"]) & (rank(a) < rank(b)))
    return F.when(less, -1).when((a["start"] == b["start"]) & (rank(a) == rank(b)), 0).otherwise(1)


def told(spans) -> F.Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def digests(found: DataFrame) -> DataFrame:
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    return found.select("doc_id", *(count(k) for k in KINDS[:3]), F.sha2(told("base"), 256).alias("base_sha256"), told("found").alias("spans"), "n_confirmed")
