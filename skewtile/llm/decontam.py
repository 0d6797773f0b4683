"""Benchmark decontamination by the q-gram lemma in diagonal bands, verified by banded alignment.

Texts and items are normalised alike (lower case, runs of other characters than letters and digits to
one space). An item of m characters occurring with at most e edits shares at least
m - q + 1 - q * e of its q-grams, whose diagonals (place in the text less place in the item) spread by at
most e. Diagonals fall into overlapping bands of width 2(e + 1), so one band holds them all; bands in which enough
places of the text share a q-gram are kept, neighbouring ones as one region of bounded width, and regions are aligned within their
diagonals and the edits counted. Shared q-grams are counted in pieces of bounded size, however often text and items repeat themselves.

The benchmark is the stated query set: it is sent to the tasks in blocks of bounded size, every
block against all documents. Items too short for the lemma (under q + 1 characters at the given rate) are looked
up as whole strings, without edits.

Cases: null and empty texts hold nothing; null, empty or wordless items are found nowhere; repeated
rows are reported alike, repeated items each under their own id; an empty table on either side gives
no rows; of the inputs only doc_id, text, item_id are read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.llm.scratch import with_ids

Q = 12
RATE = 0.05
BLOCK_CHARS = 1 << 22
"""Normalised benchmark characters that go to the tasks at once."""
PIECE, REGION = 1 << 19, 1 << 14
"""Pairs of equal q-grams that are held at once, and diagonals that are aligned at once."""
_OTHER = re.compile(r"[\W_]+")
_B, _B2, _B4 = (np.uint64(pow(0x9E3779B97F4A7C15, k, 2**64)) for k in (1, 2, 4))
_BITS, _BAND_BITS = 22, 40
SCHEMA = "doc_id long, item_id long, start long, end long, edits int"


def normalise(text: str | None) -> str:
    return _OTHER.sub(" ", (text or "").lower()).strip()


def codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def q_grams(c: np.ndarray) -> np.ndarray:
    """Hashes of all runs of Q codes, by doubling."""
    n = len(c) - Q + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    one = c.astype(np.uint64)
    two = one[:-1] * _B + one[1:]
    four = two[:-2] * _B2 + two[2:]
    eight = four[:-4] * _B4 + four[4:]
    return (eight[:n] * _B4 + four[8 : 8 + n]) * np.uint64(0xD6E8FEB86659FD93)


def edits_allowed(m: int, rate: float) -> int:
    """The budget of an item: the rate, as far as the lemma can still ask for one shared q-gram."""
    return max(0, min(int(rate * m), (m - Q) // Q))


def banded_edits(item: np.ndarray, text: np.ndarray, low: int, high: int, most: int) -> tuple[int, int, int]:
    """(edits, start, end) of the item's best occurrence in text among alignments on diagonals low to high; more
    than `most` edits count as most + 1. Start and end are places in text."""
    width, m = high - low + 1, len(item)
    far = most + 1
    diagonals = np.arange(width)
    cost = np.zeros(width, np.int32)
    begin = low + diagonals
    cost[(begin < 0) | (begin > len(text))] = far
    for i in range(m):
        at = i + low + diagonals
        inside = (at >= 0) & (at < len(text))
        differ = np.ones(width, np.int32)
        differ[inside] = text[at[inside]] != item[i]
        swap = np.where(inside, cost + differ, far)
        skip = np.append(cost[1:] + 1, far)  # the item's character is left out
        take_skip = skip < swap
        new = np.where(take_skip, skip, swap)
        origin = np.where(take_skip, np.append(begin[1:], 0), begin)
        run = new - diagonals  # then characters of the text are left out
        best = np.minimum.accumulate(run)
        source = np.maximum.accumulate(np.where(run == best, diagonals, 0))
        cost, begin = np.minimum(best + diagonals, far), origin[source]
        if cost.min() >= far:
            break
    k = int(cost.argmin())
    return int(cost[k]), int(begin[k]), m + low + k


@dataclass(frozen=True)
class Block:
    ids: np.ndarray
    items: list[np.ndarray]
    texts: list[str]
    budgets: np.ndarray
    needed: np.ndarray
    grams: np.ndarray
    gram_at: np.ndarray
    gram_item: np.ndarray
    gram_place: np.ndarray
    long_enough: np.ndarray
    longest: int
    short: list[int]

    @classmethod
    def of(cls, rows: list[tuple[int, str]], rate: float) -> Block:
        items = [codes(t) for _, t in rows]
        budgets = np.array([edits_allowed(len(c), rate) for c in items], np.int64)
        sizes = np.array([len(c) for c in items], np.int64)
        parts = [q_grams(c) for c in items]
        every = np.concatenate(parts) if parts else np.zeros(0, np.uint64)
        item = np.repeat(np.arange(len(items)), [len(p) for p in parts])
        place = np.concatenate([np.arange(len(p)) for p in parts]) if parts else np.zeros(0, np.int64)
        order = np.argsort(every, kind="stable")
        grams, first = np.unique(every[order], return_index=True)
        return cls(
            np.array([i for i, _ in rows], np.int64), items, [t for _, t in rows], budgets, sizes - Q + 1 - Q * budgets,
            grams, np.append(first, len(every)), item[order], place[order], sizes > Q, int(sizes.max(initial=0)) + Q, [i for i, c in enumerate(items) if len(c) <= Q],
        )

    def bands(self, text_codes: np.ndarray, flags: np.ndarray) -> Iterator[tuple[int, int, int]]:
        """(item, first diagonal, last diagonal) of the regions with enough shared q-grams, diagonals ascending for each item."""
        h = q_grams(text_codes)
        maybe = np.flatnonzero(flags[h >> np.uint64(64 - _BITS)])
        if not len(maybe) or not len(self.grams):
            return
        g = np.searchsorted(self.grams, h[maybe])
        g[g == len(self.grams)] = 0
        hit = self.grams[g] == h[maybe]
        maybe, g = maybe[hit], g[hit]
        total = np.append(0, np.cumsum(self.gram_at[g + 1] - self.gram_at[g]))
        if not total[-1]:
            return
        open_keys, open_counts = np.zeros(0, np.int64), np.zeros(0, np.int64)
        region: dict[int, list[int]] = {}
        at = 0
        while at < len(maybe):
            to = max(at + 1, int(np.searchsorted(total, total[at] + PIECE, "right")) - 1)
            keys, counts = self._counted(maybe[at:to], g[at:to])
            if len(open_keys):
                open_keys, code = np.unique(np.concatenate([open_keys, keys]), return_inverse=True)
                open_counts = np.bincount(code, weights=np.concatenate([open_counts, counts])).astype(np.int64)
            else:
                open_keys, open_counts = keys, counts
            item, band = open_keys >> _BAND_BITS, (open_keys & ((1 << _BAND_BITS) - 1)) - (1 << (_BAND_BITS - 1))
            step = self.budgets[item] + 1
            # later places of the text have diagonals above their own place less the longest item
            done = (band + 2) * step <= maybe[to] - self.longest if to < len(maybe) else np.ones(len(open_keys), bool)
            enough = done & (open_counts >= self.needed[item])
            for i, b, s in zip(item[enough].tolist(), band[enough].tolist(), step[enough].tolist()):
                low, high = b * s, (b + 2) * s - 1
                if i in region and low <= region[i][1] + 1 and high - region[i][0] < max(REGION, 2 * s):
                    region[i][1] = max(region[i][1], high)
                else:
                    if i in region:
                        yield i, *region[i]
                    region[i] = [low, high]
            open_keys, open_counts = open_keys[~done], open_counts[~done]
            at = to
        for i, (low, high) in region.items():
            yield i, low, high

    def _counted(self, places: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(item and band as one number, places of the text that share a q-gram with the item in that band)."""
        n = self.gram_at[g + 1] - self.gram_at[g]
        entry = np.repeat(self.gram_at[g] - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())
        item, at = self.gram_item[entry], np.repeat(places, n)
        use = self.long_enough[item]
        item, at, diagonal = item[use], at[use], (at - self.gram_place[entry])[use]
        key = (item << _BAND_BITS) + diagonal // (self.budgets[item] + 1) + (1 << (_BAND_BITS - 1))
        if not len(key):
            return key, key
        key, at = np.concatenate([key, key - 1]), np.concatenate([at, at])
        order = np.lexsort((at, key))
        key, at = key[order], at[order]
        new = np.append(True, (key[1:] != key[:-1]) | (at[1:] != at[:-1]))  # a place counts once a band
        key = key[new]
        edge = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        return key[edge], np.diff(np.append(edge, len(key)))

def _matches(text: str, block: Block, flags: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
    """(item, start, end, edits): the best occurrence of each item found."""
    best: dict[int, tuple[int, int, int]] = {}
    c = codes(text)
    for i, low, high in block.bands(c, flags):
        e = int(block.budgets[i])
        if i in best and best[i][0] == 0:  # an exact occurrence that stands before all others
            continue
        near = (max(0, low - e), min(len(c), high + e + len(block.items[i])))
        exact = text.find(block.texts[i], *near)
        if exact >= 0:
            got = (0, exact, exact + len(block.items[i]))
        else:
            got = banded_edits(block.items[i], c[near[0] : near[1]], low - e - near[0], high + e - near[0], e)
            got = (got[0], got[1] + near[0], got[2] + near[0])
        if got[0] <= e and (i not in best or got < best[i]):
            best[i] = got
    for i in block.short:
        if block.texts[i] and f" {block.texts[i]} " in f" {text} ":
            at = f" {text} ".index(f" {block.texts[i]} ")
            best[i] = (0, at, at + len(block.texts[i]))
    for i, (edits, start, end) in sorted(best.items()):
        yield i, start, end, edits


def _scan(block: Block):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        flags = np.zeros(1 << _BITS, bool)
        flags[block.grams >> np.uint64(64 - _BITS)] = True
        for b in batches:
            rows = []
            for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()):
                rows += ((doc, int(block.ids[i]), s, e, n) for i, s, e, n in _matches(normalise(text), block, flags))
            cols = list(zip(*rows)) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(cols, [pa.int64()] * 4 + [pa.int32()])], ["doc_id", "item_id", "start", "end", "edits"])

    return run


def find_contamination(docs: DataFrame, benchmark: DataFrame, rate: float = RATE, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """(doc_id, item_id, start, end, edits): for each document and item, the best occurrence with at most rate * m edits.
    start and end are places in the normalised text."""
    blocks: list[list[tuple[int, str]]] = [[]]
    size = 0
    for r in benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).where("item_id is not null").orderBy("item_id").toLocalIterator():
        if text := normalise(r["text"]):
            if size + len(text) > block_chars and blocks[-1]:
                blocks.append([])
                size = 0
            blocks[-1].append((r["item_id"], text))
            size += len(text)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return reduce(DataFrame.unionByName, (rows.mapInArrow(_scan(Block.of(b, rate)), SCHEMA) for b in blocks))


def contaminated(docs: DataFrame, benchmark: DataFrame, rate: float = RATE) -> DataFrame:
    """One row per document that holds an item: doc_id, item_ids (ascending), least_edits."""
    return find_contamination(docs, benchmark, rate).groupBy("doc_id").agg(F.sort_array(F.collect_set("item_id")).alias("item_ids"), F.min("edits").alias("least_edits"))


def clean_documents(docs: DataFrame, benchmark: DataFrame, rate: float = RATE) -> DataFrame:
    """The documents that hold no item, rows and columns as they were."""
    return with_ids(docs, find_contamination(docs, benchmark, rate).select("doc_id").distinct(), "left_anti")
