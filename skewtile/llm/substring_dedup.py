"""Substring deduplication: repeated runs of words, found with an FM-index per shard.

A window of `window` words is removed when its words also start in a document with a smaller doc_id. Windows
reach the shard that can hold their repeats by content: each has as anchor the smallest hash among
its runs of GRAM words, so equal windows have equal anchors. Anchors of one document alone cannot repeat
across documents and end there. Neighbouring windows of one anchor travel as one segment; equal
segments are folded before the shuffle into one with its smallest doc_id; windows of an anchor that very many
documents have travel on their own hash, so no shard gathers them. Each shard indexes its segments, compressed, and
streams the documents' segments through backward search, which gives for every window the interval of its
occurrences, and the smallest doc_id in it.

Cases: null and empty texts have no words; texts shorter than a window lose nothing; ties (rows of one
doc_id) are one document and don't remove each other's words; a null doc_id neither removes nor loses words; an empty table gives no
rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.llm import tokens as tk
from skewtile.llm.fm_index import FMIndex
from skewtile.llm.runs import shared
from skewtile.llm.scratch import drop_settled, settle

WINDOW, GRAM = 13, 6
SHARD_WORDS = 1_000_000


def _sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minima of all runs of w entries, by doubling."""
    have, out = 1, x
    while have < w:
        step = min(have, w - have)
        out = np.minimum(out[: len(out) - step], out[step:])
        have += step
    return out


def _words(batch: pa.RecordBatch) -> tuple:
    raw, off = tk.text_buffer(batch.column("text"))
    starts, ends, first = tk.word_spans(raw, off)
    return raw, starts, ends, first, tk.word_hashes(raw, starts, ends, lower=False)


def _anchors(words: np.ndarray, window: int) -> np.ndarray:
    """The anchor of the window at each word; windows may cross texts."""
    if len(words) < window:
        return np.zeros(0, np.uint64)
    return _sliding_min(tk.gram_hashes(words, GRAM), window - GRAM + 1)


def _emit_anchors(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in tk.slices(whole, "text"):
                _, _, _, first, words = _words(b)
                anchor = _anchors(words, window).view(np.int64)
                docs = b.column("doc_id").to_numpy(zero_copy_only=False)
                keys, ids = [], []
                for i in range(b.num_rows):
                    if first[i + 1] - first[i] >= window:
                        own = np.unique(anchor[first[i] : first[i + 1] - window + 1])
                        keys.append(own)
                        ids.append(np.full(len(own), docs[i]))
                if keys:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(np.concatenate(ids))], ["anchor", "doc"])

    return run


def _emit_segments(window: int):
    """(doc, start, n_words, route, key, seg): runs of windows whose anchors other documents share."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in tk.slices(batch, "text"):
                raw, starts, ends, first, words = _words(b)
                data = raw.tobytes()
                anchor = _anchors(words, window).view(np.int64)
                whole = tk.gram_hashes(words, window).view(np.int64)
                docs = b.column("doc_id").to_pylist()
                lists, longs = b.column("anchors"), b.column("long_anchors")
                rows = ([], [], [], [], [], [])
                for i in range(b.num_rows):
                    a, z = first[i], first[i + 1] - window + 1
                    own = anchor[a:z]
                    common, many = lists[i].values.to_numpy(zero_copy_only=False), longs[i].values.to_numpy(zero_copy_only=False)
                    in_long = np.isin(own, many)
                    use = np.isin(own, common) | in_long
                    edge = np.append(True, own[1:] != own[:-1]) | in_long
                    edge[1:] |= use[1:] != use[:-1]
                    at = np.append(np.flatnonzero(edge), len(own))
                    for x, y in zip(at, at[1:]):
                        if use[x]:
                            s, e = a + x, a + y - 1 + window - 1
                            seg = b" ".join(data[starts[s] : ends[e]].split())
                            key = int.from_bytes(hashlib.blake2b(seg, digest_size=8).digest(), "little", signed=True)
                            for column, value in zip(rows, (docs[i], x, y - x + window - 1, whole[s] if in_long[x] else own[x], key, seg)):
                                column.append(value)
                if rows[0]:
                    types = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types)], ["doc", "start", "n_words", "route", "key", "seg"])

    return run


def index_shard(segs: list[bytes], least: np.ndarray, window: int) -> list[np.ndarray]:
    """For each segment, the smallest doc_id among the segments that hold the window at each of its words."""
    joined = b" \x00 ".join(segs) + b" \x00"
    raw = np.frombuffer(joined, np.uint8)
    starts, ends, _ = tk.word_spans(raw, np.array([0, len(raw)]))
    words = tk.word_hashes(raw, starts, ends, lower=False)
    sizes = np.array([s.count(b" ") + 1 for s in segs], np.int64)
    begin = np.append(0, np.cumsum(sizes + 1)[:-1])
    of = np.repeat(np.arange(len(segs)), sizes + 1)
    text = np.unique(words, return_inverse=True)[1].astype(np.int64) + 1
    text[begin + sizes] = 0  # the stop symbol is the smallest
    index = FMIndex(text, window, least[of])
    at, low, _ = index.match(text, begin, sizes)
    found = np.empty(len(text), np.int64)
    found[at] = index.least_label(low)
    return [found[b : b + n - window + 1] for b, n in zip(begin, sizes)]


def _search(window: int):
    def run(table: pa.Table) -> pa.Table:
        segs = table.column("seg").to_pylist()
        least = table.column("least").to_numpy()
        found = index_shard(segs, least, window)
        at = pa.array(np.append(0, np.cumsum([len(f) for f in found])), pa.int32())
        owners = pa.ListArray.from_arrays(at, pa.array(np.concatenate(found)))
        return pa.table([table.column("route").combine_chunks(), table.column("key").combine_chunks(), owners], ["route", "key", "owners"])

    return run


def _cut(window: int):
    """doc_id, n_words, n_removed, kept: the text's words outside the windows that start at `starts`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in tk.slices(whole, "text"):
                n, gone, kept = [], [], []
                for text, starts in zip(b.column("text").to_pylist(), b.column("starts")):
                    words = (text or "").encode("utf-8", "surrogatepass").split()
                    n.append(len(words))
                    removed = 0
                    if starts.is_valid and len(starts.values):
                        change = np.zeros(len(words) + 1, np.int64)
                        at = starts.values.to_numpy(zero_copy_only=False)
                        np.add.at(change, at, 1)
                        np.add.at(change, at + window, -1)
                        stay = np.cumsum(change[:-1]) == 0
                        removed = len(words) - int(stay.sum())
                        words = [words[i] for i in np.flatnonzero(stay)]
                    gone.append(removed)
                    kept.append(b" ".join(words).decode("utf-8", "surrogatepass"))
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.string())],
                    ["doc_id", "n_words", "n_removed", "kept"],
                )

    return run


def repeated_windows(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc, starts): the word places at which each document's windows repeat a smaller document's; documents with any."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("doc_id is not null")
    anchors = rows.mapInArrow(_emit_anchors(window), "anchor long, doc long").repartition("anchor").sortWithinPartitions("anchor", "doc")
    common = anchors.mapInArrow(shared("anchor", True), "anchor long, doc long, long_run boolean")
    per_doc = common.groupBy("doc").agg(
        F.collect_list(F.when(~F.col("long_run"), F.col("anchor"))).alias("anchors"),
        F.collect_list(F.when(F.col("long_run"), F.col("anchor"))).alias("long_anchors"),
    )
    with_anchors = rows.join(per_doc, F.col("doc_id") == F.col("doc")).drop("doc")
    segments = settle(with_anchors.mapInArrow(_emit_segments(window), "doc long, start int, n_words int, route long, key long, seg binary"), "segments")
    distinct = segments.groupBy("route", "key").agg(F.min("doc").alias("least"), F.count(F.lit(1)).alias("n"), F.first("seg").alias("seg"))
    distinct = settle(distinct, "distinct")
    words = segments.agg(F.sum("n_words")).first()[0] or 0
    shards = max(1, -(-int(words) // SHARD_WORDS))
    sharded = distinct.withColumn("shard", F.pmod(F.xxhash64("route"), F.lit(shards)))
    owners = sharded.groupBy("shard").applyInArrow(_search(window), "route long, key long, owners array<long>")
    owners = settle(owners, "owners")
    drop_settled(distinct)
    owners = owners.select(F.col("route").alias("_route"), F.col("key").alias("_key"), "owners")
    hits = segments.select("doc", "start", "route", "key").join(owners, (F.col("route") == F.col("_route")) & (F.col("key") == F.col("_key")))
    places = F.transform("owners", lambda o, i: F.when(o < F.col("doc"), F.col("start") + i))
    hits = hits.select("doc", F.filter(places, lambda p: p.isNotNull()).alias("starts")).where(F.size("starts") > 0)
    return hits.groupBy("doc").agg(F.flatten(F.collect_list("starts")).alias("starts"))


def remove_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept (the words left, joined by spaces); one row per document."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    hits = settle(repeated_windows(docs, window), "hits")
    return rows.join(hits, F.col("doc_id") == F.col("doc"), "left").drop("doc").mapInArrow(_cut(window), "doc_id long, n_words long, n_removed long, kept string")
