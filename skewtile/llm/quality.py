"""Quality rules: counts within a text, and line frequency across the documents of a host.

Lines are normalised (A-Z lower-cased, white space folded) and hashed; each (host, line) counts the
distinct documents that hold it. A line above the limit of its host is boilerplate: it is taken out of the text, and a
document left with too few words, or too small a part of them, is rejected.

Cases: a null or empty text has no words and fails the base rule; a null host is a host of its own;
rows of one doc_id are judged each and count as one document of their host, as do those without one; lines without words count
nowhere; an empty table gives no rows; of the input only doc_id, text and the host column are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.llm import tokens as tk
from skewtile.llm.scratch import settle

_SYMBOL = np.zeros(256, np.int64)
_SYMBOL[list(b"#*$%&|<>")] = 1  # fixed values: the symbol characters
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_HEAD = (~_SPACE & ((np.arange(256) & 0xC0) != 0x80)).astype(np.int64)

SCHEMA = "doc_id long, host string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, lines array<long>, line_words array<int>"


@dataclass(frozen=True)
class Rules:
    min_words: int = 50
    repeat_percent: int = 50
    line_share: float = 0.05
    """A line is boilerplate in a host when more than this share of the host's documents hold it,"""
    line_least: int = 10
    """and more than this many."""
    keep_share: float = 0.2
    """Documents left with less than this share of their words, or fewer than min_words, are rejected."""


def _sums(values: np.ndarray, off: np.ndarray) -> np.ndarray:
    total = np.zeros(len(values) + 1, np.int64)
    np.cumsum(values, out=total[1:])
    return total[off[1:]] - total[off[:-1]]


def _repeated(words: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Per text, the words within three-word windows that occur twice or more in it."""
    n = len(words) - 2
    if n <= 0:
        return np.zeros(len(first) - 1, np.int64)
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    at = np.flatnonzero(doc[:n] == doc[2:])
    key = tk.mix(tk.gram_hashes(words, 3)[at] ^ (doc[at].astype(np.uint64) * tk.U(0x9E3779B97F4A7C15)))
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    twice = np.zeros(len(at), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(len(words), np.int64)
    for i in range(3):
        covered[at[twice] + i] = 1
    return _sums(covered, first)


def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for b in tk.slices(whole, "text"):
            raw, off = tk.text_buffer(b.column("text"))
            starts, ends, first = tk.word_spans(raw, off)
            words = tk.word_hashes(raw, starts, ends, lower=False)
            data = raw.tobytes()
            dup, lines, counts, at = np.zeros(b.num_rows, np.int64), [], [], [0]
            for i in range(b.num_rows):
                text = data[off[i] : off[i + 1]]
                seen, own = set(), {}
                for line in text.split(b"\n"):
                    if parts := line.split():
                        if line in seen:
                            dup[i] += 1
                        seen.add(line)
                        h = xxhash.xxh64_intdigest(b" ".join(parts).lower()) - 2**63
                        own[h] = own.get(h, 0) + len(parts)
                lines += own.keys()
                counts += own.values()
                at.append(len(lines))
            at = pa.array(at, pa.int32())
            yield pa.RecordBatch.from_arrays(
                [
                    b.column("doc_id").cast(pa.int64()), b.column("host").cast(pa.string()),
                    pa.array(np.diff(first)), pa.array(_sums(_HEAD[raw], off)), pa.array(_sums(_SYMBOL[raw], off)), pa.array(dup), pa.array(_repeated(words, first)),
                    pa.ListArray.from_arrays(at, pa.array(lines, pa.int64())), pa.ListArray.from_arrays(at, pa.array(counts, pa.int32())),
                ],
                ["doc_id", "host", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "lines", "line_words"],
            )


def measure(docs: DataFrame, host: str = "source") -> DataFrame:
    """The base counts of each document, and its distinct normalised lines with their words."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col(host).cast("string").alias("host"), F.col("text").cast("string"))
    return rows.mapInArrow(_measure, SCHEMA)


def boilerplate(measured: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """(host, line, n_docs) of the lines above their host's limit. Documents are gathered by doc_id, then lines are counted with
    partial counts before the shuffle, so neither a large host nor a frequent line is one task."""
    docs = measured.groupBy("host", "doc_id").agg(F.array_distinct(F.flatten(F.collect_list("lines"))).alias("lines"))
    per_host = docs.groupBy(F.col("host").alias("_host")).agg(F.count(F.lit(1)).alias("docs"))
    lines = docs.select("host", F.explode("lines").alias("line")).groupBy("host", "line").agg(F.count(F.lit(1)).alias("n_docs"))
    lines = lines.where(F.col("n_docs") > rules.line_least)
    out = lines.join(per_host, F.col("host").eqNullSafe(F.col("_host")))
    return out.where(F.col("n_docs") > rules.line_share * F.col("docs")).select("host", "line", "n_docs")


def _judged(docs: DataFrame, rules: Rules, host: str) -> DataFrame:
    """The columns of judge(), host, and gone: the normalised lines of the document above its host's limit."""
    measured = settle(measure(docs, host).withColumn("_row", F.monotonically_increasing_id()), "measured")
    common = settle(boilerplate(measured, rules), "boilerplate")
    lines = measured.select("_row", "host", F.explode(F.arrays_zip("lines", "line_words")).alias("l"))
    lines = lines.select("_row", F.col("host").alias("_host"), F.col("l.lines").alias("_line"), F.col("l.line_words").alias("w"))
    gone = lines.join(common, F.col("_host").eqNullSafe(F.col("host")) & (F.col("_line") == F.col("line")), "left_semi")
    gone = gone.groupBy(F.col("_row").alias("_gone")).agg(F.sum("w").alias("n_boilerplate_words"), F.collect_list("_line").alias("gone"))
    out = measured.drop("lines", "line_words").join(gone, F.col("_row") == F.col("_gone"), "left")
    out = out.withColumn("n_boilerplate_words", F.coalesce("n_boilerplate_words", F.lit(0)))
    failed = (F.col("n_words") < rules.min_words) | (100 * F.col("n_repeat_words") > rules.repeat_percent * F.col("n_words"))
    left = F.col("n_words") - F.col("n_boilerplate_words")
    out = out.withColumn("base_failed", failed)
    return out.withColumn("kept", ~failed & (left >= rules.min_words) & (left >= rules.keep_share * F.col("n_words")))


def judge(docs: DataFrame, rules: Rules = Rules(), host: str = "source") -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, n_boilerplate_words, kept."""
    return _judged(docs, rules, host).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "n_boilerplate_words", "kept")


def _without(text: pa.Array, gone: pa.Array) -> pa.Array:
    """Each text without the lines whose normalised form is among those gone."""
    out = []
    for t, g in zip(text, gone):
        if (t := t.as_py()) is not None and (g := g.as_py()):
            g = set(g)
            stays = lambda parts: not parts or xxhash.xxh64_intdigest(b" ".join(parts).lower()) - 2**63 not in g  # noqa: E731, B023
            t = b"\n".join(x for x in t.encode().split(b"\n") if stays(x.split())).decode()
        out.append(t)
    return pa.array(out, pa.string())


def clean_documents(docs: DataFrame, rules: Rules = Rules(), host: str = "source") -> DataFrame:
    """The documents that the rules keep, without their lines above the limit; n_chars, if there is one, follows the text. Other
    columns are as they were. Documents of one doc_id go or stay together."""
    per_host = _judged(docs, rules, host).groupBy("doc_id", "host").agg(F.min("kept").alias("kept"), F.array_distinct(F.flatten(F.collect_list("gone"))).alias("gone"))
    kept = per_host.groupBy("doc_id").agg(F.min("kept").alias("all_kept"), F.collect_list(F.when(F.size("gone") > 0, F.struct("host", "gone"))).alias("gone")).where("all_kept")
    key, cut = "_key", "_cut"
    while {key, cut} & set(docs.columns):
        key, cut = key + "_", cut + "_"
    kept = kept.select(F.col("doc_id").alias(key), F.col("gone").alias(cut))
    out = docs.join(kept, docs["doc_id"].eqNullSafe(kept[key]))
    own = F.get(F.filter(cut, lambda x: x["host"].eqNullSafe(F.col(host).cast("string"))), F.lit(0))["gone"]
    out = out.withColumn(cut, own)
    changed = F.col(cut).isNotNull()
    out = out.withColumn("text", F.when(changed, F.arrow_udf(_without, "string")(F.col("text").cast("string"), F.col(cut))).otherwise(F.col("text")))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(changed, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)
