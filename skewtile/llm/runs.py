"""Runs of equal keys in sorted Arrow batches, streamed with a bounded carry."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

HOLD = 4096
"""Rows of an unfinished run that are held back at most."""


def bounded_runs(batches: Iterator[pa.RecordBatch], columns: list[str], hold: int = HOLD) -> Iterator[tuple[list[np.ndarray], int]]:
    """Columns of rows sorted by the first one, and a piece number: -1 for blocks of whole runs of up to `hold` rows or
    a batch; 0, 1, ... for the pieces of one longer run."""
    held, piece = None, -1
    for b in batches:
        cols = [b.column(b.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in columns]
        if held is not None:
            cols = [np.concatenate(x) for x in zip(held, cols)]
            held = None
        if not len(cols[0]):
            continue
        if piece >= 0:  # a long run goes on
            to = int(np.searchsorted(cols[0], long_key, "right"))
            if to:
                piece += 1
                yield [c[:to] for c in cols], piece
                cols = [c[to:] for c in cols]
            if not len(cols[0]):
                continue
            piece = -1
        cut = int(np.searchsorted(cols[0], cols[0][-1], "left"))
        if cut:
            yield [c[:cut] for c in cols], -1
        last = [c[cut:] for c in cols]
        if len(last[0]) > hold:
            piece, long_key = 0, last[0][0]
            yield last, 0
        else:
            held = last
    if held is not None:
        yield held, -1


def edges(key: np.ndarray) -> np.ndarray:
    """Starts of the runs of a sorted array, and its length."""
    return np.append(np.flatnonzero(np.append(True, key[1:] != key[:-1])), len(key))


def distinct_pairs(key: np.ndarray, value: np.ndarray) -> np.ndarray:
    """Marks the first of each run of equal (key, value)."""
    return np.append(True, (key[1:] != key[:-1]) | (value[1:] != value[:-1]))


def shared(key_name: str, with_long: bool):
    """A mapInArrow function: drops keys that one document alone has, and repeated (key, doc); rows come sorted by both.
    with_long: a third column tells whether the key's run is longer than HOLD."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for (key, doc), piece in bounded_runs(batches, [key_name, "doc"]):
            new = distinct_pairs(key, doc)
            if piece > 0 and doc[0] == last:
                new[0] = False
            last = doc[-1]
            key, doc = key[new], doc[new]
            if piece < 0 and len(key):
                edge = np.append(True, key[1:] != key[:-1])
                keep = ~(edge & np.append(edge[1:], True))
                key, doc = key[keep], doc[keep]
            cols = [pa.array(key), pa.array(doc)] + ([pa.array(np.full(len(key), piece >= 0))] if with_long else [])
            yield pa.RecordBatch.from_arrays(cols, [key_name, "doc"] + (["long_run"] if with_long else []))

    return run
