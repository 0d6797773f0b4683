"""Measures: balance, routed records, filter quality, times, stragglers, speed-ups."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from skewtile.operators.rangejoin import Cells, cell_join, tile_times
from skewtile.operators.tiled import TiledTable
from skewtile.plans import route


def timed(run: Callable[[], object]) -> tuple[object, float]:
    began = time.perf_counter()
    out = run()
    return out, time.perf_counter() - began


def balance(values: np.ndarray) -> dict[str, float]:
    """Largest over mean, Gini coefficient, and the share of the five largest."""
    v = np.sort(np.asarray(values, float))
    n, total = len(v), v.sum()
    if not n or not total:
        return {"max_over_mean": 1.0, "gini": 0.0, "top5_share": 0.0}
    return {"max_over_mean": float(v[-1] / v.mean()), "gini": float((2 * np.arange(1, n + 1) - n - 1) @ v / (n * total)), "top5_share": float(v[-5:].sum() / total)}


def routed_records(q: DataFrame, tt: TiledTable, filtered: bool) -> int:
    """Shuffle cost: query records sent to tiles."""
    return route.ranges(q, tt.tiles, tt.filters if filtered else None).count()


def observed(df: DataFrame, name: str = "join") -> tuple[DataFrame, Observation]:
    """df and an observation that its next action fills: rows and distinct queries (about), counted as they pass."""
    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows"), F.approx_count_distinct("qid").alias("queries")), seen


def visited_tiles(q: DataFrame, tt: TiledTable, filtered: bool) -> DataFrame:
    """(qid, n_tiles) of queries that visit any tile."""
    return route.ranges(q, tt.tiles, tt.filters if filtered else None).groupBy("qid").agg(F.count(F.lit(1)).alias("n_tiles"))


def filter_quality(q: DataFrame, tt: TiledTable) -> DataFrame:
    """One row over all (query, overlapped tile) probes: tp, fp, tn, fn, fpr = fp / (fp + tn), fdr = fp / (fp + tp)."""
    probes = route.ranges(q.select("qid", "x1", "y1", "x2", "y2"), tt.tiles)
    said = tt.filters.prune(probes).select("qid", "tile", F.lit(1).alias("said"))
    true = cell_join(tt.rows.select("pid", "x", "y", "tile"), probes, Cells.of(q, tt.tiles), tt.tiles).select("qid", "tile", F.lit(1).alias("held")).distinct()
    both = probes.select("qid", "tile").join(said, ["qid", "tile"], "left").join(true, ["qid", "tile"], "left").na.fill(0, ["said", "held"])
    cell = lambda s, h: F.count_if((F.col("said") == s) & (F.col("held") == h))
    out = both.agg(cell(1, 1).alias("tp"), cell(1, 0).alias("fp"), cell(0, 0).alias("tn"), cell(0, 1).alias("fn"))
    return out.withColumn("fpr", F.col("fp") / F.greatest(F.col("fp") + F.col("tn"), F.lit(1))).withColumn("fdr", F.col("fp") / F.greatest(F.col("fp") + F.col("tp"), F.lit(1)))


def stragglers(seconds: np.ndarray, threshold: float) -> dict[str, float]:
    """Mean of the five slowest tasks, and the share of tasks under a threshold."""
    s = np.sort(np.asarray(seconds, float))
    return {"top5_mean_s": float(s[-5:].mean()) if len(s) else 0.0, "share_under": float((s < threshold).mean()) if len(s) else 1.0}


def straggler_profile(q: DataFrame, tt: TiledTable, threshold: float, local: str = "auto") -> dict[str, float]:
    """stragglers() of the tiles' local joins as their tasks timed them: a row a tile comes here."""
    return stragglers(np.array([r["seconds"] for r in tile_times(q, tt, local).select("seconds").collect()]), threshold)


def speed_up(baseline_s: float, engine_s: float) -> float:
    return baseline_s / max(engine_s, 1e-9)
