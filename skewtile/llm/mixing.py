"""Mixing sources to target weights by systematic sampling, in DataFrame functions only.

A document's expected copies are its source's target over its source's size. Documents stand in one
order within their source (by size, then a hash), expected copies are summed along it, one random
offset per source is added, and a document is emitted once for each whole number that the sum
passes on it. The order by size makes the sample follow every size class, so taken sizes come near
the target; copies never pass the rounded-up expectation, which is 3 at most.

Cases: a null text has size 0 and is emitted like others; a null source is a source of its own and
comes last; a source without words has target 0 and takes nothing; repeated rows are documents of
their own, and copies of equal rows are shared among them; an empty table gives no rows; columns named as ours in
the input are ignored by mix_sources and kept by take_copies.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from skewtile.llm.ranks import ranked
from skewtile.llm.scratch import settle

LIMIT = 3
_BLANKS = "\t\n\x0b\x0c\r"


def word_count(text: Column) -> Column:
    flat = F.trim(F.translate(text, _BLANKS, " " * len(_BLANKS)))
    return F.when(F.length(flat) > 0, F.size(F.split(flat, " +"))).otherwise(0).cast("long")


def targets(sizes: DataFrame, weights: tuple[float, ...] = (1, 2, 3), limit: int = LIMIT) -> DataFrame:
    """sizes: (source, source_size). Adds weight and target: shares of the total by weight, filled up to limit times
    the source's size, what is over shared again by weight. Sources go by code point, null last, and get the weights in turn.
    One row per source: the windows here run over sources, never over documents."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    kinds = F.array(*(F.lit(float(w)) for w in weights))
    s = sizes.withColumn("weight", F.element_at(kinds, ((F.row_number().over(by_name) - 1) % len(weights) + 1).cast("int")))
    s = s.withColumn("ratio", limit * F.col("source_size") / F.col("weight"))
    first = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    full = first.rowsBetween(Window.unboundedPreceding, -1)
    rest = first.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.partitionBy()
    # the level at which the sources before this one are full and this and later ones share the rest
    level = (F.sum("source_size").over(everything) - limit * F.coalesce(F.sum("source_size").over(full), F.lit(0))) / F.sum("weight").over(rest)
    s = s.withColumn("level", level)
    s = s.withColumn("level", F.max(F.when(F.col("level") <= F.col("ratio"), F.col("level"))).over(everything))
    return s.select("source", "source_size", "weight", F.least(F.col("level") * F.col("weight"), (limit * F.col("source_size")).cast("double")).alias("target"))


def offset(source: Column, seed: int) -> Column:
    """A number in [0, 1) for each source and seed."""
    told = F.md5(F.concat_ws("\x00", F.lit(str(seed)), F.coalesce(source, F.lit("\x00"))))
    return F.conv(F.substring(told, 1, 8), 16, 10).cast("double") / F.lit(2.0**32)


def _row_key(doc_id: Column, source: Column, text: Column) -> Column:
    """Equal for equal rows, whatever their other columns."""
    return F.xxhash64(doc_id, source, text)


def mix_sources(docs: DataFrame, seed: int = 7, weights: tuple[float, ...] = (1, 2, 3)) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken; one row per document."""
    return _mixed(docs, seed, weights).drop("_tie")


def _mixed(docs: DataFrame, seed: int, weights: tuple[float, ...]) -> DataFrame:
    """mix_sources and each row's key."""
    light = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), _row_key(F.col("doc_id"), F.col("source"), F.col("text")).alias("_tie"))
    light = settle(light, "sizes")  # range partitioning reads its input twice: the texts once only
    place = ranked(light, "source", ["size", F.md5(F.col("doc_id").cast("string")), "_tie"], "rank")
    sizes = place.groupBy("source").agg(F.sum("size").alias("source_size"))
    goal = targets(sizes, weights).select(F.col("source").alias("_source"), "source_size", "target")
    out = place.join(goal, F.col("source").eqNullSafe(F.col("_source")))
    share = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    u = offset(F.col("source"), seed)
    passed = F.floor(u + share * (F.col("rank") + 1)) - F.floor(u + share * F.col("rank"))
    out = out.withColumn("copies", passed.cast("long"))
    return out.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), "_tie")


def take_copies(docs: DataFrame, seed: int = 7, weights: tuple[float, ...] = (1, 2, 3)) -> DataFrame:
    """The mix itself: each document's row as many times as it was emitted. The copies of equal rows are dealt evenly among them, as
    the sample can't tell them apart."""
    plan = _mixed(docs, seed, weights).groupBy(F.col("_tie").alias("_mixed")).agg(F.sum("copies").alias("_copies"), F.count(F.lit(1)).alias("_rows")).where("_copies > 0")
    own = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("_doc"))  # so that no name can clash
    own = own.withColumn("_own", _row_key(F.col("_doc.doc_id"), F.col("_doc.source"), F.col("_doc.text")))
    taken = own.join(plan, F.col("_own") == F.col("_mixed"))
    turn = F.row_number().over(Window.partitionBy("_own").orderBy("_own"))  # the join's own partitioning and order
    taken = taken.withColumn("_turn", turn).withColumn("_times", F.floor(F.col("_copies") / F.col("_rows")) + (F.col("_turn") <= F.col("_copies") % F.col("_rows")).cast("int"))
    taken = taken.where("_times > 0").select("_doc", F.explode(F.sequence(F.lit(1), F.col("_times").cast("int"))).alias("_copy"))
    return taken.select("_doc.*")
