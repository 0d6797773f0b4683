"""Balanced label propagation: linked documents move towards their neighbours' shards under quotas.

Links are hyperedges: documents that share a hub (by default, equal texts). In each round every hub tells
how many bytes it has in each shard, each linked document asks for the shard where its neighbours
have most, and the moves asked between each pair of shards are cut to what capacity allows. Only linked documents
count against capacity, as unlinked ones make room in the end. Moves of small hubs are taken or left whole, those of
hubs that are large against a shard document by document. Rounds go on until none is asked for, or no longer help. A
last pass evens the sizes out: over-full shards give their smallest unlinked documents to the others.

The rounds join tables of linked documents and hubs; the driver sees one row per pair of shards only.

Cases: a null text has no bytes and shares no link; empty texts are equal texts; ties of
shards go to one told by a hash of the hub; repeated rows are documents of their own; an empty table gives no rows;
other columns of the input are left alone, whatever their names.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.llm.ranks import ranked
from skewtile.llm.scratch import settle

SHARDS, ROUNDS, SLACK, HEAVY = 8, 4, 0.02, 0.02


def quotas(load: np.ndarray, asked: np.ndarray, capacity: float) -> np.ndarray:
    """The largest scaled-down moves between shards that leave no shard over capacity, if it wasn't before."""
    moves = asked.astype(float).copy()
    for _ in range(200):
        into, out = moves.sum(0), moves.sum(1)
        over = load + into - out - np.maximum(capacity, load)
        if (over <= 1e-6 * capacity).all():
            break
        moves *= np.where(over > 0, np.maximum(0, 1 - over / np.maximum(into, 1e-9)), 1.0)
    return moves


def _proposals(state: DataFrame, links: DataFrame, n_shards: int, heavy: float) -> DataFrame:
    """_row, size, shard, goal, tie: the moves asked for; tie is shared by the documents of a small hub."""
    at = links.join(state, "_row")
    per_hub = at.groupBy("hub").agg(*(F.sum(F.when(F.col("shard") == s, F.col("size")).otherwise(0)).alias(f"b{s}") for s in range(n_shards)))
    votes = per_hub.select(F.col("hub").alias("_hub"), F.array(*(f"b{s}" for s in range(n_shards))).alias("votes"))
    asked = at.join(votes, F.col("hub") == F.col("_hub"))
    total = F.aggregate("votes", F.lit(0).cast("long"), lambda a, x: a + x)
    asked = asked.groupBy("_row").agg(
        F.first("size").alias("size"), F.first("shard").alias("shard"),
        F.array(*(F.sum(F.element_at("votes", s + 1)) for s in range(n_shards))).alias("votes"),
        F.max(total).alias("total"), F.min("hub").alias("hub"), F.first("h").alias("h"),
    )
    best = F.array_max("votes")
    turn = F.pmod(F.xxhash64("hub"), F.lit(n_shards)).cast("int")  # the shard from which the search for the best starts
    turned = F.concat(F.slice("votes", turn + 1, n_shards - turn), F.slice("votes", F.lit(1), turn))
    goal = F.pmod(F.array_position(turned, best) - 1 + turn, F.lit(n_shards)).cast("int")
    own = F.element_at("votes", F.col("shard") + 1)
    asked = asked.withColumn("goal", goal).where((own < best) | (F.col("goal") != F.col("shard")))
    return asked.select("_row", "size", "shard", "goal", F.when(F.col("total") > heavy, F.xxhash64("h")).otherwise(F.xxhash64("hub")).alias("tie"))


def _load(state: DataFrame, n_shards: int) -> np.ndarray:
    load = np.zeros(n_shards)
    for r in state.groupBy("shard").agg(F.sum("size").alias("b")).collect():  # n_shards rows
        load[r["shard"]] = r["b"]
    return load


def propagate(nodes: DataFrame, links: DataFrame, n_shards: int = SHARDS, rounds: int = ROUNDS, slack: float = SLACK) -> DataFrame:
    """nodes: (_row, h, size, shard), h a hash that tells documents apart; links: (_row, hub). Returns nodes with the shards after the
    rounds, and linked. Rounds end when no move is asked for, or when `rounds` of them in a row haven't brought the bytes asked to move down."""
    linked = links.select(F.col("_row").alias("_linked")).distinct()
    nodes = nodes.join(linked, F.col("_row") == F.col("_linked"), "left").select("_row", "h", "size", "shard", F.col("_linked").isNotNull().cast("int").alias("linked"))
    nodes = settle(nodes, "shards")
    capacity = _load(nodes, n_shards).sum() / n_shards * (1 + slack)
    state = nodes.where("linked = 1").select("_row", "h", "size", "shard")
    least, waited, k = np.inf, 0, 0
    while True:
        asked = settle(_proposals(state, links, n_shards, HEAVY * capacity), "asked")
        wanted = np.zeros((n_shards, n_shards))
        for r in asked.groupBy("shard", "goal").agg(F.sum("size").alias("b")).collect():  # n_shards squared rows
            wanted[r["shard"], r["goal"]] = r["b"]
        waited = 0 if wanted.sum() < 0.99 * least else waited + 1
        least = min(least, wanted.sum())
        if not wanted.any() or waited >= rounds:
            break
        share = quotas(_load(state, n_shards), wanted, capacity) / np.maximum(wanted, 1)
        table = F.array(*(F.lit(float(x)) for x in share.ravel()))
        luck = F.pmod(F.xxhash64("tie", F.lit(k)), F.lit(1 << 20)) / F.lit(float(1 << 20))
        moved = asked.where(luck < F.element_at(table, F.col("shard") * n_shards + F.col("goal") + 1)).select("_row", F.col("goal").alias("_goal"))
        state = settle(state.join(moved, "_row", "left").select("_row", "h", "size", F.coalesce("_goal", "shard").alias("shard")), "shards")
        k += 1
    return nodes.where("linked = 0").unionByName(state.withColumn("linked", F.lit(1)))


def even_out(state: DataFrame, n_shards: int = SHARDS) -> DataFrame:
    """state: (_row, h, size, shard, linked). Moves the fewest small unlinked documents that make the sizes near equal."""
    load = _load(state, n_shards)
    goal = load.sum() / n_shards
    order = [F.col("linked").desc(), F.col("size").desc(), "h"]
    summed = ranked(state, "shard", order, "_rank", "size", "_before")
    stays = F.col("_before") + F.col("size") <= F.lit(float(goal))
    kept = summed.where(stays).select("_row", "h", "size", "shard", "linked")
    pool = summed.where(~stays).select("_row", "h", "size", "linked", F.lit(0).alias("_all"))
    kept_load = np.zeros(n_shards)
    for r in summed.where(stays).groupBy("shard").agg(F.sum("size").alias("b")).collect():  # n_shards rows
        kept_load[r["shard"]] = r["b"]
    room = np.maximum(0, goal - kept_load)
    upto = np.cumsum(room) * (load.sum() - kept_load.sum()) / max(room.sum(), 1e-9)
    dealt = ranked(pool, "_all", [F.col("size").desc(), "h"], "_rank", "size", "_before")
    middle = F.col("_before") + F.col("size") / 2
    shard = F.lit(n_shards - 1)
    for s in reversed(range(n_shards - 1)):
        shard = F.when(middle < float(upto[s]), s).otherwise(shard)
    return kept.unionByName(dealt.select("_row", "h", "size", shard.cast("int").alias("shard"), "linked"))


def equal_text_links(rows: DataFrame) -> DataFrame:
    """(_row, hub) of the rows whose text another row has too."""
    hubs = rows.where("text_key is not null").groupBy("text_key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("text_key").alias("hub"))
    return rows.join(hubs, F.col("text_key") == F.col("hub")).select("_row", "hub")


def shard_documents(docs: DataFrame, n_shards: int = SHARDS, rounds: int = ROUNDS, hubs: DataFrame | None = None) -> DataFrame:
    """doc_id, size, text_crc32, text_key, shard, slot: every document in a shard, sizes in bytes near equal, slots
    gapless from 0 within each shard. hubs: (doc_id, hub long) of other links than equal texts, such as classes of near copies."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(
        "doc_id",
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.when(F.col("text").isNotNull(), F.xxhash64(text, F.octet_length(text))).alias("text_key"),
        F.xxhash64("doc_id", text).alias("h"),
        F.monotonically_increasing_id().alias("_row"),
    )
    rows = settle(rows, "documents")
    links = equal_text_links(rows) if hubs is None else rows.join(hubs.select(F.col("doc_id").alias("_doc"), "hub").distinct(), F.col("doc_id") == F.col("_doc")).select("_row", "hub")
    links = settle(links, "links")
    start = rows.select("_row", "h", "size", F.pmod("h", F.lit(n_shards)).cast("int").alias("shard"))
    state = propagate(start, links, n_shards, rounds)
    for _ in range(2):  # the second pass evens out what the first one's borders left
        state = even_out(settle(state, "shards"), n_shards)
    placed = rows.join(state.select("_row", "shard"), "_row")
    return ranked(placed, "shard", ["h", "_row"], "slot").drop("_row", "h")


def cut_bytes(sharded: DataFrame) -> DataFrame:
    """One row: bytes of documents whose text another one has too, those of them outside their hub's fullest shard, and the largest and
    smallest shard's bytes."""
    hub = sharded.where("text_key is not null").groupBy("text_key", "shard").agg(F.sum("size").alias("b"), F.count(F.lit(1)).alias("n"))
    hub = hub.groupBy("text_key").agg((F.sum("b") - F.max("b")).alias("cut"), F.sum("b").alias("b"), F.sum("n").alias("n")).where("n > 1")
    hub = hub.agg(F.coalesce(F.sum("b"), F.lit(0)).alias("linked_bytes"), F.coalesce(F.sum("cut"), F.lit(0)).alias("cut_bytes"))
    sizes = sharded.groupBy("shard").agg(F.sum("size").alias("b")).agg(F.max("b").alias("most_bytes"), F.min("b").alias("least_bytes"))
    return hub.join(sizes)
