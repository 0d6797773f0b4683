"""N-gram Jaccard self-join by a token-group matrix.

Documents become sets of hashed word shingles; equal sets are one class. Classes are partitioned into
groups of similar ones, each group keeps the union of its tokens, a query class's overlap with that
union bounds its overlap with every member, and only groups whose bound reaches the least overlap that a link
needs are opened and compared member by member. No pair that could link is left out:

* a link needs an overlap of t times the larger set at least, so two linked sets share the first tokens of their overlap among
  the first tokens of each, in one order of all tokens: classes that share fewer of those with all others are left out;
* of the others, those are left out whose tokens that any other one has are fewer than a link needs:
  this is the bound against the union of all other groups;
* two sets of sizes x <= y that link differ in at most r(x + y) tokens, r = (1 - t) / (1 + t), and y <= x / t;
* token space is cut into m ranges of hash values, m above that difference, for each band of sizes, so two linked sets
  of neighbouring bands agree on at least one whole range; a signature hashes one range's tokens;
* at least the slack of those ranges agree, of which as many may be empty as the class has gaps: classes that share fewer signatures with
  all others than the slack less the gaps, or none, are left out;
* signatures that two of the rest share name the groups which a group's classes must be tried on. Ranges empty on both sides
  count as agreement too: classes with so many empty ranges that those alone might agree write them as well.

Copies are folded into their class before any comparison. A token that many classes of a task have leaves the task once, so no
frequent token gathers its documents. Groups and the query blocks sent to them are bounded in tokens and classes, however many classes look alike.

Cases: A-Z fold to a-z; null and empty texts have no shingles and link with nothing; texts
shorter than a shingle count as one; rows of one doc_id are one document (rows with other texts under it are linked to it); a
null doc_id stays alone; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.llm import tokens as tk
from skewtile.llm.components import components
from skewtile.llm.runs import bounded_runs, edges
from skewtile.llm.scratch import drop_settled, settle, with_ids

GROUP_TOKENS, GROUP_CLASSES, QUERY_TOKENS, QUERY_CLASSES, EXPAND = 60_000, 256, 200_000, 512, 1 << 21
PAIRS, BLOCK_TOKENS = 1 << 20, 1 << 21
"""Pairs of groups that a task holds, and tokens that it combines, at a time."""
BROADCAST_IDS = 1 << 20
"""Ids of documents to read again that may be broadcast (8 MB); more are joined by a shuffle."""
_S1, _S2, _S3 = (tk.U(x) for x in (0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3))


@dataclass(frozen=True)
class Similarity:
    """Links two sets when 100 * intersection >= percent * union; shingles of `words` words."""

    words: int = 5
    percent: int = 80

    def band(self, n: int) -> tuple[int, int]:
        """(number, largest size) of the size band of n."""
        i, low = 0, 1
        while True:
            high = low * 100 // self.percent
            if n <= high:
                return i, high
            i, low = i + 1, high + 1

    def ranges(self, largest: int) -> tuple[int, int]:
        """(ranges of token space, slack) for sets of up to `largest` tokens: ranges - slack differences at most."""
        d = 2 * largest * (100 - self.percent) // (100 + self.percent)
        slack = 1 if d == 0 else 3 + d // 10
        return d + slack, slack

    def needed(self, x, y):
        """The least intersection of linked sets of sizes x and y."""
        return -(-self.percent * (x + y) // (100 + self.percent))

    def first_tokens(self, n: int) -> tuple[int, int]:
        """(tokens of a set of n, in order, that are tried first; how many of them any set that links with it has among its own)."""
        least = -(-self.percent * n // 100)
        return min(n, n - least + max(1, n // 10)), max(1, least // 10)


def shingle_sets(batch: pa.RecordBatch, k: int) -> Iterator[tuple[int, np.ndarray]]:
    """(row, sorted distinct shingle hashes) of each text with a word."""
    raw, off = tk.text_buffer(batch.column("text"))
    starts, ends, first = tk.word_spans(raw, off)
    words = tk.word_hashes(raw, starts, ends, lower=True)
    grams = tk.gram_hashes(words, k)
    for i in range(batch.num_rows):
        a, b = first[i], first[i + 1]
        if b - a >= k:
            yield i, np.unique(grams[a : b - k + 1])
        elif b > a:
            yield i, tk.gram_hashes(words[a:b], int(b - a)) ^ tk.U(int(_S3) * int(b - a) % 2**64)


def signatures(toks: np.ndarray, sim: Similarity) -> tuple[np.ndarray, int]:
    """The signatures of a set, and how many of them any set that links with it has too, at least."""
    n = len(toks)
    number, high = sim.band(n)
    out, need = [], []
    value = tk.mix(toks ^ _S1)
    for band, largest in ((number, high), (number + 1, sim.band(high + 1)[1])):
        m, slack = sim.ranges(largest)
        at = ((toks >> tk.U(32)) * tk.U(m)) >> tk.U(32)
        cut = np.append(0, np.flatnonzero(at[1:] != at[:-1]) + 1)
        place = at[cut] * _S2 + tk.U((band + 1) * int(_S3) % 2**64)
        out.append(tk.mix(np.add.reduceat(value, cut) + place))
        gaps = m - len(cut)
        need.append(max(1, slack - gaps))  # a partner with fewer gaps than the slack writes no empty ranges
        if gaps >= slack:
            empty = np.setdiff1d(np.arange(m, dtype=np.uint64), at[cut])
            out.append(tk.mix(_S1 ^ (empty * _S2 + tk.U((band + 1) * int(_S3) % 2**64))))
    return np.concatenate(out), min(need)


def _sketch(sim: Similarity):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in tk.slices(whole, "text"):
                n = np.zeros(b.num_rows, np.int64)
                k1, k2 = np.zeros(b.num_rows, np.uint64), np.zeros(b.num_rows, np.uint64)
                first = [np.zeros(0, np.uint64)] * b.num_rows
                for i, toks in shingle_sets(b, sim.words):
                    n[i], k1[i], k2[i] = len(toks), tk.mix(toks ^ _S2).sum(), tk.mix(toks ^ _S3).sum()
                    first[i] = toks[: sim.first_tokens(len(toks))[0]]
                at = pa.array(np.append(0, np.cumsum([len(s) for s in first])), pa.int32())
                flat = pa.array(np.concatenate(first).view(np.int64))
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id"), pa.array(n), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), pa.ListArray.from_arrays(at, flat)],
                    ["doc_id", "n_shingles", "k1", "k2", "first"],
                )

    return run


def _combined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(tok, n, cls) of batches (cls, toks): a token that one class of a block has, with n = 0; one that several have, once, with
    n = -1; and for each class how many of its tokens are of the latter kind, under its own hash, with that n."""

    def flush(toks: np.ndarray, cls: np.ndarray) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((cls, toks))
        toks, cls = toks[order], cls[order]
        new = np.append(True, (toks[1:] != toks[:-1]) | (cls[1:] != cls[:-1]))
        toks, cls = toks[new], cls[new]
        at = edges(toks)
        many = np.repeat(np.diff(at) > 1, np.diff(at))
        who, n = np.unique(cls[many], return_counts=True)
        once = at[:-1][np.diff(at) > 1]
        own = tk.mix(who.view(np.uint64) ^ _S1).view(np.int64)
        cols = (np.concatenate(x) for x in ((toks[~many], toks[once], own), (np.zeros((~many).sum(), np.int64), np.full(len(once), -1), n), (cls[~many], cls[once], who)))
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["tok", "n", "cls"])

    held, room = [], 0
    for whole in batches:
        for i in range(0, whole.num_rows, 1024):
            b = whole.slice(i, 1024)
            sets = b.column("toks")
            size = np.diff(sets.offsets.to_numpy())
            held.append((sets.flatten().to_numpy(), np.repeat(b.column("cls").to_numpy(), size)))
            room += int(size.sum())
            if room >= BLOCK_TOKENS:
                yield from flush(*(np.concatenate(x) for x in zip(*held)))
                held, room = [], 0
    if room:
        yield from flush(*(np.concatenate(x) for x in zip(*held)))


def _credits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(cls, has): tokens that a class shares with another one; rows come sorted by (tok, n, cls)."""
    common, lone = False, None
    for (tok, n, cls), piece in bounded_runs(batches, ["tok", "n", "cls"]):
        passed = n > 0
        out = [(cls[passed], n[passed])]
        tok, n, cls = tok[~passed], n[~passed], cls[~passed]
        if piece < 0:
            if len(tok):
                new = np.append(True, (tok[1:] != tok[:-1]) | (cls[1:] != cls[:-1]) | (n[1:] != n[:-1]))
                tok, n, cls = tok[new], n[new], cls[new]
                at = edges(tok)
                shared_here = np.repeat((np.diff(at) > 1) | (n[at[:-1]] < 0), np.diff(at)) & (n == 0)
                out.append((cls[shared_here], np.ones(shared_here.sum(), np.int64)))
        else:
            if piece == 0:
                common, lone = False, None
            common |= bool((n < 0).any())
            cls = cls[n == 0]
            cls = cls[np.append(True, cls[1:] != cls[:-1])] if len(cls) else cls
            if lone is not None and len(cls) and cls[0] == lone:
                cls = cls[1:]
            if lone is not None and not common and len(cls):
                common = True
                out.append((np.array([lone]), np.ones(1, np.int64)))
            if len(cls):
                common |= len(cls) > 1
                lone = cls[-1]
                if common:
                    out.append((cls, np.ones(len(cls), np.int64)))
        who, has = (np.concatenate(x) for x in zip(*out))
        if len(who):
            who, code = np.unique(who, return_inverse=True)
            yield pa.RecordBatch.from_arrays([pa.array(who), pa.array(np.bincount(code, weights=has).astype(np.int64))], ["cls", "has"])


def shared_tokens(sets: DataFrame) -> DataFrame:
    """(cls, has) of sets (cls, toks): the tokens of a class that another class has too, for classes with any. Rows that repeat a class may
    count a token again."""
    rows = sets.mapInArrow(_combined, "tok long, n long, cls long").repartition("tok").sortWithinPartitions("tok", "n", "cls")
    return rows.mapInArrow(_credits, "cls long, has long").groupBy("cls").agg(F.sum("has").alias("has"))


def _range_signatures(sim: Similarity):
    """(doc, need, sigs) of rows (rep, toks)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, 1024):
                b = whole.slice(i, 1024)
                got = [signatures(x.values.to_numpy().view(np.uint64), sim) for x in b.column("toks")]
                at = pa.array(np.append(0, np.cumsum([len(s) for s, _ in got])), pa.int32())
                flat = pa.array(np.concatenate([s for s, _ in got]).view(np.int64))
                yield pa.RecordBatch.from_arrays([b.column("rep"), pa.array([n for _, n in got], pa.int32()), pa.ListArray.from_arrays(at, flat)], ["doc", "need", "sigs"])

    return run


def _group_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(grp, target), target < grp: groups of which some members share a signature; rows come distinct and sorted by (sig, grp). PAIRS
    pairs are held at a time; of an unfinished run only the groups seen are carried."""
    before, held, room = np.zeros(0, np.int64), [], 0

    def flush() -> pa.RecordBatch:
        pairs = np.unique(np.concatenate(held), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["grp", "target"])

    def meet(low: np.ndarray, high: np.ndarray) -> Iterator[pa.RecordBatch]:
        nonlocal held, room
        held.append(np.stack([high, low], 1))
        room += len(low)
        if room >= PAIRS:
            yield flush()
            held, room = [], 0

    for (sig, grp), piece in bounded_runs(batches, ["sig", "grp"]):
        known = before if piece > 0 else before[:0]
        for i in range(0, len(known), max(1, PAIRS // len(grp))):
            part = known[i : i + max(1, PAIRS // len(grp))]
            yield from meet(np.tile(part, len(grp)), np.repeat(grp, len(part)))
        if piece >= 0:
            before = np.append(known, grp)
        at, step = np.arange(len(sig)), 1
        while len(at := at[at + step < len(sig)]) and len(at := at[sig[at + step] == sig[at]]):  # pairs that stand `step` apart
            yield from meet(grp[at], grp[at + step])
            step += 1
    if room:
        yield flush()


def _tokens(sim: Similarity):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in tk.slices(whole, "text"):
                rows, sets = [], []
                for i, toks in shingle_sets(b, sim.words):
                    rows.append(i)
                    sets.append(toks.view(np.int64))
                at = pa.array(np.append(0, np.cumsum([len(s) for s in sets])), pa.int32())
                toks = pa.ListArray.from_arrays(at, pa.array(np.concatenate(sets) if sets else np.zeros(0, np.int64)))
                yield pa.RecordBatch.from_arrays([b.column("doc_id").take(pa.array(rows, pa.int64())), toks], ["rep", "toks"])

    return run


def _labels(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest reachable node of each of n nodes under edges a-b."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def open_group(ids: np.ndarray, is_member: np.ndarray, weight: np.ndarray, sets: list[np.ndarray], own: np.ndarray, sim: Similarity) -> tuple[list, list, list, dict]:
    """Compares the query classes of one block with one group's members (repeated ids count once). Returns (node, smallest linked node, links)
    of every linked class, and counters of what was bounded and opened. own: the query is itself a member."""
    members, queries = (np.flatnonzero(x)[np.unique(ids[x], return_index=True)[1]] for x in (is_member, ~is_member))
    size = np.array([len(s) for s in sets], np.int64)
    flat = np.concatenate([sets[i] for i in members])
    of = np.repeat(np.arange(len(members)), size[members])
    order = np.argsort(flat, kind="stable")
    union, first = np.unique(flat[order], return_index=True)
    postings, first = of[order], np.append(first, len(flat))
    least = size[members].min()
    pairs_q, pairs_m, opened = [], [], 0
    at = 0
    while at < len(queries):
        block, room = [], 0
        while at < len(queries) and (not block or room + size[queries[at]] * len(members) <= EXPAND):
            block.append(queries[at])
            room += size[queries[at]] * len(members)
            at += 1
        toks = np.concatenate([sets[q] for q in block])
        who = np.repeat(np.arange(len(block)), size[block])
        place = np.searchsorted(union, toks)
        place[place == len(union)] = 0
        hit = union[place] == toks
        bound = np.bincount(who[hit], minlength=len(block))
        n = size[block]
        worth = bound >= sim.needed(n, np.maximum(least, -(-sim.percent * n // 100)))
        opened += int(worth.sum())
        use = hit & worth[who]
        place, who = place[use], who[use]
        many = first[place + 1] - first[place]
        if not many.sum():
            continue
        entry = np.repeat(first[place] - np.append(0, np.cumsum(many)[:-1]), many) + np.arange(many.sum())
        overlap = np.bincount(np.repeat(who, many) * len(members) + postings[entry], minlength=len(block) * len(members)).reshape(len(block), len(members))
        linked = overlap >= sim.needed(n[:, None], size[members][None, :])
        linked &= ids[block][:, None] != ids[members][None, :]
        q, m = np.nonzero(linked)
        pairs_q.append(np.array(block)[q])
        pairs_m.append(members[m])
    if not pairs_q:
        return [], [], [], {"bounded": len(queries), "opened": opened}
    a, b = np.concatenate(pairs_q), np.concatenate(pairs_m)
    links = np.bincount(a, weights=weight[b], minlength=len(ids))
    across = ~own[a]
    links += np.bincount(b[across], weights=weight[a[across]], minlength=len(ids))
    values, code = np.unique(ids, return_inverse=True)
    root = values[_labels(code[a], code[b], len(values))][code]
    linked = np.flatnonzero((links > 0) | (root != ids))
    return ids[linked].tolist(), root[linked].tolist(), links[linked].astype(np.int64).tolist(), {"bounded": len(queries), "opened": opened}


def _open(sim: Similarity):
    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        get = lambda c: table.column(c).to_numpy()
        sets = [x.values.to_numpy().view(np.uint64) for x in table.column("toks")]
        member = get("member").astype(bool)
        out = ([], [], [])
        if member.any() and not member.all():
            out = open_group(get("rep"), member, get("weight"), sets, get("own").astype(bool), sim)[:3]
        return pa.table([pa.array(x, pa.int64()) for x in out], ["node", "root", "links"])

    return run


def _few(ids: DataFrame) -> DataFrame:
    """Ids to join with: broadcast when they are counted and few, else left to a shuffle."""
    ids = settle(ids, "ids")
    return F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids


def _classes(sketch: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rep, cls, n, weight) of each class of equal sets, and (doc_id, n_shingles, rep, weight) of each document."""
    light = sketch.select("doc_id", "n_shingles", "k1", "k2")
    classes = light.where("n_shingles > 0").groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.countDistinct("doc_id").alias("weight"), F.first("n_shingles").alias("n"))
    classes = settle(classes, "classes")
    told = classes.select(F.col("k1").alias("_k1"), F.col("k2").alias("_k2"), "rep", "weight")
    member = light.join(told, (F.col("k1") == F.col("_k1")) & (F.col("k2") == F.col("_k2")) & (F.col("n_shingles") > 0), "left")
    return classes.select("rep", F.col("k1").alias("cls"), "n", "weight"), settle(member.select("doc_id", "n_shingles", "rep", "weight"), "members")


def join_documents(docs: DataFrame, sim: Similarity = Similarity()) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links, itself included), n_links (documents it links with)."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    sketch = settle(rows.mapInArrow(_sketch(sim), "doc_id long, n_shingles long, k1 long, k2 long, first array<long>"), "sketch")
    classes, member = _classes(sketch)
    t = sim.percent
    least = f"(({t} * n + 99) div 100)"

    tried = shared_tokens(sketch.where("n_shingles > 0 AND doc_id is not null").select(F.col("k1").alias("cls"), F.col("first").alias("toks")))
    live = classes.join(tried, "cls").where(f"rep is not null AND has >= greatest(1, {least} div 10)")
    sets = settle(rows.join(_few(live.select(F.col("rep").alias("_w"))), F.col("doc_id") == F.col("_w"), "left_semi").mapInArrow(_tokens(sim), "rep long, toks array<long>"), "sets")
    drop_settled(sketch)
    size = classes.groupBy("rep").agg(F.max("n").alias("n"), F.min("n").alias("n_least"), F.max("weight").alias("weight"))  # several texts may have one doc_id
    common = shared_tokens(sets.select(F.col("rep").alias("cls"), "toks")).withColumnRenamed("cls", "rep")
    alive = common.join(size, "rep").withColumn("n", F.col("n_least")).where(F.expr(f"has >= ({t} * (n + {least}) + {99 + t}) div {100 + t}"))
    sets = settle(sets.join(_few(alive.select(F.col("rep").alias("_w"))), F.col("rep") == F.col("_w"), "left_semi"), "sets")

    signed = sets.mapInArrow(_range_signatures(sim), "doc long, need int, sigs array<long>").select("doc", "need", F.explode("sigs").alias("sig"))
    signed = settle(signed, "signatures")
    firsts = signed.groupBy("sig").agg(F.min("doc").alias("family"), F.max("doc").alias("_last")).where("family < _last").select(F.col("sig").alias("_sig"), "family")
    lists = settle(signed.join(firsts, F.col("sig") == F.col("_sig")).select("sig", "doc", "need", "family"), "lists")
    family = lists.groupBy("doc").agg(F.countDistinct("sig").alias("has"), F.min("need").alias("need"), F.min("family").alias("family")).where("has >= need")
    family = family.join(size, F.col("doc") == F.col("rep")).select("doc", "family", "n", "weight")
    family = settle(family.withColumn("bin", F.floor(F.log2("n") * 8).cast("int")), "family")
    bins = family.groupBy(F.col("family").alias("_f"), F.col("bin").alias("_b")).agg(F.greatest(F.ceil(F.sum("n") / GROUP_TOKENS), F.ceil(F.count(F.lit(1)) / GROUP_CLASSES)).alias("parts"))
    grouped = family.join(bins, (F.col("family") == F.col("_f")) & (F.col("bin") == F.col("_b")))
    grouped = grouped.withColumn("grp", F.xxhash64("family", "bin", F.pmod(F.xxhash64("doc"), F.col("parts"))))
    grouped = settle(grouped.select("doc", "grp", "n", "weight"), "groups")

    labelled = lists.join(grouped.select(F.col("doc").alias("_d"), "grp"), F.col("doc") == F.col("_d")).select("sig", "grp").distinct()
    pairs = labelled.repartition("sig").sortWithinPartitions("sig", "grp").mapInArrow(_group_pairs, "grp long, target long").distinct()
    own = grouped.select("doc", F.col("grp").alias("target"), "n", "weight", F.lit(True).alias("own"))
    tries = own.unionByName(grouped.join(pairs, "grp").select("doc", "target", "n", "weight", F.lit(False).alias("own")))
    tries = settle(tries, "tries")
    blocks = tries.groupBy(F.col("target").alias("_t")).agg(F.greatest(F.ceil(F.sum("n") / QUERY_TOKENS), F.ceil(F.count(F.lit(1)) / QUERY_CLASSES)).alias("blocks"))
    asking = tries.join(blocks, F.col("target") == F.col("_t")).select(
        "doc", "target", F.pmod(F.xxhash64("doc"), F.col("blocks")).alias("block"), "weight", "own", F.lit(False).alias("member"))
    holding = grouped.join(blocks, F.col("grp") == F.col("_t")).select(
        "doc", F.col("grp").alias("target"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"), "weight", F.lit(True).alias("own"), F.lit(True).alias("member"))
    work = asking.unionByName(holding)

    opened = work.join(sets, F.col("doc") == F.col("rep")).select("target", "block", "rep", "weight", "own", "member", "toks")
    found = settle(opened.groupBy("target", "block").applyInArrow(_open(sim), "node long, root long, links long"), "links")

    part = components(found.select(F.col("node").alias("u"), F.col("root").alias("v")))
    links = found.groupBy(F.col("node").alias("_node")).agg(F.sum("links").alias("links"))
    out = member.join(part, F.col("rep") == F.col("node"), "left").join(links, F.col("rep") == F.col("_node"), "left")
    return out.select(
        "doc_id", "n_shingles",
        F.coalesce("component", "rep", "doc_id").alias("component_id"),
        (F.coalesce(F.col("weight") - 1, F.lit(0)) + F.coalesce("links", F.lit(0))).alias("n_links"),
    )


def one_of_each(docs: DataFrame, sim: Similarity = Similarity()) -> DataFrame:
    """The documents with one left of each component (that with the smallest doc_id), rows and columns as they were."""
    gone = join_documents(docs, sim).where("doc_id <> component_id").select("doc_id").distinct()
    return with_ids(docs, gone, "left_anti")
