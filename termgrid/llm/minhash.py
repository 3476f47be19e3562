"""Near-duplicate documents by bottom-k sketches of one hash function."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import shipped
from .common import broadcast_below, checkpointed, components, unused
from .shingles import list_array, mixed, shingle_sets

#: Smallest hashes kept for a document; chance that a similar pair falls below the sketch filter.
SKETCH, MISS = 32, 1e-9
#: Lists of at most so many members are compared member by member; larger ones through leaders.
SMALL_LIST = 12
#: Documents and shingles of a part of a block comparison; values held by more documents of a block are compared as a
#: matrix, so many at once.
BLOCK, BLOCK_VALUES, DENSE, COLUMNS = 2048, 1 << 19, 16, 2048
#: Largest table of ids that is broadcast.
ID_ROWS = 1_000_000


def least_overlap(similarity: float, k: int = SKETCH, miss: float = MISS) -> int:
    """Least number of common values among the k smallest of a union that a pair of this similarity keeps, but for ``miss``."""
    below = 0.0
    for c in range(k + 1):
        below += math.comb(k, c) * similarity**c * (1 - similarity) ** (k - c)
        if below > miss:
            return max(1, c)
    return k


def sketches(docs: DataFrame, width: int, k: int = SKETCH) -> DataFrame:
    """``(doc_id, n, sig_a, sig_b, sketch)``: set size, two hashes of the whole set, its k smallest values."""

    def run(batches):
        for batch in batches:
            n, a, b, s = [], [], [], []
            for x in shingle_sets(batch.column(1), width):
                n.append(len(x))
                a.append(int(x.sum(dtype=np.int64)))
                b.append(int(np.bitwise_xor.reduce(mixed(x.view(np.uint64) + np.uint64(1))).view(np.int64)) if len(x) else 0)
                s.append(x[:k])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), list_array(s)], ["doc_id", "n", "sig_a", "sig_b", "sketch"])

    return shipped(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n long, sig_a long, sig_b long, sketch array<long>")


def full_sets(docs: DataFrame, width: int) -> DataFrame:
    """``(id, members)``: every shingle hash of each whole text."""

    def run(batches):
        for batch in batches:
            ids, part = [], []
            for i, x in zip(batch.column(0), shingle_sets(batch.column(1), width), strict=True):
                ids.append(i.as_py())
                part.append(x)
                if sum(map(len, part)) > 500_000:
                    yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), list_array(part)], ["id", "members"])
                    ids, part = [], []
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), list_array(part)], ["id", "members"])

    return shipped(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "id long, members array<long>")


def inverted_lists(reps: DataFrame, need: int, k: int) -> DataFrame:
    """``(v, id, score)``: for each class its rarest retained values, enough to meet every class with ``need`` of k in common.

    Two sketches with ``need`` common values share one of the (shared - need + 1) rarest shared values of each. A class with
    fewer shared values than that is in no list. ``score`` is high for classes whose values many others hold.
    """
    values = reps.select("id", F.size("sketch").alias("m"), F.explode("sketch").alias("v"))
    often = values.groupBy("v").agg(F.count("*").alias("df")).where("df > 1")
    held = values.join(often, "v").groupBy("id", "m").agg(F.sort_array(F.collect_list(F.struct("df", "v"))).alias("vs"), F.sum("df").alias("score"))
    least = F.ceil(F.col("m") * F.lit(need) / F.lit(k)).cast("int")
    return held.where(F.size("vs") >= least).select("id", "score", F.explode(F.slice("vs", 1, F.size("vs") - least + 1)).alias("x")).select("x.v", "id", "score")


def _estimated(pairs: DataFrame, reps: DataFrame, need: int, k: int, percent: int) -> DataFrame:
    """Pairs of fitting sizes whose common values among the k smallest of the union reach the least overlap."""
    side = lambda s: reps.select(F.col("id").alias(s), F.col("n").alias(f"n{s}"), F.col("sketch").alias(f"s{s}"))
    both = pairs.join(side("b"), "b").join(side("a"), "a").where(100 * F.least("na", "nb") >= percent * F.greatest("na", "nb"))
    union = F.slice(F.sort_array(F.array_union("sa", "sb")), 1, k)
    return both.where(F.size(F.array_intersect(F.array_intersect("sa", "sb"), union)) * k >= need * F.size(union)).select("a", "b").distinct()


def _confirmed(pairs: DataFrame, docs: DataFrame, width: int, percent: int) -> DataFrame:
    """Pairs whose full sets have ``100 * common >= percent * union``."""
    ids = checkpointed(pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct())
    sets = checkpointed(full_sets(docs.join(broadcast_below(ids, ID_ROWS), "doc_id", "left_semi"), width).dropDuplicates(["id", "members"]))
    side = lambda s: sets.select(F.col("id").alias(s), F.col("members").alias(f"m{s}"))
    both = pairs.join(side("b"), "b").join(side("a"), "a").withColumn("common", F.size(F.array_intersect("ma", "mb")))
    return both.where(100 * F.col("common") >= percent * (F.size("ma") + F.size("mb") - F.col("common"))).select("a", "b")


def links(docs: DataFrame, reps: DataFrame, width: int, percent: int, k: int) -> DataFrame:
    """``(node, component)`` of the classes that are linked to others."""
    need = least_overlap(percent / 100, k)
    lists = checkpointed(inverted_lists(reps, need, k))
    small = lists.groupBy("v").agg(F.count("*").alias("n")).where("n > 1")
    lists = checkpointed(lists.join(small, "v"))
    few = lists.where(F.col("n") <= SMALL_LIST)
    pairs = few.select("v", F.col("id").alias("a")).join(few.select("v", F.col("id").alias("b")), "v").where("a < b").select("a", "b")
    many = lists.where(F.col("n") > SMALL_LIST).select("v", "id", "score")
    # the leader of a long list is the member whose values are the most common: in a group of copies most likely the original
    led = many.groupBy("v").agg(F.max(F.struct("score", "id")).getField("id").alias("b"))
    star = many.select("v", F.col("id").alias("a")).join(led, "v").where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    found = checkpointed(_estimated(pairs.unionByName(star).distinct(), reps, need, k, percent))
    edges = checkpointed(_confirmed(found, docs, width, percent))
    linked = checkpointed(components(edges, "a", "b"))
    # lists that are not one component yet: their documents are looked at with whole sets
    of = many.select("v", "id").join(linked.select(F.col("node").alias("id"), "component"), "id", "left").select("v", "id", F.coalesce("component", "id").alias("comp"))
    rest = checkpointed(_split_lists(of).select("id", "comp").distinct())
    if rest.isEmpty():
        return linked
    sets = full_sets(docs.join(broadcast_below(rest.select(F.col("id").alias("doc_id")), ID_ROWS), "doc_id", "left_semi"), width)
    sets = checkpointed(sets.select("id", "members").distinct().select("id", "members", F.size("members").alias("n")))
    whole = lambda s: inverted_lists(s.select("id", F.col("members").alias("sketch")), percent, 100)
    # far more documents share a passage than can have a partner: the others' values no longer count in the second round
    hopeful = broadcast_below(checkpointed(whole(sets).select("id").distinct()), ID_ROWS)
    left = _split_lists(whole(sets.join(hopeful, "id", "left_semi")).select("v", "id").join(rest, "id"))
    left = checkpointed(left.select("id", "comp", "head").distinct())
    groups = checkpointed(components(left.select(F.col("id").alias("src"), F.col("head").alias("dst"))))
    if groups.isEmpty():
        return linked
    rows = sets.join(rest, "id").join(groups.select(F.col("node").alias("id"), F.col("component").alias("cluster")), "id")
    dealt = _dealt(rows, percent).repartition("cluster", "lo", "hi").sortWithinPartitions("cluster", "lo", "hi")
    more = dealt.select("cluster", "lo", "hi", "own", "id", "comp", "members").mapInArrow(_blocks(percent), "a long, b long")
    return checkpointed(components(edges.unionByName(more), "a", "b"))


def _split_lists(lists: DataFrame) -> DataFrame:
    """Rows ``(v, id, comp)`` of the lists that hold several components, with the list's smallest id as its ``head``."""
    several = lists.groupBy("v").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.min("id").alias("head")).where("lo <> hi").select("v", "head")
    return lists.join(several, "v")


def _dealt(rows: DataFrame, percent: int) -> DataFrame:
    """Rows ``(cluster, id, comp, n, members)`` dealt to blocks ``(lo, hi)`` of two parts each; ``own`` is a row's part.

    Sizes fall into bands so wide that linked sets are in one band or in neighbouring ones, and a band into parts of a
    bounded number of documents and shingles. A part meets the parts of its own band and of the bands beside it only.
    """
    band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(100.0 / percent * 1.0001))).cast("long")
    rows = checkpointed(rows.withColumn("band", band))
    parts = rows.groupBy("cluster", "band").agg(F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n") / BLOCK_VALUES)).cast("long").alias("parts"))
    parts = broadcast_below(checkpointed(parts), ID_ROWS)
    near = lambda by, name: parts.select(F.col("cluster"), (F.col("band") + by).alias("band"), F.col("parts").alias(name))
    rows = rows.join(near(0, "own_parts"), ["cluster", "band"])
    for by, name in ((1, "below"), (-1, "above")):
        rows = rows.join(near(by, name), ["cluster", "band"], "left")
    code = lambda band, part: F.shiftleft(band, 32) + part
    every = lambda band, n: F.when(F.coalesce(n, F.lit(0)) > 0, F.transform(F.sequence(F.lit(0).cast("long"), n - 1), lambda p: code(band, p))).otherwise(F.array().cast("array<bigint>"))
    own = code(F.col("band"), F.pmod(F.xxhash64("id"), F.col("own_parts")))
    beside = F.concat(every(F.col("band"), F.col("own_parts")), every(F.col("band") - 1, F.col("below")), every(F.col("band") + 1, F.col("above")))
    rows = rows.withColumn("own", own).withColumn("with", F.explode(beside))
    return rows.select("cluster", F.least("own", "with").alias("lo"), F.greatest("own", "with").alias("hi"), "own", "id", "comp", "members")


def _common(owner: np.ndarray, value: np.ndarray, left: np.ndarray, right: np.ndarray, n: int) -> np.ndarray:
    """Shared values of each row of ``left`` with each of ``right``: frequent values by matrix products, rare ones pair by pair."""
    _, value, held = np.unique(value, return_inverse=True, return_counts=True)
    order = np.argsort(value, kind="stable")
    owner, value = owner[order], value[order]
    dense = held[value] > DENSE
    common = np.zeros((len(left), len(right)), np.float32)
    at_left, at_right = np.full(n, -1), np.full(n, -1)
    at_left[left], at_right[right] = np.arange(len(left)), np.arange(len(right))
    column = (np.cumsum(held > DENSE) - 1)[value[dense]]
    who = owner[dense]
    for v in range(0, int(column[-1]) + 1 if len(column) else 0, COLUMNS):
        a, b = np.searchsorted(column, (v, v + COLUMNS))
        has = np.zeros((n, COLUMNS), np.float32)
        has[who[a:b], column[a:b] - v] = 1
        common += has[left] @ has[right].T
    who, column = owner[~dense], value[~dense]
    flat = common.reshape(-1)
    for step in range(min(DENSE, len(column))):
        # neighbours at each distance among the holders of one value, in both orders
        a = np.flatnonzero(column[: len(column) - step] == column[step:])
        for x, y in ((who[a], who[a + step]), (who[a + step], who[a])) if step else ((who[a], who[a]),):
            x, y = at_left[x], at_right[y]
            both = (x >= 0) & (y >= 0)
            if both.any():
                cell, times = np.unique(x[both] * len(right) + y[both], return_counts=True)
                flat[cell] += times
    return common


def _blocks(percent: int):
    """Links between documents of different components, for rows sorted by block: a spanning forest for each block."""

    def forest(t: pa.Table) -> pa.RecordBatch:
        n = len(t)
        ids, comp, own, lo, hi = (t[c].to_numpy() for c in ("id", "comp", "own", "lo", "hi"))
        left, right = np.flatnonzero(own == lo[0]), np.flatnonzero(own == hi[0])
        label = np.arange(n)
        if len(left) and len(right) and len(np.unique(comp)) > 1:
            members = t["members"].combine_chunks()
            sizes = np.diff(members.offsets.to_numpy())
            common = _common(np.repeat(np.arange(n), sizes), members.flatten().to_numpy(), left, right, n)
            union = sizes[left][:, None] + sizes[right][None, :] - common
            r, c = np.nonzero((100 * common >= percent * union) & (comp[left][:, None] != comp[right][None, :]))
            r, c = left[r], right[c]
            while len(r):
                before = label.copy()
                low = np.minimum(label[r], label[c])
                np.minimum.at(label, r, low)
                np.minimum.at(label, c, low)
                label = label[label]
                if (label == before).all():
                    break
        some = np.flatnonzero(label != np.arange(n))
        return pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(ids[label[some]])], ["a", "b"])

    def run(batches):
        held, key = [], None
        for batch in batches:
            marks = np.stack([batch.column(c).to_numpy() for c in range(3)], 1)
            edges = [0, *(np.flatnonzero((marks[1:] != marks[:-1]).any(1)) + 1).tolist(), len(marks)]
            for x, y in zip(edges, edges[1:]):
                if x == y:
                    continue
                if held and tuple(marks[x]) != key:
                    yield forest(pa.Table.from_batches(held).combine_chunks())
                    held = []
                key = tuple(marks[x])
                held.append(batch.slice(x, y - x))
        if held:
            yield forest(pa.Table.from_batches(held).combine_chunks())

    return run


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, k: int = SKETCH) -> DataFrame:
    """``doc_id``, ``n_shingles``, ``component_id`` and ``kept`` for each row.

    Documents with equal sets form a class; a class is compared through its smallest id. Candidates share retained values
    (``inverted_lists``), are filtered by the similarity estimated from the sketch of the union, and are confirmed on the
    full sets. A long list is not paired out: its leader is compared with all members. Documents of lists that are then
    still in several components are listed again by their whole sets, where those that share too little with all others
    fall out, and what is left is compared in blocks of similar size, which return a spanning forest. So no link between
    components is lost but with the chance ``MISS`` of the sketch filter, and rows stay in proportion to documents.

    Texts that are null or without words have the size 0 and are alone. Rows with one ``doc_id`` form one node. Rows with
    a null ``doc_id`` link with nothing: their component and ``kept`` are null. Other columns don't matter.
    """
    docs = docs.select("doc_id", "text")
    sk = checkpointed(sketches(docs, width, k))
    full = sk.where("n > 0 and doc_id is not null")
    classes = checkpointed(full.groupBy("n", "sig_a", "sig_b").agg(F.min("doc_id").alias("id")))
    reps = checkpointed(full.select(F.col("doc_id").alias("id"), "n", "sig_a", "sig_b", "sketch").join(classes, ["n", "sig_a", "sig_b", "id"]).select("id", "n", "sketch").distinct())
    same = full.join(classes, ["n", "sig_a", "sig_b"]).select("doc_id", "id")
    comp = links(docs, reps, width, percent, k)
    # a doc_id with several texts is in several classes
    ids = same.join(comp, F.col("id") == F.col("node"), "left").groupBy("doc_id").agg(F.min(F.coalesce("component", "id")).alias("c"))
    out = sk.select("doc_id", F.col("n").alias("n_shingles")).join(ids.select(F.col("doc_id").alias("key"), "c"), F.col("doc_id") == F.col("key"), "left")
    component = F.coalesce("c", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), (component == F.col("doc_id")).alias("kept"))


def one_of_each(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` less all but the first document of each group of near duplicates; null ids stay, repeated rows once."""
    key = unused("near_key", docs)
    judged = near_duplicates(docs, width, percent).where("not kept").select(F.col("doc_id").alias(key)).distinct()
    return docs.join(judged, F.col("doc_id") == F.col(key), "left_anti")
