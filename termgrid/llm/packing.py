"""Best-fit packing planned on a histogram of lengths."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..shipping import shipped
from .common import broadcast_below, checkpointed
from .tokens import KEPT, encoder, in_pieces

CAPACITY, END = 2048, 0
#: Parts in which the ranks of one length are counted.
PARTS = 256
#: Rows whose texts become strings at once.
ROWS = 256


def best_fit(histogram: dict[int, int], capacity: int = CAPACITY) -> np.ndarray:
    """Slots for all lengths: rows (length, first rank, first sequence, documents in a sequence, offset), sorted.

    Best fit over counts: lengths descend; each goes to the open sequences with the least room that is enough, as many to
    a sequence as fit, a whole range of sequences at a time, else to new ones. Work and plan depend on the number of
    different lengths and of room sizes, never on that of documents.
    """
    room: list[list[tuple[int, int]]] = [[] for _ in range(capacity + 1)]
    rows, fresh = [], 0
    for length in sorted((x for x in histogram if histogram[x]), reverse=True):
        rank, left, r = 0, histogram[length], length
        while left:
            while r < capacity and not room[r]:
                r += 1
            first, n = room[r].pop() if room[r] else (fresh, -(-left // (capacity // length)))
            if first == fresh:
                r, fresh = capacity, fresh + n
            each = min(r // length, left)
            full = min(n, left // each)
            rows.append((length, rank, first, each, capacity - r))
            if full < n:
                room[r].append((first + full, n - full))
            rest = r - each * length
            if rest:
                room[rest].append((first, full))
            rank, left = rank + full * each, left - full * each
            r = length
    return np.array(rows, np.int64).reshape(-1, 5)[np.lexsort((np.array([x[1] for x in rows], np.int64), np.array([x[0] for x in rows], np.int64)))] if rows else np.zeros((0, 5), np.int64)


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end: int = END, kept: int = KEPT) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32``: each document's ids with the end id, cut into pieces from its end.

    A worker keeps the ids of ``kept`` frequent strings, twice at most.
    """
    tail = int(end).to_bytes(4, "little")

    def run(batches):
        # what earlier stages of this worker have freed
        pa.default_memory_pool().release_unused()
        encode = encoder(tokenizer, kept)
        for batch in (b.slice(k, ROWS) for b in batches for k in range(0, len(b), ROWS)):
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for i, j in in_pieces(texts):
                out = []
                for key, data in zip(ids[i:j], encode.encode(texts[i:j]), strict=True):
                    view = memoryview(data + tail)
                    n = len(view) // 4
                    first = n % capacity or capacity
                    edges = [0, *range(first, n + 1, capacity)]
                    out += [(key, k, a, b - a, zlib.crc32(view[4 * a : 4 * b])) for k, (a, b) in enumerate(zip(edges, edges[1:]))]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return shipped(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def pack(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end: int = END, kept: int = KEPT) -> DataFrame:
    """Every piece of every row with ``sequence_id`` and ``offset``; sequences are filled without gaps.

    The histogram of lengths (at most ``capacity`` rows) is planned on the driver; pieces take the slots by their rank
    among those of their length. Ranks are counted in parts by a hash of the id, so a frequent length spreads over tasks.
    Null and empty texts give the end id alone; null ids and repeated rows are packed like others. No rows give none.
    """
    cut = checkpointed(pieces(docs, tokenizer, capacity, end, kept).withColumn("part", F.pmod(F.xxhash64("doc_id", "ids_crc32"), F.lit(PARTS))))
    counts = checkpointed(cut.groupBy("length", "part").agg(F.count("*").alias("n")))
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    slots = best_fit(histogram, capacity)
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("length", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("length", "part").orderBy("doc_id", "piece", "start")
    ranked = cut.withColumn("rank", F.row_number().over(inside) - 1).join(broadcast_below(checkpointed(base), (capacity + 1) * PARTS), ["length", "part"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("rank") + F.col("base")).alias("rank"))
    sent = docs.sparkSession.sparkContext.broadcast(slots)

    def place(batches):
        plan = sent.value
        shift = 1 << 44
        keys = plan[:, 0] * shift + plan[:, 1]
        for batch in batches:
            length, rank = batch.column(3).to_numpy(), batch.column(5).to_numpy()
            row = plan[np.searchsorted(keys, length * shift + rank, "right") - 1]
            k = rank - row[:, 1]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(row[:, 2] + k // row[:, 3]), pa.array(row[:, 4] + k % row[:, 3] * length)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
