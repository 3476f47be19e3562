"""Token ids as binary shards with a minimal perfect hash index."""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..shipping import shipped
from .common import broadcast_below
from .shingles import mixed
from .tokens import encoder, in_pieces

#: Ids after which a shard is closed, bits for each key on a level of the index, most levels.
SHARD_IDS, GAMMA, LEVELS = 1 << 20, 2, 40
SHARD_ROWS = 2_000_000
#: Steps of the key range in which keys meet shards, groups that share the keys asked of one shard, parts named in a filter.
STEPS, GROUPS, MOST_PARTS = 1 << 16, 16, 10_000

# A shard is one row of a Parquet table, so that any store Spark can reach will do: ``ids`` holds the ids of its documents
# as little-endian unsigned 32-bit integers, one document after the other, ``ends`` the id count up to the end of each
# (int64), ``keys`` their ids for scans in order. ``levels`` (int32 sizes), ``bits``, ``prints`` (uint32), ``firsts`` and
# ``repeats`` (int32) are the index: key -> slot -> fingerprint, first document, documents with this key.
SCHEMA = "part int, seq int, n_docs long, n_ids long, first_key long, last_key long, keys array<long>, levels binary, bits binary, prints binary, firsts binary, repeats binary, ends binary, ids binary"


def _spread(keys: np.ndarray, level: int) -> np.ndarray:
    return mixed(keys.view(np.uint64) + np.uint64((0x9E3779B97F4A7C15 * (level + 1)) & 0xFFFFFFFFFFFFFFFF))


def _print(keys: np.ndarray) -> np.ndarray:
    return (_spread(keys, 77) >> np.uint64(32)).astype(np.uint32)


class Index:
    """Minimal perfect hash of distinct 64-bit keys: on each level the keys that hash alone take a bit, the rest go on."""

    def __init__(self, levels: np.ndarray, bits: np.ndarray, prints: np.ndarray):
        self.levels, self.bits, self.prints = levels, bits, prints
        self.rank = np.concatenate(([0], np.cumsum(bits))) if len(bits) else np.zeros(1, np.int64)
        self.base = np.concatenate(([0], np.cumsum(levels)))

    @classmethod
    def build(cls, keys: np.ndarray) -> tuple[Index, np.ndarray]:
        """The index and the slot of each key."""
        levels, parts, rest = [], [], np.arange(len(keys))
        while len(rest) and len(levels) < LEVELS:
            size = max(8, GAMMA * len(rest))
            at = (_spread(keys[rest], len(levels)) % np.uint64(size)).astype(np.int64)
            bits = np.bincount(at, minlength=size) == 1
            levels.append(size)
            parts.append(bits)
            rest = rest[~bits[at]]
        if len(rest):
            raise ValueError("keys of an index must differ")
        self = cls(np.array(levels, np.int32), np.concatenate(parts) if parts else np.zeros(0, bool), np.zeros(0, np.uint32))
        slots = self.slots(keys)
        self.prints = np.zeros(len(keys), np.uint32)
        self.prints[slots] = _print(keys)
        return self, slots

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """Slot of each key, -1 for keys that no level holds; a fixed number of probes for each."""
        slot = np.full(len(keys), -1, np.int64)
        open_ = np.arange(len(keys))
        for level, size in enumerate(self.levels):
            at = self.base[level] + (_spread(keys[open_], level) % np.uint64(size)).astype(np.int64)
            hit = self.bits[at]
            slot[open_[hit]] = self.rank[at[hit]]
            open_ = open_[~hit]
            if not len(open_):
                break
        return slot

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Slots with the right fingerprint, -1 else."""
        slot = self.slots(keys)
        return np.where((slot >= 0) & (self.prints[np.maximum(slot, 0)] == _print(keys)), slot, -1) if len(self.prints) else slot


def _shard(part: int, seq: int, keys: list, parts: list[bytes]) -> pa.RecordBatch:
    ends = np.cumsum([len(p) // 4 for p in parts]).astype("<i8")
    known = np.array([k for k in keys if k is not None], np.int64)  # sorted, nulls first
    distinct, first, repeats = np.unique(known, return_index=True, return_counts=True)
    index, slots = Index.build(distinct)
    firsts, counts = np.zeros(len(distinct), "<i4"), np.zeros(len(distinct), "<i4")
    firsts[slots], counts[slots] = first + len(keys) - len(known), repeats
    row = {
        "part": part, "seq": seq, "n_docs": len(keys), "n_ids": int(ends[-1]), "first_key": int(known[0]) if len(known) else None, "last_key": int(known[-1]) if len(known) else None,
        "keys": keys, "levels": index.levels.astype("<i4").tobytes(), "bits": np.packbits(index.bits).tobytes(), "prints": index.prints.astype("<u4").tobytes(),
        "firsts": firsts.tobytes(), "repeats": counts.tobytes(), "ends": ends.tobytes(), "ids": b"".join(parts),
    }
    return pa.RecordBatch.from_pylist([row], _ARROW)


_ARROW = pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("n_docs", pa.int64()), ("n_ids", pa.int64()), ("first_key", pa.int64()), ("last_key", pa.int64()), ("keys", pa.list_(pa.int64())), *[(c, pa.binary()) for c in ("levels", "bits", "prints", "firsts", "repeats", "ends", "ids")]])


def write(docs: DataFrame, tokenizer: str, end: int, path: str) -> None:
    """Encode every whole text, append the end id, and write shards in ascending ``doc_id`` order to ``path``.

    Rows are dealt by ranges of the id, ties by their place in the input, so one id with many rows spreads over shards.
    A shard closes after ``SHARD_IDS`` ids; a longer document makes a larger one. Null texts are empty; null ids come first.
    """
    tail = int(end).to_bytes(4, "little")

    def run(batches):
        encode, part, seq, keys, parts, size = encoder(tokenizer), TaskContext.get().partitionId(), 0, [], [], 0
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for i, j in in_pieces(texts):
                for key, data in zip(ids[i:j], encode.encode(texts[i:j]), strict=True):
                    keys.append(key)
                    parts.append(data + tail)
                    size += len(parts[-1]) // 4
                    if size >= SHARD_IDS:
                        yield _shard(part, seq, keys, parts)
                        seq, keys, parts, size = seq + 1, [], [], 0
        if keys:
            yield _shard(part, seq, keys, parts)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.monotonically_increasing_id().alias("place"))
    ordered = shipped(rows).repartitionByRange("doc_id", "place").sortWithinPartitions("doc_id", "place").select("doc_id", "text")
    ordered.mapInArrow(run, SCHEMA).write.mode("errorifexists").option("compression", "zstd").parquet(path)


def _index(batch: pa.RecordBatch, i: int) -> tuple[Index, np.ndarray, np.ndarray, np.ndarray, memoryview]:
    get = lambda c: batch.column(c)[i].as_buffer()
    levels = np.frombuffer(get("levels"), "<i4")
    bits = np.unpackbits(np.frombuffer(get("bits"), np.uint8))[: int(levels.sum())].astype(bool)
    return Index(levels, bits, np.frombuffer(get("prints"), "<u4")), *(np.frombuffer(get(c), k) for c, k in (("firsts", "<i4"), ("repeats", "<i4"), ("ends", "<i8"))), memoryview(get("ids"))


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document, found through the index of its shard."""

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                index, firsts, repeats, ends, ids = _index(batch, i)
                keys = batch.column("keys")[i].as_py()
                known = np.array([k for k in keys if k is not None], np.int64)
                slot = index.find(known)
                if (slot < 0).any():
                    raise ValueError("a key is missing from its index")
                turn = np.arange(len(known)) - np.searchsorted(known, known)
                if (turn >= repeats[slot]).any():
                    raise ValueError("a key has more documents than its index says")
                rows = np.concatenate((np.arange(len(keys) - len(known)), firsts[slot] + turn)).astype(np.int64)
                starts = np.where(rows > 0, ends[rows - 1], 0)
                crc = [zlib.crc32(ids[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends[rows].tolist())]
                n = len(keys)
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(np.full(n, batch.column("part")[i].as_py(), np.int32)), pa.array(np.full(n, batch.column("seq")[i].as_py(), np.int32)), pa.array(starts), pa.array(ends[rows] - starts), pa.array(crc, pa.int64())], ["doc_id", "part", "seq", "start", "n_tokens", "ids_crc32"])

    shards = _shards(spark, path)
    found = shipped(shards).mapInArrow(run, "doc_id long, part int, seq int, start long, n_tokens long, ids_crc32 long")
    # ids before a shard: those of the parts before, then those of its part
    sizes = shards.select("part", "seq", "n_ids")
    parts = sizes.groupBy("part").agg(F.sum("n_ids").alias("n")).withColumn("before", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("n")
    inner = F.coalesce(F.sum("n_ids").over(Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    base = sizes.withColumn("inner", inner).join(parts, "part").select("part", "seq", (F.col("inner") + F.col("before")).alias("base"))
    return found.join(broadcast_below(base, SHARD_ROWS), ["part", "seq"]).select("doc_id", (F.col("start") + F.col("base")).alias("start"), "n_tokens", "ids_crc32")


def _by_directory(wanted: DataFrame, directory: DataFrame) -> DataFrame:
    """``(part, seq, doc_id)`` of the shards whose range holds a key, by binary search in the directory."""
    rows = sorted((r.part, r.seq, r.first_key, r.last_key) for r in directory.collect())
    sent = wanted.sparkSession.sparkContext.broadcast(np.array(rows, np.int64).reshape(-1, 4))

    def run(batches):
        part, seq, first, last = sent.value.T
        for batch in batches:
            keys = batch.column(0).to_numpy()
            a, b = np.searchsorted(last, keys, "left"), np.searchsorted(first, keys, "right")
            n = np.maximum(b - a, 0)
            # an id of many rows may lie in several shards, one after the other
            at = np.repeat(a, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            yield pa.RecordBatch.from_arrays([pa.array(part[at].astype(np.int32)), pa.array(seq[at].astype(np.int32)), pa.array(np.repeat(keys, n))], ["part", "seq", "doc_id"])

    return shipped(wanted).mapInArrow(run, "part int, seq int, doc_id long")


def _by_steps(wanted: DataFrame, directory: DataFrame) -> DataFrame:
    """The same by a join: keys and shards meet in equal steps of the key range."""
    ends = directory.agg(F.min("first_key").alias("lo"), F.max("last_key").alias("hi")).first()
    lo, hi = (0, 0) if ends.lo is None else (ends.lo, ends.hi)
    step = -(-(hi - lo + 1) // STEPS)
    at = lambda c: F.floor((F.col(c).cast("decimal(20,0)") - F.lit(lo).cast("decimal(20,0)")) / F.lit(step).cast("decimal(20,0)")).cast("long")
    cells = directory.withColumn("cell", F.explode(F.sequence(at("first_key"), at("last_key"))))
    placed = wanted.where(F.col("doc_id").between(lo, hi)).withColumn("cell", at("doc_id")).join(cells, "cell")
    return placed.where(F.col("doc_id").between(F.col("first_key"), F.col("last_key"))).select("part", "seq", "doc_id")


def lookup(spark: SparkSession, path: str, keys: DataFrame) -> DataFrame:
    """``doc_id, ids`` (array of long) and ``ids_crc32`` for each document whose id is in ``keys``; unknown keys give no row.

    The directory (one row a shard; sent to all up to ``SHARD_ROWS``, else joined) tells the shards of a key. A file holds
    one ``part``, so a filter on it, pushed down to the files' statistics, opens only those asked for. In a shard the index gives the place of a key in a
    fixed number of probes; a key that it lacks is refused by the fingerprint, but for one in 2**32. Keys of one shard are
    dealt to ``GROUPS`` lists; a list holds no more keys than its shard has documents, as ids are distinct. Null keys find nothing.
    """
    shards = _shards(spark, path)
    directory = shards.where("first_key is not null").select("part", "seq", "first_key", "last_key")
    wanted = keys.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id is not null").distinct()
    few = directory.limit(SHARD_ROWS + 1).count() <= SHARD_ROWS
    placed = _by_directory(wanted, directory) if few else _by_steps(wanted, directory)
    asked = placed.groupBy("part", "seq", F.pmod(F.xxhash64("doc_id"), F.lit(GROUPS)).alias("group")).agg(F.collect_list("doc_id").alias("asked"))

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                index, firsts, repeats, ends, ids = _index(batch, i)
                asked = np.array(batch.column("asked")[i].as_py(), np.int64)
                slot = index.find(asked)
                asked, slot = asked[slot >= 0], slot[slot >= 0]
                rows = [(k, d) for k, s in zip(asked.tolist(), slot.tolist()) for d in range(firsts[s], firsts[s] + repeats[s])]
                raw = [ids[4 * (int(ends[d - 1]) if d else 0) : 4 * int(ends[d])] for _, d in rows]
                values = [np.frombuffer(x, "<u4").astype(np.int64) for x in raw]
                yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in rows], pa.int64()), pa.array(values, pa.list_(pa.int64())), pa.array([zlib.crc32(x) for x in raw], pa.int64())], ["doc_id", "ids", "ids_crc32"])

    parts = [r.part for r in asked.select("part").distinct().limit(MOST_PARTS + 1).collect()]
    some = shards.where(F.col("part").isin(parts)) if len(parts) <= MOST_PARTS else shards
    return shipped(some.join(asked, ["part", "seq"])).mapInArrow(run, "doc_id long, ids array<long>, ids_crc32 long")


def _shards(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMA).parquet(path)


def fresh_path(spark: SparkSession) -> str:
    """A new folder below the session's shared checkpoint folder."""
    from .common import checkpoint_folder

    return f"{checkpoint_folder(spark)}/token-shards-{uuid.uuid4().hex}"
