"""Near-duplicate vectors by cross-polytope hashing after fast Hadamard rotations."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import shipped
from .common import checkpointed, components
from .shingles import mixed

#: Chance that a pair at the threshold meets in no table; tables follow from it, however many these are.
MISS = 1e-6
#: Rows of a bucket that one task compares; larger buckets are cut into parts, and pairs of parts go to tasks.
BLOCK = 4096
#: Names of tables in a bucket's number; least chance to meet in a table that is assumed.
TABLE_NAMES, LEAST_MET = 1 << 10, 0.01
#: Runs of rows up to this length are compared without a matrix.
SHORT_RUN = 48
#: Buckets for each vector that the number of rotations aims at.
SPREAD = 16
#: Least length of a sketch, and what rounding to single precision may take from an inner product of sketches.
LEAST_SKETCH, ROUNDING = 24, 1e-4
SEED = 29


def hadamard(x: np.ndarray) -> np.ndarray:
    """Walsh-Hadamard transform of the rows; their length is a power of two."""
    n, d = x.shape
    step = 1
    while step < d:
        y = x.reshape(n, d // (2 * step), 2, step)
        x = np.stack((y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]), 2).reshape(n, d)
        step *= 2
    return x


def codes(unit: np.ndarray, tables: int, turns: int) -> np.ndarray:
    """For each row and table its own bucket, then one probe for each rotation, where the second-best vertex stands in."""
    n, dim = unit.shape
    d = 1 << max(0, (dim - 1).bit_length())
    x = np.zeros((n, d))
    x[:, :dim] = unit
    rng = np.random.default_rng([SEED, dim])
    out = np.empty((n, tables, 1 + turns), np.int64)
    rows = np.arange(n)
    for t in range(tables):
        own, other = np.empty((n, turns), np.int64), np.empty((n, turns), np.int64)
        for k in range(turns):
            y = x
            for _ in range(3):
                y = hadamard(y * (rng.integers(0, 2, d) * 2 - 1))
            size = np.abs(y)
            for put in (own, other):
                best = size.argmax(1)
                put[:, k] = best * 2 + (y[rows, best] > 0)
                size[rows, best] = -1
        # a bucket is named by the length, the table and the vertices: exactly where they fit 64 bits, by their hash else
        weight = (2 * d) ** np.arange(turns)
        base = own @ weight
        cells = np.concatenate((base[:, None], base[:, None] + (other - own) * weight), 1)
        if (dim + 1) * TABLE_NAMES * (2 * d) ** turns < 2**63:
            out[:, t] = cells + (dim * TABLE_NAMES + t) * (2 * d) ** turns
        else:
            out[:, t] = mixed(mixed(cells.view(np.uint64)) ^ np.uint64(dim << 20 | t)).view(np.int64)
    return out.reshape(n, -1)


def plan(vectors: int, dim: int, cosine: float) -> tuple[int, int]:
    """Tables and rotations in each: ``SPREAD`` buckets for each vector, and tables enough for the wanted recall.

    The chance that a pair at the threshold meets in one table is measured on random pairs. Turns end at 6, which makes
    buckets larger, not recall smaller.
    """
    d = 1 << max(1, (dim - 1).bit_length())
    turns = min(6, max(2, math.ceil(math.log(max(vectors, 2) * SPREAD) / math.log(2 * d))))
    rng = np.random.default_rng(SEED)
    a = rng.normal(size=(1500, dim))
    b = rng.normal(size=(1500, dim))
    a /= np.linalg.norm(a, axis=1)[:, None]
    b -= (a * b).sum(1)[:, None] * a
    b /= np.maximum(np.linalg.norm(b, axis=1), 1e-12)[:, None]
    near = a * cosine + b * math.sqrt(max(0.0, 1 - cosine * cosine))
    p, q = (codes(x, 4, turns).reshape(-1, 4, 1 + turns) for x in (a, near / np.linalg.norm(near, axis=1)[:, None]))
    met = ((p[:, :, :1] == q) | (q[:, :, :1] == p)).any(2).mean()
    return (1 if met >= 1 else max(4, math.ceil(math.log(MISS) / math.log1p(-max(met, LEAST_MET))))), turns


def _owned(cx: np.ndarray, cy: np.ndarray, bucket: np.ndarray, width: int) -> np.ndarray:
    """True for pairs that meet in ``bucket`` before any other bucket, so that each pair counts once."""
    cx, cy = cx.reshape(len(cx), -1, width), cy.reshape(len(cy), -1, width)
    big = np.iinfo(np.int64).max
    hx, hy = cx[:, :, :1], cy[:, :, :1]
    at = np.minimum(np.where((hx == cy).any(2), hx[:, :, 0], big), np.where((hy == cx).any(2), hy[:, :, 0], big))
    first = (at != big).argmax(1)
    return at[np.arange(len(at)), first] == bucket


def sketches(unit: np.ndarray) -> np.ndarray:
    """Short vectors whose inner products are never below those of the rows, which have length 1.

    A row is projected onto a quarter of its dimensions, ``LEAST_SKETCH`` at least, of a random orthonormal basis; the
    length of what is left stands as one component more. By the Cauchy-Schwarz inequality the products of what is left are
    at most those of the lengths.
    """
    dim = unit.shape[1]
    kept = min(dim, max(LEAST_SKETCH, dim // 4))
    basis = np.linalg.qr(np.random.default_rng([SEED, dim, 1]).normal(size=(dim, kept)))[0]
    short = unit @ basis
    rest = np.sqrt(np.maximum(0.0, 1 - (short * short).sum(1)))
    return np.concatenate((short, rest[:, None]), 1).astype(np.float32)


def _meeting(t: pa.Table, column: str, least: float):
    """Row numbers ``(a, b)`` of pairs that meet in a block of ``t`` with an inner product of ``column`` of ``least`` or more.

    Rows are sorted by block; at least one of a pair is at home in the bucket.
    """
    n = len(t)
    home, part, lo, hi, bucket, ids = (t[c].to_numpy() for c in ("home", "part", "lo", "hi", "bucket", "id"))
    vector = t[column].combine_chunks().flatten().to_numpy().reshape(n, -1)
    new = np.ones(n, bool)
    new[1:] = (bucket[1:] != bucket[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])
    starts = np.flatnonzero(new)
    run = np.cumsum(new) - 1
    sizes = np.diff(np.append(starts, n))
    large = (sizes > SHORT_RUN) | (lo[starts] != hi[starts])
    # short runs: neighbours at each distance, over all runs at once
    short = ~large[run]
    for step in range(1, int(sizes[~large].max(initial=1))):
        a = np.flatnonzero(short[:-step] & (run[:-step] == run[step:]) & (home[:-step] | home[step:]) & (ids[:-step] != ids[step:]))
        for j in range(0, len(a), 20_000):
            x = a[j : j + 20_000]
            near = np.einsum("ij,ij->i", vector[x], vector[x + step]) >= least
            yield x[near], x[near] + step
    for k in np.flatnonzero(large):
        rows = np.arange(starts[k], starts[k] + sizes[k])
        left, right = rows[part[rows] == lo[starts[k]]], rows[part[rows] == hi[starts[k]]]
        for i in range(0, len(left), 512):
            r, c = np.nonzero(vector[left[i : i + 512]] @ vector[right].T >= least)
            r, c = left[i : i + 512][r], right[c]
            fit = (home[r] | home[c]) & ((r < c) | (lo[starts[k]] != hi[starts[k]])) & (ids[r] != ids[c])
            yield r[fit], c[fit]


def _matches(t: pa.Table, cosine: float, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers of the linked pairs that belong to the blocks of ``t``, whose rows are sorted by block."""
    bucket = t["bucket"].to_numpy()
    code = t["codes"].combine_chunks().flatten().to_numpy().reshape(len(t), -1)
    firsts, seconds = [], []
    for a, b in _meeting(t, "unit", cosine):
        for j in range(0, len(a), 50_000):
            x, y = a[j : j + 50_000], b[j : j + 50_000]
            mine = _owned(code[x], code[y], bucket[x], width)
            firsts.append(x[mine])
            seconds.append(y[mine])
    return tuple(np.concatenate(x) if x else np.zeros(0, np.int64) for x in (firsts, seconds))


def _by_length(t: pa.Table, column: str):
    """``t`` cut by the lengths of the vectors of ``column``, with the row numbers of each cut."""
    lengths = np.diff(t[column].combine_chunks().offsets.to_numpy())
    for length in np.unique(lengths):
        rows = np.flatnonzero(lengths == length)
        yield rows, t if len(rows) == len(t) else t.take(pa.array(rows))


def _whole_blocks(answer):
    """``answer`` of tables of whole blocks, over batches sorted by block."""

    def run(batches):
        held = None
        for batch in batches:
            t = pa.Table.from_batches([batch])
            t = pa.concat_tables([held, t]) if held is not None else t
            key = [t[c].to_numpy() for c in ("bucket", "lo", "hi")]
            last = len(t) - int(np.logical_and.reduce([k == k[-1] for k in key])[::-1].argmin() or len(t)) if len(t) else 0
            if last:
                yield answer(t.slice(0, last).combine_chunks())
            held = t.slice(last)
        if held is not None and len(held):
            yield answer(held.combine_chunks())

    return run


def _possible(cosine: float):
    """Over rows sorted by block: those that may have a link in their block, by their sketches. None that has is left out."""

    def answer(t: pa.Table) -> pa.RecordBatch:
        some = np.zeros(len(t), bool)
        for rows, cut in _by_length(t, "sketch"):
            for a, b in _meeting(cut, "sketch", cosine - ROUNDING):
                some[rows[a]] = some[rows[b]] = True
        kept = t.drop_columns(["sketch"]).filter(pa.array(some))
        return pa.RecordBatch.from_arrays([c.combine_chunks() for c in kept.columns], schema=kept.schema)

    return _whole_blocks(answer)


def _compare(cosine: float, width: int):
    """Over rows sorted by block: sums of linked copies and a forest of the links, for whole blocks at a time."""

    def answer(t: pa.Table) -> pa.RecordBatch:
        ids, where = np.unique(t["id"].to_numpy(), return_inverse=True)
        links, label = np.zeros(len(ids), np.int64), np.arange(len(ids))
        weight = t["copies"].to_numpy()
        for rows, cut in _by_length(t, "unit"):
            r, c = _matches(cut, cosine, width)
            r, c = rows[r], rows[c]
            a, b = where[r], where[c]
            np.add.at(links, a, weight[c])
            np.add.at(links, b, weight[r])
            while len(a):
                before = label.copy()
                low = np.minimum(label[a], label[b])
                np.minimum.at(label, a, low)
                np.minimum.at(label, b, low)
                label = label[label]
                if (label == before).all():
                    break
        some = np.flatnonzero(links)
        return pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(links[some]), pa.array(ids[label[some]])], ["id", "links", "root"])

    return _whole_blocks(answer)


def near_duplicate_vectors(vectors: DataFrame, cosine: float = 0.95) -> DataFrame:
    """``vec_id``, ``n_links``, ``component_id`` and ``kept`` for each row.

    Equal vectors form a class, hashed once. A class is listed in its own bucket of each table and, as a probe, in the
    buckets of its second-best vertices. Sketches go to the buckets first: rows whose sketches rule out every link in
    their block leave it, so that whole vectors only go where links are likely. The rows that stay are compared in blocks
    in double precision, each pair counting in the first bucket where it meets. A block returns sums and a spanning
    forest, never pairs. Buckets over ``BLOCK`` rows are cut into parts whose pairs are spread over tasks.

    Vectors that are null, empty, zero or hold null or non-finite components have no links and are kept. Vectors of other
    lengths link with nothing. Rows with a null ``vec_id`` count as partners of their copies only; their component and
    ``kept`` are null. Labels and other columns don't matter.
    """
    e = F.col("embedding").cast("array<double>")
    fine = F.coalesce(~F.exists(e, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(e, lambda x: x != 0), F.lit(False))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.when(fine, e).alias("e"))
    classes = checkpointed(rows.where("e is not null").groupBy("e").agg(F.min("vec_id").alias("id"), F.count("*").alias("copies")))
    usable = classes.where("id is not null")
    size = usable.agg(F.count("*").alias("n"), F.max(F.size("e")).alias("d")).first()
    tables, turns = plan(size.n, size.d or 1, cosine) if size.n else (1, 1)
    width = 1 + turns

    def hashed(batches):
        for batch in batches:
            lists = batch.column(1)
            lengths = np.diff(lists.offsets.to_numpy())
            for dim in np.unique(lengths):
                take = np.flatnonzero(lengths == dim)
                for i in range(0, len(take), 2000):
                    some = batch.take(pa.array(take[i : i + 2000]))
                    x = some.column(1).flatten().to_numpy().reshape(-1, dim)
                    x = x / np.abs(x).max(1)[:, None]
                    x = x / np.linalg.norm(x, axis=1)[:, None]
                    pack = lambda m: pa.FixedSizeListArray.from_arrays(pa.array(m.ravel()), m.shape[1]).cast(pa.list_(pa.from_numpy_dtype(m.dtype)))
                    yield pa.RecordBatch.from_arrays([some.column(0), some.column(2), pack(x), pack(codes(x, tables, turns)), pack(sketches(x))], ["id", "copies", "unit", "codes", "sketch"])

    known = checkpointed(shipped(usable).select("id", "e", "copies").mapInArrow(hashed, "id long, copies long, unit array<double>, codes array<long>, sketch array<float>"))
    cells = known.select("id", F.posexplode("codes").alias("pos", "bucket")).select("id", "bucket", (F.col("pos") % width == 0).alias("home"))
    useful = cells.groupBy("bucket").agg(F.count("*").alias("n"), F.max("home").alias("any")).where("n > 1 and any").select("bucket", "n")
    placed = cells.join(useful, "bucket").withColumn("parts", F.ceil(F.col("n") / BLOCK).cast("int")).withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int"))
    blocks = placed.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("id", "bucket", "home", "part", F.least("part", "with").alias("lo"), F.greatest("part", "with").alias("hi"))
    placing = "bucket", "lo", "hi"
    short = blocks.join(known.select("id", "sketch"), "id").repartition(*placing).sortWithinPartitions(*placing).select(*placing, "part", "home", "id", "sketch")
    possible = short.mapInArrow(_possible(cosine), "bucket long, lo int, hi int, part int, home boolean, id long")
    whole = possible.join(known.select("id", "copies", "unit", "codes"), "id").repartition(*placing).sortWithinPartitions(*placing)
    found = checkpointed(whole.select(*placing, "part", "home", "id", "copies", "unit", "codes").mapInArrow(_compare(cosine, width), "id long, links long, root long"))
    linked = components(found.select(F.col("id").alias("src"), F.col("root").alias("dst")))
    sums = found.groupBy("id").agg(F.sum("links").alias("links"))
    of = classes.join(sums, "id", "left").join(linked, F.col("id") == F.col("node"), "left").select("e", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "id").alias("component"))
    out = rows.join(of, "e", "left").withColumn("component_id", F.when(F.col("vec_id").isNotNull(), F.coalesce("component", "vec_id")))
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept"))
