"""Language identification by a sparse multinomial logistic regression on TF-IDF character n-grams."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import shipped
from .shingles import mixed

#: Buckets of hashed n-grams, longest n-gram, characters hashed at once.
BITS, LONGEST, PIECE = 16, 3, 1 << 18
#: Labelled documents that the classifier is fitted on at most, over all languages.
SAMPLE = 4000
#: Follow-the-regularised-leader: rate, smoothing, L1, L2 and passes.
RATE, SMOOTH, L1, L2, PASSES = 1.0, 1.0, 2e-3, 1e-3, 3
UNKNOWN = "und"
_letters: list = []


def letters() -> np.ndarray:
    if not _letters:
        _letters.append(np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000))
    return _letters[0]


def grams(text: str | None) -> tuple[np.ndarray, np.ndarray] | None:
    """Buckets and counts of the n-grams of a whole text in lower case, runs of non-letters as one space; None without letters."""
    if not text:
        return None
    x = np.frombuffer(text.lower().encode("utf-32-le", "replace"), np.uint32)
    is_letter = letters()[x]
    if not is_letter.any():
        return None
    x = np.where(is_letter, x, 32).astype(np.uint64)
    again = np.zeros(len(x), bool)
    again[1:] = ~is_letter[1:] & ~is_letter[:-1]
    x = np.concatenate(([np.uint64(32)], x[~again], [np.uint64(32)]))
    counts = np.zeros(1 << BITS, np.int64)
    for n in range(1, LONGEST + 1):
        for s in range(0, len(x) - n + 1, PIECE):
            part = x[s : s + PIECE + n - 1]
            h = part[: len(part) - n + 1].copy()
            for k in range(1, n):
                h = h * np.uint64(0x1F123BB5159E3B4D) + part[k : len(part) - n + 1 + k]
            counts += np.bincount((mixed(h + np.uint64(n << 40)) >> np.uint64(64 - BITS)).astype(np.int64), minlength=1 << BITS)
    where = np.flatnonzero(counts)
    return where, counts[where]


def vector(found: tuple[np.ndarray, np.ndarray], idf: np.ndarray) -> np.ndarray:
    x = np.log1p(found[1]) * idf[found[0]]
    return x / max(np.linalg.norm(x), 1e-12)


class Model:
    """Weights for each bucket and language, intercepts and the temperature."""

    def __init__(self, langs: list[str], idf: np.ndarray):
        self.langs, self.idf, self.temperature = langs, idf, 1.0
        self.weights = np.zeros((len(idf) + 1, len(langs)))

    def logits(self, found) -> np.ndarray:
        return vector(found, self.idf) @ self.weights[found[0]] + self.weights[-1]

    def predict(self, found) -> tuple[str, float]:
        if found is None or not self.langs:
            return UNKNOWN, 0.0
        z = self.logits(found) / self.temperature
        p = np.exp(z - z.max())
        return self.langs[int(p.argmax())], float(p.max() / p.sum())


def fit(langs: list[str], idf: np.ndarray, rows: list[tuple[str, tuple]]) -> Model:
    """Every fifth row is left out of the fit and sets the temperature."""
    model = Model(langs, idf)
    sums, squares = np.zeros_like(model.weights), np.zeros_like(model.weights)
    of = {x: i for i, x in enumerate(langs)}
    train = [r for k, r in enumerate(rows) if k % 5] or rows
    held = [r for k, r in enumerate(rows) if not k % 5]
    order = np.random.default_rng(5)
    for _ in range(PASSES):
        for k in order.permutation(len(train)):
            lang, found = train[k]
            at = np.append(found[0], len(idf))
            x = np.append(vector(found, idf), 1.0)
            z, n = sums[at], squares[at]
            w = np.where(np.abs(z) <= L1, 0.0, -(z - np.sign(z) * L1) / ((SMOOTH + np.sqrt(n)) / RATE + L2))
            s = x @ w
            p = np.exp(s - s.max())
            p /= p.sum()
            p[of[lang]] -= 1
            g = x[:, None] * p
            squares[at] = n + g * g
            sums[at] = z + g - (np.sqrt(squares[at]) - np.sqrt(n)) / RATE * w
    model.weights = np.where(np.abs(sums) <= L1, 0.0, -(sums - np.sign(sums) * L1) / ((SMOOTH + np.sqrt(squares)) / RATE + L2))
    scored = [(model.logits(f), of[lang]) for lang, f in held]
    if scored and len(langs) > 1:
        def loss(t: float) -> float:
            return sum(np.logaddexp.reduce(z / t) - z[y] / t for z, y in scored)

        model.temperature = float(min(np.geomspace(0.05, 5, 60), key=loss))
    return model


def _frequencies(batches):
    df, n = np.zeros(1 << BITS, np.int64), 0
    for batch in batches:
        for text in batch.column(0).to_pylist():
            if (found := grams(text)) is not None:
                df[found[0]] += 1
                n += 1
    where = np.flatnonzero(df)
    yield pa.RecordBatch.from_arrays([pa.array(np.append(where, -1)), pa.array(np.append(df[where], n))], ["bucket", "docs"])


def _features(batches):
    for batch in batches:
        rows = [(lang, found, key) for lang, text, key in zip(*(c.to_pylist() for c in batch.columns), strict=True) if (found := grams(text)) is not None]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1][0].astype("<i4").tobytes() for r in rows], pa.binary()), pa.array([r[1][1].astype("<i4").tobytes() for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.int64())], ["lang", "buckets", "counts", "key"])


def train(docs: DataFrame, sample: int = SAMPLE) -> Model:
    """A model from the rows of ``docs`` that have a language and a text.

    Document frequencies and languages are counted over all of them. The classifier is fitted on the driver on at most
    about ``sample`` rows: each language gives an equal share, or all it has, chosen by a hash of the id. No more than
    twice that reach the driver, the first by a hash of id and text.
    """
    rows = docs.where("lang is not null and text is not null").select("doc_id", "lang", "text")
    sizes = {r.lang: r.n for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # one row for each language
    langs = sorted(sizes)
    idf = np.zeros(1 << BITS)
    if not langs:
        return Model([], idf)
    counts = shipped(rows).select("text").mapInArrow(_frequencies, "bucket long, docs long").groupBy("bucket").agg(F.sum("docs").alias("docs")).toPandas()  # one row for each bucket
    total = int(counts.docs[counts.bucket == -1].sum())
    seen = counts[counts.bucket >= 0]
    idf[seen.bucket] = np.log((1 + total) / (1 + seen.docs)) + 1
    share = max(8, sample // len(langs))
    draw = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    rate = F.create_map(*[F.lit(v) for lang in langs for v in (lang, min(1.0, share / sizes[lang]))])
    picked = rows.where(draw < rate[F.col("lang")]).select("lang", "text", F.xxhash64("doc_id", "text").alias("key")).mapInArrow(_features, "lang string, buckets binary, counts binary, key long")
    found = sorted((r.lang, bytes(r.buckets), bytes(r.counts)) for r in picked.orderBy("key", "lang").limit(2 * sample + 8 * len(langs)).collect())
    order = np.random.default_rng(3).permutation(len(found))
    data = [(found[k][0], (np.frombuffer(found[k][1], "<i4").astype(np.int64), np.frombuffer(found[k][2], "<i4").astype(np.int64))) for k in order]
    return fit(langs, idf, data) if data else Model([], idf)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """``doc_id``, ``lang_pred`` and ``score`` of each row; texts that are null or without letters give ``und`` and 0."""
    sent = docs.sparkSession.sparkContext.broadcast((model.langs, model.idf, model.weights, model.temperature))

    def run(batches):
        langs, idf, weights, temperature = sent.value
        own = Model(langs, idf)
        own.weights, own.temperature = weights, temperature
        for batch in batches:
            out = [own.predict(grams(t)) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([o[0] for o in out], pa.string()), pa.array([o[1] for o in out], pa.float64())], ["doc_id", "lang_pred", "score"])

    return shipped(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def identify(docs: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """``doc_id``, ``held_out``, ``lang_pred`` and ``score`` for every row of ``docs``.

    Documents with crc32 of the id, as text, leaving 2 on division by 4 are held out of training; so are null ids and null
    languages. Repeated rows are predicted alike. An empty table gives no rows, one without languages ``und`` for all.
    """
    fold = F.crc32(F.col("doc_id").cast("string")) % 4 == 2
    model = train(docs.where(~fold), sample)
    return predict(docs, model).withColumn("held_out", F.coalesce(fold, F.lit(False))).select("doc_id", "held_out", "lang_pred", "score")
