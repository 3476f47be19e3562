"""Search for the terms that co-occur most with a keyword query."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .catalog import Database
from .functions.text import without
from .operators.frequency import star_frequencies, star_frequencies_by_key, top_terms, total_frequencies
from .operators.trees import compile_tree, joined, starify, tree_frequencies
from .operators.tuplesets import mask_histogram, tag
from .plans.networks import Node, classify, enumerate_networks

RELATIONS = ("part", "supplier", "orders", "customer", "lineitem")


def networks(db: Database, keywords: Sequence[str], rmax: int, relations: Sequence[str] = RELATIONS) -> list[Node]:
    """The candidate networks of a query; one aggregate of a few rows tells which tuple sets have rows."""
    sets = [(r.relation, r.kw_mask) for r in mask_histogram(db, keywords, relations).collect()]
    return enumerate_networks(db.graph, sets, len(keywords), rmax)


def network_frequencies(db: Database, keywords: Sequence[str], tree: Node, method: str = "volume", drop: bool = True) -> DataFrame:
    """``(term, freq)`` of one network by ``volume``, ``by_key``, ``tree`` (two sweeps) or ``join`` (full join)."""
    gone = list(keywords) if drop else []
    shape, tree = classify(tree)
    branch = compile_tree(db, keywords, tree)
    if method == "join":
        return joined(branch).select(F.explode(without(F.col("terms"), gone)).alias("term")).groupBy("term").agg(F.count("*").alias("freq"))
    if method == "tree":
        return tree_frequencies(branch, gone)
    return (star_frequencies if method == "volume" else star_frequencies_by_key)(starify(branch), gone)


def cooccurring_terms(db: Database, keywords: Sequence[str], k: int, rmax: int, method: str = "volume", stopwords: Sequence[str] = (), relations: Sequence[str] = RELATIONS, store: str | None = None) -> DataFrame:
    """``(term, freq, rank)``: the k terms, other than the keywords, with the most occurrences over all results.

    With ``store``, a folder, the relations are scanned once: their rows are kept there by the keywords they hold, and all
    networks read the folders of their tuple sets. Without, each tuple set scans its relation.
    """
    if store is not None:
        db = tag(db, keywords, relations, store)
    found = networks(db, keywords, rmax, relations)
    if not found:
        return db.spark.createDataFrame([], "term string, freq bigint, rank bigint")
    freq = total_frequencies([network_frequencies(db, keywords, t, method) for t in found])
    return top_terms(freq.where(~F.col("term").isin(list(stopwords))) if stopwords else freq, k)


def keyword_results(db: Database, keywords: Sequence[str], rmax: int, relations: Sequence[str] = RELATIONS) -> DataFrame:
    """``(cn_id, tuples, terms)`` of every joined result; ``tuples`` names its rows by relation and keys, in order.

    Queries without a network give no rows.
    """
    parts = [joined(compile_tree(db, keywords, classify(t)[1], True)).select(F.lit(i).alias("cn_id"), F.array_sort("tuples").alias("tuples"), "terms") for i, t in enumerate(networks(db, keywords, rmax, relations))]
    if not parts:
        return db.spark.createDataFrame([], "cn_id int, tuples array<string>, terms array<string>")
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def expand_query(keywords: Sequence[str], terms: DataFrame, m: int = 1) -> list[str]:
    """The query with the m most frequent terms added."""
    return [*keywords, *[r.term for r in top_terms(terms.select("term", "freq"), m).orderBy("rank").collect()]]


def refine_counts(results: DataFrame, candidates: Sequence[str]) -> DataFrame:
    """``(term, n_results)``: results that are left if a term is added to the query."""
    each = F.explode(F.array_intersect("terms", F.array(*[F.lit(c) for c in candidates]))).alias("term")
    return results.select(each).groupBy("term").agg(F.count("*").alias("n_results"))
