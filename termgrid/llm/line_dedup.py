"""Line de-duplication by a tree of line templates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE_RUN, SPACES, broadcast_below, checkpointed, unused

#: Tokens that lead to a leaf, parts of the rest of which one may vary, tokens from which a part may vary.
LEADING, PARTS, VARIES_FROM = 3, 4, 12
#: Tokens that lead to a leaf of shorter lines, and tokens from which one of the others may vary.
SHORT_LEADING, ONE_FROM = 2, 5
#: Documents in which a template must occur to recur.
MIN_DOCS = 5
#: Words above which a line is a passage, and documents in which the template of a passage must occur to recur.
PASSAGE_WORDS, PASSAGE_DOCS = 50, 2
#: Largest table of ids of several rows that is broadcast.
REPEATED_ROWS = 1_000_000


def _templates(line: Column) -> Column:
    """Array of the templates of a line without white space at its ends, each a pair of 64-bit hashes.

    The path to the leaf is the token count and the leading tokens, tokens with digits being fields. Under it the other
    tokens form equal parts; a template leaves one part open, so lines that differ in that part only share it. Lines of 5
    to 11 tokens have a template for each token but the two leading ones, which it leaves open; shorter lines have one
    without an open token. Lines of more fields than words keep their tokens. The lowest bit of the first hash tells passages.
    """
    bound = lambda x, f: F.get(F.transform(F.array(x), f), F.lit(0))
    pair = lambda flag, open_, *of: F.struct(F.xxhash64(open_, *of).bitwiseAND(F.lit(-2)).bitwiseOR(flag).alias("a"), F.xxhash64(*of, open_, F.lit("b")).alias("b"))

    # lambdas are interpreted and share nothing, so each hash of tokens is bound before the templates combine it
    def of(w: Column) -> Column:
        n = F.size(w)
        step, none = F.ceil((n - LEADING) / PARTS).cast("int"), F.lit(0).cast("long")
        lead = F.xxhash64(n, F.slice(w, 1, LEADING))
        parts = lambda step: F.array(lead, *[F.xxhash64(F.slice(w, LEADING + 1 + step * p, F.greatest(step, F.lit(0)))) for p in range(PARTS)], (n > PASSAGE_WORDS).cast("long"))
        four = bound(bound(step, parts), lambda h: F.array(*[pair(F.get(h, F.lit(PARTS + 1)), F.lit(p), *[F.get(h, F.lit(k)) for k in range(PARTS + 1) if k != p + 1]) for p in range(PARTS)]))
        each = lambda h: bound(F.aggregate(h, none, lambda x, y: x.bitwiseXOR(y)), lambda all_: F.transform(F.slice(h, SHORT_LEADING + 1, n), lambda x, i: pair(none, i, n, all_.bitwiseXOR(x))))
        one = bound(F.transform(w, lambda x, i: F.xxhash64(x, i)), each)
        return F.when(n < ONE_FROM, F.array(pair(none, F.lit(-1), lead, F.xxhash64(w)))).when(n < VARIES_FROM, one).otherwise(four)

    # single spaces need no regular expression, which splitting would compile for each line
    plain = lambda x: F.when(x.contains("  ") | x.rlike(r"[\x09-\x0D]"), F.split(x, SPACE_RUN)).otherwise(F.split(x, " "))
    masked = F.regexp_replace(line, r"[^\x20\x09-\x0D0-9]*+[0-9][^\x20\x09-\x0D]*+", "<*>")
    # a line of more fields than words, such as a row of a table, has no template but itself
    fields = lambda w: F.size(w) - F.size(F.array_remove(w, "<*>"))
    chosen = F.when(line.rlike("[0-9]"), bound(bound(masked, plain), lambda w: F.when(2 * fields(w) > F.size(w), plain(line)).otherwise(w))).otherwise(plain(line))
    return bound(chosen, of)


def repeated_lines(docs: DataFrame, min_docs: int = MIN_DOCS, passage_docs: int = PASSAGE_DOCS) -> DataFrame:
    """``(doc_id, drop)``: positions, from 0, of the lines to drop, for documents that have any.

    A line is dropped if one of its templates occurs in ``min_docs`` documents or more (``passage_docs`` for passages) and
    in a document of smaller ``doc_id``: the first document keeps its lines. Counting is a partial aggregate, so one line
    in every document costs one row for each task. Only rows that share a ``doc_id`` are brought together before.
    """
    trimmed = F.transform(F.split("text", "\n"), lambda x: F.btrim(x, F.lit(SPACES)))
    rows = docs.where("doc_id is not null and text is not null").select("doc_id", F.transform(trimmed, lambda x: F.when(x != "", _templates(x))).alias("lines"))
    seen = checkpointed(rows)
    again = broadcast_below(checkpointed(docs.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id")), REPEATED_ROWS)
    flat = seen.select("doc_id", F.posexplode("lines").alias("pos", "ts")).where("ts is not null").select("doc_id", "pos", F.inline("ts"))
    # within a document a template counts once
    whole = seen.select("doc_id", F.array_distinct(F.flatten(F.filter("lines", lambda x: x.isNotNull()))).alias("ts"))
    alone = whole.join(again, "doc_id", "left_anti").select("doc_id", F.inline("ts"))
    shared = whole.join(again, "doc_id", "left_semi").select("doc_id", F.inline("ts")).distinct()
    least = F.when(F.col("a").bitwiseAND(F.lit(1)) == 1, passage_docs).otherwise(min_docs)
    recurring = alone.unionByName(shared).groupBy("a", "b").agg(F.count("*").alias("n"), F.min("doc_id").alias("first")).where(F.col("n") >= least).select("a", "b", "first")
    return flat.join(recurring, ["a", "b"]).where("doc_id > first").groupBy("doc_id").agg(F.collect_set("pos").alias("drop"))


def count_names(docs: DataFrame) -> tuple[str, str]:
    """Names of the two columns that ``drop_repeated_lines`` adds, other than those of ``docs``."""
    return unused("tpl_lines", docs), unused("tpl_dropped", docs)


def drop_repeated_lines(docs: DataFrame, min_docs: int = MIN_DOCS, passage_docs: int = PASSAGE_DOCS) -> DataFrame:
    """``docs`` with ``text`` less its repeated lines, and ``tpl_lines`` / ``tpl_dropped`` (lines with a word, those dropped).

    Null ids and null texts pass untouched, with 0 lines for null texts; empty and blank lines stay. Rows with one
    ``doc_id`` count as one document and lose the same positions. Other columns stay, those called ``tpl_*`` too:
    ``count_names`` then tells the names of the counts.
    """
    key, drop = unused("tpl_key", docs), unused("tpl_drop", docs)
    drops = repeated_lines(docs, min_docs, passage_docs).select(F.col("doc_id").alias(key), F.col("drop").alias(drop))
    out = docs.join(drops, F.col("doc_id") == F.col(key), "left")
    lines = F.split("text", "\n")
    rest = F.array_join(F.filter(lines, lambda x, i: ~F.array_contains(F.col(drop), i)), "\n")
    n = F.size(F.filter(F.coalesce(lines, F.array().cast("array<string>")), lambda x: F.btrim(x, F.lit(SPACES)) != "")).cast("long")
    counted, dropped = count_names(docs)
    return out.select(
        *[F.when(F.col(drop).isNull(), F.col("text")).otherwise(rest).alias("text") if c == "text" else F.col(c) for c in docs.columns],
        n.alias(counted), F.coalesce(F.size(drop), F.lit(0)).cast("long").alias(dropped),
    )


#: DuckDB twin of the query.
SQL = rf"""
with l as (select doc_id, unnest(string_split(text, chr(10))) as line, unnest(range(0, len(string_split(text, chr(10))))) as pos from documents where text is not null),
m as (select *, regexp_extract_all(regexp_replace(line, '[^\x20\x09-\x0D]*[0-9][^\x20\x09-\x0D]*', '<*>', 'g'), '[^\x20\x09-\x0D]+') as m from l),
t as (select doc_id, pos, case when 2 * len(list_filter(m, lambda x: x = '<*>')) > len(m) then regexp_extract_all(line, '[^\x20\x09-\x0D]+') else m end as w from m),
u as (select *, len(w) as n, ceil((len(w) - {LEADING}) / {PARTS}.0)::int as step from t where len(w) > 0),
k as (select doc_id, pos, n, unnest(case when n < {ONE_FROM} then ['-1 ' || array_to_string(w, ' ')]
  when n < {VARIES_FROM} then list_transform(range({SHORT_LEADING}, n), lambda i: i || ' ' || n || ' ' || array_to_string(list_concat(w[1:i], ['<*>'], w[i + 2:]), ' ')) else
  list_transform(range(0, {PARTS}), lambda p: p || ' ' || n || ' ' || array_to_string(list_concat(w[1:{LEADING} + p * step], ['*'], w[{LEADING} + (p + 1) * step + 1:]), ' ')) end) as key from u),
r as (select key, min(doc_id) as first from k group by key having count(distinct doc_id) >= case when max(n) > {PASSAGE_WORDS} then {PASSAGE_DOCS} else {MIN_DOCS} end),
x as (select distinct doc_id, pos from k join r using (key) where doc_id > first),
o as (select doc_id, string_agg(line, chr(10) order by pos) as text from l anti join x using (doc_id, pos) group by doc_id),
c as (select doc_id, count(*) as n from u group by doc_id), dr as (select doc_id, count(*) as n from x group by doc_id)
select d.doc_id, coalesce(c.n, 0)::bigint as n_lines, coalesce(dr.n, 0)::bigint as n_dropped, case when d.text is not null then length(coalesce(o.text, '')) end::bigint as n_chars_left, case when d.text is not null then md5(coalesce(o.text, '')) end as text_md5
from documents d left join o using (doc_id) left join c using (doc_id) left join dr using (doc_id)
"""
