"""Quality rules whose cutoffs carry a guarantee against false rejection."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, broadcast_below, checkpointed, words

#: Most good documents of a stratum that all rules together may reject, and the chance that the guarantee fails.
FALSE_REJECTION, FAILURE = 0.05, 0.05
#: One labelled document in so many helps to choose joint cutoffs; the others certify them.
CHOOSING = 3
#: Largest table of strata that is broadcast.
STRATA = 1_000_000
#: Candidate cutoffs in thousandths, the same for each rule.
CUTOFFS = (20, 50, 80, 120, 160, 200, 250, 300, 350, 400, 450, 500, 600, 700, 800, 900)
#: Scores in thousandths; a document is rejected by a rule if its score is above the cutoff.
RULES = {
    "symbols": "1000 * n_symbols / greatest(word_chars, 1)",
    "dup_lines": "1000 * n_dup_lines / greatest(n_word_lines, 1)",
    "repeats": "1000 * n_repeat_words / greatest(n_words, 1)",
    "shouting": "1000 * n_shouts / greatest(n_words, 1)",
    "long_words": "20 * word_chars / greatest(n_words, 1)",
}


def _repeat_words(ws: Column) -> Column:
    """Positions covered by 3-word windows that occur twice or more, for an array of words.

    Windows are sorted with their positions, so that equal ones are neighbours: n log n in the length of a text.
    """
    grams = F.transform(F.slice(ws, 1, F.greatest(F.size(ws) - 2, F.lit(0))), lambda w, i: F.struct(F.concat_ws(" ", w, F.get(ws, i + 1), F.get(ws, i + 2)).alias("g"), i.alias("i")))

    def covered(s: Column) -> Column:
        again = F.filter(s, lambda x, k: (F.get(s, k - 1)["g"] == x["g"]) | (F.get(s, k + 1)["g"] == x["g"]))
        return F.size(F.array_distinct(F.flatten(F.transform(again, lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2)))))

    bound = F.get(F.transform(F.array(F.sort_array(grams)), covered), F.lit(0))
    return F.when(F.size(ws) < 4, F.lit(0)).otherwise(F.coalesce(bound, F.lit(0))).cast("long")


def features(docs: DataFrame, text: str = "text", *keep: str) -> DataFrame:
    """``keep`` columns with the base counts of each whole text; null texts count as empty."""
    body = F.coalesce(F.col(text), F.lit(""))
    lines = F.filter(F.split(body, "\n"), lambda x: F.btrim(x, F.lit(SPACES)) != "")
    # an array of one element binds the words, so that lambdas below index a value, not the split itself
    counts = F.get(
        F.transform(
            F.array(F.struct(words(F.col(text)).alias("w"), lines.alias("l"))),
            lambda x: F.struct(
                F.size(x["w"]).cast("long").alias("n_words"),
                F.length(F.array_join(x["w"], "")).cast("long").alias("word_chars"),
                (F.size(x["l"]) - F.size(F.array_distinct(x["l"]))).cast("long").alias("n_dup_lines"),
                F.size(x["l"]).cast("long").alias("n_word_lines"),
                _repeat_words(x["w"]).alias("n_repeat_words"),
            ),
        ),
        F.lit(0),
    )
    return (
        docs.select(*keep, counts.alias("c"), F.regexp_count(body, F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"), F.regexp_count(body, F.lit("!!")).cast("long").alias("n_shouts"))
        .select(*keep, "c.*", "n_symbols", "n_shouts")
        .withColumn("base_failed", F.expr("n_words < 50 or 100 * n_repeat_words > 50 * n_words"))
    )


def _certified(n: Column, k: Column, risk: float, tests: Column) -> Column:
    """True if a false rejection rate above ``risk`` is refuted at level FAILURE / tests by k rejections of n good documents.

    The exact binomial tail P(X <= k | n, risk), in logarithms: its last term, times the sum of the ratios below it.
    """
    last = F.aggregate(F.sequence(F.lit(1), F.greatest(k, F.lit(1))), F.lit(0.0), lambda a, i: a + F.when(i <= k, F.log((n - k + i) / i)).otherwise(0.0)) + k * F.log(F.lit(risk)) + (n - k) * F.log(F.lit(1 - risk))
    ratios = F.aggregate(
        F.sequence(F.lit(1), F.greatest(k, F.lit(1))),
        F.struct(F.lit(1.0).alias("t"), F.lit(1.0).alias("s")),
        # j runs k, k - 1, ..., 1
        lambda a, i: F.when(i <= k, F.struct((a["t"] * (k - i + 1) / (n - (k - i + 1) + 1) * ((1 - risk) / risk)).alias("t"), (a["s"] + a["t"] * (k - i + 1) / (n - (k - i + 1) + 1) * ((1 - risk) / risk)).alias("s"))).otherwise(a),
        lambda a: a["s"],
    )
    # with k at or above the mean the tail is near a half or more: refuted at no useful level
    return F.when(k < n * risk, last + F.log(ratios) <= F.log(F.lit(FAILURE) / tests)).otherwise(F.lit(False))


def _tallies(labelled: DataFrame) -> DataFrame:
    """For each stratum and rule the good documents ``n``, and the bad (``b``) and good (``g``) ones above each cutoff."""
    rows = labelled.select("stratum", "quality", F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.col(r).alias("score")) for r in RULES])).alias("x"))
    return rows.groupBy("stratum", "x.rule").agg(
        F.sum((F.col("quality") == 1).cast("long")).alias("n"),
        *[F.sum(((F.col("quality") == q) & (F.col("x.score") > c)).cast("long")).alias(f"{'bg'[q]}{c}") for c in CUTOFFS for q in (0, 1)],
    )


def cutoffs(scored: DataFrame, labels: DataFrame, risk: float = FALSE_REJECTION) -> DataFrame:
    """``(stratum, rule, cutoff)`` of cutoffs that are certified together, at the full risk.

    A third of the labelled documents, by a hash of their id, chooses: for each stratum and rule the cutoff with the most
    bad less good rejections, the mildest among equals, of those that reject at most half the risk of the third's good
    ones; rules are ordered by that gain. The others certify in that order: first the first rule alone, then with the
    second, and so on, each time all good documents that any of the rules so far rejects. The first set that fails the
    exact bound ends the sequence, so each test of a stratum has the whole level, divided by the strata alone. With s strata
    ln(FAILURE / s) / ln(1 - risk) good documents are needed to certify, 86 for 4 strata: about 129 labelled in all.
    Strata with fewer have no cutoff and reject nothing. The guarantee is about documents that pass the base rules: what
    those reject is outside it. A document labelled twice counts as bad if one label says so; labels without quality and
    labels of unknown documents don't count.
    """
    known = labels.where("quality is not null").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    rows = checkpointed(scored.join(known, "doc_id").select("stratum", "quality", (F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long") % CHOOSING == 0).alias("chooses"), *RULES))
    cells = _tallies(rows.where("chooses")).select("stratum", "rule", "n", F.explode(F.array(*[F.struct(F.lit(c).alias("cutoff"), F.col(f"b{c}").alias("bad"), F.col(f"g{c}").alias("k")) for c in CUTOFFS])).alias("c")).select("stratum", "rule", "n", "c.*")
    best = cells.where((F.col("bad") > F.col("k")) & (2 * F.col("k") <= risk * F.col("n"))).groupBy("stratum", "rule").agg(F.max(F.struct((F.col("bad") - F.col("k")).alias("gain"), "cutoff")).alias("x"))
    steps = best.groupBy(F.col("stratum").alias("of")).agg(F.sort_array(F.collect_list(F.struct((-F.col("x.gain")).alias("less"), "rule", F.col("x.cutoff").alias("cutoff")))).alias("steps"))
    # the first step that rejects a good document counts it for that step and all later ones
    score = F.create_map(*[x for r in RULES for x in (F.lit(r), F.col(r))])
    at = F.array_position(F.transform("steps", lambda s: F.element_at(score, s["rule"]) > s["cutoff"]), True)
    good = rows.where("not chooses and quality = 1").join(F.broadcast(steps), F.col("stratum").eqNullSafe(F.col("of"))).select("stratum", "steps", at.alias("at"))
    sums = good.groupBy("stratum").agg(F.first("steps").alias("steps"), F.count("*").alias("n"), *[F.sum(F.col("at").between(1, i + 1).cast("long")).alias(f"k{i}") for i in range(len(RULES))])
    strata = rows.agg(F.countDistinct(F.coalesce(F.concat(F.lit("="), F.col("stratum")), F.lit("-"))).alias("strata"))
    passed = F.array(*[_certified(F.col("n"), F.col(f"k{i}"), risk, F.col("strata")) for i in range(len(RULES))])
    fails = F.array_position(passed, False)
    held = F.when(fails == 0, len(RULES)).otherwise(fails - 1).cast("int")
    out = sums.crossJoin(F.broadcast(strata)).select("stratum", F.explode(F.slice("steps", 1, held)).alias("s"))
    return out.select("stratum", "s.rule", "s.cutoff")


def judge(docs: DataFrame, labels: DataFrame, stratum: str = "lang", keep: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id`` and ``keep`` of every row with the base counts, ``base_failed`` and ``kept``, by the certified cutoffs.

    Rows keep their number, repeated ones too. Null and empty texts have no words and fail the base rules. A null stratum
    is a stratum. Empty tables give no rows; without labels only the base rules reject. Other columns don't matter.
    """
    named = docs.select("doc_id", "text", F.col(stratum).alias("stratum"), *keep)
    scored = checkpointed(features(named, "text", "doc_id", "stratum", *keep).withColumns({r: F.expr(f"cast(floor({e}) as long)") for r, e in RULES.items()}))
    chosen = cutoffs(scored.where(~F.col("base_failed")), labels).groupBy("stratum").pivot("rule", list(RULES)).agg(F.first("cutoff"))
    chosen = checkpointed(chosen.select(F.col("stratum").alias("of"), *[F.col(r).alias(f"max_{r}") for r in RULES]))
    # one row for each stratum that has a cutoff
    out = scored.join(broadcast_below(chosen, STRATA), F.col("stratum").eqNullSafe(F.col("of")), "left")
    over = F.greatest(*[F.coalesce((F.col(r) > F.col(f"max_{r}")).cast("int"), F.lit(0)) for r in RULES]) == 1
    return out.withColumn("kept", ~F.col("base_failed") & ~over).drop("of", *[f"max_{r}" for r in RULES])


def _sql() -> str:
    """DuckDB twin of the query; the tail is summed term by term from lgamma."""
    scores = ", ".join(f"cast(floor({e}) as bigint) as {r}" for r, e in RULES.items())
    long = " union all ".join(f"select doc_id, stratum, '{r}' as rule, {r} as score from p where not base_failed" for r in RULES)
    grid = ", ".join(f"({c})" for c in CUTOFFS)
    risk = FALSE_REJECTION
    at = lambda i: f"count(*) filter (step <= {i})"
    tail = lambda k: f"{k} < n * {risk} and (select sum(exp(lgamma(n + 1) - lgamma(j + 1) - lgamma(n - j + 1) + j * ln({risk}) + (n - j) * ln(1 - {risk}))) from (select unnest(range(0, {k}::bigint + 1)) as j)) <= {FAILURE} / strata"
    held, passed = "0", "true"
    for i in range(1, len(RULES) + 1):
        passed += f" and {tail(f'k{i}')}"
        held += f" + ({passed})::int"
    return rf"""
with t as (select doc_id, lang, coalesce(text, '') as text from documents),
w as (select *, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as ws, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as ls from t),
g as (select doc_id, unnest(range(1, len(ws) - 1)) as i, ws from w where len(ws) > 2),
gr as (select doc_id, i, count(*) over (partition by doc_id, ws[i], ws[i + 1], ws[i + 2]) as c from g),
rep as (select doc_id, count(distinct i + o) as n from gr, (values (0), (1), (2)) v(o) where c > 1 group by doc_id),
f as (select w.doc_id, lang as stratum, len(ws)::bigint as n_words, length(array_to_string(ws, ''))::bigint as word_chars,
  len(regexp_extract_all(text, '[#*$%&|<>]'))::bigint as n_symbols, (len(ls) - len(list_distinct(ls)))::bigint as n_dup_lines, len(ls)::bigint as n_word_lines,
  len(regexp_extract_all(text, '!!'))::bigint as n_shouts, coalesce(rep.n, 0)::bigint as n_repeat_words from w left join rep using (doc_id)),
p as (select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed, {scores} from f),
s as ({long}),
y as (select doc_id, min(quality) as quality from labels where quality is not null group by doc_id),
z as (select s.*, y.quality, ('0x' || substr(md5(s.doc_id::varchar), 1, 8))::bigint % {CHOOSING} = 0 as chooses from s join y using (doc_id)),
c as (select stratum, rule, cutoff, sum((quality = 1)::int) as n, sum((quality = 1 and score > cutoff)::int) as k, sum((quality = 0 and score > cutoff)::int) as bad
  from z, (values {grid}) v(cutoff) where chooses group by all),
pick as (select stratum, rule, max(bad - k) as gain, arg_max(cutoff, (bad - k) * 10000 + cutoff) as cutoff from c where bad > k and 2 * k <= {risk} * n group by all),
steps as (select *, row_number() over (partition by stratum order by gain desc, rule) as step from pick),
hit as (select z.doc_id, z.stratum, min(case when z.score > t.cutoff then t.step end) as step from z join steps t on z.stratum is not distinct from t.stratum and z.rule = t.rule where not chooses and quality = 1 group by all),
ns as (select count(distinct coalesce('=' || stratum, '-')) as strata from z),
tally as (select stratum, strata, count(*) as n, {', '.join(f'{at(i)} as k{i}' for i in range(1, len(RULES) + 1))} from hit, ns group by all),
held as (select stratum, {held} as held from tally),
best as (select t.* from steps t join held h on t.stratum is not distinct from h.stratum where t.step <= h.held),
r as (select distinct s.doc_id from s join best on s.stratum is not distinct from best.stratum and s.rule = best.rule where s.score > best.cutoff)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and doc_id not in (select doc_id from r) as kept from p
"""


SQL = _sql()
