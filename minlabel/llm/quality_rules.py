"""Quality rules with risk-controlled cutoffs, in DataFrame functions only.

Base measures of a text (words are runs without ASCII white space) feed a few badness scales, whole numbers from 0 to
100. Labelled good documents that pass the base rules are the holdout. For each stratum and scale the cutoffs are
tested from the loosest to the strictest: rejecting at cutoff c is allowed if the exact binomial tail
P(Bin(n, risk) <= wrong(c)) is at most the level, where wrong(c) of the stratum's n good documents would go. Tests along
a scale are a fixed sequence (wrong(c) only grows as c gets stricter); over strata and scales the level is divided by
their number, and each scale gets an equal share of the risk. So with probability 1 - level, in every stratum at most
the stated share of good documents is rejected by the scales together.

Counts for the tails are pre-aggregated to at most 101 bins for each stratum and scale; nothing is collected.

Defined cases: a null or empty text has no words and fails the base rules; a null stratum is the stratum "und"; strata
without enough labels get no cutoff and reject nothing; labels are joined by id, repeated labels of a document count as
often as they stand, and repeated rows are judged each; other columns pass through keep_good, also ones that begin with
ml_, as names of the operator's own do (measures, cutoffs and judged take tables without such names).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from minlabel.llm.shared import aside
from minlabel.session import stored

#: Share of good documents that may go, and probability of exceeding it anywhere.
RISK, LEVEL = 0.05, 0.05
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50
#: Labelled good documents whose ids may be broadcast.
FEW_IDS = 1_000_000
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
#: Badness of a document on a scale, 0 to 100, from the base measures; larger is worse.
SCALES = {
    "repeats": "100 * n_repeat_words div n_words",
    "symbols": "100 * n_symbols div word_chars",
    "dup_lines": "100 * n_dup_lines div n_lines",
    "long_words": "word_chars div n_words",
    "short_words": "100 - 10 * word_chars div n_words",
    "few_lines": "n_words div n_lines div 10",
}


def measures(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with ml_ columns of the base measures. Everything works inside a row: no shuffle."""
    words = r"split(trim(BOTH ' \t\n\u000B\u000C\r' FROM ml_t), '[ \\t-\\r]+')"
    # Windows that may occur twice: their hashes without the low bits, which hold the place, are equal to a neighbour's
    # when sorted. Only these are compared by the whole hash.
    steps = [
        ("ml_t", f"coalesce(cast(`{text}` as string), '')"),
        ("ml_w", f"if(ml_t rlike '[^ \\\\t-\\\\r]', {words}, cast(array() as array<string>))"),
        ("ml_n_words", "cast(size(ml_w) as bigint)"),
        ("ml_word_chars", "aggregate(ml_w, 0L, (a, w) -> a + length(w))"),
        ("ml_n_symbols", "cast(size(split(ml_t, '[#*$%&|<>]')) - 1 as bigint)"),
        ("ml_lines", "filter(split(ml_t, '\\n'), l -> l rlike '[^ \\\\t-\\\\r]')"),
        ("ml_n_lines", "cast(size(ml_lines) as bigint)"),
        ("ml_n_dup_lines", "ml_n_lines - size(array_distinct(ml_lines))"),
        ("ml_h", "transform(slice(ml_w, 1, greatest(size(ml_w) - 2, 0)), (w, i) -> xxhash64(w, ml_w[i + 1], ml_w[i + 2]))"),
        ("ml_b", "cast(ceil(log2(size(ml_h) + 2)) as int)"),
        ("ml_s", "sort_array(transform(ml_h, (h, i) -> shiftleft(shiftright(h, ml_b), ml_b) | cast(i as bigint)))"),
        ("ml_c", "filter(ml_s, (x, i) -> (i > 0 and shiftright(ml_s[i - 1], ml_b) = shiftright(x, ml_b)) or (i + 1 < size(ml_s) and shiftright(ml_s[i + 1], ml_b) = shiftright(x, ml_b)))"),
        ("ml_p", "sort_array(transform(ml_c, x -> named_struct('h', ml_h[cast(x & (shiftleft(1L, ml_b) - 1) as int)], 'p', cast(x & (shiftleft(1L, ml_b) - 1) as int))))"),
        ("ml_r", "sort_array(transform(filter(ml_p, (x, i) -> (i > 0 and ml_p[i - 1].h = x.h) or (i + 1 < size(ml_p) and ml_p[i + 1].h = x.h)), x -> x.p))"),
        # each repeated window covers three words; a word that the window before covers too counts once
        ("ml_n_repeat_words", "aggregate(ml_r, named_struct('n', 0L, 'e', 0), (a, p) -> named_struct('n', a.n + p + 3 - greatest(p, a.e), 'e', p + 3)).n"),
    ]
    out = docs
    for name, expression in steps:
        out = out.withColumn(name, F.expr(expression))
    # As one generated column the measures are made once: conditions on them are not moved below and spelled out again.
    own = F.explode(F.array(F.struct(*[F.col(f"ml_{m}") for m in MEASURES]))).alias("ml_m")
    return out.select(*[F.col(f"`{c}`") for c in docs.columns], own).select(*[F.col(f"`{c}`") for c in docs.columns], "ml_m.*")


def base_failed() -> F.Column:
    return F.expr(f"ml_n_words < {MIN_WORDS} or 100 * ml_n_repeat_words > {MAX_REPEAT_PERCENT} * ml_n_words")


def badness() -> F.Column:
    """array<struct<scale, bin>> of a measured document."""
    one = lambda name, rule: f"named_struct('scale', '{name}', 'bin', cast(greatest(0, least(100, coalesce({_own(rule)}, 0))) as int))"
    return F.expr(f"array({', '.join(one(*x) for x in SCALES.items())})")


def _own(rule: str) -> str:
    for m in MEASURES:
        rule = rule.replace(f"div {m}", f"div nullif(ml_{m}, 0)").replace(f"* {m}", f"* ml_{m}")
        rule = f"ml_{rule}" if rule.startswith(m) else rule
    return rule


def stratum(docs: DataFrame, column: str) -> F.Column:
    return F.coalesce(docs[column].cast("string"), F.lit("und"))


def cutoffs(measured: DataFrame, labels: DataFrame, key: str = "doc_id", good: str = "quality", by: str = "lang", risk: float = RISK, level: float = LEVEL) -> DataFrame:
    """stratum, scale, cutoff (reject at or above), n_good, wrong: the strictest allowed cutoff, if there is one."""
    share = risk / len(SCALES)
    mine = measured.where(~base_failed()).select(F.col(key).alias("ml_key"), stratum(measured, by).alias("stratum"), badness().alias("bad"))
    holdout = mine.join(labels.where(F.col(good) == 1).select(F.col(key).alias("ml_key")), "ml_key")
    binned = holdout.select("stratum", F.explode("bad").alias("b")).groupBy("stratum", F.col("b.scale").alias("scale"), F.col("b.bin").alias("bin")).agg(F.count("*").alias("n"))
    whole = Window.partitionBy("stratum", "scale")
    tests = binned.withColumn("n_good", F.sum("n").over(whole)).groupBy("stratum", "scale", "n_good").agg(F.map_from_entries(F.collect_list(F.struct("bin", "n"))).alias("at"))  # 101 bins at most
    tests = stored(tests, "tests")
    number = tests.select("stratum").distinct().count() * len(SCALES)
    walked = tests.select(
        "stratum", "scale", "n_good",
        F.expr("explode(transform(sequence(1, 101), c -> named_struct('cutoff', c, 'wrong', aggregate(map_entries(at), 0L, (a, e) -> a + if(e.key >= c, e.value, 0L)))))").alias("t"),
    ).select("stratum", "scale", "n_good", "t.cutoff", "t.wrong")
    # P(Bin(n, share) <= wrong): each term from the one before, in logarithms
    tail = (
        f"aggregate(sequence(0L, wrong), named_struct('l', cast(n_good as double) * ln(1 - {share}D), 'p', 0D), (a, i) -> named_struct("
        f"'l', a.l + ln(cast(greatest(n_good - i, 1) as double) / (i + 1) * {share / (1 - share)!r}D), 'p', a.p + exp(a.l))).p"
    )
    allowed = walked.where(f"wrong <= {share}D * n_good").withColumn("p", F.expr(tail)).where(f"p <= {level}D / {max(number, 1)}")  # beyond the mean a tail is about a half
    return allowed.groupBy("stratum", "scale").agg(F.min("cutoff").alias("cutoff"), F.max("n_good").alias("n_good"), F.max("wrong").alias("wrong"))


def judged(measured: DataFrame, limits: DataFrame, by: str = "lang") -> DataFrame:
    """measured with ml_base_failed and ml_kept."""
    per = limits.groupBy(F.col("stratum").alias("ml_stratum")).agg(F.map_from_entries(F.collect_list(F.struct("scale", "cutoff"))).alias("ml_limits"))
    out = measured.withColumn("ml_stratum", stratum(measured, by)).join(per, "ml_stratum", "left")
    bad = badness()
    out = out.withColumn("ml_base_failed", base_failed()).withColumn("ml_bad", bad)
    over = F.exists("ml_bad", lambda b: F.coalesce(b["bin"] >= F.col("ml_limits")[b["scale"]], F.lit(False)))
    return out.withColumn("ml_kept", ~F.col("ml_base_failed") & ~over).drop("ml_stratum", "ml_limits", "ml_bad")


def quality_report(docs: DataFrame, labels: DataFrame, by: str = "lang") -> DataFrame:
    """doc_id, base measures, base_failed and kept of each row; texts are read once, the rest works on the stored measures."""
    kept = stored(measures(docs.select("doc_id", "text", by)).drop("text"), "quality")
    out = judged(kept, cutoffs(kept, labels, by=by), by)
    return out.select("doc_id", *[F.col(f"ml_{m}").alias(m) for m in MEASURES], F.col("ml_base_failed").alias("base_failed"), F.col("ml_kept").alias("kept"))


def keep_good(docs: DataFrame, labels: DataFrame, by: str = "lang") -> DataFrame:
    """The rows of docs that are kept, with their columns as they were."""
    good, labelled = labels.where(F.col("quality") == 1).select("doc_id"), docs.select("doc_id", "text", by)
    if good.limit(FEW_IDS + 1).count() <= FEW_IDS:  # then only labelled texts are measured; otherwise all are, and no text is moved to its label
        labelled = labelled.join(F.broadcast(good), "doc_id", "left_semi")
    limits = stored(cutoffs(stored(measures(labelled).drop("text"), "quality"), labels, by=by), "limits")
    given, names = aside(docs)
    return judged(measures(given), limits, names[by]).where("ml_kept").select(*[F.col(f"`{names[c]}`").alias(c) for c in docs.columns])


#: The same in DuckDB's SQL, for the given tables.
def oracle(docs: str = "documents", labels: str = "labels") -> str:
    rule = lambda r: r.replace(" div ", " // ")
    scales = " union all ".join(f"select doc_id, stratum, base_failed, '{name}' as scale, greatest(0, least(100, coalesce({_sql(rule(r))}, 0))) as bin from m" for name, r in SCALES.items())
    share = RISK / len(SCALES)
    return f"""
with t as (select doc_id, coalesce(text, '') as text, coalesce(lang, 'und') as stratum from {docs}),
w as (select doc_id, stratum, text, list_filter(regexp_split_to_array(text, '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> '') as w,
      list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^ \\t\\n\\x0B\\f\\r]')) as l from t),
g as (select doc_id, i, w[i] as a, w[i+1] as b, w[i+2] as c from (select doc_id, w, unnest(range(1, len(w) - 1)) as i from w)),
d as (select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, a, b, c) as n from g) where n > 1),
r as (select doc_id, count(distinct i + k) as n_repeat_words from d, (select unnest([0, 1, 2]) as k) group by doc_id),
m as (select w.doc_id, stratum, cast(len(w) as bigint) as n_words, coalesce(cast(list_sum(list_transform(w, lambda x: length(x))) as bigint), 0) as word_chars,
      cast(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) as bigint) as n_symbols,
      cast(len(l) - len(list_distinct(l)) as bigint) as n_dup_lines, coalesce(n_repeat_words, 0) as n_repeat_words, cast(len(l) as bigint) as n_lines,
      len(w) < {MIN_WORDS} or 100 * coalesce(n_repeat_words, 0) > {MAX_REPEAT_PERCENT} * len(w) as base_failed
      from w left join r on w.doc_id = r.doc_id),
s as ({scales}),
h as (select stratum, scale, bin from s join {labels} on s.doc_id = labels.doc_id where quality = 1 and not base_failed),
n as (select stratum, scale, count(*) as n_good from h group by all),
k as (select n.stratum, n.scale, n_good, c as cutoff, (select count(*) from h where h.stratum = n.stratum and h.scale = n.scale and h.bin >= c) as wrong
      from n, (select unnest(range(1, 102)) as c)),
p as (select *, list_sum(list_transform(range(0, wrong + 1), lambda i: exp(lgamma(n_good + 1) - lgamma(i + 1) - lgamma(n_good - i + 1) + i * ln({share}) + (n_good - i) * ln(1 - {share})))) as p
      from k where wrong <= {share} * n_good),
u as (select stratum, scale, min(cutoff) as cutoff from p where p <= {LEVEL} / ((select count(distinct stratum) from n) * {len(SCALES)}) group by all),
o as (select s.doc_id, bool_or(coalesce(s.bin >= u.cutoff, false)) as over from s left join u on s.stratum = u.stratum and s.scale = u.scale group by s.doc_id)
select m.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, base_failed, not base_failed and not over as kept
from m join o on m.doc_id = o.doc_id"""


def _sql(rule: str) -> str:
    for m in MEASURES:
        rule = rule.replace(f"// {m}", f"// nullif({m}, 0)")
    return rule
