"""Quality rules with risk-controlled cutoffs.  DataFrame operations only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from geocensus.llm.shared import WORD, join_checked, materialise, text_or_empty, words_of

_N = 5
#: Rules that reject above a cutoff, and the cutoffs tried, loosest first.
RULES = {
    "symbols_per_word": (2.0, 1.5, 1.0, 0.75, 0.5, 0.4, 0.3, 0.2),
    "marks_per_word": (2.0, 1.5, 1.0, 0.75, 0.5, 0.4, 0.3, 0.2),
    "dup_line_share": (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3),
    "repeat_share": (0.18, 0.16, 0.14, 0.12, 0.1),
    "word_length": (30.0, 25.0, 20.0, 16.0, 14.0, 12.0),
}


def counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """``doc_id, stratum, n_words, word_chars, n_symbols, n_marks, n_lines, n_dup_lines, n_repeat_words`` of every whole text."""
    t = F.col("t")
    d = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(stratum_col), F.lit("")).alias("stratum"), text_or_empty(text_col).alias("t"))
    d = d.withColumn("ws", words_of(t)).withColumns({
        "lines": F.filter(F.split(t, "\n", -1), lambda x: x.rlike(WORD)), "n_words": F.size("ws"),
        "n_symbols": F.regexp_count(t, F.lit(r"[#*$%&|<>]")), "n_marks": F.length(t) - F.length(F.replace(t, F.lit("!"), F.lit(""))),
        "word_chars": F.length(F.array_join("ws", "")), "h1": F.transform("ws", lambda w: F.xxhash64(w)),
    })
    # A window's hash joins those of words 1 and 2, then 3 and 4, then 5: three passes without look-ups.
    both = lambda x, y: F.xxhash64(x, y)
    later = lambda c, k: F.slice(c, F.lit(k + 1), F.greatest(F.col("n_words") - k, F.lit(0)))
    d = d.withColumn("h2", F.zip_with("h1", later("h1", 1), both))
    d = d.withColumn("h4", F.zip_with("h2", later("h2", 2), both))
    d = d.withColumn("h", F.slice(F.zip_with("h4", later("h1", 4), both), F.lit(1), F.greatest(F.col("n_words") - (_N - 1), F.lit(0))))
    d = d.select("doc_id", "stratum", "n_words", "word_chars", "n_symbols", "n_marks", F.size("lines").alias("n_lines"), (F.size("lines") - F.size(F.array_distinct("lines"))).alias("n_dup_lines"), "h", (F.size(F.array_distinct("h")) < F.size("h")).alias("again"))
    # Only texts that repeat a window sort theirs: equal hashes are neighbours then, and their places give the words covered.
    none = F.array().cast("array<struct<h:bigint,i:int>>")
    d = d.withColumn("s", F.when(F.col("again"), F.sort_array(F.transform("h", lambda x, i: F.struct(x.alias("h"), i.alias("i"))))).otherwise(none))
    twin = lambda x, i: (F.get("s", i + 1)["h"].eqNullSafe(x["h"])) | ((i > 0) & F.get("s", F.greatest(i - 1, F.lit(0)))["h"].eqNullSafe(x["h"]))
    d = d.withColumn("at", F.sort_array(F.transform(F.filter("s", twin), lambda x: x["i"])))
    covered = F.aggregate(F.transform("at", lambda x, i: F.least(F.lit(_N), F.coalesce(F.get("at", i + 1) - x, F.lit(_N)))), F.lit(0), lambda a, x: a + x)
    longs = [F.col(c).cast("long").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_marks", "n_lines", "n_dup_lines")]
    return d.select("doc_id", "stratum", *longs, covered.cast("long").alias("n_repeat_words"))


def _value(rule: str) -> Column:
    per = {"symbols_per_word": ("n_symbols", "n_words"), "marks_per_word": ("n_marks", "n_words"), "dup_line_share": ("n_dup_lines", "n_lines"), "repeat_share": ("n_repeat_words", "n_words"), "word_length": ("word_chars", "n_words")}
    a, b = per[rule]
    return F.coalesce(F.col(a) / F.col(b), F.lit(0.0))


def binomial_tail(n: Column, k: Column, p: float) -> Column:
    """P(Bin(n, p) <= k), summed exactly in logarithms; callers keep k below about n p."""
    start = F.struct((n * F.lit(math.log1p(-p))).alias("t"), F.exp(n * F.lit(math.log1p(-p))).alias("s"))

    def step(a: Column, i: Column) -> Column:
        t = a["t"] + F.log((n - i + 1) / i) + F.lit(math.log(p / (1 - p)))
        return F.struct(t.alias("t"), (a["s"] + F.exp(t)).alias("s"))

    none = F.array().cast("array<bigint>")
    return F.aggregate(F.when(k > 0, F.sequence(F.lit(1).cast("long"), k.cast("long"))).otherwise(none), start, step)["s"]


def certified_cutoffs(features: DataFrame, labels: DataFrame, risk: float = 0.01, delta: float = 0.05) -> DataFrame:
    """``stratum, rule, cutoff``: per stratum and rule the strictest cutoff whose false rejection of good rows is at most ``risk``.

    With probability 1 - ``delta`` all of them hold at once: exact binomial tests, in a fixed sequence from loose to strict
    within a rule and stratum (a sequence ends at its first failure), Bonferroni over rules and strata.  A stratum with too
    few labels certifies nothing, and its documents are then kept by these rules.
    """
    good = features.join(labels.where("quality = 1").select(F.col("doc_id").alias("__id")).distinct(), F.col("doc_id") == F.col("__id"), "left_semi")
    tests = F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(i).alias("step"), F.lit(c).alias("cutoff"), (_value(r) > c).alias("hit")) for r, cs in RULES.items() for i, c in enumerate(cs)]))
    cells = good.select("stratum", tests.alias("t")).groupBy("stratum", "t.rule", "t.step", "t.cutoff").agg(F.count("*").alias("n"), F.count_if("t.hit").alias("k"))
    strata = cells.select(F.count_distinct("stratum").alias("strata"))
    cells = cells.crossJoin(F.broadcast(strata))  # one row
    p = F.when(F.col("k") <= F.col("n") * risk, binomial_tail(F.col("n"), F.col("k"), risk)).otherwise(1.0)
    cells = cells.withColumn("pass", p <= delta / (F.col("strata") * len(RULES)))
    so_far = Window.partitionBy("stratum", "rule").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    cells = cells.withColumn("all", F.min(F.col("pass").cast("int")).over(so_far)).where("all = 1")
    return cells.groupBy("stratum", "rule").agg(F.min("cutoff").alias("cutoff"))


def judge(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """The counts of every document, ``base_failed`` and ``kept``.

    Null and empty texts have no words and fail the base rule; a null stratum counts as its own; unlabelled strata only
    have the base rule; rows that repeat an id are judged alike.
    """
    features = materialise(counts(docs, id_col, text_col, stratum_col), "rules-counts")
    cuts = certified_cutoffs(features, labels).groupBy("stratum").agg(*[F.max(F.when(F.col("rule") == r, F.col("cutoff"))).alias(r) for r in RULES])
    cuts = materialise(cuts, "rules-cuts")
    out = join_checked(features, cuts, "stratum")
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    bad = F.lit(False)
    for r in RULES:
        bad = bad | F.coalesce(_value(r) > F.col(r), F.lit(False))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & ~bad).alias("kept"), "stratum")


def _sql() -> str:
    """The query in SQL: counts on words themselves, tails by gamma functions."""
    tried = ", ".join(f"('{r}', {i}, {c}::double)" for r, cs in RULES.items() for i, c in enumerate(cs))
    return rf"""
with b as (select doc_id, coalesce(lang, '') as stratum, coalesce(text, '') as t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
g as (select doc_id, i, array_to_string(w[i:i + 4], ' ') as g from (select doc_id, w, unnest(range(1, len(w) - 3)) as i from b where len(w) >= 5)),
r as (select doc_id, i from (select *, count(*) over (partition by doc_id, g) as c from g) where c > 1),
c as (select doc_id, count(distinct i + k) as n from r, (select unnest(range(0, 5)) as k) group by 1),
l as (select doc_id, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as lines from b),
f as (select b.doc_id, stratum, len(w) as n_words, length(array_to_string(w, '')) as word_chars, len(regexp_extract_all(t, '[#*$%&|<>]')) as n_symbols, length(t) - length(replace(t, '!', '')) as n_marks, len(lines) as n_lines, len(lines) - len(list_distinct(lines)) as n_dup_lines, coalesce(c.n, 0) as n_repeat_words
      from b join l using (doc_id) left join c using (doc_id)),
v as (select f.doc_id, stratum, rule, step, cutoff, coalesce(case rule when 'symbols_per_word' then n_symbols / nullif(n_words, 0) when 'marks_per_word' then n_marks / nullif(n_words, 0) when 'dup_line_share' then n_dup_lines / nullif(n_lines, 0) when 'repeat_share' then n_repeat_words / nullif(n_words, 0) else word_chars / nullif(n_words, 0) end, 0) as value
      from f, (values {tried}) x(rule, step, cutoff)),
k as (select stratum, rule, step, cutoff, count(*) as n, count(*) filter (value > cutoff) as k from v where doc_id in (select doc_id from labels where quality = 1) group by all),
p as (select *, case when k <= n * 0.01::double then list_sum([exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln(0.01::double) + (n - i) * ln(0.99::double)) for i in range(0, k + 1)]) else 1 end as p, (select count(distinct stratum) from k) as strata from k),
a as (select *, min((p <= 0.05::double / (strata * {len(RULES)}))::int) over (partition by stratum, rule order by step) as passed from p),
cut as (select stratum, rule, min(cutoff) as cutoff from a where passed = 1 group by 1, 2),
bad as (select distinct doc_id from v join cut using (stratum, rule) where value > cut.cutoff)
select doc_id, n_words::bigint as n_words, word_chars::bigint as word_chars, n_symbols::bigint as n_symbols, n_dup_lines::bigint as n_dup_lines, n_repeat_words::bigint as n_repeat_words, n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed,
  not (n_words < 10 or 100 * n_repeat_words > 20 * n_words) and doc_id not in (select doc_id from bad) as kept, stratum from f
"""


SQL = _sql()
