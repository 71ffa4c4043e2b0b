"""The study end to end: census, sampled estimate, judged study, and a scan of everything."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geocensus.functions.columns import has_address, has_coords
from geocensus.operators import sampling as S
from geocensus.operators import study as Y
from geocensus.sources.index import fetch_by_scan, stored

Detector = Callable[[Column], Column]
# A few of the commonest words of the four languages of the tables.
STOP_WORDS = {"en": "the|of|and|to|in|is|that|was", "de": "der|die|und|den|das|ist|nicht|mit", "fr": "le|et|les|des|un|est|pour|dans", "es": "que|el|los|y|del|las|por|con"}


def census(index: DataFrame) -> DataFrame:
    """``mime, release, files, pct_of_release`` in long form, over every release."""
    n = index.groupBy("release").agg(F.count("*").alias("all"))
    long = Y.mime_census(index).unpivot("mime", ["R2019", "R2021", "R2024"], "release", "files")
    return long.join(F.broadcast(n), "release", "left").select("mime", "release", "files", F.round(100.0 * F.col("files") / F.col("all"), 4).alias("pct_of_release"))  # one row per release


def estimate(frame: DataFrame, docs: DataFrame, id_col: str, text_col: str, k: int, strata: list[str], seed: str, by: str, detector: tuple[Detector, Detector] = (has_coords, has_address), z: float = 1.96) -> DataFrame:
    """Prevalence in a stratified sample: ids from the narrow frame, bodies of those only.  ``detector`` tells coordinates and addresses."""
    ids = S.stratified_sample(frame.select(id_col, *strata), strata, k, seed, [id_col])
    return Y.prevalence(Y.doc_flags(fetch_by_scan(docs, ids, id_col), text_col, [id_col, by], *detector), by, z)


def full_scan(docs: DataFrame, text_col: str, keep: list[str], by: str, detector: tuple[Detector, Detector] = (has_coords, has_address), z: float = 1.96) -> DataFrame:
    """No sample: every document, by rules only."""
    return Y.prevalence(Y.doc_flags(docs, text_col, keep, *detector), by, z)


def judge_study(planted: DataFrame, id_col: str, text_col: str) -> dict[str, DataFrame]:
    """Responses, categories and both audits of the rule judge."""
    r = Y.triage(stored(Y.rule_judge(planted, id_col, text_col), "responses"))
    return {"responses": r, "verdicts": Y.categorise(r), "grounding": Y.audit_grounding(r, planted, id_col, text_col), "misses": Y.audit_misses(r, planted, id_col)}


def lang_group(html: Column) -> Column:
    """English, English and another, other, or unknown: the declared language, and a stop-word vote over the advert."""
    first = F.regexp_extract(html, '<html[^>]{0,80}lang="([a-z]{2})', 1)
    ad = F.concat(F.lit(" "), F.lower(F.regexp_extract(html, '<div class="ad">([^<]*)', 1)), F.lit(" "))
    votes = {k: F.regexp_count(ad, F.lit(f" (?:{w}) ")) for k, w in STOP_WORDS.items()}
    best = F.greatest(*votes.values())
    second = F.when(best == 0, "")
    for k, v in votes.items():
        second = second.when(v == best, k)
    english, other = (first == "en") | (second == "en"), ((first != "en") & (first != "")) | ((second != "en") & (second != ""))
    return F.when(english & other, "english_other").when(english, "english").when(other, "other").otherwise("unknown")


def lang_group_sql(html: str = "html") -> str:
    first = f"regexp_extract({html}, '<html[^>]{{0,80}}lang=\"([a-z]{{2}})', 1)"
    ad = f"(' ' || lower(regexp_extract({html}, '<div class=\"ad\">([^<]*)', 1)) || ' ')"
    votes = {k: f"len(regexp_extract_all({ad}, ' (?:{w}) '))" for k, w in STOP_WORDS.items()}
    best = f"greatest({', '.join(votes.values())})"
    second = f"case when {best} = 0 then '' " + " ".join(f"when {v} = {best} then '{k}'" for k, v in votes.items()) + " end"
    return f"(select case when (a = 'en' or b = 'en') and ((a <> 'en' and a <> '') or (b <> 'en' and b <> '')) then 'english_other' when a = 'en' or b = 'en' then 'english' when a <> '' or b <> '' then 'other' else 'unknown' end from (select {first} as a, {second} as b))"
