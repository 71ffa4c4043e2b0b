"""Exact duplicates: skew-safe combining on digests, with full content compared at every stage.  DataFrame operations only."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from geocensus.llm.shared import materialise, strip_white, text_or_empty

_SPAN = "cast(18446744073709551616 as decimal(20,0))"
_TOP = "cast(9223372036854775807 as decimal(20,0))"
_NO_ID = 9223372036854775807


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = 16, hot_share: int = 1000) -> DataFrame:
    """One row per document: ``doc_id, keep_id, group_size, kept, text_sha256``.

    Texts are equal when they are identical without white space; null counts as empty.  The row with the most code points
    in its original text stays, of equal ones the smallest id.  Rows that repeat an id and its text all count and all
    carry ``kept`` if their id stays.  A null id loses every tie; an empty table gives no rows; other columns are ignored.

    Stages, each grouping by digest *and* normalised text: a partial aggregate in every map task (local), groups of
    (digest, salt, text), then the salts' winners.  Only a digest with more than 1/``hot_share`` of the rows is salted; at
    most ``hot_share`` digests are, which bounds the broadcast.  A text is shuffled once, or once per map task and salt.
    """
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("t"))
    base = base.select("doc_id", F.char_length("t").alias("n"), strip_white(F.col("t")).alias("norm"))
    base = base.withColumns({"digest": F.unhex(F.sha2("norm", 256)), "tag": F.xxhash64("norm")})
    keys = materialise(base.select("doc_id", "digest", "tag"), "exact-keys")
    limit = keys.count() // hot_share + 1
    hot = F.broadcast(keys.groupBy("digest").count().where(F.col("count") > limit).select("digest", F.lit(True).alias("hot")))

    # Code points first, then the smaller id: one number, so that hash aggregates can hold it.
    rank = F.expr(f"cast(n as decimal(12,0)) * {_SPAN} + ({_TOP} - cast(coalesce(doc_id, {_NO_ID}) as decimal(20,0)))")
    salt = F.when(F.col("hot"), F.pmod(F.xxhash64("doc_id"), F.lit(salts))).otherwise(F.lit(-1))
    rows = base.join(hot, "digest", "left").withColumns({"rank": rank, "salt": salt})
    best = [F.max("rank").alias("rank"), F.count("*").alias("group_size")]
    salted = rows.groupBy("digest", "tag", "salt", "norm").agg(*best)
    # A digest that isn't salted is final here; its content isn't needed again.
    salted = materialise(salted.withColumn("norm", F.when(F.col("salt") >= 0, F.col("norm"))), "exact-salted")
    warm = salted.where("salt >= 0").groupBy("digest", "tag", "norm").agg(F.max("rank").alias("rank"), F.sum("group_size").alias("group_size"))
    groups = salted.where("salt < 0").drop("salt", "norm").unionByName(warm.drop("norm"))
    keep = F.expr(f"cast({_TOP} - rank % {_SPAN} as decimal(19,0))").cast("long")
    groups = groups.select("digest", "tag", F.nullif(keep, F.lit(_NO_ID)).alias("keep_id"), "group_size")
    # The way back: a hot digest's rows are dealt over the salts again, and meet a copy of its group at each.
    dealt = F.explode(F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(-1))))
    groups = groups.join(hot, "digest", "left").withColumn("salt", dealt).drop("hot")
    out = keys.join(hot, "digest", "left").withColumn("salt", salt.cast("int")).drop("hot").join(groups, ["digest", "tag", "salt"])
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row of each group of equal texts, all its columns kept.

    Rows are told apart by id alone where ids are unique.  Else, null ids included, a row stays for its id and its text, so
    different texts under one id all stay, and rows that repeat both leave one.
    """
    found = materialise(exact_duplicates(docs, id_col, text_col), "exact-found")
    kept = found.where("kept").select(F.col("doc_id").alias("__keep"), F.unhex("text_sha256").alias("__digest")).distinct()
    same = F.col("__id").eqNullSafe(F.col("__keep"))
    own = docs.withColumn("__id", F.col(id_col).cast("long"))
    if found.count() == found.select("doc_id").distinct().count():
        return own.join(kept, same, "left_semi").drop("__id")
    norm = strip_white(text_or_empty(text_col))
    own = own.withColumn("__own", F.unhex(F.sha2(norm, 256))).join(kept, same & (F.col("__own") == F.col("__digest")), "left_semi")
    longest = Window.partitionBy("__id", "__own").orderBy(F.desc(F.char_length(text_or_empty(text_col))))
    return own.withColumn("__nth", F.row_number().over(longest)).where("__nth = 1").drop("__id", "__own", "__nth")


SQL = r"""
with d as (select doc_id, length(coalesce(text, '')) as n, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') as norm from documents),
g as (select *, first_value(doc_id) over (partition by norm order by n desc, doc_id rows between unbounded preceding and unbounded following) as keep_id,
             count(*) over (partition by norm) as group_size from d)
select doc_id, keep_id, group_size, doc_id = keep_id as kept, sha256(norm) as text_sha256 from g
"""
