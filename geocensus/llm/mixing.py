"""Mixing sources to target weights: Pareto order sampling after whole copies.  DataFrame operations only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from geocensus.llm.shared import WORD, join_checked, materialise, text_or_empty

#: Weights of the sources in code-point order, repeating.
WEIGHTS = (5, 2, 1)
MOST = 3
SEED = "mix"
_BUCKETS = 4096
_HALF = 50  # words at which a document gets half the inclusion of a very long one


def _unit(id_col: Column) -> Column:
    """A number in (0, 1) that only depends on the seed and the id."""
    digits = F.substring(F.md5(F.concat(F.lit(f"{SEED}|"), F.coalesce(id_col.cast("string"), F.lit("null")))), 1, 13)
    return (F.conv(digits, 16, 10).cast("double") + 0.5) / F.lit(float(2**52))


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    """``skey, source_size, target`` of a table ``skey, source, size``: shares by weight of all words, capped at ``most`` sizes.

    The excess of capped sources is shared again by weight: sources in the order of cap/weight, of which a prefix is capped.
    The single-task windows run over one row per source.
    """
    s = sizes.groupBy("skey").agg(F.max("source").alias("source"), F.sum("size").alias("source_size"))
    nth = (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)
    s = s.withColumn("w", F.element_at(F.array(*[F.lit(w).cast("long") for w in weights]), (nth + 1).cast("int")))
    s = s.withColumn("cap", F.col("source_size") * most)
    order = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    s = s.withColumns({"nth": F.row_number().over(order), "caps": F.coalesce(F.sum("cap").over(before), F.lit(0)), "ws": F.sum("w").over(every) - F.coalesce(F.sum("w").over(before), F.lit(0)), "all": F.sum("source_size").over(every)})
    free = F.col("w").cast("decimal(9,0)") * (F.col("all") - F.col("caps")).cast("decimal(19,0)") <= F.col("cap").cast("decimal(19,0)") * F.col("ws").cast("decimal(9,0)")
    s = s.withColumn("first", F.min(F.struct(F.when(free, F.col("nth")).otherwise(F.lit(2**31 - 1)).alias("nth"), "caps", "ws")).over(every))
    share = ((F.col("all") - F.col("first.caps")) * F.col("w")).cast("double") / F.col("first.ws")
    return s.select("skey", "source_size", F.when(F.col("nth") < F.col("first.nth"), F.col("cap").cast("double")).otherwise(share).alias("target"))


def _gain(size: Column) -> Column:
    """Inclusion of a document before scaling, in thousandths: longer documents count for more, up to 1,000."""
    return F.floor(size * 1000 / (size + _HALF)).cast("long")


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", keep: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, size, source_size, target, taken`` for every document (and the columns ``keep``).

    A document's expected copies are proportional to its inclusion, at most 3, and scaled so that a source's expected
    words equal its target.  Whole expected copies are certain.  For the rest, documents rank by Pareto's key, the odds of
    their random number over the odds of their inclusion, and the first of them are taken up to the source's remaining
    words (the last one if that comes nearer).  Rows that repeat an id share its random number.  Null texts and texts
    without a word have size 0 and are never taken; a null source is a source of its own, last in order; an empty table
    gives no rows.  Reruns agree.

    No window runs over a whole source: ranks are found in 4,096 intervals of the key, and only documents in the interval
    in which a source reaches its target are sorted.
    """
    size = F.regexp_count(text_or_empty(text_col), F.lit(WORD)).cast("long")
    skey = F.when(F.col(source_col).isNull(), F.lit("-")).otherwise(F.concat(F.lit("+"), F.col(source_col)))
    d = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), size.alias("size"), skey.alias("skey"))
    d = materialise(d, "mix-sizes")
    plan, cuts = _plan(d)
    out = docs.select(F.col(id_col).alias("doc_id"), size.alias("size"), skey.alias("skey"), *[F.col(c).alias(f"__{c}") for c in keep]) if keep else d.drop("source")
    out = _chosen(join_checked(_ranked(join_checked(out, plan, "skey")), cuts, "skey"))
    taken = (F.col("size") * (F.col("whole") + F.col("chosen").cast("long"))).cast("long")
    return out.select("doc_id", "size", "source_size", "target", taken.alias("taken"), *[F.col(f"__{c}").alias(c) for c in keep])


def mix_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix: every row of ``docs`` as often as it is taken, all its columns kept; texts are not shuffled."""
    extra = tuple(c for c in docs.columns if c != id_col)
    out = mix(docs, id_col, text_col, source_col, keep=extra).where("taken > 0")
    out = out.withColumn("__copy", F.explode(F.sequence(F.lit(1), (F.col("taken") / F.col("size")).cast("int"))))
    return out.select(*[F.col("doc_id").alias(id_col) if c == id_col else F.col(c) for c in docs.columns])


def _plan(d: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Per source: target and scale; and where its key order is cut."""
    targets = source_targets(d)
    hist = d.where("size > 0").groupBy("skey", "size").agg(F.count("*").alias("n")).join(targets, "skey")
    words, weight = F.col("n") * F.col("size"), (F.col("n") * F.col("size") * _gain(F.col("size"))).cast("decimal(30,0)")
    larger = Window.partitionBy("skey").orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, -1)
    rest = Window.partitionBy("skey").orderBy(F.desc("size")).rowsBetween(0, Window.unboundedFollowing)
    hist = hist.withColumns({"over": F.coalesce(F.sum(words).over(larger), F.lit(0)), "weight": F.sum(weight).over(rest).cast("double")})
    room = F.col("target") - 3.0 * F.col("over")
    scale = hist.where(room * _gain(F.col("size")) <= 3.0 * F.col("weight")).groupBy("skey").agg(F.max(F.struct("size", room.alias("room"), "weight")).alias("m"))
    plan = targets.join(scale, "skey", "left").select("skey", "source_size", "target", F.col("m.size").alias("upto"), F.col("m.room").alias("room"), F.col("m.weight").alias("weight"))
    plan = materialise(plan, "mix-plan")

    ranked = _ranked(join_checked(d.where("size > 0"), plan, "skey"))
    certain = ranked.groupBy("skey").agg(F.sum(F.col("whole") * F.col("size")).alias("sure"))
    hist = ranked.where("part > 0").groupBy("skey", "bucket").agg(F.sum("size").alias("words"))
    before = Window.partitionBy("skey").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    hist = hist.withColumn("before", F.coalesce(F.sum("words").over(before), F.lit(0)))
    hist = hist.join(certain, "skey").join(plan.select("skey", "target"), "skey").withColumn("left", F.col("target") - F.col("sure"))
    edge = hist.where((F.col("before") < F.col("left")) & (F.col("before") + F.col("words") > F.col("left"))).select("skey", F.col("bucket").alias("edge"), F.col("before").alias("edge_before"), "left")
    within = join_checked(ranked.where("part > 0"), edge, "skey", "inner").where("bucket = edge")
    order = Window.partitionBy("skey").orderBy("key", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    within = within.withColumn("cum", F.col("edge_before") + F.coalesce(F.sum("size").over(order), F.lit(0)))
    last = within.where(F.col("cum") + F.col("size") / 2.0 <= F.col("left")).groupBy("skey").agg(F.max(F.struct("key", "doc_id")).alias("last"))
    # A source without an edge takes all (its targets end at a bucket's end) or none.
    full = hist.where(F.col("before") + F.col("words") <= F.col("left")).groupBy("skey").agg(F.max("bucket").alias("full"))
    cuts = plan.select("skey").join(full, "skey", "left").join(last, "skey", "left").select("skey", "full", F.col("last.key").alias("last_key"), F.col("last.doc_id").alias("last_id"))
    return plan, materialise(cuts, "mix-cuts")


def _ranked(d: DataFrame) -> DataFrame:
    """Adds whole copies, the part of a copy left, Pareto's key and its interval."""
    copies = F.when(F.col("size") == 0, 0.0).when(F.col("upto").isNull() | (F.col("size") > F.col("upto")), 3.0).otherwise(F.least(F.lit(3.0), F.col("room") * _gain(F.col("size")) / F.col("weight")))
    d = d.withColumn("copies", F.coalesce(copies, F.lit(0.0)))
    d = d.withColumn("whole", F.floor("copies").cast("long")).withColumn("part", F.col("copies") - F.col("whole"))
    d = d.withColumn("u", _unit(F.col("doc_id")))
    key = F.when(F.col("part") > 0, (F.col("u") / (1.0 - F.col("u"))) / (F.col("part") / (1.0 - F.col("part"))))
    d = d.withColumn("key", key)
    return d.withColumn("bucket", F.floor(F.col("key") / (1.0 + F.col("key")) * _BUCKETS).cast("int"))


def _chosen(d: DataFrame) -> DataFrame:
    key, last = F.col("key"), F.col("last_key")
    in_edge = (key < last) | ((key == last) & (F.col("doc_id") <= F.col("last_id")))
    return d.withColumn("chosen", F.coalesce((F.col("part") > 0) & (F.coalesce(F.col("bucket") <= F.col("full"), F.lit(False)) | F.coalesce(in_edge, F.lit(False))), F.lit(False)))


SQL = r"""
with d as (select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size from documents),
s0 as (select source, sum(size)::bigint as source_size from d group by source),
s1 as (select *, [5, 2, 1][((row_number() over (order by source nulls last) - 1) % 3 + 1)::int]::bigint as w, 3 * source_size as cap from s0),
s2 as (select *, row_number() over o as nth, coalesce(sum(cap) over (o rows between unbounded preceding and 1 preceding), 0) as caps,
              sum(w) over () - coalesce(sum(w) over (o rows between unbounded preceding and 1 preceding), 0) as ws, sum(source_size) over () as total
       from s1 window o as (order by cap / w, source nulls last)),
f as (select nth as fn, caps as fc, ws as fw from s2 where w * (total - caps) <= cap * ws order by nth limit 1),
t as (select source, source_size, case when fn is null or nth < fn then cap::double else ((total - fc) * w)::bigint::double / fw::bigint end as target from s2 left join f on true),
h0 as (select source, size, count(*) as n, (floor(size * 1000 / (size + 50)))::bigint as a from d where size > 0 group by source, size),
h as (select h0.*, target, coalesce(sum(n * size) over (partition by source order by size desc rows between unbounded preceding and 1 preceding), 0)::double as larger,
             (sum(n * size * a) over (partition by source order by size desc rows between current row and unbounded following))::double as weight
      from h0 join t using (source)),
c as (select source, max(size) as upto, arg_max(target - 3.0 * larger, size) as room, arg_max(weight, size) as weight from h where (target - 3.0 * larger) * a <= 3.0 * weight group by source),
e as (select d.*, source_size, target, case when size = 0 then 0.0 when upto is null or size > upto then 3.0
             else least(3.0::double, room * (floor(size * 1000 / (size + 50)))::bigint / weight) end::double as copies,
             (('0x' || substr(md5('mix|' || doc_id), 1, 13))::bigint::double + 0.5) / 4503599627370496.0::double as u
      from d join t using (source) left join c using (source)),
k as (select *, floor(copies)::bigint as whole, copies - floor(copies) as part from e),
q as (select *, (u / (1.0 - u)) / (part / (1.0 - part)) as pk from k where part > 0),
r as (select source, target - sum(whole * size) as room_left from k group by source, target),
z as (select doc_id, coalesce(sum(size) over (partition by source order by pk, doc_id rows between unbounded preceding and 1 preceding), 0) + size / 2.0 <= room_left as chosen from q join r using (source))
select k.doc_id, size, source_size, target, (size * (whole + coalesce(chosen, false)::bigint))::bigint as taken from k left join z using (doc_id)
"""
