"""Operators that users need around the study: scans, joins, aggregates, windows, sets, functions; each with SQL that gives its rows."""

from __future__ import annotations

import functools
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from geocensus.functions import columns as C
from geocensus.functions.patterns import ANY_DECIMAL
from geocensus.operators.sampling import bernoulli_sample
from geocensus.plans.workloads import PD, doc_flags, planted_docs
from geocensus.sources import index as I
from geocensus.sources.planter import quoted

Query = Callable[[SparkSession, str], DataFrame]
_Q: dict[str, Query] = {}
_SQL: dict[str, str] = {}
T = I.table


def _add(name: str, f: Query, sql: str | None = None) -> None:
    _Q[name] = f
    if sql:
        _SQL[name] = sql


def _view(s: SparkSession, d: str, *names: str) -> SparkSession:
    for n in names:
        T(s, d, n).createOrReplaceTempView(n)
    return s


def _plain(name: str, sql: str, tables: tuple[str, ...], duck: str | None = None) -> None:
    """A query that Spark's and the other engine's SQL read alike."""
    _add(name, lambda s, d: _view(s, d, *tables).sql(sql), duck or sql)


# Sources and sinks.


def _round_trip(fmt: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        e = T(s, d, "events").select("event_id", "user_id", "event_type", "props") if fmt != "text" else T(s, d, "events").select(F.concat_ws("|", "event_id", "event_type").alias("value"))
        path = I.scratch(s, f"round-{fmt}")
        getattr(e.write.option("header", True) if fmt == "csv" else e.write, fmt)(path)
        r = s.read.schema(e.schema)
        return getattr(r.option("header", True) if fmt == "csv" else r, fmt)(path)

    return run


def _partitioned(s: SparkSession, d: str) -> DataFrame:
    path = I.scratch(s, "parts")
    I.crawl_index(s, d).select("page_id", "url", "release", "part").write.partitionBy("release", "part").parquet(path)
    return s.read.parquet(path).where("release = 'R2021' and part = 2").select("page_id", "url")


def _idempotent(s: SparkSession, d: str) -> DataFrame:
    path = I.scratch(s, "sink")
    i = I.crawl_index(s, d).select("page_id", "release", "part")
    i.write.partitionBy("release", "part").parquet(path)
    i.where("release = 'R2019' and part = 1").write.partitionBy("release", "part").option("partitionOverwriteMode", "dynamic").mode("overwrite").parquet(path)
    return s.read.parquet(path).groupBy("release").agg(F.count("*").alias("n"))


def _ranges(s: SparkSession, d: str) -> DataFrame:
    """All bodies, written by the executors as archive files in the shared folder, and read again at every offset of the index."""
    path = I.scratch(s, "archives")
    I.write_archives(T(s, d, "pages"), path)
    i = I.with_offsets(I.crawl_index(s, d)).select(F.concat(F.lit(I.local(path) + "/"), I.archive_name(), F.lit(".arc")).alias("path"), "page_id", "offset", F.coalesce("length", F.lit(0)).alias("length"))
    lists = I.scratch(s, "ranges")
    i.repartition("path").sortWithinPartitions("path", "offset").select(F.concat_ws("|", "path", "page_id", "offset", "length")).write.text(lists)
    s.dataSource.register(I.RangeSource)
    return s.read.format("byte_ranges").option("lists", I.local(lists)).load().select("id", F.length("bytes").cast("long").alias("n_bytes"))


def _binary(s: SparkSession, d: str) -> DataFrame:
    """All bodies as files of at most 10,000 records; only the files' lengths are read."""
    path = I.scratch(s, "bodies")
    T(s, d, "pages").select(F.coalesce("html", F.lit("")).alias("value")).write.option("maxRecordsPerFile", 10_000).text(path)
    return s.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select(F.col("length").alias("n_bytes"))


def _sources() -> None:
    _plain("scan_pruned", "select page_id, url from pages", ("pages",))
    _add("scan_pushdown", lambda s, d: T(s, d, "lineitem").where(F.col("l_returnflag").isin("R", "A") & F.col("l_quantity").between(10, 20)).select("l_orderkey", "l_quantity", "l_returnflag"), "select l_orderkey, l_quantity, l_returnflag from lineitem where l_returnflag in ('R', 'A') and l_quantity between 10 and 20")
    _add("scan_partitioned", _partitioned, "select page_id, url from pages where page_id % 3 = 1 and (page_id // 3) % 5 = 2")
    for fmt in ("csv", "json", "orc", "parquet"):
        _add(f"roundtrip_{fmt}", _round_trip(fmt), "select event_id, user_id, event_type, props from events")
    _add("roundtrip_text", _round_trip("text"), "select event_id || '|' || event_type as value from events")
    _add("sink_idempotent", _idempotent, "select ['R2019', 'R2021', 'R2024'][(page_id % 3 + 1)::int] as release, count(*) as n from pages group by 1")
    _add("range_source", _ranges)
    _add("binary_files", _binary)
    _plain("project_exprs", "select l_orderkey, l_extendedprice * (1 - l_discount) as net, case when l_quantity > 25 then 'big' else 'small' end as size, cast(l_quantity as int) as q from lineitem", ("lineitem",))
    _add("filter_predicates", lambda s, d: T(s, d, "documents").where(F.col("n_chars").between(100, 3000) & F.col("lang").isin("en", "de") & F.col("text").like("%the%") & F.col("text").rlike("[0-9]") & ~F.col("source").eqNullSafe("src3")).select("doc_id"), "select doc_id from documents where n_chars between 100 and 3000 and lang in ('en', 'de') and text like '%the%' and regexp_matches(text, '[0-9]') and source is distinct from 'src3'")


def _joins() -> None:
    _add("join_broadcast", lambda s, d: T(s, d, "supplier").join(F.broadcast(T(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name"), "select s_suppkey, n_name from supplier join nation on s_nationkey = n_nationkey")
    sql = "select o_orderpriority, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by 1"
    for name, hint in (("join_sortmerge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
        _add(name, lambda s, d, hint=hint: T(s, d, "orders").join(T(s, d, "lineitem").hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), sql)
    for how, side in (("left_semi", "where exists (select 1 from labels l where l.doc_id = d.doc_id)"), ("left_anti", "where not exists (select 1 from labels l where l.doc_id = d.doc_id)")):
        _add(f"join_{how[5:]}", lambda s, d, how=how: T(s, d, "documents").select("doc_id").join(T(s, d, "labels").select("doc_id"), "doc_id", how), f"select d.doc_id from documents d {side}")
    for how in ("left", "right", "full"):
        _add(f"join_{how}_outer", lambda s, d, how=how: T(s, d, "documents").select("doc_id", "lang").join(T(s, d, "labels").select("doc_id", "quality"), "doc_id", how), f"select coalesce(d.doc_id, l.doc_id) as doc_id, lang, quality from documents d {how} join labels l on d.doc_id = l.doc_id")
    _add("join_cross", lambda s, d: T(s, d, "region").crossJoin(T(s, d, "nation")).select("r_name", "n_name"), "select r_name, n_name from region, nation")
    band = "select a.p_partkey as a, b.p_partkey as b from part a join part b on a.p_size = b.p_size and a.p_retailprice < b.p_retailprice and b.p_retailprice < a.p_retailprice + 5"
    _add("join_theta", lambda s, d: _band(T(s, d, "part"), 5), band)
    _add("join_range", lambda s, d: _range_join(s, d), "select e.event_id, w.k from events e join (select distinct user_id as k, date_trunc('day', ts) as lo from events where event_type = (select min(event_type) from events)) w on e.user_id = w.k and e.ts >= w.lo and e.ts < w.lo + interval 6 hour")
    _add("join_asof", lambda s, d: _asof(s, d), "select event_id, (select max(o_orderdate) from orders where o_custkey = e.user_id and o_orderdate <= e.ts) as last_order from events e")
    pair = "select a.source, a.doc_id as first, b.doc_id as later from documents a join documents b on a.source = b.source and a.n_chars = b.n_chars and a.doc_id < b.doc_id"
    _plain("join_self", pair, ("documents",))
    _add("join_nullsafe", lambda s, d: T(s, d, "labels").select(F.when(F.col("doc_id") % 5 > 0, F.col("quality")).alias("k")).distinct().join(T(s, d, "labels").select(F.when(F.col("doc_id") % 7 > 0, F.col("toxic")).alias("j")).distinct(), F.col("k").eqNullSafe(F.col("j"))), "select * from (select distinct case when doc_id % 5 > 0 then quality end as k from labels) join (select distinct case when doc_id % 7 > 0 then toxic end as j from labels) on k is not distinct from j")
    _add("join_salted", lambda s, d: _salted(s, d), "select p_brand, count(*) as n, sum(l_quantity) as qty from lineitem join part on l_partkey = p_partkey group by 1")
    _plain("fn_subquery", "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > (select avg(o_totalprice) from orders)) and not exists (select 1 from nation where n_nationkey = c_nationkey and n_regionkey = 0)", ("customer", "orders", "nation"))


def _band(part: DataFrame, width: int) -> DataFrame:
    """Pairs of one size whose prices differ by less than ``width``: the lower price goes to the bucket of its own price and to those
    up to its limit, the higher one to its own, so each pair meets once.  Rounding is monotone, so no pair falls between buckets."""
    bucket = lambda price: F.floor(price / width)
    low, price = part.select(F.col("p_partkey").alias("a"), "p_size", F.col("p_retailprice").alias("low")), F.col("p_retailprice")
    low = low.withColumn("bucket", F.explode(F.sequence(bucket(F.col("low")), bucket(F.col("low") + width))))
    high = part.select(F.col("p_partkey").alias("b"), "p_size", "p_retailprice", bucket(price).alias("bucket"))
    return low.hint("merge").join(high, ["p_size", "bucket"]).where((F.col("low") < price) & (price < F.col("low") + width)).select("a", "b")


def _range_join(s: SparkSession, d: str) -> DataFrame:
    """Points in intervals: both sides carry the day as a bucket, and the interval is checked within it."""
    e = T(s, d, "events").withColumn("day", F.date_trunc("day", "ts"))
    kind = e.agg(F.min("event_type").alias("kind"))
    w = e.join(F.broadcast(kind), F.col("event_type") == F.col("kind")).select(F.col("user_id").alias("k"), F.col("day").alias("lo")).distinct()
    return e.join(w, (F.col("user_id") == F.col("k")) & (F.col("day") == F.col("lo")) & (F.col("ts") < F.col("lo") + F.expr("interval 6 hours"))).select("event_id", "k")


def _asof(s: SparkSession, d: str) -> DataFrame:
    """The last order at or before each event: one union, one shuffle by customer, the last value carried forward."""
    e = T(s, d, "events").select(F.col("user_id").alias("k"), "ts", "event_id", F.lit(None).cast("timestamp").alias("o"), F.lit(1).alias("side"))
    o = T(s, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderdate").alias("o"), F.lit(0).alias("side"))
    w = Window.partitionBy("k").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(o).withColumn("last_order", F.last("o", ignorenulls=True).over(w)).where("side = 1").select("event_id", "last_order")


def _salted(s: SparkSession, d: str, salts: int = 8) -> DataFrame:
    """A join whose keys are split by a salt.  Spark takes the copies that ``explode`` makes for no larger than the table, and would
    broadcast them through the driver; hence the hint."""
    left = T(s, d, "lineitem").withColumn("salt", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(salts)).cast("int"))
    right = T(s, d, "part").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right.hint("merge"), (left["l_partkey"] == right["p_partkey"]) & (left["salt"] == right["salt"])).groupBy("p_brand").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"))


_POINT = r"@(-?[0-9]+\.[0-9]+),(-?[0-9]+\.[0-9]+)"


def points(s: SparkSession, d: str) -> DataFrame:
    """A point per document: latitude and longitude in hundredths from its id, for the spatial helpers."""
    b = C.bucket("geo", "doc_id", 1_000_000)
    return T(s, d, "documents").select("doc_id", ((b % 18_000) / 100.0 - 90.0).alias("lat"), ((F.floor(b / 7) % 36_000) / 100.0 - 180.0).alias("lon"))


PTS = "pts as (select doc_id, (b % 18000) / 100.0::double - 90.0::double as lat, ((b // 7) % 36000) / 100.0::double - 180.0::double as lon from (select doc_id, ('0x' || substr(md5('geo|' || doc_id), 1, 8))::bigint % 1000000 as b from documents))"


def _nearest(s: SparkSession, d: str, cell: float = 20.0) -> DataFrame:
    """The nearest other point within a cell and its neighbours.  Documents at one place are told apart first.  Each place then
    looks into nine small cells, and only one that finds nothing within a side of its cell looks again, in cells four times as
    wide: those that look again lie a side apart, so no point is compared with more than a bounded number of them."""
    w = Window.partitionBy("lat", "lon").orderBy("doc_id")
    first = F.first("doc_id").over(w)
    p = points(s, d).where("doc_id is not null").repartition("lat", "lon").distinct()
    p = I.stored(p.select("*", (first == F.col("doc_id")).alias("leads"), F.coalesce(F.when(first != F.col("doc_id"), first), F.lead("doc_id").over(w)).alias("same")), "points")
    places = p.where("leads").select("lat", "lon", F.col("doc_id").alias("other"))
    todo, found = places, []
    for k in (10, 8, 6, 4, 2, 0):
        side = cell / 2**k  # halves are exact, so small cells lie within the large ones
        x, y = F.floor(F.col("lon") / side), F.floor(F.col("lat") / side)
        q = todo.select("lat", "lon", F.explode(F.array(*[F.struct((x + i).alias("x"), (y + j).alias("y")) for i in (-1, 0, 1) for j in (-1, 0, 1)])).alias("c")).select(F.col("lat").alias("lat1"), F.col("lon").alias("lon1"), "c.x", "c.y")
        sq = F.round(F.pow(F.col("lat1") - F.col("lat"), 2) + F.pow(F.col("lon1") - F.col("lon"), 2), 6)
        m = F.min(F.when((F.col("lat1") != F.col("lat")) | (F.col("lon1") != F.col("lon")), F.struct(sq.alias("sq"), "other")))
        # Whatever lies outside the nine cells is farther than a side, also after rounding.
        near = F.coalesce(F.col("m.sq") + 2e-6 < side * side, F.lit(False)) if k else F.lit(True)
        j = q.hint("merge").join(places.withColumns({"x": x, "y": y}), ["x", "y"]).groupBy("lat1", "lon1").agg(m.alias("m"))
        level = I.stored(j.select(F.col("lat1").alias("lat"), F.col("lon1").alias("lon"), "m", near.alias("near")), "nearest")
        found.append(level.where("near").drop("near"))
        todo = level.where("not near").select("lat", "lon")
        if todo.isEmpty():
            break
    here = F.when(F.col("same").isNotNull(), F.struct(F.lit(0.0).alias("sq"), F.col("same").alias("other")))
    return p.join(functools.reduce(DataFrame.unionByName, found).hint("merge"), ["lat", "lon"]).select("doc_id", F.least(here, F.col("m"))["other"].alias("other")).where("other is not null")


def _spatial() -> None:
    km = "2 * 6371.0088::double * asin(sqrt(power(sin(radians(51.5::double - lat) / 2), 2) + cos(radians(lat)) * cos(radians(51.5::double)) * power(sin(radians(-0.12::double - lon) / 2), 2)))"
    _add("geo_haversine", lambda s, d: points(s, d).select("doc_id", F.round(C.haversine_km(F.col("lat"), F.col("lon"), F.lit(51.5), F.lit(-0.12)), 3).alias("km")), f"with {PTS} select doc_id, round({km}, 3) as km from pts")
    _add("geo_bbox", lambda s, d: points(s, d).where("lat between 35 and 60 and lon between -10 and 30"), f"with {PTS} select * from pts where lat between 35 and 60 and lon between -10 and 30")
    _add("geo_grid_count", lambda s, d: points(s, d).groupBy(F.floor(F.col("lat") / 30).alias("y"), F.floor(F.col("lon") / 30).alias("x")).agg(F.count("*").alias("n")), f"with {PTS} select floor(lat / 30)::bigint as y, floor(lon / 30)::bigint as x, count(*) as n from pts group by all")
    _add("geo_nearest", _nearest, f"with {PTS}, c as (select *, floor(lon / 20) as x, floor(lat / 20) as y from pts), j as (select a.doc_id, b.doc_id as other, round(power(a.lat - b.lat, 2) + power(a.lon - b.lon, 2), 6) as sq from c a join c b on abs(a.x - b.x) <= 1 and abs(a.y - b.y) <= 1 and a.doc_id <> b.doc_id) select doc_id, other from (select *, row_number() over (partition by doc_id order by sq, other) as nth from j) where nth = 1")


def _aggregates() -> None:
    _add("agg_hash", lambda s, d: T(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_shipdate").alias("lo"), F.max("l_shipdate").alias("hi")), "select l_returnflag, l_linestatus, count(*) as n, sum(l_quantity) as qty, round(avg(l_discount), 6) as disc, min(l_shipdate) as lo, max(l_shipdate) as hi from lineitem group by all")
    _plain("agg_sort", "select source, min(text) as lo, max(lang) as hi from documents group by source", ("documents",))
    _add("agg_conditional", lambda s, d: planted_docs(s, d).groupBy("release").agg(F.count_if("truth_addr").alias("addr"), F.bool_or("truth_coord").alias("some"), F.round(F.avg(F.when(F.col("truth_addr"), 1.0).otherwise(0.0)), 6).alias("share")), f"with {PD} select release, count(*) filter (truth_addr) as addr, bool_or(truth_coord) as some, round(avg(case when truth_addr then 1.0::double else 0.0::double end), 6) as share from pd group by 1")
    _plain("agg_distinct", "select event_type, count(distinct user_id) as users from events group by event_type", ("events",))
    _plain("agg_multi_distinct", "select count(distinct user_id) as users, count(distinct event_type) as kinds from events", ("events",))
    _add("agg_approx_distinct", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users")))
    _add("agg_hll", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("h")).agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("users")))
    for name, clause in (("agg_grouping_sets", "grouping sets ((l_returnflag), (l_linestatus), ())"), ("agg_cube", "cube (l_returnflag, l_linestatus)"), ("agg_rollup", "rollup (l_returnflag, l_linestatus)")):
        _plain(name, f"select l_returnflag, l_linestatus, cast(grouping(l_returnflag) * 2 + grouping(l_linestatus) as int) as g, count(*) as n from lineitem group by {clause}", ("lineitem",))
    _add("agg_pivot", lambda s, d: T(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0), "select o_orderpriority, count(*) filter (o_orderstatus = 'F') as F, count(*) filter (o_orderstatus = 'O') as O, count(*) filter (o_orderstatus = 'P') as P from orders group by 1")
    _add("agg_unpivot", lambda s, d: T(s, d, "labels").select("doc_id", "quality", "toxic").unpivot("doc_id", ["quality", "toxic"], "kind", "value"), "select doc_id, 'quality' as kind, quality as value from labels union all select doc_id, 'toxic', toxic from labels")
    _add("agg_percentile", lambda s, d: T(s, d, "documents").groupBy("lang").agg(F.expr("percentile(n_chars, 0.5)").alias("median")), "select lang, quantile_cont(n_chars, 0.5)::double as median from documents group by 1")
    _add("agg_percentile_approx", lambda s, d: T(s, d, "documents").agg(F.percentile_approx("n_chars", 0.9).alias("p90")))
    _add("agg_moments", lambda s, d: T(s, d, "documents").agg(F.round(F.stddev("n_chars"), 4).alias("sd"), F.round(F.corr("n_chars", "doc_id"), 6).alias("r"), (F.skewness("n_chars") > 0).alias("right_skewed")), "select round(stddev(n_chars), 4) as sd, round(corr(n_chars, doc_id), 6) as r, skewness(n_chars) > 0 as right_skewed from documents")
    _add("agg_collect", lambda s, d: T(s, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",").alias("roles")), "select conv_id, string_agg(role, ',' order by turn, role) as roles from conversations group by 1")
    _add("agg_min_max_by", lambda s, d: T(s, d, "orders").groupBy("o_orderpriority").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top")), "select o_orderpriority, (max({'p': o_totalprice, 'k': o_orderkey})).k as top from orders group by 1")
    _add("agg_topk_approx", lambda s, d: I.crawl_index(s, d).agg(F.expr("approx_top_k(tld, 3)").alias("t")).select(F.explode("t").alias("x")).select("x.item", "x.count"))
    _plain("agg_having", "select event_type, count(*) as n from events group by event_type having count(*) > 10", ("events",))


def _windows() -> None:
    for name, cols in (
        ("win_ranking", "row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd"),
        ("win_analytic", "lag(o_orderkey) over w as prev, lead(o_orderkey) over w as nxt, first_value(o_orderkey) over w as f, nth_value(o_orderkey, 2) over w as second"),
        ("win_rows_frame", "sum(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row) as running, round(avg(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row), 4) as mean3"),
    ):
        sql = f"select o_orderkey, {cols} from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)"
        _plain(name, sql, ("orders",), sql.replace("sum(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row)", "(sum(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row))::bigint").replace("row_number() over w", "(row_number() over w)::int").replace("rank() over w as rk", "(rank() over w)::int as rk").replace("dense_rank() over w as dr", "(dense_rank() over w)::int as dr").replace("ntile(4) over w", "(ntile(4) over w)::int"))
    _add("win_range_frame", lambda s, d: T(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("n")), "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as n from events")
    _add("win_share_of_total", lambda s, d: I.crawl_index(s, d).groupBy("tld").agg(F.count("*").alias("n")).withColumn("pct", F.round(100.0 * F.col("n") / F.sum("n").over(Window.partitionBy()), 4)), "select string_split(regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1), '.')[-1] as tld, count(*) as n, round(100.0::double * count(*) / sum(count(*)) over (), 4) as pct from pages group by 1")
    _plain("win_topk_per_group", "select l_suppkey, l_orderkey, l_linenumber, l_partkey from (select *, row_number() over (partition by l_suppkey order by l_extendedprice desc, l_orderkey, l_linenumber, l_partkey, l_shipdate) as nth from lineitem) q where nth <= 3", ("lineitem",))
    _add("sort_global", lambda s, d: T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey", "o_totalprice"), "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey")
    _add("sort_within", lambda s, d: T(s, d, "orders").sortWithinPartitions("o_orderdate").select("o_orderkey"), "select o_orderkey from orders")
    _plain("topk", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25", ("orders",))
    _plain("limit_offset", "select o_orderkey from orders order by o_orderkey limit 10 offset 20", ("orders",))
    for name, op in (("set_union_all", "union all"), ("set_union", "union"), ("set_intersect", "intersect"), ("set_intersect_all", "intersect all"), ("set_except", "except"), ("set_except_all", "except all")):
        _plain(name, f"select doc_id from documents {op} select doc_id from labels", ("documents", "labels"))
    _add("set_union_by_name", lambda s, d: T(s, d, "documents").select(F.col("doc_id").alias("id"), "lang").unionByName(T(s, d, "pages").select(F.col("page_id").alias("id"), "url"), allowMissingColumns=True), "select doc_id as id, lang, null::varchar as url from documents union all select page_id, null, url from pages")
    _add("dedup_texts", lambda s, d: T(s, d, "documents").groupBy(F.sha2("text", 256).alias("h")).agg(F.min("doc_id").alias("doc_id")), "select sha256(text) as h, min(doc_id) as doc_id from documents group by 1")


def _functions() -> None:
    p = "documents"
    _add("fn_string", lambda s, d: T(s, d, "part").select("p_partkey", F.lower("p_name").alias("a"), F.upper(F.trim("p_type")).alias("b"), F.substring_index("p_type", " ", 1).alias("c"), F.instr("p_type", "A").cast("long").alias("i"), F.translate("p_brand", "#0", "_o").alias("e"), F.levenshtein("p_name", "p_brand").cast("long").alias("f"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("g"), F.replace("p_name", F.lit("a"), F.lit("")).alias("h"), F.reverse("p_brand").alias("j")), "select p_partkey, lower(p_name) as a, upper(trim(p_type)) as b, split_part(p_type, ' ', 1) as c, instr(p_type, 'A') as i, translate(p_brand, '#0', '_o') as e, levenshtein(p_name, p_brand) as f, lpad(p_size::varchar, 4, '0') as g, replace(p_name, 'a', '') as h, reverse(p_brand) as j from part")
    _add("fn_regex", lambda s, d: T(s, d, p).select("doc_id", F.col("text").rlike("[0-9]{4}").alias("a"), F.regexp_extract("text", "([0-9]+)", 1).alias("b"), F.regexp_count("text", F.lit(ANY_DECIMAL)).cast("long").alias("n"), F.md5(F.regexp_replace("text", "[aeiou]", "*")).alias("c")), f"select doc_id, regexp_matches(text, '[0-9]{{4}}') as a, regexp_extract(text, '([0-9]+)', 1) as b, len(regexp_extract_all(text, '{ANY_DECIMAL}')) as n, md5(regexp_replace(text, '[aeiou]', '*', 'g')) as c from documents")
    _add("fn_url", lambda s, d: T(s, d, "pages").select("page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.parse_url("url", F.lit("HOST")).alias("host"), C.decode_url(F.lit("a+b%2Cc")).alias("x")), "select page_id, regexp_extract(url, '^([a-z]+):', 1) as scheme, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) as host, 'a b,c' as x from pages")
    _add("fn_hash", lambda s, d: T(s, d, p).select("doc_id", F.md5("text").alias("a"), F.sha2("text", 256).alias("b"), F.sha1("text").alias("c")), "select doc_id, md5(text) as a, sha256(text) as b, sha1(text) as c from documents")
    _add("fn_hash_fast", lambda s, d: T(s, d, p).select("doc_id", F.xxhash64("text").alias("h")))
    _add("fn_date", lambda s, d: T(s, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.quarter("o_orderdate").cast("long").alias("q"), F.date_trunc("month", "o_orderdate").alias("m"), F.datediff(F.lit("2000-01-01").cast("date"), F.col("o_orderdate").cast("date")).cast("long").alias("d"), F.unix_timestamp("o_orderdate").alias("u")), "select o_orderkey, year(o_orderdate) as y, quarter(o_orderdate) as q, date_trunc('month', o_orderdate)::timestamp as m, date_diff('day', o_orderdate::date, date '2000-01-01') as d, epoch(o_orderdate)::bigint as u from orders")
    _add("fn_math", lambda s, d: T(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round("l_extendedprice", 1).alias("a"), F.floor("l_extendedprice").alias("b"), F.ceil(F.col("l_discount") * 100).alias("c"), F.round(F.sqrt("l_quantity"), 6).alias("e"), F.pmod("l_orderkey", F.lit(7)).alias("f"), F.col("l_quantity").cast("decimal(12,2)").cast("double").alias("g")), "select l_orderkey, l_linenumber, round(l_extendedprice, 1) as a, floor(l_extendedprice)::bigint as b, ceil(l_discount * 100)::bigint as c, round(sqrt(l_quantity), 6) as e, l_orderkey % 7 as f, l_quantity::decimal(12,2)::double as g from lineitem")
    w = lambda: F.split("text", " ")
    _add("fn_array", lambda s, d: T(s, d, p).select("doc_id", F.size(w()).cast("long").alias("n"), F.size(F.array_distinct(w())).cast("long").alias("k"), F.size(F.filter(w(), lambda x: F.length(x) > 6)).cast("long").alias("long"), F.exists(w(), lambda x: x == "the").alias("the"), F.aggregate(F.transform(w(), F.length), F.lit(0), lambda a, x: a + x).cast("long").alias("chars"), F.element_at(F.sort_array(w()), 1).alias("low")), "select doc_id, len(string_split(text, ' ')) as n, len(list_distinct(string_split(text, ' '))) as k, len(list_filter(string_split(text, ' '), lambda x: length(x) > 6)) as long, list_contains(string_split(text, ' '), 'the') as the, list_sum(list_transform(string_split(text, ' '), lambda x: length(x)))::bigint as chars, list_sort(string_split(text, ' '))[1] as low from documents")
    _add("fn_map", lambda s, d: T(s, d, "labels").select("doc_id", F.create_map(F.lit("quality"), "quality", F.lit("toxic"), "toxic").alias("m")).select("doc_id", F.col("m")["toxic"].alias("toxic"), F.size(F.map_filter("m", lambda k, v: v > 0)).cast("long").alias("positive")), "select doc_id, toxic, (case when quality > 0 then 1 else 0 end + case when toxic > 0 then 1 else 0 end)::bigint as positive from labels")
    _add("fn_json", lambda s, d: T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("j"), F.to_json(F.struct("event_id")).alias("o")), "select event_id, (props->>'$.k')::bigint as k, (props->>'$.k')::bigint as j, '{\"event_id\":' || event_id || '}' as o from events")
    _add("fn_variant", lambda s, d: T(s, d, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "long").alias("k")), "select event_id, (props->>'$.k')::bigint as k from events")
    _add("fn_explode", lambda s, d: T(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "x")).select("vec_id", "pos", F.col("x").cast("double").alias("x")), "select vec_id, (unnest(range(0, len(embedding))))::int as pos, unnest(embedding)::double as x from embeddings")
    _add("fn_unescape", lambda s, d: T(s, d, "region").select("r_regionkey", C.unescape_unicode(F.concat("r_name", F.lit(" \\u0436\\u00e9 x \\ud83d\\ude00"))).alias("t")), "select r_regionkey, r_name || ' жé x 😀' as t from region")
    softened = "regexp_replace(html, '<[^>]{0,1000}>', ' ', 'g')"
    for name, value in C.ENTITIES:
        softened = f"replace({softened}, {quoted(name)}, {quoted(value)})"
    _add("fn_soften", lambda s, d: T(s, d, "pages").select("page_id", F.md5(C.as_shown(F.col("html"))).alias("h")), f"select page_id, md5({softened}) as h from pages")


def _user_functions() -> None:
    raw = "select doc_id, regexp_matches(text, '[0-9]{1,3}\\.[0-9]+') as hit from documents"

    def sql_udf(s: SparkSession, d: str) -> DataFrame:
        s.sql("create or replace temporary function has_decimal(t string) returns boolean return rlike(t, '[0-9]{1,3}[.][0-9]+')")
        return T(s, d, "documents").selectExpr("doc_id", "has_decimal(text) as hit")

    def python_udf(s: SparkSession, d: str) -> DataFrame:
        import re

        rx = re.compile(ANY_DECIMAL)
        f = F.udf(lambda x: bool(rx.search(x or "")), "boolean")
        return T(s, d, "documents").select("doc_id", f("text").alias("hit"))

    def pandas_udf(s: SparkSession, d: str) -> DataFrame:
        def hit(x: pd.Series) -> pd.Series:
            return x.str.contains(ANY_DECIMAL, regex=True)

        return T(s, d, "documents").select("doc_id", F.pandas_udf(hit, "boolean")("text").alias("hit"))

    def map_in_pandas(s: SparkSession, d: str) -> DataFrame:
        def run(batches):  # noqa: ANN001, ANN202
            for b in batches:
                yield pd.DataFrame({"doc_id": b["doc_id"], "hit": b["text"].str.contains(ANY_DECIMAL, regex=True)})

        return T(s, d, "documents").select("doc_id", "text").mapInPandas(run, "doc_id long, hit boolean")

    def arrow_udf(s: SparkSession, d: str) -> DataFrame:
        def hit(x):  # noqa: ANN001, ANN202
            import pyarrow.compute as pc

            return pc.match_substring_regex(x, ANY_DECIMAL)

        return T(s, d, "documents").select("doc_id", F.arrow_udf(hit, "boolean")("text").alias("hit"))

    def cogroup(s: SparkSession, d: str) -> DataFrame:
        """Sample against population, source by source: narrow rows of one source at a time, counted beforehand."""

        def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
            k = a["source"].iloc[0] if len(a) else b["source"].iloc[0]
            return pd.DataFrame({"source": [k], "in_all": [int(a["n"].sum())], "in_sample": [int(b["n"].sum())]})

        count = lambda x: x.groupBy("source", "lang").agg(F.count("*").alias("n"))
        all_docs = T(s, d, "documents").select("doc_id", "source", "lang")
        sample = bernoulli_sample(all_docs, 0.2, "lb", ["doc_id"])
        return count(all_docs).groupBy("source").cogroup(count(sample).groupBy("source")).applyInPandas(both, "source string, in_all long, in_sample long")

    _add("cogroup_in_pandas", cogroup, "select source, count(*) as in_all, count(*) filter (('0x' || substr(md5('lb|' || doc_id), 1, 8))::bigint < 858993459) as in_sample from documents group by 1")
    _add("udf_native", lambda s, d: T(s, d, "documents").select("doc_id", F.col("text").rlike(ANY_DECIMAL).alias("hit")), raw)
    for name, f in (("udf_sql", sql_udf), ("udf_python", python_udf), ("udf_pandas", pandas_udf), ("udf_arrow", arrow_udf), ("map_in_pandas", map_in_pandas)):
        _add(name, f, raw)

    def udaf(s: SparkSession, d: str) -> DataFrame:
        def mean(x: pd.Series) -> float:
            return float(x.mean())

        return T(s, d, "documents").groupBy("lang").agg(F.round(F.pandas_udf(mean, "double")("n_chars"), 4).alias("mean"))

    _add("udaf_pandas", udaf, "select lang, round(avg(n_chars), 4) as mean from documents group by 1")

    def apply_in_pandas(s: SparkSession, d: str) -> DataFrame:
        def top(g: pd.DataFrame) -> pd.DataFrame:
            return g.sort_values(["n_chars", "doc_id"], ascending=[False, True]).head(1)

        return T(s, d, "documents").select("lang", "doc_id", "n_chars").groupBy("lang").applyInPandas(top, "lang string, doc_id long, n_chars long")

    _add("apply_in_pandas", apply_in_pandas, "select lang, doc_id, n_chars from (select *, row_number() over (partition by lang order by n_chars desc, doc_id) as nth from documents) where nth = 1")

    def udtf(s: SparkSession, d: str) -> DataFrame:
        @F.udtf(returnType="raw string")
        class Matches:
            def eval(self, text: str):  # noqa: ANN202
                import re

                for m in re.finditer(ANY_DECIMAL, text or ""):
                    yield (m[0],)

        s.udtf.register("decimal_matches", Matches)
        T(s, d, "documents").createOrReplaceTempView("documents")
        return s.sql("select doc_id, raw from documents, lateral decimal_matches(text)")

    _add("udtf_matches", udtf, f"select doc_id, unnest(regexp_extract_all(text, '{ANY_DECIMAL}')) as raw from documents")


for _part in (_sources, _joins, _spatial, _aggregates, _windows, _functions, _user_functions):
    _part()


def queries() -> dict[str, Query]:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
