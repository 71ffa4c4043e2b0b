"""The study's workloads on the given tables: each a query, and SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geocensus.functions import columns as C
from geocensus.functions.patterns import ADDRESSES, ANY_DECIMAL, BARE_MASKS, COORDS, DECOYS, KEYED_MASKS, KEYWORDS, LICENCE, READ_AS_SHOWN
from geocensus.operators import sampling as S
from geocensus.operators import study as Y
from geocensus.sources import index as I
from geocensus.sources.planter import COORD_SNIPPETS, plant, plant_sql, quoted

Query = Callable[[SparkSession, str], DataFrame]
_Q: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def _add(name: str, f: Query, sql: str | None = None) -> None:
    _Q[name] = f
    if sql:
        _SQL[name] = sql


def docs(spark: SparkSession, sf: str) -> DataFrame:
    return I.table(spark, sf, "documents")


def planted_docs(spark: SparkSession, sf: str) -> DataFrame:
    return plant(docs(spark, sf), "doc_id", "text").withColumn("release", I.release_of("doc_id"))


def planted_pages(spark: SparkSession, sf: str) -> DataFrame:
    return plant(I.table(spark, sf, "pages"), "page_id", "html").withColumn("release", I.release_of("page_id"))


REL = "['R2019', 'R2021', 'R2024'][({} % 3 + 1)::int]"
PD = f"pd as ({plant_sql('documents', 'doc_id', 'text', 'doc_id, lang, source, n_chars, ' + REL.format('doc_id') + ' as release')})"
PP = f"pp as ({plant_sql('pages', 'page_id', 'html', 'page_id, url, ' + REL.format('page_id') + ' as release')})"


def _masked(t: str, kinds: tuple[str, ...] = BARE_MASKS) -> str:
    for k in kinds:
        t = f"regexp_replace({t}, {quoted(DECOYS[k])}, '\\1 \\2', 'g')"
    return t


def _shown(t: str) -> str:
    t = f"regexp_replace({t}, '<[^>]{{0,1000}}>', ' ', 'g')"
    for name, value in C.ENTITIES:
        t = f"replace({t}, {quoted(name)}, {quoted(value)})"
    return t


def _coord_format_sql(t: str, k: str) -> str:
    seen = _masked(t, BARE_MASKS if k == "c1_bare_pair" else KEYED_MASKS)
    out = f"(regexp_matches({t}, {quoted(COORDS[k])}) and regexp_matches({seen}, {quoted(COORDS[k])}))"
    return f"({out} or regexp_matches({_shown(t)}, {quoted(COORDS[k])}))" if k in READ_AS_SHOWN else out


def _coord_sql(t: str) -> str:
    """Without the gates, which must change nothing."""
    return f"(regexp_matches({t}, '[0-9]') and (" + " or ".join(_coord_format_sql(t, k) for k in COORDS) + "))"


def _addr_sql(t: str) -> str:
    return "(" + " or ".join(f"regexp_matches({t}, {quoted(v)})" for v in ADDRESSES.values()) + ")"


FLAGS = f"{PD}, f as (select *, {_coord_sql('text')} as has_coord, {_addr_sql('text')} as has_addr from pd)"
PAGE_FLAGS = f"{PP}, f as (select *, {_coord_sql('html')} as has_coord, {_addr_sql('html')} as has_addr from pp)"
MARGINS = ", ".join(f"round(100.0::double * 1.96::double * sqrt(({x} / n) * (1.0::double - {x} / n) / n), 4) as margin_pp{y}" for x, y in (("x_any", ""), ("x_addr", "_addr"), ("x_coord", "_coord"), ("x_both", "_both")))
PREV = f"""n, x_any, x_addr, x_coord, x_both, round(100.0::double * x_any / n, 4) as pct_any, round(100.0::double * x_addr / n, 4) as pct_addr, round(100.0::double * x_coord / n, 4) as pct_coord, round(100.0::double * x_both / n, 4) as pct_both,
  {MARGINS}, round(100.0::double * x_both / nullif(x_addr, 0), 4) as coord_given_addr, round(100.0::double * x_both / nullif(x_coord, 0), 4) as addr_given_coord"""
COUNTS = "count(*) as n, count(*) filter (has_addr or has_coord) as x_any, count(*) filter (has_addr) as x_addr, count(*) filter (has_coord) as x_coord, count(*) filter (has_addr and has_coord) as x_both"


def _prev_sql(head: str, by: str | None, source: str = "f") -> str:
    if not by:
        return f"with {head} select {PREV} from (select {COUNTS} from {source})"
    return f"with {head} select coalesce({by}, 'all') as {by}, {PREV} from (select {by}, {COUNTS} from {source} group by rollup ({by}))"


def doc_flags(spark: SparkSession, sf: str) -> DataFrame:
    return Y.doc_flags(planted_docs(spark, sf), "text", ["doc_id", "release", "lang", "truth_addr", "truth_coord", "truth_class", "truth_format"])


def _census() -> None:
    idx = I.INDEX_SQL
    geo = ", ".join(f"'{m}'" for m in C.GEO_MIMES)
    _add("mime_census", lambda s, d: Y.mime_census(I.crawl_index(s, d)), f"with i as ({idx}), dim as (select unnest([{geo}]) as mime) select dim.mime, " + ", ".join(f"count(*) filter (release = '{r}') as {r}" for r in C.RELEASES) + " from dim left join i using (mime) group by dim.mime")
    _add("mime_census_summary", lambda s, d: Y.mime_census_summary(I.crawl_index(s, d)), f"with i as ({idx}), g as (select release, count(*) filter (mime in ({geo})) as geo_files, count(*) as all_files from i group by rollup (release)) select coalesce(release, 'all') as release, geo_files, all_files, round(100.0::double * geo_files / all_files, 4) as pct from g")
    _add("mime_candidates", lambda s, d: Y.mime_candidates(I.crawl_index(s, d)), f"with i as ({idx}) select mime, count(*) as n from i where regexp_matches(mime, 'geo|gml|gpx|kml|kmz|shape|tcx|georss|openstreetmap') group by mime")
    _add("mime_from_url", lambda s, d: I.table(s, d, "pages").select("page_id", C.mime_from_url(F.concat("url", F.when(F.col("page_id") % 4 == 0, ".geojson").otherwise(".kml"))).alias("mime")), "select page_id, case when regexp_matches(url, '[?#]') then null when page_id % 4 = 0 then 'application/geo+json' else 'application/vnd.google-earth.kml+xml' end as mime from pages")
    _add("crawl_index", lambda s, d: I.crawl_index(s, d), idx)
    _add("index_offsets", lambda s, d: I.with_offsets(I.crawl_index(s, d)).select("page_id", "warc_file", "offset", "length"), f"with i as ({idx}) select page_id, release || '/' || part as warc_file, coalesce(sum(length) over (partition by release, part order by page_id rows between unbounded preceding and 1 preceding), 0)::bigint as \"offset\", length from i")
    ranges = f"with i as ({idx}), o as (select page_id, release || '/' || part as warc_file, coalesce(sum(length) over (partition by release, part order by page_id rows between unbounded preceding and 1 preceding), 0)::bigint as lo, length from i), k as (select *, max(lo + length) over (partition by warc_file order by lo rows between unbounded preceding and 1 preceding) as e from o), n as (select *, sum(case when e is null or lo > e + 3000 then 1 else 0 end) over (partition by warc_file order by lo rows between unbounded preceding and current row) as island from k) select warc_file, min(lo)::bigint as lo, max(lo + length)::bigint as hi, count(*) as records from n group by warc_file, island"
    _add("coalesce_ranges", lambda s, d: I.coalesce_ranges(I.with_offsets(I.crawl_index(s, d)), 3000), ranges)
    _add("tld_frequency", lambda s, d: Y.tld_frequency(I.crawl_index(s, d)), f"with i as ({idx}), g as (select tld, count(*) as n, round(100.0::double * count(*) / (select count(*) from i), 4) as pct from i group by tld) select tld, case tld " + " ".join(f"when '{t}' then '{c}'" for t, c in C.TLD_COUNTRY if c) + " end as country, n, pct from g where pct > 1.0")


def _samples() -> None:
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    line = "md5('s1|' || l_orderkey || '|' || l_linenumber || '|' || l_partkey || '|' || l_suppkey), l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate"
    out = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_returnflag"

    def frame(s: SparkSession, d: str) -> DataFrame:
        return I.table(s, d, "lineitem").select(*keys, "l_returnflag", "l_extendedprice", "l_shipdate", (F.col("l_orderkey") % 300).cast("int").alias("part"), (F.col("l_linenumber") % 3).cast("int").alias("release"))

    def draw(strata: list[str], k: int) -> Query:
        return lambda s, d: S.stratified_sample(frame(s, d), strata, k, "s1", keys, ["l_extendedprice", "l_shipdate"]).select(*keys, "l_returnflag", "part", "release")

    for name, strata, k in (("stratified_300x133", ["part"], 133), ("stratified_3x300x133", ["release", "part"], 133)):
        _add(name, draw(strata, k), f"select {out}, part, release from (select *, row_number() over (partition by {', '.join(strata)} order by {line}) as nth from (select *, (l_orderkey % 300)::int as part, (l_linenumber % 3)::int as release from lineitem)) where nth <= {k}")
    share = f"with f as (select *, (l_orderkey % 300)::int as part from lineitem), x as (select * from (select *, row_number() over (partition by part order by {line}) as nth from f) where nth <= 133) select (select count(*) from f) as rows_all, count(*) as rows_drawn, count(*) filter (l_returnflag = 'R') as hits, (select count(*) from f where l_returnflag = 'R') as hits_all from x"
    _add("sample_precision", lambda s, d: draw(["part"], 133)(s, d).agg(F.count("*").alias("rows_drawn"), F.count_if(F.col("l_returnflag") == "R").alias("hits")).crossJoin(frame(s, d).agg(F.count("*").alias("rows_all"), F.count_if(F.col("l_returnflag") == "R").alias("hits_all"))), share)
    _add("short_strata", lambda s, d: S.coverage(frame(s, d), ["release", "part"], 133), "select (l_linenumber % 3)::int as release, (l_orderkey % 300)::int as part, count(*) as n from lineitem group by all having count(*) < 133")
    cover = """with f as (select source, doc_id, lang = 'en' as hit from documents), z as (select source, count(*) as a, count(*) filter (hit) as h from f group by 1), tot as (select sum(a)::double as n, sum(h)::double / sum(a) as p from z),
      d as (select * from (select f.*, seed, row_number() over (partition by seed, source order by md5('cover' || seed || '|' || doc_id), doc_id) as nth from f, (select unnest(range(0, 60)) as seed)) where nth <= 10),
      c as (select seed, d.source, count(*) as m, count(*) filter (hit) as x, any_value(a) as a from d join z using (source) group by 1, 2),
      s as (select seed, sum(m)::double as m, sum(x)::double as x, sum(a / n * x / m) as ps, sum(case when m > 1 then power(a / n, 2) * (x / m) * (1 - x / m) / (m - 1) * (1 - m / a) else 0 end) as vs, any_value(n) as n, any_value(p) as p from c, tot group by 1),
      w as (select *, 1.96::double * sqrt((x / m) * (1 - x / m) / m) as plain from s), y as (select *, plain * sqrt((n - m) / greatest(n - 1, 1)) as fpc from w)
      select count(*) as seeds, count(*) filter (abs(x / m - p) <= plain + 1e-12) as covered, count(*) filter (abs(x / m - p) <= fpc + 1e-12) as covered_fpc, count(*) filter (abs(ps - p) <= 1.96::double * sqrt(vs) + 1e-12) as covered_stratified, round(avg(plain), 6) as mean_margin, round(avg(fpc), 6) as mean_margin_fpc from y"""
    _add("sample_coverage", lambda s, d: S.interval_coverage(docs(s, d).select("source", "doc_id", (F.col("lang") == "en").alias("hit")), "source", "doc_id", "hit", 10, 60), cover)
    _add("bernoulli_sample", lambda s, d: S.bernoulli_sample(docs(s, d), 0.01, "s1", ["doc_id"]).select("doc_id"), "select doc_id from documents where ('0x' || substr(md5('s1|' || doc_id), 1, 8))::bigint < 42949672")
    _add("fixed_sample", lambda s, d: S.fixed_sample(docs(s, d), 100, "s1", ["doc_id"]).select("doc_id"), "select doc_id from documents order by md5('s1|' || doc_id), doc_id limit 100")
    _add("proportional_sample", lambda s, d: S.proportional_sample(docs(s, d).select("doc_id", "lang"), ["lang"], 100, "s1", ["doc_id"]).select("doc_id", "lang"), "select doc_id, lang from (select *, row_number() over (partition by lang order by md5('s1|' || doc_id), doc_id) as nth, count(*) over (partition by lang) as size, (select count(*) from documents) as total from documents) where nth <= ceil(size * 100 / total)")
    _add("sample_then_fetch", lambda s, d: S.sample_then_fetch(I.crawl_index(s, d).select("page_id", "release", "part"), I.table(s, d, "pages"), ["release", "part"], 3, "s1", "page_id").select("page_id", F.length("html").cast("long").alias("n_chars")), "select page_id, length(html)::bigint as n_chars from (select *, row_number() over (partition by page_id % 3, (page_id // 3) % 5 order by md5('s1|' || page_id), page_id) as nth from pages) where nth <= 3")
    _add("fetch_by_scan", lambda s, d: I.fetch_by_scan(I.table(s, d, "pages"), I.crawl_index(s, d).where("part = 1"), "page_id").select("page_id", "url"), "select page_id, url from pages where (page_id // 3) % 5 = 1")
    _add("cluster_profile", lambda s, d: S.cluster_profile(I.table(s, d, "embeddings"), 8))

    sizes = "with p as (select (l_linenumber % 3)::int as release, (l_orderkey % 300)::int as part, count(*) as n from lineitem group by all), g as (select release, sum(n)::bigint as population, count(*) as parts from p group by 1) select release, population, parts, ceil(1.96 * 1.96 * 0.25 / 0.000025)::bigint as plain, ceil(1.959964 * 1.959964 * 0.25 / 0.000025)::bigint as z_1959964, (38416 * population + population + 38414) // (population + 38415) as finite, (38416 + 1484 + parts - 1) // parts as per_part from g"
    _add("sample_sizes", lambda s, d: S.sample_sizes(frame(s, d), "release", "part", 0.005, 1_484), sizes)
    bound = "select source, {0}::int as sides, n, round(1 - power({1}::double, 1.0::double / n), 6) as bound from g"
    _add("audit_bounds", lambda s, d: S.zero_error_bounds(S.stratified_sample(docs(s, d).select("doc_id", "source"), ["source"], 100, "audit", ["doc_id"]), "source"), f"with a as (select source, row_number() over (partition by source order by md5('audit|' || doc_id), doc_id) as nth from documents), g as (select source, count(*) as n from a where nth <= 100 group by 1) {bound.format(1, 0.05)} union all {bound.format(2, 0.025)}")


def _detection() -> None:
    _add("planted_docs", lambda s, d: planted_docs(s, d).select("doc_id", "truth_class", "truth_format", F.md5("text").alias("text_md5")), f"with {PD} select doc_id, truth_class, truth_format, md5(text) as text_md5 from pd")
    _add("planted_pages", lambda s, d: planted_pages(s, d).select("page_id", "truth_class", "truth_format", F.md5("html").alias("html_md5")), f"with {PP} select page_id, truth_class, truth_format, md5(html) as html_md5 from pp")
    _add("doc_flags", lambda s, d: doc_flags(s, d).select("doc_id", "has_coord", "has_addr"), f"with {FLAGS} select doc_id, has_coord, has_addr from f")
    _add("flags_raw", lambda s, d: Y.doc_flags(docs(s, d), "text", ["doc_id"]), f"select doc_id, {_coord_sql('text')} as has_coord, {_addr_sql('text')} as has_addr from documents")
    for kind, pats in (("coord", COORDS), ("addr", ADDRESSES)):
        for k, v in pats.items():
            has = C.has_coord_format if kind == "coord" else C.has_address_format
            cond = _coord_format_sql("text", k) if kind == "coord" else f"regexp_matches(text, {quoted(v)})"
            _add(f"detect_{kind}_{k}", lambda s, d, k=k, has=has: planted_docs(s, d).where(has(F.col("text"), k)).select("doc_id", "truth_class"), f"with {PD} select doc_id, truth_class from pd where {cond}")
    for k, v in DECOYS.items():
        _add(f"decoy_{k}", lambda s, d, v=v: planted_docs(s, d).where(F.col("text").rlike(v)).select("doc_id", "truth_class"), f"with {PD} select doc_id, truth_class from pd where regexp_matches(text, {quoted(v)})")
    recall = "with {}, m as (select truth_format, count(*) as n, count(*) filter (case when truth_coord then has_coord else true end and case when truth_addr then has_addr else true end) as found from f where truth_class in ('both', 'address', 'coord') group by 1) select * from m"
    full = lambda: (F.when(F.col("truth_coord"), F.col("has_coord")).otherwise(True)) & (F.when(F.col("truth_addr"), F.col("has_addr")).otherwise(True))
    _add("recall_by_format", lambda s, d: doc_flags(s, d).where("truth_class in ('both', 'address', 'coord')").groupBy("truth_format").agg(F.count("*").alias("n"), F.count_if(full()).alias("found")), recall.format(FLAGS))
    for k in ("coord", "addr"):
        conf = f"with {FLAGS}, g as (select count(*) filter (p and t) as tp, count(*) filter (p and not t) as fp, count(*) filter (not p and t) as fn, count(*) filter (not p and not t) as tn from (select has_{k} as p, truth_{k} as t from f)) select tp, fp, fn, tn, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(tp + fn, 0), 6) as recall, round(2.0::double * tp / nullif(2 * tp + fp + fn, 0), 6) as f1 from g"
        _add(f"confusion_{k}", lambda s, d, k=k: Y.confusion(doc_flags(s, d), f"has_{k}", f"truth_{k}"), conf)
    t1 = f"regexp_replace(text, {quoted(DECOYS['ipv4'])}, ' ', 'g')"
    _add("naive_regex_fp", lambda s, d: Y.naive_counts(docs(s, d), "text"), f"select count(*) filter (regexp_matches(text, {quoted(ANY_DECIMAL)})) as plain, count(*) filter (regexp_matches({t1}, {quoted(ANY_DECIMAL)})) as ip_masked, count(*) filter (regexp_matches(regexp_replace({t1}, {quoted(LICENCE)}, ' ', 'g'), {quoted(ANY_DECIMAL)})) as licence_masked from documents")
    _add("coord_sources", lambda s, d: Y.coord_sources(planted_pages(s, d), "html"), f"with {PP} " + " union all ".join(f"select '{k}' as format, count(*) filter ({_coord_format_sql('html', k)}) as docs from pp" for k in COORDS))
    _add("evidence", lambda s, d: planted_docs(s, d).select("doc_id", F.explode(C.evidence(F.col("text"))).alias("e")).select("doc_id", "e.kind", "e.format", "e.raw"))
    _add("long_windows", lambda s, d: docs(s, d).select("doc_id", F.explode(C.windows(F.col("text"), 2000, 200)).alias("x")).select("doc_id", "x.start", F.md5("x.text").alias("md5")), "select doc_id, (k * 1800)::int as start, md5(substr(text, (k * 1800 + 1)::bigint, 2000)) as md5 from (select doc_id, text, unnest(range(0, greatest(0, ceil((length(text) - 200) / 1800)::bigint - 1) + 1)) as k from documents)")


def _estimates() -> None:
    _add("prevalence_overall", lambda s, d: Y.prevalence(doc_flags(s, d)), _prev_sql(FLAGS, None))
    _add("prevalence_by_release", lambda s, d: Y.prevalence(doc_flags(s, d), "release"), _prev_sql(FLAGS, "release"))
    _add("prevalence_by_lang", lambda s, d: Y.prevalence(doc_flags(s, d).withColumn("lang_group", F.when(F.col("lang") == "en", "english").otherwise("other")), "lang_group"), _prev_sql(FLAGS + ", g2 as (select *, case when lang = 'en' then 'english' else 'other' end as lang_group from f)", "lang_group", "g2"))
    _add("page_prevalence", lambda s, d: Y.prevalence(Y.doc_flags(planted_pages(s, d), "html", ["page_id", "release"]), "release"), _prev_sql(PAGE_FLAGS, "release"))
    truth = lambda s, d: planted_docs(s, d).select("release", F.col("truth_addr").alias("has_addr"), F.col("truth_coord").alias("has_coord"))
    _add("truth_prevalence", lambda s, d: Y.prevalence(truth(s, d), "release"), _prev_sql(PD + ", f as (select release, truth_addr as has_addr, truth_coord as has_coord from pd)", "release"))
    _add("conditional_rates", lambda s, d: Y.prevalence(doc_flags(s, d)).select("x_both", "coord_given_addr", "addr_given_coord"), f"select x_both, coord_given_addr, addr_given_coord from ({_prev_sql(FLAGS, None)})")
    _add("identity_gap", lambda s, d: Y.identity_gap(doc_flags(s, d)), f"select x_any - x_addr - x_coord + x_both as gap from ({_prev_sql(FLAGS, None)})")
    _add("stability", lambda s, d: Y.stability(Y.prevalence(doc_flags(s, d), "release"), "release"), f"select round(max(pct_any) - min(pct_any), 4) as spread_pp from ({_prev_sql(FLAGS, 'release')}) where release <> 'all'")
    z = "(x1 / n1 - x2 / n2) / nullif(sqrt(((x1 + x2) / (n1 + n2)) * (1 - (x1 + x2) / (n1 + n2)) * (1 / n1 + 1 / n2)), 0)"
    pair = " union all ".join(f"select '{k}' as kind, max(n) filter (release = 'R2019')::double as n1, max(n) filter (release = 'R2024')::double as n2, max(x_{k}) filter (release = 'R2019')::double as x1, max(x_{k}) filter (release = 'R2024')::double as x2 from g" for k in ("any", "addr", "coord", "both"))
    _add("stability_z", lambda s, d: Y.two_proportion_z(Y.prevalence(doc_flags(s, d), "release"), "release", "R2019", "R2024"), f"with g as ({_prev_sql(FLAGS, 'release')}), h as ({pair}) select kind, round({z}, 6) as z from h")
    w = lambda k, sign: f"round((x_{k} / n + 1.96::double * 1.96::double / (2 * n) {sign} 1.96::double * sqrt((x_{k} / n) * (1 - x_{k} / n) / n + 1.96::double * 1.96::double / (4 * n * n::double))) / (1 + 1.96::double * 1.96::double / n), 6)"
    _add("wilson_intervals", lambda s, d: Y.wilson_intervals(Y.prevalence(doc_flags(s, d), "release"), "release"), f"with g as ({_prev_sql(FLAGS, 'release')}) " + " union all ".join(f"select release, '{k}' as kind, {w(k, '-')} as lo, {w(k, '+')} as hi from g" for k in ("any", "addr", "coord", "both")))
    _add("extrapolation", lambda s, d: Y.extrapolate(Y.prevalence(doc_flags(s, d)), 250e9), f"select 250e9::double * x_any / n as documents from ({_prev_sql(FLAGS, None)})")
    lang = "with p as (select coalesce(lang, 'UNK') as lang, round(100.0::double * count(*) / (select count(*) from documents), 4) as pop_pct from documents group by 1), k as (select * from documents where ('0x' || substr(md5('lb|' || doc_id), 1, 8))::bigint < 858993459), s as (select coalesce(lang, 'UNK') as lang, round(100.0::double * count(*) / (select count(*) from k), 4) as sample_pct from k group by 1), b as (select lang, coalesce(pop_pct, 0) as pop_pct, coalesce(sample_pct, 0) as sample_pct, round(coalesce(sample_pct, 0) - coalesce(pop_pct, 0), 4) as diff from p full join s using (lang) where lang <> 'en')"
    balance = lambda s, d, top=20: Y.language_balance(docs(s, d), S.bernoulli_sample(docs(s, d), 0.2, "lb", ["doc_id"]), top, "en" if top else None)
    lang_all = lang.replace(" where lang <> 'en'", "")
    _add("language_balance", balance, f"{lang} select * from b")
    _add("language_distance", lambda s, d: Y.total_variation(balance(s, d, None)), f"{lang_all} select round(sum(abs(diff)) / 2.0::double, 4) as tv_pct from b")
    k = lambda s, d: S.bernoulli_sample(docs(s, d), 0.2, "lb", ["doc_id"]).agg(F.count("*").alias("m"))
    _add("language_distances", lambda s, d: Y.distribution_distances(balance(s, d, None).crossJoin(F.broadcast(k(s, d))), F.col("m")), f"{lang_all} select round(sum(abs(diff)) / 2.0::double, 4) as tv_pct, round(sum((select count(*) from k) * power(sample_pct / 100 - pop_pct / 100, 2) / nullif(pop_pct / 100, 0)), 4) as chi_square, round(sum(case when sample_pct > 0 then sample_pct / 100 * ln((sample_pct / 100) / nullif(pop_pct / 100, 0)) else 0 end), 6) as kl from b")
    tok = "len(regexp_extract_all(text, '[^ \\t\\r\\n.,;:!?]+|[.,;:!?]'))::bigint"
    _add("length_histogram", lambda s, d: Y.length_histogram(docs(s, d), "text"), f"select (floor(least({tok} + 60, 200000) / 100) * 100)::bigint as tokens_from, count(*) as n from documents group by 1")
    _add("length_stats", lambda s, d: Y.length_stats(docs(s, d), "text"), "select count(*) as n, round(avg(t), 4) as mean, max(t) as max, quantile_cont(t, 0.5)::double as median, quantile_cont(t, 0.9)::double as p90, round(case when count(*) > 0 and stddev_pop(t) > 0 then (avg(power(t::double, 3)) - 3 * avg(t) * avg(power(t::double, 2)) + 2 * power(avg(t), 3)) / power(stddev_pop(t), 3) end, 4) as skewness from (select ceil(length(text) / 4)::bigint as t from documents)")


def _example_sql(t: str, kind: str) -> str:
    pats = COORDS if kind == "coord" else ADDRESSES
    has = (lambda k: _coord_format_sql(t, k)) if kind == "coord" else (lambda k: f"regexp_matches({t}, {quoted(ADDRESSES[k])})")
    return "coalesce(" + ", ".join(f"case when {has(k)} then nullif(regexp_extract({t}, {quoted(v)}, 0), '') end" for k, v in pats.items()) + ")"


def _bucket_sql(seed: str, col: str = "doc_id") -> str:
    return f"(('0x' || substr(md5('{seed}|' || {col}), 1, 8))::bigint % 1000)"


def _review() -> None:
    b = _bucket_sql("judge")
    number = "coalesce(" + ", ".join(f"nullif(regexp_extract(t, {quoted(DECOYS[k])}, 0), '')" for k in ("phone", "ipv4")) + ")"
    both = f"concat_ws('{Y.BETWEEN}', c, a)"
    resp = f"""{PD}, j0 as (select doc_id as id, text as t, truth_addr, truth_coord, {b} as b, {_bucket_sql("judge-miss")} < 20 as missed, {_bucket_sql("judge-invent")} < 10 as invents,
      case when regexp_matches(text, '[0-9]') then {_example_sql("text", "coord")} end as c, {_example_sql("text", "address")} as a from pd),
      j1 as (select *, case when invents then '{Y.INVENTED}' when missed then null when c is not null or a is not null then case b % 3 when 0 then {both} when 1 then coalesce(c, a) else coalesce(a, c) end when b >= 500 then {number} end as said from j0),
      r as (select id, t as body, truth_addr, truth_coord, case when b < 12 then 'internal_error' when b < 20 then 'unsafe' else 'ok' end as status,
      case when b < 20 then '' when said is not null then '{Y.PREFIX}' || said when b % 2 = 0 then 'None' else 'None.' end as text from j1),
      t as (select *, case when status <> 'ok' then 'failed' when len(regexp_extract_all(trim(text), '[A-Za-z0-9]+|[^A-Za-z0-9 \\t\\r\\n]')) <= 2 then 'negative' else 'to_review' end as outcome from r)"""
    verdict = f"k as (select id, {_coord_sql('text')} as c, {_addr_sql('text')} as a from t where outcome = 'to_review'), v as (select id, case when c and a then 'both' when c then 'coords' when a then 'address' else 'discarded' end as category from k)"
    page = lambda s, d: planted_docs(s, d).select("doc_id", "text")
    responses = lambda s, d: Y.triage(I.stored(Y.rule_judge(page(s, d), "doc_id", "text"), "responses"))
    _add("judge_responses", lambda s, d: responses(s, d).select("id", "status", "text", "outcome"), f"with {resp} select id, status, text, outcome from t")
    _add("triage_counts", lambda s, d: responses(s, d).groupBy("outcome").agg(F.count("*").alias("n")), f"with {resp} select outcome, count(*) as n from t group by 1")
    _add("review_categories", lambda s, d: Y.categorise(responses(s, d)).groupBy("category").agg(F.count("*").alias("n")), f"with {resp}, {verdict} select category, count(*) as n from v group by 1")
    _add("judge_verdicts", lambda s, d: Y.categorise(responses(s, d)).select("id", "category"), f"with {resp}, {verdict} select id, category from v")
    _add("audit_grounding", lambda s, d: Y.audit_grounding(responses(s, d), page(s, d), "doc_id", "text"), f"with {resp} select count(*) as n, count(*) filter (len(list_filter(string_split(substr(text, {len(Y.PREFIX) + 1}), '{Y.BETWEEN}'), lambda e: not contains(body, e))) = 0) as found from (select * from t where outcome = 'to_review' order by md5('audit|' || id), id limit 100)")
    _add("audit_misses", lambda s, d: Y.audit_misses(responses(s, d), planted_docs(s, d), "doc_id"), f"with {resp} select count(*) as n, count(*) filter (truth_addr or truth_coord) as missed from (select * from t where outcome = 'negative' order by md5('audit|' || id), id limit 100)")
    _add("retry_list", lambda s, d: Y.retry_list(docs(s, d).select(F.col("doc_id").alias("id")), responses(s, d)), f"select doc_id as id from documents where {b} < 12")
    e = [_bucket_sql("judge" if k == 0 else f"judge-{k}") + " < 12" for k in range(3)]
    asked = ["true", f"({e[0]})", f"({e[0]} and {e[1]})"]
    rounds = " union all ".join(f"select {k + 1}::int as round, {asked[k]} as asked, {asked[k]} and {e[k]} as error, {asked[k]} and {b} between 12 and 19 as refused from documents" for k in range(3))
    _add("retry_rounds", lambda s, d: Y.retry_rounds(docs(s, d), "doc_id"), f"with x as ({rounds}), g as (select round, count(*) filter (asked) as asked, count(*) filter (error) as errors, count(*) filter (refused) as refused, count(*) as n from x group by 1) select round, asked, asked - errors - refused as answered, refused, errors, (select refused from g where round = 1) + errors as lost, floor(n * 3.7 / 100)::bigint as headroom from g")
    heard = {m: f"{_bucket_sql('ask-' + m)} >= 20" for m in ("combined", "coord", "addr")}
    _add("compare_modes", lambda s, d: Y.compare_modes(planted_docs(s, d), "doc_id", "text"), f"with {FLAGS} select (has_coord or has_addr) and {heard['combined']} as combined, (has_coord and {heard['coord']}) or (has_addr and {heard['addr']}) as separate, count(*) as n from f group by 1, 2")
    _add("prompts", lambda s, d: docs(s, d).select("doc_id", F.md5(Y.build_prompt(F.col("text"))).alias("prompt_md5"), C.n_tokens(Y.build_prompt(F.col("text")), "char4").alias("n_tokens")), "select doc_id, md5(p) as prompt_md5, ceil(length(p) / 4)::bigint as n_tokens from (select doc_id, '<<page>>' || chr(10) || text || chr(10) || '<<end>>' || chr(10) || 'List up to three coordinate pairs or street addresses in the page above that point to one place on Earth. Write None if there are none.' as p from documents)")
    _add("prompts_separate", lambda s, d: docs(s, d).select("doc_id", F.posexplode(Y.build_prompt(F.col("text"), "separate")).alias("k", "p")).select("doc_id", "k", F.length("p").cast("long").alias("n_chars")), "select doc_id, k::int as k, (length(text) + 18 + [115, 115][k + 1])::bigint as n_chars from documents, (select unnest([0, 1]) as k)")
    _add("injection_flags", lambda s, d: docs(s, d).agg(F.count_if(Y.flag_injection(F.col("text"))).alias("n")), "select count(*) filter (regexp_matches(text, '[Ii]gnore (?:all |the )?(?:previous|above) instructions|[Yy]ou are now ')) as n from documents")
    _add("context_gate", lambda s, d: docs(s, d).select(C.n_tokens(F.col("text"), "char4").alias("t")).agg(F.count_if(Y.fits_context(F.col("t"), 2000)).alias("fits"), F.count_if(~Y.fits_context(F.col("t"), 2000)).alias("windowed")), "select count(*) filter (ceil(length(text) / 4) <= 2000) as fits, count(*) filter (ceil(length(text) / 4) > 2000) as windowed from documents")
    _add("cost_model", lambda s, d: Y.cost_model(docs(s, d), "text"), "with w as (select coalesce(sum(greatest(0, ceil((length(coalesce(text, '')) - 200) / 7800)::bigint - 1) + 1), 0)::bigint as n from documents) select mode, (n * q)::bigint as queries, per_day::bigint as per_day, round(n * q / per_day, 4) as quota_days, round(n * q * 30.0::double / 8 / 86400, 4) as work_days from w, (values ('combined', 1), ('separate', 2)) m(mode, q), (values (1500), (10000)) p(per_day)")


def _baselines() -> None:
    pr = lambda cond, truth: f"with {PD}, g as (select count(*) filter (p and t) as tp, count(*) filter (p and not t) as fp, count(*) filter (not p and t) as fn, count(*) filter (not p and not t) as tn from (select {cond} as p, {truth} as t from pd)) select tp, fp, fn, tn, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(tp + fn, 0), 6) as recall, round(2.0::double * tp / nullif(2 * tp + fp + fn, 0), 6) as f1 from g"
    run = lambda f, truth: lambda s, d: Y.confusion(planted_docs(s, d).select(f(F.col("text")).alias("p"), truth), "p", truth)
    _add("baseline_any_decimal", run(Y.naive_decimal, "truth_coord"), pr(f"regexp_matches(text, {quoted(ANY_DECIMAL)})", "truth_coord"))
    from geocensus.functions.patterns import ANY_PAIR

    _add("baseline_any_pair", run(Y.naive_pair, "truth_coord"), pr(f"regexp_matches(text, {quoted(ANY_PAIR)})", "truth_coord"))
    _add("baseline_keyword", run(Y.keyword_lookup, "truth_addr"), pr("(" + " or ".join(f"contains(lower(text), '{w}')" for w in KEYWORDS) + ")", "truth_addr"))
    _add("baseline_short_strings", run(Y.short_string_address, "truth_addr"), pr(f"len(list_filter(string_split(text, chr(10)), lambda x: length(x) <= 200 and regexp_matches(x, {quoted(ADDRESSES['a1_number_street'])}))) > 0", "truth_addr"))
    places = " or ".join(f"contains(x, '{p}')" for p in Y.GAZETTEER)
    for name, strip in (("baseline_gazetteer", True), ("baseline_gazetteer_tags_kept", False)):
        x = "regexp_replace(text, '<[^>]{0,1000}>', ' ', 'g')" if strip else "text"
        sql = pr("p0", "truth_addr").replace("from pd))", f"from (select truth_addr, ({places}) and {_addr_sql('x')} as p0 from (select truth_addr, {x} as x from pd))))")
        _add(name, run(lambda t, strip=strip: Y.gazetteer_address(t, strip=strip), "truth_addr"), sql)
    street = "^(?:Street|St|Road|Rd|Avenue|Ave|Lane|Drive|Close|Square|rue|Calle)$"
    label = f"array_to_string(list_transform(regexp_extract_all(coalesce(text, ''), '[A-Za-zÀ-ÿ]+|[0-9]+|[^A-Za-zÀ-ÿ0-9 \\t\\r\\n]'), lambda w: case when regexp_matches(w, '^[0-9]{{1,5}}$') then 'N' when regexp_matches(w, '{street}') then 'S' when regexp_matches(w, '^[A-Z]') then 'C' else 'o' end), '')"
    runs = "list_distinct(list_filter(flatten([[substr(c, i, n) for i in range(1, length(c) - n + 2)] for n in [3, 4, 5]]), lambda x: contains(x, 'N') and contains(x, 'S')))"
    tagged = f"{PD}, c0 as (select doc_id, truth_addr, {_bucket_sql('mine')} < 500 as train, {label} as c from pd), c1 as (select doc_id, truth_addr, train, unnest({runs}) as pattern from c0), mined as (select pattern, count(*) as n, count(*) filter (truth_addr) as x from c1 where train group by 1 having count(*) filter (truth_addr) >= 5 and count(*) filter (truth_addr) >= 0.8 * count(*))"
    _add("mined_patterns", lambda s, d: Y.mined_patterns(planted_docs(s, d), "doc_id", "text"), f"with {tagged} select pattern, n, x from mined")
    found = f"with {tagged}, h as (select distinct doc_id from c1 join mined using (pattern)), g as (select count(*) filter (p and t) as tp, count(*) filter (p and not t) as fp, count(*) filter (not p and t) as fn, count(*) filter (not p and not t) as tn from (select h.doc_id is not null as p, truth_addr as t from c0 left join h using (doc_id) where not train)) select tp, fp, fn, tn, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(tp + fn, 0), 6) as recall, round(2.0::double * tp / nullif(2 * tp + fp + fn, 0), 6) as f1 from g"
    _add("baseline_sequence_labels", lambda s, d: Y.sequence_labels(planted_docs(s, d), "doc_id", "text"), found)
    by_lang = f"with {FLAGS}, g as (select lang, count(*) filter (p and t) as tp, count(*) filter (p and not t) as fp, count(*) filter (not p and t) as fn, count(*) filter (not p and not t) as tn from (select lang, has_addr as p, truth_addr as t from f) group by 1) select lang, tp, fp, fn, tn, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(tp + fn, 0), 6) as recall, round(2.0::double * tp / nullif(2 * tp + fp + fn, 0), 6) as f1 from g"
    _add("confusion_by_lang", lambda s, d: Y.confusion(doc_flags(s, d), "has_addr", "truth_addr", "lang"), by_lang)
    _add("baseline_svm_windows", lambda s, d: Y.svm_windows(planted_docs(s, d), "doc_id", "text"))
    needles = tuple(x for _, x in COORD_SNIPPETS)
    put = f"(select doc_id, t, d, [{', '.join(quoted(x) for x in needles)}][(('0x' || substr(md5('needle|' || doc_id), 1, 8))::bigint % {len(needles)})::int + 1] as needle from (select doc_id, coalesce(text, '') as t, [0, 25, 50, 75, 100][(('0x' || substr(md5('depth|' || doc_id), 1, 8))::bigint % 5)::int + 1] as d from documents))"
    at = "floor(length(t) * d / 100)::bigint"
    grid = f"with p as (select d::int as depth, floor(log2(greatest(length(t), 1)::double) / 2)::int as length_class, substr(t, 1, {at}) || chr(10) || needle || chr(10) || substr(t, {at} + 1) as text from {put}) select depth, length_class, count(*) as n, count(*) filter ({_coord_sql('text')}) as found from p group by 1, 2"
    _add("needle_recall", lambda s, d: Y.needle_grid(docs(s, d), "doc_id", "text", needles), grid)


def _composites() -> None:
    from geocensus.operators import composites as X

    _add("census_long", lambda s, d: X.census(I.crawl_index(s, d)), f"with i as ({I.INDEX_SQL}), n as (select release, count(*) as a from i group by 1), dim as (select unnest([{', '.join(quoted(m) for m in C.GEO_MIMES)}]) as mime), g as (select mime, release, count(*) as f from i group by all) select dim.mime, n.release, coalesce(f, 0) as files, round(100.0::double * coalesce(f, 0) / a, 4) as pct_of_release from dim cross join n left join g on g.mime = dim.mime and g.release = n.release")
    _add("estimate_sampled", lambda s, d: X.estimate(docs(s, d).select("doc_id", "source"), planted_docs(s, d), "doc_id", "text", 10, ["source"], "s1", "release"), _prev_sql(FLAGS + ", k as (select doc_id from (select doc_id, row_number() over (partition by source order by md5('s1|' || doc_id), doc_id) as nth from documents) where nth <= 10), g2 as (select f.* from f join k using (doc_id))", "release", "g2"))
    _add("full_scan", lambda s, d: X.full_scan(docs(s, d).withColumn("release", I.release_of("doc_id")), "text", ["doc_id", "release"], "release"), _prev_sql(f"f as (select {REL.format('doc_id')} as release, {_coord_sql('text')} as has_coord, {_addr_sql('text')} as has_addr from documents)", "release"))
    _add("page_lang_groups", lambda s, d: I.table(s, d, "pages").select("page_id", X.lang_group(F.col("html")).alias("lang_group")), f"select page_id, {X.lang_group_sql()} as lang_group from pages")
    _add("page_prevalence_by_lang", lambda s, d: Y.prevalence(planted_pages(s, d).select(X.lang_group(F.col("html")).alias("lang_group"), C.has_coords(F.col("html")).alias("has_coord"), C.has_address(F.col("html")).alias("has_addr")), "lang_group"), _prev_sql(PAGE_FLAGS + f", g2 as (select *, {X.lang_group_sql()} as lang_group from f)", "lang_group", "g2"))
    _add("adjusted_prevalence", lambda s, d: Y.prevalence(doc_flags(s, d)).select(F.round(F.lit(1.0) * (F.col("x_any") / F.col("n") + 0.98 - 1) / (0.95 + 0.98 - 1), 6).alias("p")), f"select round(1.0::double * (x_any / n + 0.98::double - 1) / (0.95::double + 0.98::double - 1), 6) as p from ({_prev_sql(FLAGS, None)})")


for _part in (_census, _samples, _detection, _estimates, _review, _baselines, _composites):
    _part()


def queries() -> dict[str, Query]:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
