"""Census, profiles, estimates, the judge, its review, costs and the baselines."""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from geocensus.functions.columns import GEO_MIMES, RELEASES, TLD_COUNTRY, bucket, first_example, has_address, has_coord_format, has_coords, is_geo_mime, n_tokens, normal_mime
from geocensus.functions.patterns import ADDRESSES, ANY_DECIMAL, ANY_PAIR, COORDS, DECOYS, KEYWORDS, LICENCE

# Census.


def mime_census(index: DataFrame) -> DataFrame:
    """Files per geospatial type and release, zeros included; ``html`` is never read."""
    spark = index.sparkSession
    dim = spark.createDataFrame([(m,) for m in GEO_MIMES], "mime string")
    got = index.select(normal_mime(F.col("mime")).alias("mime"), "release").where(is_geo_mime(F.col("mime"))).groupBy("mime").pivot("release", list(RELEASES)).count()
    return F.broadcast(dim).join(got, "mime", "left").select("mime", *[F.coalesce(r, F.lit(0)).cast("long").alias(r) for r in RELEASES])


def mime_census_summary(index: DataFrame) -> DataFrame:
    """Per release and pooled: geospatial files, all documents, percentage; one pass."""
    geo = F.count_if(is_geo_mime(F.col("mime"))).cast("long")
    out = index.rollup("release").agg(geo.alias("geo_files"), F.count("*").alias("all_files"))
    return out.select(F.coalesce("release", F.lit("all")).alias("release"), "geo_files", "all_files", F.round(100.0 * F.col("geo_files") / F.nullif(F.col("all_files"), F.lit(0)), 4).alias("pct"))


def mime_candidates(index: DataFrame, pattern: str = "geo|gml|gpx|kml|kmz|shape|tcx|georss|openstreetmap") -> DataFrame:
    return index.groupBy(normal_mime(F.col("mime")).alias("mime")).agg(F.count("*").alias("n")).where(F.col("mime").rlike(pattern))


# Flags and estimates.


def doc_flags(df: DataFrame, text_col: str, keep: list[str], coords: Callable[[Column], Column] = has_coords, addresses: Callable[[Column], Column] = has_address) -> DataFrame:
    """``keep`` with ``has_coord, has_addr``: any occurrence counts, its number doesn't."""
    return df.select(*keep, coords(F.col(text_col)).alias("has_coord"), addresses(F.col(text_col)).alias("has_addr"))


def prevalence(flags: DataFrame, by: str | None = None, z: float = 1.96) -> DataFrame:
    """Shares of any, address, coordinates and both, with margins and conditionals; per ``by`` and pooled in one pass."""
    a, c = F.col("has_addr"), F.col("has_coord")
    counts = [F.count("*").alias("n"), F.count_if(a | c).alias("x_any"), F.count_if(a).alias("x_addr"), F.count_if(c).alias("x_coord"), F.count_if(a & c).alias("x_both")]
    g = flags.rollup(by).agg(*counts).withColumn(by, F.coalesce(F.col(by).cast("string"), F.lit("all"))) if by else flags.agg(*counts)
    n = F.nullif(F.col("n"), F.lit(0))  # an empty population has no shares
    share = lambda x: F.round(100.0 * F.col(x) / n, 4)
    p = lambda x: F.col(x) / n
    margin = lambda x: F.round(100.0 * F.lit(z) * F.sqrt(p(x) * (1.0 - p(x)) / n), 4)
    kinds = ("any", "addr", "coord", "both")
    return g.select(
        *([by] if by else []), "n", *[f"x_{k}" for k in kinds], *[share(f"x_{k}").alias(f"pct_{k}") for k in kinds], *[margin(f"x_{k}").alias("margin_pp" if k == "any" else f"margin_pp_{k}") for k in kinds],
        F.round(100.0 * F.col("x_both") / F.nullif(F.col("x_addr"), F.lit(0)), 4).alias("coord_given_addr"), F.round(100.0 * F.col("x_both") / F.nullif(F.col("x_coord"), F.lit(0)), 4).alias("addr_given_coord"),
    )


def identity_gap(flags: DataFrame) -> DataFrame:
    """any - (addresses + coordinates - both): zero for every population."""
    return prevalence(flags).select((F.col("x_any") - F.col("x_addr") - F.col("x_coord") + F.col("x_both")).alias("gap"))


def stability(prevalences: DataFrame, by: str) -> DataFrame:
    """Largest difference of any share between releases, in points."""
    return prevalences.where(F.col(by) != "all").agg(F.round(F.max("pct_any") - F.min("pct_any"), 4).alias("spread_pp"))


def two_proportion_z(prevalences: DataFrame, by: str, first: str, second: str) -> DataFrame:
    """``kind, z``: the pooled two-proportion statistic of two groups' shares."""
    one = lambda k, name: F.max(F.when(F.col(by) == k, F.col(name)))
    kinds = ("any", "addr", "coord", "both")
    g = prevalences.agg(one(first, "n").alias("n1"), one(second, "n").alias("n2"), *[one(k, f"x_{x}").alias(f"{x}{i}") for x in kinds for i, k in ((1, first), (2, second))])

    def z(x: str) -> Column:
        pool = (F.col(f"{x}1") + F.col(f"{x}2")) / (F.col("n1") + F.col("n2"))
        spread = F.sqrt(pool * (1.0 - pool) * (1.0 / F.col("n1") + 1.0 / F.col("n2")))
        return F.round((F.col(f"{x}1") / F.col("n1") - F.col(f"{x}2") / F.col("n2")) / F.nullif(spread, F.lit(0.0)), 6)

    return g.select(F.inline(F.array(*[F.struct(F.lit(x).alias("kind"), z(x).alias("z")) for x in kinds])))


def wilson_intervals(prevalences: DataFrame, by: str, z: float = 1.96) -> DataFrame:
    """``kind, lo, hi`` per group: Wilson's intervals of all four shares, which stay inside 0 and 1 for rare kinds."""
    n, zz = F.col("n"), F.lit(z * z)

    def ends(x: str) -> Column:
        p = F.col(f"x_{x}") / n
        mid, half = p + zz / (2 * n), F.lit(z) * F.sqrt(p * (1.0 - p) / n + zz / (4 * n * n))
        return F.struct(F.lit(x).alias("kind"), F.round((mid - half) / (1 + zz / n), 6).alias("lo"), F.round((mid + half) / (1 + zz / n), 6).alias("hi"))

    return prevalences.where("n > 0").select(by, F.inline(F.array(*[ends(x) for x in ("any", "addr", "coord", "both")])))


def extrapolate(prevalences: DataFrame, population: float) -> DataFrame:
    return prevalences.select((F.lit(population) * F.col("x_any") / F.nullif(F.col("n"), F.lit(0))).alias("documents"))


def confusion(flags: DataFrame, pred: str, truth: str, by: str | None = None) -> DataFrame:
    """Counts, precision, recall and F of a flag against planted truth, over every row, or per ``by``."""
    p, t = F.col(pred), F.col(truth)
    g = (flags.groupBy(by) if by else flags).agg(F.count_if(p & t).alias("tp"), F.count_if(p & ~t).alias("fp"), F.count_if(~p & t).alias("fn"), F.count_if(~p & ~t).alias("tn"))
    tp = F.col("tp")
    return g.select(*([by] if by else []), "tp", "fp", "fn", "tn", F.round(tp / F.nullif(tp + F.col("fp"), F.lit(0)), 6).alias("precision"), F.round(tp / F.nullif(tp + F.col("fn"), F.lit(0)), 6).alias("recall"), F.round(2.0 * tp / F.nullif(2 * tp + F.col("fp") + F.col("fn"), F.lit(0)), 6).alias("f1"))


def coord_sources(df: DataFrame, text_col: str) -> DataFrame:
    """``format, docs``: documents in which each coordinate format occurs, by the detector's own rules.  One pass."""
    got = df.agg(*[F.count_if(F.coalesce(has_coord_format(F.col(text_col), k), F.lit(False))).alias(k) for k in COORDS])
    return got.select(F.explode(F.array(*[F.struct(F.lit(k).alias("format"), F.col(k).alias("docs")) for k in COORDS])).alias("x")).select("x.format", "x.docs")


# Profiles.


def language_balance(population: DataFrame, sample: DataFrame, top: int | None = 20, exclude: str | None = "en") -> DataFrame:
    """Shares of each language in both; the report leaves out one language and keeps the ``top`` of the rest, distances keep all."""

    def share(d: DataFrame, name: str) -> DataFrame:
        g = d.groupBy(F.coalesce("lang", F.lit("UNK")).alias("lang")).agg(F.count("*").alias("n"))
        return g.crossJoin(F.broadcast(d.agg(F.count("*").alias("all")))).select("lang", F.round(100.0 * F.col("n") / F.col("all"), 4).alias(name))

    out = share(population, "pop_pct").join(share(sample, "sample_pct"), "lang", "full_outer")
    out = out if exclude is None else out.where(F.col("lang") != exclude)
    out = out.select("lang", F.coalesce("pop_pct", F.lit(0.0)).alias("pop_pct"), F.coalesce("sample_pct", F.lit(0.0)).alias("sample_pct"))
    out = out.withColumn("diff", F.round(F.col("sample_pct") - F.col("pop_pct"), 4))
    return out if top is None else out.orderBy(F.desc("pop_pct"), "lang").limit(top)


def total_variation(balance: DataFrame) -> DataFrame:
    return balance.agg(F.round(F.sum(F.abs("diff")) / 2.0, 4).alias("tv_pct"))


def distribution_distances(balance: DataFrame, n_sample: Column) -> DataFrame:
    """Total variation, chi-square of the sample's counts, and divergence of the sample from the population, in nats."""
    p, q = F.col("pop_pct") / 100, F.col("sample_pct") / 100
    chi, kl = n_sample * F.pow(q - p, 2) / F.nullif(p, F.lit(0.0)), F.when(q > 0, q * F.ln(q / F.nullif(p, F.lit(0.0)))).otherwise(0.0)
    return balance.agg(F.round(F.sum(F.abs("diff")) / 2.0, 4).alias("tv_pct"), F.round(F.sum(chi), 4).alias("chi_square"), F.round(F.sum(kl), 6).alias("kl"))


def tld_frequency(index: DataFrame, min_pct: float = 1.0) -> DataFrame:
    spark = index.sparkSession
    dim = spark.createDataFrame(list(TLD_COUNTRY), "tld string, country string")
    g = index.groupBy("tld").agg(F.count("*").alias("n")).crossJoin(F.broadcast(index.agg(F.count("*").alias("all"))))
    g = g.withColumn("pct", F.round(100.0 * F.col("n") / F.col("all"), 4)).where(F.col("pct") > min_pct)
    return g.join(F.broadcast(dim), "tld", "left").select("tld", "country", "n", "pct")


def length_histogram(docs: DataFrame, text_col: str, width: int = 100, cap: int = 200_000, prompt_tokens: int = 60) -> DataFrame:
    """Documents per class of length in tokens, the prompt's included; longer ones share the last class."""
    t = F.least((n_tokens(F.col(text_col)) + prompt_tokens), F.lit(cap))
    return docs.groupBy((F.floor(t / width) * width).cast("long").alias("tokens_from")).agg(F.count("*").alias("n"))


def length_stats(docs: DataFrame, text_col: str) -> DataFrame:
    t = docs.select(n_tokens(F.col(text_col), "char4").alias("t"))
    return t.agg(F.count("*").alias("n"), F.round(F.avg("t"), 4).alias("mean"), F.max("t").alias("max"), F.expr("percentile(t, 0.5)").alias("median"), F.expr("percentile(t, 0.9)").alias("p90"), F.round(F.skewness("t"), 4).alias("skewness"))


# The judge.


def build_prompt(doc: Column, mode: str = "combined") -> Column:
    """Our wording: the page between marks, then the question; ``separate`` gives an array of two prompts."""
    page = F.concat(F.lit("<<page>>\n"), doc, F.lit("\n<<end>>\n"))
    ask = "List up to three {} in the page above that point to one place on Earth. Write None if there are none."
    if mode == "combined":
        return F.concat(page, F.lit(ask.format("coordinate pairs or street addresses")))
    return F.array(*[F.concat(page, F.lit(ask.format(x))) for x in ("coordinate pairs", "street addresses")])


def fits_context(tokens: Column, limit: int = 1_000_000) -> Column:
    return tokens <= limit


def flag_injection(text: Column) -> Column:
    return text.rlike(r"[Ii]gnore (?:all |the )?(?:previous|above) instructions|[Yy]ou are now ")


def ask(df: DataFrame, judge: Callable[[list[str]], list[tuple[str, str]]], id_col: str, prompt_col: str) -> DataFrame:
    """``id, status, text`` from any judge object; batches of a partition, no shuffle."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            got = judge(b[prompt_col].tolist())
            yield pd.DataFrame({"id": b[id_col], "status": [s for s, _ in got], "text": [t for _, t in got]})

    return df.select(id_col, prompt_col).mapInPandas(run, "id long, status string, text string")


PREFIX, BETWEEN = "The page has places: ", " ¦ "
INVENTED = "12.34567, 98.76543"


def rule_judge(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``id, status, text``: a judge without a model, that answers from the page alone and errs by id.

    Of 1,000 pages 12 fail, 8 are refused, 20 have their places missed, and 10 get a place that is not in them.  A third each of the
    answers names both kinds, coordinates first, addresses first; half of the pages with a telephone number or a machine's address have
    it taken for a place; negatives come with and without full stop.
    """
    b, text = bucket("judge", id_col), F.col(text_col)
    d = docs.select(F.col(id_col).alias("id"), b.alias("b"), (bucket("judge-miss", id_col) < 20).alias("missed"), (bucket("judge-invent", id_col) < 10).alias("invents"), F.when(text.rlike("[0-9]"), first_example(text, "coord")).alias("c"), first_example(text, "address").alias("a"), text.alias("t"))
    number = F.coalesce(*[F.nullif(F.regexp_extract("t", DECOYS[k], 0), F.lit("")) for k in ("phone", "ipv4")])
    style = F.col("b") % 3
    said = F.when(style == 0, F.concat_ws(BETWEEN, "c", "a")).when(style == 1, F.coalesce("c", "a")).otherwise(F.coalesce("a", "c"))
    said = F.when(F.col("invents"), F.lit(INVENTED)).when(F.col("missed"), F.lit(None)).when(F.col("c").isNotNull() | F.col("a").isNotNull(), said).when(F.col("b") >= 500, number)
    status = F.when(F.col("b") < 12, "internal_error").when(F.col("b") < 20, "unsafe").otherwise("ok")
    d = d.select("id", status.alias("status"), "b", said.alias("said"))
    answer = F.when(F.col("status") != "ok", "").when(F.col("said").isNotNull(), F.concat(F.lit(PREFIX), F.col("said"))).when(F.col("b") % 2 == 0, "None").otherwise("None.")
    return d.select("id", "status", answer.alias("text"))


def triage(responses: DataFrame) -> DataFrame:
    """``outcome``: failed; negative, one or two tokens; or to_review."""
    short = F.regexp_count(F.trim("text"), F.lit(r"[A-Za-z0-9]+|[^A-Za-z0-9 \t\r\n]")) <= 2
    return responses.withColumn("outcome", F.when(F.col("status") != "ok", "failed").when(short, "negative").otherwise("to_review"))


def apply_definition(d: DataFrame, text_col: str) -> DataFrame:
    """``c`` and ``a``: whether what a text names counts by the definition.  Origin pairs, celestial pairs, addresses of machines,
    telephone numbers and bare landmarks don't."""
    return d.withColumns({"c": has_coords(F.col(text_col)), "a": has_address(F.col(text_col))})


def categorise(responses: DataFrame) -> DataFrame:
    """Category of each reviewed response, from the definition applied to its own text; other hits are discarded."""
    d = apply_definition(responses.where("outcome = 'to_review'"), "text")
    return d.withColumn("category", F.when(F.col("c") & F.col("a"), "both").when(F.col("c"), "coords").when(F.col("a"), "address").otherwise("discarded"))


def retry_list(todo: DataFrame, responses: DataFrame, id_col: str = "id") -> DataFrame:
    """Ids still without a final answer: refused ones are final, internal errors are not."""
    return todo.join(responses.where("status <> 'internal_error'").select(id_col), id_col, "left_anti")


def _drawn(responses: DataFrame, outcome: str, n: int, seed: str) -> DataFrame:
    """A random ``n`` of the responses with an outcome; a bound, so it may be broadcast."""
    return responses.where(F.col("outcome") == outcome).orderBy(F.md5(F.concat_ws("|", F.lit(seed), F.col("id").cast("string"))), "id").limit(n)


def audit_grounding(responses: DataFrame, docs: DataFrame, id_col: str, text_col: str, n: int = 100, seed: str = "audit") -> DataFrame:
    """Of a random ``n`` positives, in how many every example occurs in the page.  The sample is the broadcast side."""
    pos = _drawn(responses, "to_review", n, seed).select(F.col("id").alias("__id"), F.split(F.substring("text", F.lit(len(PREFIX) + 1), F.length("text")), BETWEEN).alias("said"))
    j = docs.select(id_col, text_col).join(F.broadcast(pos), F.col(id_col) == F.col("__id"))
    grounded = F.forall("said", lambda e: F.contains(F.col(text_col), e))
    return j.agg(F.count("*").alias("n"), F.count_if(grounded).alias("found"))


def audit_misses(responses: DataFrame, truth: DataFrame, id_col: str, n: int = 100, seed: str = "audit") -> DataFrame:
    """Of a random ``n`` negatives, how many hold a place by ``truth_addr`` and ``truth_coord``, which the judge never sees."""
    neg = _drawn(responses, "negative", n, seed).select(F.col("id").alias("__id"))
    j = truth.select(id_col, "truth_addr", "truth_coord").join(F.broadcast(neg), F.col(id_col) == F.col("__id"))
    return j.agg(F.count("*").alias("n"), F.count_if(F.col("truth_addr") | F.col("truth_coord")).alias("missed"))


def compare_modes(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """One combined question against two separate ones, each call missing places on its own in 20 of 1,000 pages."""
    d = doc_flags(docs, text_col, [id_col])
    heard = lambda mode: bucket(f"ask-{mode}", id_col) >= 20
    c, a = F.col("has_coord"), F.col("has_addr")
    return d.select(((c | a) & heard("combined")).alias("combined"), ((c & heard("coord")) | (a & heard("addr"))).alias("separate")).groupBy("combined", "separate").agg(F.count("*").alias("n"))


def ask_until_done(todo: DataFrame, judge: Callable[[list[str]], list[tuple[str, str]]], id_col: str, prompt_col: str, folder: str, rounds: int = 3) -> DataFrame:
    """Answers of ``ask``; pages with an internal error are asked again, up to ``rounds`` times, refused ones are final.

    Each round is written below ``folder``, so a lost executor or driver asks no page again that has its answer.
    """
    spark, done = todo.sparkSession, None
    for k in range(rounds):
        left = todo if done is None else todo.join(done.select(F.col("id").alias(id_col)), id_col, "left_anti")
        ask(left, judge, id_col, prompt_col).write.mode("overwrite").parquet(f"{folder}/round={k}")
        final = spark.read.parquet(folder).where(f"status <> 'internal_error' or round = {k}")
        done = final.where("status <> 'internal_error'")
        if final.where("status = 'internal_error'").isEmpty():
            break
    return final.select("id", "status", "text")


def retry_rounds(docs: DataFrame, id_col: str, rounds: int = 3, headroom_pct: float = 3.7) -> DataFrame:
    """``round, asked, answered, refused, errors, lost, headroom``: the rule judge's failures, asked again, against the sample's headroom."""
    err = [bucket("judge" if k == 0 else f"judge-{k}", id_col) < 12 for k in range(rounds)]
    refused = bucket("judge", id_col).between(12, 19)
    asked, rows = F.lit(True), []
    for k in range(rounds):
        rows.append(F.struct(F.lit(k + 1).alias("round"), asked.alias("asked"), (asked & err[k]).alias("error"), (asked & refused).alias("refused")))
        asked = asked & err[k] & ~refused
    g = docs.select(F.inline(F.array(*rows))).groupBy("round").agg(F.count_if("asked").alias("asked"), F.count_if("error").alias("errors"), F.count_if("refused").alias("refused"), F.count("*").alias("n"))
    first = F.max(F.when(F.col("round") == 1, F.col("refused"))).over(Window.partitionBy())  # of a few rounds
    return g.select("round", "asked", (F.col("asked") - F.col("errors") - F.col("refused")).alias("answered"), "refused", "errors", (first + F.col("errors")).alias("lost"), F.floor(F.col("n") * F.lit(headroom_pct) / 100).cast("long").alias("headroom"))


# Costs.


def cost_model(docs: DataFrame, text_col: str, size: int = 8_000, overlap: int = 200, sec_per_query: float = 30.0, workers: int = 8, per_day: tuple[int, ...] = (1_500, 10_000)) -> DataFrame:
    """Queries, days at each quota and at a speed, for one combined question and for two separate ones about every window of every
    text; an empty text is asked once."""
    windows = F.greatest(F.lit(0), F.ceil((F.length(F.coalesce(text_col, F.lit(""))) - overlap) / (size - overlap)) - 1) + 1
    rows = [F.struct(F.lit(mode).alias("mode"), F.lit(q).alias("q"), F.lit(quota).cast("long").alias("per_day")) for mode, q in (("combined", 1), ("separate", 2)) for quota in per_day]
    g = docs.agg(F.coalesce(F.sum(windows), F.lit(0)).alias("n")).select("n", F.inline(F.array(*rows))).withColumn("queries", F.col("n") * F.col("q"))
    return g.select("mode", "queries", "per_day", F.round(F.col("queries") / F.col("per_day"), 4).alias("quota_days"), F.round(F.col("queries") * sec_per_query / workers / 86_400, 4).alias("work_days"))


# Baselines.


def naive_decimal(text: Column) -> Column:
    return text.rlike(ANY_DECIMAL)


def naive_pair(text: Column) -> Column:
    return text.rlike(ANY_PAIR)


def naive_counts(df: DataFrame, text_col: str) -> DataFrame:
    """Rows on which the widest pattern fires: as it is, with addresses of machines masked, and with licence versions too."""
    t = F.col(text_col)
    no_ip = F.regexp_replace(t, DECOYS["ipv4"], " ")
    return df.agg(F.count_if(naive_decimal(t)).alias("plain"), F.count_if(naive_decimal(no_ip)).alias("ip_masked"), F.count_if(naive_decimal(F.regexp_replace(no_ip, LICENCE, " "))).alias("licence_masked"))


def short_string_address(text: Column, longest: int = 200) -> Column:
    """Parsers for short strings: only lines up to ``longest`` characters, one format."""
    return F.exists(F.split(text, "\n"), lambda x: (F.length(x) <= longest) & x.rlike(ADDRESSES["a1_number_street"]))


# A gazetteer of its own: large cities, written down without a look at what is planted.
GAZETTEER = (
    "Amsterdam", "Athens", "Barcelona", "Berlin", "Birmingham", "Boston", "Bremen", "Bristol", "Brussels", "Budapest", "Chicago", "Cologne", "Copenhagen", "Dallas", "Denver", "Dresden", "Dublin", "Frankfurt", "Glasgow", "Hamburg",
    "Houston", "Leeds", "Lille", "Lisbon", "Liverpool", "London", "Lyon", "Madrid", "Manchester", "Marseille", "Melbourne", "Milan", "Munich", "Naples", "Nice", "Oslo", "Paris", "Prague", "Rome", "Seattle", "Seville", "Stockholm",
    "Stuttgart", "Sydney", "Toronto", "Toulouse", "Turin", "Valencia", "Vienna", "Warsaw", "Zurich",
)


def gazetteer_address(text: Column, places: tuple[str, ...] = GAZETTEER, strip: bool = True) -> Column:
    """Patterns plus place names; with tags stripped first, attributes and scripts are lost."""
    t = F.regexp_replace(text, "<[^>]{0,1000}>", " ") if strip else text
    named = functools.reduce(lambda a, b: a | b, [F.contains(t, F.lit(p)) for p in places])
    return has_address(t) & named


def keyword_lookup(text: Column, words: tuple[str, ...] = KEYWORDS) -> Column:
    low = F.lower(text)
    return functools.reduce(lambda a, b: a | b, [F.contains(low, F.lit(w)) for w in words])


def token_classes(text: Column) -> Column:
    """An array of letters, one per token: N number, S street word, C capitalised word, o any other."""
    tokens = F.regexp_extract_all(text, F.lit(r"[A-Za-zÀ-ÿ]+|[0-9]+|[^A-Za-zÀ-ÿ0-9 \t\r\n]"), F.lit(0))
    street = r"^(?:Street|St|Road|Rd|Avenue|Ave|Lane|Drive|Close|Square|rue|Calle)$"
    label = F.transform(tokens, lambda w: F.when(w.rlike("^[0-9]{1,5}$"), "N").when(w.rlike(street), "S").when(w.rlike("^[A-Z]"), "C").otherwise("o"))
    return label


def mined_patterns(planted: DataFrame, id_col: str, text_col: str, support: int = 5, precision: float = 0.8) -> DataFrame:
    """``pattern, n, x``: runs of three to five token classes that tell addresses on the training half of the ids.

    ``x`` of the ``n`` training documents with the run have an address; a run needs ``support`` of them and that precision.
    """
    train = _tagged(planted, id_col, text_col).where("train").select("truth_addr", F.explode("runs").alias("pattern"))
    return train.groupBy("pattern").agg(F.count("*").alias("n"), F.count_if("truth_addr").alias("x")).where((F.col("x") >= support) & (F.col("x") >= precision * F.col("n")))


def _tagged(planted: DataFrame, id_col: str, text_col: str) -> DataFrame:
    d = planted.select(F.col(id_col).alias("__id"), F.coalesce("truth_addr", F.lit(False)).alias("truth_addr"), (bucket("mine", id_col) < 500).alias("train"), F.explode(F.array(token_classes(F.coalesce(F.col(text_col), F.lit(""))))).alias("c1"))  # one row each; later steps read it and don't compute it again
    longer = lambda a, k: F.zip_with(a, F.slice("c1", F.lit(k), F.greatest(F.size("c1") - (k - 1), F.lit(0))), lambda x, y: F.concat(x, y))  # noqa: E731  null past the end
    d = d.withColumn("c2", longer("c1", 2)).withColumn("c3", longer("c2", 3)).withColumn("c4", longer("c3", 4)).withColumn("c5", longer("c4", 5))
    runs = F.array_distinct(F.filter(F.concat("c3", "c4", "c5"), lambda x: F.coalesce(F.contains(x, F.lit("N")) & F.contains(x, F.lit("S")), F.lit(False))))
    return d.select("__id", "truth_addr", "train", runs.alias("runs"))


def sequence_labels(planted: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Sequence labels and mined patterns: the confusion on the half of the ids that nothing was mined from."""
    test = _tagged(planted, id_col, text_col).where("not train")
    hit = test.select("__id", F.explode("runs").alias("pattern")).join(mined_patterns(planted, id_col, text_col).select("pattern"), "pattern", "left_semi").select("__id").distinct()
    return confusion(test.join(hit.withColumn("hit", F.lit(True)), "__id", "left").select(F.coalesce("hit", F.lit(False)).alias("pred"), "truth_addr"), "pred", "truth_addr")


def entity_addresses(docs: DataFrame, tagger: Callable[[list[str]], list[list[tuple[int, int, str]]]], id_col: str, text_col: str, labels: tuple[str, ...] = ("ADDRESS",)) -> DataFrame:
    """``id, has_addr, spans`` from any entity recogniser: a function from texts to (start, end, label) triples.  None is shipped."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            found = [[f"{x}:{y}" for x, y, k in spans if k in labels] for spans in tagger(b["t"].tolist())]
            yield pd.DataFrame({"id": b["id"], "has_addr": [bool(x) for x in found], "spans": found})

    return docs.select(F.col(id_col).cast("string").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("t")).mapInPandas(run, "id string, has_addr boolean, spans array<string>")


def svm_windows(planted: DataFrame, id_col: str, text_col: str, size: int = 400, overlap: int = 60) -> DataFrame:
    """N-grams over sliding windows and a linear support vector machine, trained on half the ids: its confusion on the others."""
    from pyspark.ml.classification import LinearSVC
    from pyspark.ml.feature import HashingTF, NGram

    from geocensus.functions.columns import windows
    from geocensus.sources.index import stored

    w = planted.select(id_col, "truth_addr", "truth_snippet", F.explode(windows(F.col(text_col), size, overlap)).alias("x"))
    shape = F.regexp_replace(F.regexp_replace("x.text", "[0-9]", "9"), "[a-z]{4,}", "w")
    w = w.select(id_col, "truth_addr", (F.col("truth_addr") & F.contains(F.col("x.text"), F.substring("truth_snippet", 1, 12))).cast("double").alias("label"), F.split(shape, r"[ \t\r\n]+").alias("tokens"), (bucket("svm", id_col) < 500).alias("train"))
    w = stored(w, "svm-windows")  # fit and transform read the windows; planting and cutting run once
    w = NGram(n=2, inputCol="tokens", outputCol="pairs").transform(w)
    w = HashingTF(inputCol="pairs", outputCol="features", numFeatures=4096).transform(w).withColumn("weight", F.when(F.col("label") == 1, 20.0).otherwise(1.0))
    model = LinearSVC(maxIter=15, regParam=0.001, weightCol="weight").fit(w.where("train"))
    by = model.transform(w.where("not train")).groupBy(id_col).agg((F.max("prediction") == 1.0).alias("pred"), F.max("truth_addr").alias("truth"))
    return confusion(by, "pred", "truth")


def needle_grid(docs: DataFrame, id_col: str, text_col: str, needles: tuple[str, ...], depths: tuple[int, ...] = (0, 25, 50, 75, 100)) -> DataFrame:
    """``depth, length_class, n, found``: one needle at one depth of every document, both by its id, found or not by detection.

    The length class is the power of four characters that a document reaches.
    """
    number = lambda seed, n: bucket(seed, id_col, n).cast("int")
    d = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("t"), F.element_at(F.array(*[F.lit(x) for x in needles]), number("needle", len(needles)) + 1).alias("needle"), F.element_at(F.array(*[F.lit(x) for x in depths]), number("depth", len(depths)) + 1).alias("depth"))
    at = F.floor(F.length("t") * F.col("depth") / 100).cast("int")
    put = F.concat(F.substring("t", F.lit(1), at), F.lit("\n"), F.col("needle"), F.lit("\n"), F.substring("t", at + 1, F.length("t")))
    size = F.floor(F.log2(F.greatest(F.length("t"), F.lit(1)).cast("double")) / 2).cast("int")
    d = d.select("depth", size.alias("length_class"), put.alias("t")).select("depth", "length_class", has_coords(F.col("t")).alias("hit"))
    return d.groupBy("depth", "length_class").agg(F.count("*").alias("n"), F.count_if("hit").alias("found"))
