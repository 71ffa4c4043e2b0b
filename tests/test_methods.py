"""Formulas, detection unit cases, invariants and plans."""

import re

import pytest
from geocensus.functions import columns as C
from geocensus.functions.patterns import ADDRESSES, COORDS, GATES, READ_AS_SHOWN
from geocensus.operators import sampling as S
from geocensus.operators import study as Y
from geocensus.plans.workloads import planted_docs
from geocensus.plans.workloads import queries as workload_queries
from geocensus.sources import index as I
from geocensus.sources.planter import ADDRESS_SNIPPETS, COORD_SNIPPETS, DECOY_SNIPPETS, HELD_OUT
from pyspark.sql import functions as F


def test_sample_sizes():
    assert S.sample_size(0.005) == 38_416
    assert S.sample_size(0.005, z=1.959964) == 38_415
    assert S.sample_size(0.005, population=60_000) < 38_416
    assert S.allocate(38_416, 300, 1_484) == 133
    assert abs(S.margin(39_900, 0.187) - 0.003826) < 1e-6
    assert abs(S.zero_error_bound(100) - 0.02951) < 1e-5
    assert abs(S.zero_error_bound(100, sides=2) - 0.03622) < 1e-5
    lo, hi = S.wilson(187, 1000)
    assert lo < 0.187 < hi


def flags(spark, texts):
    d = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "id long, t string")
    return {r["id"]: (r["has_coord"], r["has_addr"]) for r in Y.doc_flags(d, "t", ["id"]).collect()}


def test_snippets_are_found(spark):
    got = flags(spark, [s for _, s in COORD_SNIPPETS + ADDRESS_SNIPPETS])
    n = len(COORD_SNIPPETS)
    assert all(got[i][0] for i in range(n)), [COORD_SNIPPETS[i] for i in range(n) if not got[i][0]]
    assert all(got[n + i][1] for i in range(len(ADDRESS_SNIPPETS))), [ADDRESS_SNIPPETS[i] for i in range(len(ADDRESS_SNIPPETS)) if not got[n + i][1]]


def test_decoys_are_not(spark):
    got = flags(spark, [s for _, s in DECOY_SNIPPETS] + ["pi is 3.14159", "", None, "version 2.0, 3.1"])
    assert [k for k, v in got.items() if any(v)] == []


def test_rules(spark):
    got = flags(spark, ["at 95.1234, 10.1234 there", "lat: 95.0, lng: 10.0", "0.000, 0.000", "-0.0; 0.00", "lat=0.0, lon=0.0x 51.5012,-0.1419"])
    assert [got[i][0] for i in range(3)] == [False, True, False] and not got[3][0] and got[4][0]


def test_held_out_recall(spark):
    """Reported, not tuned: at least half of the held-out wordings are found."""
    got = flags(spark, [s for _, s in HELD_OUT])
    assert sum(any(v) for v in got.values()) >= len(HELD_OUT) // 2


def test_every_format_has_a_snippet():
    assert {k for k, _ in COORD_SNIPPETS} == set(COORDS) and {k for k, _ in ADDRESS_SNIPPETS} == set(ADDRESSES)


def test_realised_truth(spark):
    got = {r["truth_class"]: r["n"] for r in planted_docs(spark, "/root/testdata/sf0.01").groupBy("truth_class").agg(F.count("*").alias("n")).collect()}
    assert (got["both"], got["address"], got["coord"], got["decoy"]) == (44, 140, 18, 125)


def test_naive_baseline(spark):
    r = Y.naive_counts(I.table(spark, "/root/testdata/sf0.01", "documents"), "text").first()
    assert (r["plain"], r["ip_masked"], r["licence_masked"]) == (44, 20, 4)


def test_sample_is_the_same_for_any_partitioning(spark):
    d = I.table(spark, "/root/testdata/sf0.01", "documents").select("doc_id", "source")
    draws = [{r["doc_id"] for r in S.stratified_sample(d.repartition(n), ["source"], 5, "s1", ["doc_id"]).collect()} for n in (1, 4, 16)]
    assert draws[0] == draws[1] == draws[2] and len(draws[0]) == 100


def test_plans(spark, sf, capsys):
    d = I.table(spark, sf, "documents").select("doc_id", "source")
    S.stratified_sample(d, ["source"], 5, "s1", ["doc_id"]).explain()
    assert "WindowGroupLimit" in capsys.readouterr().out
    Y.mime_census(I.crawl_index(spark, sf)).explain()
    schemas = re.findall(r"ReadSchema: (\S+)", capsys.readouterr().out)
    assert schemas and not any("html" in x for x in schemas)
    Y.doc_flags(d.withColumn("t", F.col("source")), "t", ["doc_id"]).explain()
    assert "Python" not in capsys.readouterr().out


def test_text_preparation(spark):
    d = spark.createDataFrame([("a\\u0436\\ud83d\\ude00b", "<b>x</b>&deg;", "k" * 25)], "a string, b string, c string")
    r = d.select(C.unescape_unicode(F.col("a")), C.decode_entities(C.soften_tags(F.col("b"))), C.windows(F.col("c"), 10, 2)).first()
    assert r[0] == "aж😀b" and r[1] == " x °" and [w["start"] for w in r[2]] == [0, 8, 16]


def test_ask_any_judge(spark, sf):
    d = I.table(spark, sf, "documents").select("doc_id", Y.build_prompt(F.col("text")).alias("p"))
    assert Y.ask(d, lambda prompts: [("ok", "None.") for _ in prompts], "doc_id", "p").where("status = 'ok'").count() == 200


@pytest.mark.parametrize("n", [0, 1])
def test_empty_tables(spark, n):
    d = spark.createDataFrame([(1, None)][:n], "id long, t string")
    assert Y.prevalence(Y.doc_flags(d, "t", ["id"])).first()["x_any"] == 0


def test_archives_hold_every_page(spark, sf):
    from geocensus.plans import relational

    pages = {r["page_id"]: len((r["html"] or "").encode()) for r in I.table(spark, sf, "pages").collect()}
    assert {r["id"]: r["n_bytes"] for r in relational.queries()["range_source"](spark, sf).collect()} == pages
    more = I.table(spark, sf, "pages").withColumn("page_id", F.col("page_id") + 1_000_000)
    folder = I.scratch(spark, "pages-test")
    I.table(spark, sf, "pages").unionByName(more).write.parquet(f"{folder}/pages.parquet")
    files = relational.queries()["binary_files"](spark, folder).agg(F.sum("n_bytes")).first()[0]
    assert files == 2 * (sum(pages.values()) + len(pages))
    back = spark.read.format("byte_ranges")  # every byte, not only lengths
    path, lists = I.scratch(spark, "archives"), I.scratch(spark, "lists")
    I.write_archives(I.table(spark, sf, "pages"), path)
    i = I.with_offsets(I.crawl_index(spark, sf)).select(F.concat_ws("|", F.concat(F.lit(path + "/"), I.archive_name(), F.lit(".arc")), "page_id", "offset", "length"))
    i.write.text(lists)
    got = {r["id"]: bytes(r["bytes"]) for r in back.option("lists", lists).load().collect()}
    assert got == {r["page_id"]: (r["html"] or "").encode() for r in I.table(spark, sf, "pages").collect()}


def test_language_distance_beyond_twenty(spark):
    from geocensus.plans import workloads

    folder = I.scratch(spark, "languages")
    spark.range(4000).select(F.col("id").alias("doc_id"), F.concat(F.lit("l"), F.col("id") % 40).alias("lang"), F.lit("x").alias("text")).write.parquet(f"{folder}/documents.parquet")
    d = workloads.docs(spark, folder)
    all_langs = Y.language_balance(d, S.bernoulli_sample(d, 0.2, "lb", ["doc_id"]), top=1000)
    assert all_langs.count() == 40
    assert workloads.queries()["language_distance"](spark, folder).first()[0] == Y.total_variation(all_langs).first()[0]


def test_reverse_spaced_and_separate(spark):
    meta = '<meta property="place:location:latitude" content="41.90"> <meta property="place:location:longitude" content="12.49">'
    swapped = '<meta property="og:longitude" content="12.49">\n<meta property="og:latitude" content="41.90">'
    got = flags(spark, ['{"lng": 12.49637, "lat": 41.90278}', "at 51.50123 -0.14189 there", meta, swapped, "3.141 is pi", "rows 1.23 4.56", "0.0000 0.0000"])
    assert [got[i][0] for i in range(7)] == [True] * 4 + [False] * 3


#: Wordings by format that the patterns were not written from; ``{}`` takes numbers.
PLACES = ((48.13743, 11.57549), (-34.60368, -58.38157), (1.35208, 103.81983), (64.14661, -21.94264), (19.43261, -99.13321))
WORDINGS = {
    "c1_bare_pair": ("We met at ({lat}, {lon}) twice.", "waypoint {lat};{lon}", "[{lat}, {lon}]", "fix {lat} {lon}\nend"),
    "c2_constructor": ("new google.LatLng({lat}, {lon})", "var m = L.latLng({lat},{lon});", "ol.GeoPoint( {lat} , {lon} )", "L.Marker([{lat}, {lon}]).addTo(map)"),
    "c6_keys": ("{{lat:{lat},lng:{lon}}}", "'lon': '{lon}',\n 'lat': '{lat}'", "?lat={lat}&lon={lon}", "Latitude: {lat}, Longitude: {lon}"),
    "c9_map_link": ("<a href='http://maps.site/@{lat},{lon},12z'>", '<a href="https://site/map?ll={lat},{lon}&z=3">', '<a href="//map.site/?q={lat}%2C{lon}">'),
    "c11_xml_point": ("<lat>{lat}</lat>\n<lon>{lon}</lon>", "POINT({lon} {lat})", '"coordinates":[{lon},{lat}]', "<gml:pos>{lat} {lon}</gml:pos>"),
    "c5_meta": ('<meta name="ICBM" content="{lat}, {lon}">', "<meta name='geo.position' content='{lat};{lon}' />"),
}
SHOWN = ("48&deg;08&#39;14&quot;N, 11&deg;34&#39;31&quot;E", "<td>48°08'14\"N<br/>11°34'31\"E</td>", "N 48° 08' 14'' <b>E 11° 34' 31''</b>")
WRITTEN = ("14 Orchard Lane", "221 Old Mill Road, Ely", "'streetAddress':'8 Rue X'", "3, rue de la Paix", "Calle Mayor 12", "Hauptweg 5a", "улица Ленина 12", "ул. Садовая, д 7", "Οδός Ερμού 15", "上海市南京路100号", "東京都渋谷区神南1丁目", "Grand Bridge, Salem, OR")
NOT_PLACES = ("Marker(3, 4)", "price 12.345; 99.999", "version 12.345, 6.789", "LatLng(0,0)", "lat=0&lng=0", '"latitude": 0.0, "longitude": 0.0', "POINT(0 0)", "<lat>0.0</lat><lon>0</lon>", "RA 5.60361, Dec -1.20194", "RA 05h36m12s, Dec -01 12 07", "right ascension 10.68458", "0.000; -0.0", "ratio 1.234, 5.678", "+49 30 12345678", "10.0.0.1 and 10.0.0.2", "3.14159 2.71828 as numbers go"[:7], "x = 0.0, 0.0", "95.12345, 10.12345")
PLACES_STILL = ("Dec 5 51.50123, -0.14189", "CAMERA 3 51.50123, -0.14189", "LatLng(10.0, 0.05)", "50.000, 0.00512", "POINT(0 51.5)", "lat: 0, lng: 9.45", "0.00000, 9.45356")


def test_wordings_never_seen(spark):
    """Recall and precision per format on over a hundred wordings that were not planted."""
    cases = [(k, w.format(lat=a, lon=b)) for k, ws in WORDINGS.items() for w in ws for a, b in PLACES]
    got = flags(spark, [t for _, t in cases])
    recall = {k: sum(got[i][0] for i, (f, _) in enumerate(cases) if f == k) / sum(f == k for f, _ in cases) for k in WORDINGS}
    assert len(cases) >= 100 and all(v >= 0.9 for v in recall.values()), recall
    wrong = [t for (t, v) in zip(NOT_PLACES, flags(spark, NOT_PLACES).values(), strict=True) if v[0]]
    lost = [t for (t, v) in zip(PLACES_STILL + SHOWN, flags(spark, PLACES_STILL + SHOWN).values(), strict=True) if not v[0]]
    missed = [t for (t, v) in zip(WRITTEN, flags(spark, WRITTEN).values(), strict=True) if not v[1]]
    assert (wrong, lost) == ([], []) and len(missed) <= 1, (wrong, lost, missed)


def test_gates_change_nothing(spark):
    texts = [s for _, s in COORD_SNIPPETS + ADDRESS_SNIPPETS + DECOY_SNIPPETS + HELD_OUT] + list(NOT_PLACES + PLACES_STILL + SHOWN + WRITTEN)
    d = spark.createDataFrame([(t,) for t in texts], "t string")
    for pats, has in ((COORDS, C.has_coord_format), (ADDRESSES, C.has_address_format)):
        for k, v in pats.items():
            if k in GATES and k not in READ_AS_SHOWN:
                assert d.where(F.col("t").rlike(v) & ~F.col("t").rlike(GATES[k])).count() == 0, k


def test_judge_errs_at_its_rates(spark):
    d = planted_docs(spark, "/root/testdata/sf0.01")
    r = Y.triage(I.stored(Y.rule_judge(d.select("doc_id", "text"), "doc_id", "text"), "responses"))
    assert "truth_addr" not in r.columns
    shares = {x["status"]: x["n"] for x in r.groupBy("status").agg(F.count("*").alias("n")).collect()}
    assert 2 <= shares["internal_error"] <= 30 and 1 <= shares["unsafe"] <= 25
    invented = r.where(F.contains("text", F.lit(Y.INVENTED))).count()
    audit = Y.audit_grounding(r, d, "doc_id", "text", n=1000).first()
    assert invented > 0 and audit["found"] == audit["n"] - invented
    misses = Y.audit_misses(r, d, "doc_id", n=1000).first()
    assert 0 < misses["missed"] < 0.05 * misses["n"]


def test_failed_pages_are_asked_again(spark):
    d = spark.createDataFrame([(i, f"p{i}") for i in range(50)], "doc_id long, p string")
    folder = I.scratch(spark, "asked")

    def judge(prompts):  # noqa: ANN001, ANN202
        return [("unsafe", "") if p.endswith("3") else ("internal_error", "") if p.endswith("7") else ("ok", "None") for p in prompts]

    got = Y.ask_until_done(d, judge, "doc_id", "p", folder, rounds=3).groupBy("status").count().collect()
    assert {r["status"]: r["count"] for r in got} == {"ok": 40, "unsafe": 5, "internal_error": 5}
    assert spark.read.parquet(folder).where("status = 'internal_error'").count() == 15


def test_intervals_cover_the_known_share(spark):
    d = I.table(spark, "/root/testdata/sf0.01", "documents").select("source", "doc_id", (F.col("lang") == "en").alias("hit"))
    r = S.interval_coverage(d, "source", "doc_id", "hit", 10, 60).first()
    assert r["seeds"] == 60 and r["covered"] >= r["covered_fpc"] >= 0.85 * 60 and r["covered_stratified"] >= 0.85 * 60 and r["mean_margin_fpc"] < r["mean_margin"]


def test_any_entity_recogniser(spark):
    def tagger(texts):  # noqa: ANN001, ANN202
        return [[(m.start(), m.end(), "ADDRESS") for m in re.finditer("[0-9]+ Road", t)] + [(0, 1, "OTHER")] for t in texts]

    d = spark.createDataFrame([(1, "at 5 Road"), (2, "none"), (3, None)], "doc_id long, t string")
    got = {r["id"]: (r["has_addr"], r["spans"]) for r in Y.entity_addresses(d, tagger, "doc_id", "t").collect()}
    assert got == {"1": (True, ["3:9"]), "2": (False, []), "3": (False, [])}


def test_audit_bounds_of_documents(spark, sf, tmp_path):
    df = workload_queries()["audit_bounds"](spark, sf)
    assert [f for f in df.inputFiles() if "documents" in f]
    rows = [(k, "a" if k < 150 else "b" if k < 157 else None) for k in range(158)]
    spark.createDataFrame(rows, "doc_id long, source string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r["source"], r["sides"]): (r["n"], r["bound"]) for r in workload_queries()["audit_bounds"](spark, str(tmp_path)).collect()}
    assert got == {(k, sides): (n, round(S.zero_error_bound(n, sides=sides), 6)) for k, n in (("a", 100), ("b", 7), (None, 1)) for sides in (1, 2)}


def test_cost_of_documents(spark, sf):
    assert [f for f in workload_queries()["cost_model"](spark, sf).inputFiles() if "documents" in f]
    texts = [None, "", "a", "b" * 8_000, "c" * 8_001, "d" * 15_800, "\U0001f600" * 15_801]  # 1, 1, 1, 1, 2, 2 and 3 windows
    docs = spark.createDataFrame([(t,) for t in texts], "t string")
    got = [tuple(r) for r in Y.cost_model(docs, "t", per_day=(5,)).collect()]
    assert got == [(mode, n, 5, n / 5, round(n * 30 / 8 / 86_400, 4)) for mode, n in (("combined", 11), ("separate", 22))]
    assert [r["queries"] for r in Y.cost_model(docs.limit(0), "t").collect()] == [0] * 4


def test_sample_sizes_of_lineitem(spark, sf):
    assert [f for f in workload_queries()["sample_sizes"](spark, sf).inputFiles() if "lineitem" in f]
    rows = spark.range(60_000).selectExpr("1 as s", "id % 300 as p").unionAll(spark.range(7).selectExpr("2 as s", "if(id = 0, null, 0) as p")).unionAll(spark.range(1).selectExpr("null", "0"))
    for e in (0.005, 0.03):
        n = S.sample_size(e)
        got = {r["s"]: tuple(r)[1:] for r in S.sample_sizes(rows, "s", "p", e, 1_484).collect()}
        assert got == {s: (size, parts, n, S.sample_size(e, z=1.959964), S.sample_size(e, population=size), S.allocate(n, parts, 1_484)) for s, size, parts in ((1, 60_000, 300), (2, 7, 2), (None, 1, 1))}
