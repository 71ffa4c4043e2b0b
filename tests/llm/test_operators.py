"""Training-data operators on small fixtures: against brute force, SQL, round trips and held-out labels; and awkward rows."""

import hashlib
import random
import re
import zlib

import duckdb
import numpy as np
import pytest
from geocensus.llm import byte_convnet, exact_dedup, mixing, near_dup, page_text, piece_codec, pii, quality_rules, repeats, shared, toxicity
from geocensus.llm.queries import model_path, read
from geocensus.llm.shared import words_py

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, digest string, size string, key string"
LONG = "alpha beta " * 5000
ROWS = [(1, None, None, None, None, "x", "x", "x"), (2, "", "en", "b", 0, "x", "x", "x"), (3, " \t\n", "en", "b", 3, "x", "x", "x"), (4, LONG, "en", None, 1, "x", "x", "x"), (5, LONG, "en", "a", 1, "x", "x", "x"), (6, "one", None, "a", 1, "x", "x", "x"), (6, "one", None, "a", 1, "x", "x", "x")]


def frames(spark):
    return spark.createDataFrame(ROWS, SCHEMA), spark.createDataFrame([], SCHEMA)


def labels(spark, rows=()):
    return spark.createDataFrame(list(rows), "doc_id long, quality int, toxic int")


AWKWARD = {
    "near": (near_dup.near_duplicates, 7), "pii": (pii.digest, 7), "exact": (exact_dedup.exact_duplicates, 7), "repeats": (repeats.remove_repeats_digest, 7),
    "pieces": (lambda d: piece_codec.encode_digest(d, model_path()), 7), "mix": (mixing.mix, 7), "rules": (lambda d: quality_rules.judge(d, labels(d.sparkSession, [(4, 1, None), (5, None, 0)])), 7),
    "convnet": (lambda d: byte_convnet.quality(d, labels(d.sparkSession, [(4, 1, 0), (6, 0, 1)])), 7), "toxic": (lambda d: toxicity.toxicity(d, labels(d.sparkSession)), 7),
}


@pytest.mark.parametrize("name", sorted(AWKWARD))
def test_awkward_and_empty_tables(spark, name):
    run, n = AWKWARD[name]
    some, none = frames(spark)
    assert len(run(some).collect()) == n
    assert run(none).collect() == []


@pytest.mark.parametrize("module, run", [(exact_dedup, exact_dedup.exact_duplicates), (mixing, mixing.mix), (repeats, repeats.remove_repeats_digest), (quality_rules, lambda d: quality_rules.judge(d, read(d.sparkSession, "/root/testdata/sf0.001", "labels")))])
def test_sql(spark, duck, sf, module, run):
    from compare import same

    assert same(run(read(spark, sf, "documents")).toPandas(), duck.execute(module.SQL).df()).startswith("ok")


def test_near_duplicates_by_brute_force(spark, sf):
    d = read(spark, sf, "documents")
    got = {r["doc_id"]: r for r in near_dup.near_duplicates(d).collect()}
    sets = {r["doc_id"]: near_dup.grams_of(r["text"]) for r in d.collect()}
    for i, a in sets.items():
        assert got[i]["n_links"] == sum(1 for j, b in sets.items() if i != j and len(a & b) * 5 >= 4 * len(a | b) and a)


def test_large_group_of_near_copies_is_split(spark, monkeypatch):
    r = random.Random(3)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(60):
        w = list(base)
        w[r.randrange(120)] = f"x{i}"
        rows.append((i, " ".join(w)))
    monkeypatch.setattr(near_dup, "BLOCK_ROWS", 16)
    got = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    sets = [near_dup.grams_of(t) for _, t in rows]
    for g in got:
        assert g["class_id"] == 0
        assert g["n_links"] == sum(1 for j, b in enumerate(sets) if j != g["doc_id"] and len(sets[g["doc_id"]] & b) * 5 >= 4 * len(sets[g["doc_id"]] | b))


@pytest.mark.parametrize("edges, tables", [([(1, 2), (3, 1), (7, 8), (9, 9)], 1), ([], 1), ([(5, 1), (5, 2), (6, 5)], None), ([(i, i + 1) for i in range(20)], None)])
def test_components_write_and_broadcast_no_more_than_needed(spark, monkeypatch, edges, tables):
    """Stars are found to be settled as they are; no round leaves a broadcast table with the driver."""
    written, write = [], shared.materialise
    monkeypatch.setattr(shared, "materialise", lambda d, label: (written.append(d), write(d, label))[1])
    got = shared.connected_components(spark.createDataFrame(edges, "a long, b long"), "test-components").collect()
    forest = shared.Forest(50)
    for a, b in edges:
        forest.join(a, b)
    assert sorted(map(tuple, got)) == sorted((x, forest.find(x)) for x in {x for a, b in edges if a != b for x in (a, b)})
    assert tables is None or len(written) == tables
    for d in written:
        d.collect()
        assert "BroadcastHashJoin" not in d._jdf.queryExecution().executedPlan().toString()


def test_driver_gives_back_what_it_freed(spark):
    def held():
        with open("/proc/self/smaps_rollup") as f:
            return int(re.search(r"Pss_Anon:\s+(\d+)", f.read())[1])

    many = [np.ones(8000) for _ in range(1600)]  # 100 MB in pieces that malloc doesn't map on their own
    last, many = many[-1], None
    before = held()
    shared.collect_garbage(spark)
    assert before - held() > 50_000 and last[0] == 1
    assert "Trim native heap" in shared._trim(spark)


def test_pruning_keeps_likely_pairs():
    need = near_dup.least_matches()
    assert need[100] <= 62 and need[10] <= 3 and list(need) == list(range(10, 101, 10))


BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def valid(kind, s):
    d = re.sub("[^0-9]", "", s)
    if kind == "ip":
        return all(int(x) <= 255 for x in s.split("."))
    if kind == "phone":
        return 10 <= len(d) <= 15
    if kind == "card":
        return 14 <= len(d) <= 19 and sum(int(x) if i % 2 == 0 else sum(divmod(2 * int(x), 10)) for i, x in enumerate(reversed(d))) % 10 == 0
    return True


def test_personal_data_by_python_patterns(spark):
    texts = ["a@b.com+c@d.com x", "1.2.3.4.5.6.7.8 999.1.1.1 0010.1.1.1", "4111 1111 1111 1111, 4111-1111-1111-1112", "+1 (234) 567-8901 +1", "é😀 q@x.org 10.0.0.1 +44 20 7946 0958", "9" * 3000, "@ + .. 1", "x" * 2000 + "@", None]
    got = {r["doc_id"]: r for r in pii.digest(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    for i, t in enumerate(texts):
        spans = sorted((m.start(), n, k, m.end()) for n, (k, p) in enumerate(BASE.items()) for m in re.finditer(p, t or "") if valid(k, m[0]))
        assert got[i]["base_sha256"] == hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, _, k, b in spans).encode()).hexdigest()


def test_contexts_discover_identifiers(spark):
    rows = [(i, f"well then contact user{i}@mail.org today {i}") for i in range(40)] + [(100, "well then contact jdoe7788_at_mail today then")]
    got = {r["doc_id"]: r for r in pii.digest(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[100]["spans"].startswith("email:18:") and got[100]["n_email"] == 0


def test_discovered_identifiers_vouch_for_contexts(spark):
    rows = [(i, f"well then contact user{i}@mail.org today {i}") for i in range(80)]
    rows += [(100 + i, f"well then contact jdoe77{i}_at_mail today then") for i in range(12)]
    rows += [(200 + i, f"please kindly forward jdoe77{i}_at_mail onwards quickly") for i in range(12)] + [(300, "please kindly forward zoe9988_at_home onwards quickly")]
    got = {r["doc_id"]: r["spans"] for r in pii.digest(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[100 + i].startswith("email:18:") for i in range(12)) and got[300] == "email:22:37"


def patterns(inst, left, right):
    """The operator's patterns in plain Python."""
    l, r = re.findall(r"[^\x20\x09-\x0D]+", left), re.findall(r"[^\x20\x09-\x0D]+", right)
    form = re.sub("[0-9]", "9", re.sub(r"[^\W\d_]+", "a", inst))
    out = [("L", l[-1] if l else ""), ("R", r[0] if r else ""), ("B", f"{l[-1]} {r[0]}" if l and r else ""), ("LL", " ".join(l) if len(l) > 1 else ""), ("RR", " ".join(r) if len(r) > 1 else ""), ("F", form if len(form) >= pii.FORM else "")]
    return [(k, w) for k, w in out if w]


def scored(rows, rounds=3, support=5, least=0.8):
    """The graph of patterns and instances, scored by loops."""
    at, known = {}, {}
    for r in rows:
        for x in r["seeds"]:
            known[(x["inst"], x["n"])] = 1.0
        for x in [*r["seeds"], *r["mentions"]]:
            for p in patterns(x["inst"], x["left"], x["right"]):
                at.setdefault(p, set()).add(x["inst"])
    seeds, conf = {i for i, _ in known}, dict(known)
    for _ in range(rounds):
        doubt = {}
        for p, members in at.items():
            mass = {n: sum(conf.get((i, n), 0.0) for i in members) for n in range(4)}
            for n, m in mass.items():
                if m >= support and (score := m / (sum(mass.values()) if p[0] == "F" else len(members))) >= least:
                    for i in members - seeds:
                        doubt[(i, n)] = doubt.get((i, n), 1.0) * (1 - 0.999 * score)
        conf = {**known, **{k: 1 - v for k, v in doubt.items()}}
    best = {}
    for (i, n), c in conf.items():
        if i not in seeds and c >= least:
            best[i] = max(best.get(i, (0.0, -1)), (c, n))
    return best


def luhn(prefix):
    """``prefix`` with the digit that makes the checksum right, and with one that makes it wrong."""
    good = next(c for c in "0123456789" if valid("card", prefix + c))
    return prefix + good, prefix + str((int(good) + 1) % 10)


def test_bootstrap_by_brute_force(spark):
    r = random.Random(4)
    rows = []
    for i in range(60):
        a, b = "".join(r.choices("0123456789", k=15)), r.choice(["card", "account", "number"])
        rows.append(f"my {b} is {luhn(a)[i % 3 == 0]} since {i} weeks at user{i}@mail.org or jane.doe{i}(at)mail from 10.0.{i}.{i % 7}")
        rows.append(f"write to {'jane.doe' if i % 2 else 'x'}{r.randrange(30)}(at)mail soon, ratio 17.{i} and 999.{i}.1.1")
    scanned = pii.scan(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")).persist()
    got = {x["inst"]: (x["conf"], x["n"]) for x in pii.bootstrap(scanned).collect()}
    want = scored(scanned.collect())
    assert got.keys() == want.keys() and len(want) > 10
    for k, (c, n) in want.items():
        assert got[k][1] == n and got[k][0] == pytest.approx(c, abs=1e-9)


def test_unseen_identifiers_per_kind(spark):
    """Planted identifiers that no base pattern takes: refused cards, written-out mails, without digits too, and with blanks."""
    r = random.Random(8)
    card = lambda: "".join(r.choices("0123456789", k=15))
    rows = [f"word {r.random()} his card {luhn(card())[0]} thanks" for _ in range(20)] + [f"please mail person{i}@site{i}.org today or never" for i in range(60)]
    hidden = [("card", luhn(card())[1]) for _ in range(10)] + [("email", f"{a}.{b}(at)site") for a in ("ann", "bob", "cleo") for b in ("lee", "may", "orr")]
    rows += [f"{'his card' if k == 'card' else 'please mail'} {x} {'thanks' if k == 'card' else 'today or never'}" for k, x in hidden]
    rows += [f"plain prose of {i} words, version 2.{i}" for i in range(20)]
    got = {x["doc_id"]: x["spans"] for x in pii.digest(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")).collect()}
    for i, (kind, x) in enumerate(hidden, 80):
        at = rows[i].index(x)
        assert f"{kind}:{at}:{at + len(x)}" in got[i].split(",")
    assert not any(got[i] for i in range(80 + len(hidden), len(rows)))


def test_repeats_in_large_groups(spark):
    """Six thousand copies of a text and six thousand that share a passage, and rows that repeat an id or lack one."""
    passage = " ".join(f"p{i}" for i in range(25))
    rows = [(i, "copy " + passage) for i in range(6000)] + [(10_000 + i, f"own{i} words{i} {passage} tail{i}") for i in range(6000)] + [(5, "copy " + passage), (None, passage), (None, None)]
    got = repeats.remove_repeats_digest(spark.createDataFrame(rows, "doc_id long, text string").repartition(8)).toPandas()
    assert len(got) == len(rows)
    first = got[got.doc_id == 0].iloc[0]
    assert (first.n_words, first.n_removed) == (26, 0)
    copies = got[(got.doc_id > 0) & (got.doc_id < 6000)]
    assert (copies.n_removed == 26).all() and len(copies) == 6000
    assert (got[got.doc_id >= 10_000].n_removed == 25).all()
    assert sorted(got[got.doc_id.isna()].n_removed) == [0, 25]


def test_phrases_are_found_beside_other_words():
    rows = [b" ".join(b"w%d" % (i * 7 + k) for k in range(20)) for i in range(300)]
    p = repeats.Phrases(rows, [(1, 20 * i) for i in range(300)])
    words = b" x ".join([rows[3], rows[250], rows[3][:-1]]).split()
    assert sorted(p.repeated(9, words)) == [(0, 20), (21, 41)] and list(p.repeated(1, rows[2].split())) == [(0, 20)]
    assert list(repeats.Phrases(rows, [(1, 0)] * 300).repeated(1, rows[0].split())) == []
    assert list(repeats.Phrases([], []).repeated(1, words)) == []


def test_pieces_equal_the_library(spark, sf):
    codec = piece_codec.PieceCodec(model_path())
    texts = ["", " ", "a ", "▁", "a▁b", "\n\n a\t b", "日本語 😀", "a\x00b", "   a   b   ", "\r\n x;\r"] + [r["text"] for r in read(spark, sf, "documents").collect()]
    for t, (n, ids, back) in zip(texts, codec.coded(texts), strict=True):
        e = codec.sp.encode(t)
        assert (n, ids, back) == (len(e), ",".join(map(str, e)), codec.sp.decode(e))


def test_mix_comes_near_targets(spark):
    rows = [(i, "w " * (1 + i % 97), "abc"[i % 3]) for i in range(6000)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(d).toPandas()
    assert (got.taken <= 3 * got["size"]).all() and (got.taken % got["size"] == 0).all()
    for (_, target), g in got.groupby(["source_size", "target"]):
        assert abs(g.taken.sum() - target) <= 97
    again = mixing.mix(d.repartition(7)).toPandas()
    assert got.sort_values("doc_id").taken.tolist() == again.sort_values("doc_id").taken.tolist()
    assert mixing.mix_table(d).count() == int((got.taken / got["size"]).sum())


def test_rule_counts_by_brute_force(spark, sf):
    d = read(spark, sf, "documents")
    got = {r["doc_id"]: r for r in quality_rules.judge(d, read(spark, sf, "labels")).collect()}
    for r in d.collect():
        t = r["text"] or ""
        w, seen = words_py(t), {}
        for i in range(len(w) - 4):
            seen.setdefault(tuple(w[i : i + 5]), []).append(i)
        covered = {k for v in seen.values() if len(v) > 1 for i in v for k in range(i, i + 5)}
        lines = [x for x in t.split("\n") if words_py(x)]
        g = got[r["doc_id"]]
        assert (g["n_words"], g["word_chars"], g["n_symbols"], g["n_dup_lines"], g["n_repeat_words"]) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered))


def test_rule_verdicts_by_brute_force(spark):
    from math import comb

    r = random.Random(2)
    rows, known = [], []
    for i in range(2400):
        words = [f"w{r.randrange(10**6)}" for _ in range(20)]
        noisy = i % 8 == 0
        rows.append((i, " ".join(words) + (" " + "#" * 30 if noisy else "")[: 31], "ab"[i % 2] if i % 5 else None))
        known.append((i, 0 if noisy else 1, None))
    d, l = spark.createDataFrame(rows, "doc_id long, text string, lang string"), labels(spark, known)
    got = {x["doc_id"]: x for x in quality_rules.judge(d, l).collect()}
    features = {x["doc_id"]: x for x in quality_rules.counts(d).collect()}
    per = {"symbols_per_word": ("n_symbols", "n_words"), "marks_per_word": ("n_marks", "n_words"), "dup_line_share": ("n_dup_lines", "n_lines"), "repeat_share": ("n_repeat_words", "n_words"), "word_length": ("word_chars", "n_words")}
    value = lambda f, k: f[per[k][0]] / f[per[k][1]] if f[per[k][1]] else 0.0
    good = [features[i] for i, q, _ in known if q == 1]
    strata, cuts = {f["stratum"] for f in good}, {}
    for s in strata:
        own = [f for f in good if f["stratum"] == s]
        for k, tried in quality_rules.RULES.items():
            for c in tried:
                n, hits = len(own), sum(value(f, k) > c for f in own)
                p = sum(comb(n, j) * 0.01**j * 0.99 ** (n - j) for j in range(hits + 1)) if hits <= n * 0.01 else 1.0
                if p > 0.05 / (len(strata) * len(quality_rules.RULES)):
                    break
                cuts[s, k] = c
    assert len(strata) == 3 and cuts
    for i, f in features.items():
        base = f["n_words"] < 10 or 100 * f["n_repeat_words"] > 20 * f["n_words"]
        bad = any(value(f, k) > cuts.get((f["stratum"], k), float("inf")) for k in per)
        assert (got[i]["base_failed"], got[i]["kept"]) == (base, not base and not bad)
    # A stratum of 480 labels is too small to certify a cutoff, and keeps its rows.
    assert not any(got[i]["kept"] for i in range(0, 2400, 8) if i % 5) and got[40]["kept"]


def test_binomial_tail(spark):
    from math import comb

    d = spark.createDataFrame([(700, 2), (50, 0), (3000, 20)], "n long, k long")
    from pyspark.sql import functions as F

    for r in d.select("n", "k", quality_rules.binomial_tail(F.col("n"), F.col("k"), 0.01).alias("p")).collect():
        assert r["p"] == pytest.approx(sum(comb(r["n"], i) * 0.01**i * 0.99 ** (r["n"] - i) for i in range(r["k"] + 1)), rel=1e-9)


def test_main_text(spark):
    page = '<html><head><title>T &am</title><script>var t="</p>";</script></head><body><nav><a href="/">menu</a></nav><div class="ad-box">buy</div><article><h1>Head &amp; line</h1><p><b>One  two.<br><p>Three &copy; four five six seven eight.</p><div class="comments"><p>me too</p></div></article><footer>foot</footer>'
    d = spark.createDataFrame([(1, "http://a.org/1", page), (2, "http://a.org/2", page.replace("Three", "Drei")), (3, None, None), (4, "x", "")], "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in page_text.main_text(d).collect()}
    assert got[1] == "Head & line\nOne two.\nThree © four five six seven eight." and got[2].endswith("Drei © four five six seven eight.") and got[3] == got[4] == ""


PROSE = "A sentence of plain prose that goes on for long enough to count in full. "
PAGES = {
    "nested": ("<nav>menu</nav><article><h1>Head</h1><p>Lead.</p><div class='body'><p>" + 9 * PROSE + "</p></div></article>", ["Head", "Lead.", "prose"], ["menu"]),
    "header": ("<article><header><h1>Head</h1></header><div class='x'>" + 9 * PROSE + "</div></article><footer>foot</footer>", ["Head"], ["foot"]),
    "sections": ("<article><section class='intro'>First. " + 8 * PROSE + "</section><section class='methods'>Second. " + 5 * PROSE + "</section></article>", ["First.", "Second."], []),
    "list": ("<article><p>Before.</p><p>" + 3 * PROSE + "</p><ul>" + "".join(f"<li>item {i} " + PROSE for i in range(30)) + "</ul><p>After.</p></article>", ["Before.", "item 29", "After."], []),
    "plain": ("<body><nav>menu</nav><div class='wrap'><h2>Head</h2><div class='a'>One. " + 9 * PROSE + "</div><div class='b'>Two. " + 2 * PROSE + "</div></div><div class='sidebar'>" + PROSE + "aside</div></body>", ["Head", "One.", "Two."], ["menu", "aside"]),
    "ended": ("<article><p>Start. <a name='x'/>" + 3 * PROSE + "</p><svg/><div/><p>End.</p></article>", ["Start.", "End."], []),
    "named": ("<div class='page has-sidebar'><div class='share-wrap'><p>Text. " + 9 * PROSE + "</p></div></div><div class='comments'>" + PROSE + "me too</div>", ["Text."], ["me too"]),
}


@pytest.mark.parametrize("name", sorted(PAGES))
def test_main_text_is_whole(spark, name):
    page, inside, outside = PAGES[name]
    d = spark.createDataFrame([(1, "http://a.org/1", page), (2, "http://a.org/2", page)], "page_id long, url string, html string")
    for r in page_text.main_text(d).collect():
        assert all(x in r["text"] for x in inside) and not any(x in r["text"] for x in outside)


def _split(sf, label, n):
    c = duckdb.connect()
    rows = c.execute(f"select doc_id, text, {label} from '{sf}/documents.parquet' join '{sf}/labels.parquet' using (doc_id)").fetchall()
    side = [[], []]
    for i, t, y in rows:
        side[zlib.crc32(str(i).encode()) % 5 == 0].append((t, y))
    return side[0][:n], side[1]


def test_convnet_held_out():
    train, test = _split("/root/testdata/sf0.1", "quality", 1500)
    m = byte_convnet.ByteConvNet().fit([t for t, _ in train if len(t) < 12_000], np.array([y for t, y in train if len(t) < 12_000], np.float32), epochs=8)
    p, y = m.score([t for t, _ in test]), np.array([y for _, y in test])
    assert ((p >= 0.5) == y).mean() > 0.95


def test_toxicity_held_out():
    train, test = _split("/root/testdata/sf0.1", "toxic", 1500)
    m = toxicity.train([t for t, _ in train if len(t) < 12_000], np.array([y for t, y in train if len(t) < 12_000], np.float32))
    p, y = m.score([t for t, _ in test]), np.array([y for _, y in test])
    assert ((p >= 0.5) & (y == 0)).sum() <= 3 and ((p >= 0.5) & (y == 1)).sum() >= 0.8 * y.sum()
    # One insult in a clean sentence, as written, with marks or blanks between its letters, and with one character too many.
    r, words = random.Random(1), ["idiot", "stupid", "moron", "pathetic", "worthless"]
    found = lambda f: (m.score([f"There was a plain remark. The {f(w)} said so." for w in words for _ in range(20)]) >= 0.5).mean()
    cut = lambda w: r.randrange(1, len(w))
    assert found(lambda w: w) == found("-".join) == found(" ".join) == 1.0
    assert found(lambda w: (lambda i: w[:i] + w[i - 1] + w[i:])(cut(w))) >= 0.9
    assert found(lambda w: (lambda i: w[:i] + r.choice("abcdxyz019") + w[i:])(cut(w))) >= 0.4


def test_rows_that_share_ids_or_names(spark):
    big = 2**53 + 1
    rows = [(6, "one text here", "x"), (6, "another text here", "y"), (6, "one text  here", "z"), (None, "no id", "x"), (None, "none either", "x"), (None, "no id", "x"), (3, "another text here", "q")]
    d = spark.createDataFrame(rows, "doc_id long, text string, digest string")
    kept = sorted((r["doc_id"] or 0, r["text"]) for r in exact_dedup.drop_exact_duplicates(d).collect())
    assert kept == [(0, "no id"), (0, "none either"), (3, "another text here"), (6, "one text  here")]
    near = near_dup.drop_near_duplicates(d)
    assert near.columns == d.columns and sorted({r["text"].split()[0] for r in near.collect()}) == ["another", "no", "none", "one"] and near.count() == 4
    assert near_dup.near_duplicates(d).count() == len(rows)
    clash = spark.createDataFrame([(big, "fine words", 0.5, "a", 1), (None, "more words", 0.1, "b", 2), (1, None, None, None, None)], "doc_id long, text string, score double, t string, predicted int")
    for f in (lambda x: toxicity.drop_toxic(x, labels(spark)), lambda x: toxicity.drop_toxic(x, labels(spark, [(big, 1, 0), (1, 1, 1)]))):
        assert f(clash).columns == clash.columns and {r["doc_id"] for r in f(clash).collect()} == {big, None, 1}
    for f in (lambda x: toxicity.toxicity(x, labels(spark)), lambda x: byte_convnet.quality(x, labels(spark)), lambda x: piece_codec.encode_digest(x, model_path())):
        assert {r["doc_id"] for r in f(clash).collect()} == {big, None, 1}
    assert {r["score"] for r in byte_convnet.quality(clash, labels(spark)).collect()} == {0.5}


def test_pages_with_awkward_rows(spark):
    schema = "page_id long, url string, html string, text string, path string, host string"
    page = "<article><p>" + 5 * PROSE + "</p></article>"
    d = spark.createDataFrame([(1, "http://a.org/1", page, "x", "y", "z"), (1, "http://a.org/1", page, "x", "y", "z"), (None, None, page, None, None, None), (2, "not a url", None, None, None, None)], schema)
    got = page_text.main_text(d).collect()
    assert len(got) == 4 and sum("plain prose" in r["text"] for r in got) == 3
    assert page_text.main_text(spark.createDataFrame([], schema)).collect() == []


def test_kernel_by_brute_force():
    words = ["idiot", "idiiot", "banana", "stu"]
    from itertools import combinations

    def features(w):
        w, out = "^" + w, {}
        for n in range(toxicity.SHORTEST, toxicity.ORDER + 1):
            for at in combinations(range(len(w)), n):
                if at[-1] - at[0] < toxicity.SPAN:
                    k = "".join(w[i] for i in at)
                    out[k] = out.get(k, 0) + toxicity.DECAY ** (at[-1] - at[0] + 1)
        return out

    base = toxicity.Landmarks(words)
    own = toxicity.diagonal(toxicity._codes(words))
    k = base.kernel(words)
    f = [features(w) for w in words]
    for i in range(4):
        for j in range(4):
            dot = sum(v * f[j].get(u, 0) for u, v in f[i].items())
            assert k[i, j] == pytest.approx(np.exp((dot / np.sqrt(own[i] * own[j]) - 1) / toxicity.SPREAD), rel=1e-3)


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = read(spark, sf, "documents")
    for n, (_, stage) in enumerate(corpus_pipeline.STAGES[:4]):
        before, docs = docs, stage(spark, docs, sf)
        assert docs.columns == before.columns
        kept = {r["doc_id"] for r in docs.select("doc_id").collect()}
        assert kept <= {r["doc_id"] for r in before.select("doc_id").collect()} and kept, n
    sp = piece_codec.PieceCodec(model_path()).sp
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    want = sorted((r["doc_id"], len(e := sp.encode(r["text"])), sha(",".join(map(str, e))), sha(sp.decode(e))) for r in docs.collect())
    assert sorted(tuple(r) for r in corpus_pipeline.STAGES[4][1](spark, docs, sf).collect()) == want
