"""Personal data: base patterns, and identifiers found by bootstrapped contexts.  DataFrame operations only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from geocensus.llm.shared import materialise, text_or_empty

KINDS = ("email", "ip", "card", "phone")
# Each finds the same leftmost matches as its contract pattern, in linear time: a match can only begin where the last one
# ended or where a run of its first class begins, and runs are possessive.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_PART = "0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])"
# What may be an identifier, by one attempt per word: a word with a digit, and the words of digits and their marks that
# follow it by single blanks; or a word with one of these marks between its letters.
_MENTION = (
    r"(?<![^\x20\x09-\x0D])(?:[^\x20\x09-\x0D0-9]*+[0-9][^\x20\x09-\x0D]*+(?:\x20[0-9().+/-]*+[0-9][0-9().+/-]*+(?![^\x20\x09-\x0D]))*+"
    r"|[^\x20\x09-\x0D0-9@_()\[\]{}=:\\]++[@_()\[\]{}=:\\]+[^\x20\x09-\x0D0-9@_()\[\]{}=:\\][^\x20\x09-\x0D]*+)"
)
_QUAD = r"^[0-9]+(?:\.[0-9]+){3}$"
#: Characters that a spelling needs to say anything about an identifier.
FORM = 9
_EDGE = r"[\]\[.,;:!?(){}<>\"'|*#$%&-]"
_BLOCK = 128


def _valid(kind: str, m: Column) -> Column:
    digits = F.regexp_replace(m, "[^0-9]", "")
    if kind == "ip":
        return m.rlike(rf"^{_PART}(?:\.{_PART}){{3}}$")
    if kind == "phone":
        return F.length(digits).between(10, 15)
    if kind == "card":
        def worth(c: Column, i: Column) -> Column:
            d = c.cast("int")
            return F.when(i % 2 == 0, d).when(d > 4, 2 * d - 9).otherwise(2 * d)

        luhn = F.aggregate(F.transform(F.split(F.reverse(digits), "(?!$)"), worth), F.lit(0), lambda a, x: a + F.coalesce(x, F.lit(0)))
        return F.length(digits).between(14, 19) & (luhn % 10 == 0)
    return F.lit(True)


def _located(d: DataFrame, name: str, pattern: str, gate: Column, text: str = "t") -> DataFrame:
    """Adds ``{name}_m``, the matches, ``{name}_s``, the text between them, and ``{name}_p``, their starts in code points.

    Starts are sums of lengths; they are summed in blocks, so that a text with many matches costs no square of their number.
    """
    none = F.array().cast("array<string>")
    m, s, t, b, p = (f"{name}_{x}" for x in "mstbp")
    d = d.withColumn(m, F.when(gate, F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).otherwise(none))
    d = d.withColumn(s, F.when(F.size(m) > 0, F.split(text, pattern, -1)).otherwise(none))
    d = d.withColumn(t, F.zip_with(F.slice(s, F.lit(1), F.size(m)), m, lambda x, y: F.length(x) + F.length(y)))
    blocks = F.expr(f"case when size({m}) > 0 then sequence(0, (size({m}) - 1) div {_BLOCK}) else cast(array() as array<bigint>) end")
    d = d.withColumn(b, F.transform(blocks, lambda j: F.aggregate(F.slice(t, (j * _BLOCK + 1).cast("int"), F.lit(_BLOCK)), F.lit(0), lambda a, x: a + x)))
    d = d.withColumn(b, F.transform(b, lambda x, j: F.aggregate(F.slice(b, F.lit(1), j), F.lit(0), lambda a, y: a + y)))
    start = f"transform({m}, (x, i) -> element_at({b}, cast(i div {_BLOCK} as int) + 1) + aggregate(slice({t}, cast(i div {_BLOCK} as int) * {_BLOCK} + 1, i % {_BLOCK}), 0, (a, y) -> a + y) + length(element_at({s}, i + 1)))"
    return d.withColumn(p, F.expr(start)).drop(t, b)


def _context(name: str, i: Column) -> tuple[Column, Column]:
    """Up to two words before and after match ``i``, in lower case; fewer at an end of the text or next to another match."""
    s = F.col(f"{name}_s")
    left = F.lower(F.regexp_extract(F.element_at(s, i + 1), r"((?:[^\x20\x09-\x0D]+[\x20\x09-\x0D]+)?[^\x20\x09-\x0D]+)[\x20\x09-\x0D]*+$", 1))
    right = F.lower(F.regexp_extract(F.element_at(s, i + 2), r"^[^\x20\x09-\x0D]*[\x20\x09-\x0D]+([^\x20\x09-\x0D]+(?:[\x20\x09-\x0D]+[^\x20\x09-\x0D]+)?)", 1))
    return left, right


def _patterns(inst: Column, left: Column, right: Column) -> Column:
    """The patterns that an instance occurs in: side and wording.  One word or two before it, after it, one on both sides, and its own
    spelling with digits as 9 and letters as a."""
    form = F.regexp_replace(F.regexp_replace(inst, r"\p{L}+", "a"), "[0-9]", "9")
    before, after = F.regexp_extract(left, r"[^\x20\x09-\x0D]+$", 0), F.regexp_extract(right, r"^[^\x20\x09-\x0D]+", 0)
    two = lambda c: F.when(c.rlike(r"[\x20\x09-\x0D]"), F.regexp_replace(c, r"[\x20\x09-\x0D]+", " ")).otherwise("")
    both = F.when((before != "") & (after != ""), F.concat_ws(" ", before, after)).otherwise("")
    sides = {"L": before, "R": after, "B": both, "LL": two(left), "RR": two(right), "F": F.when(F.length(form) >= FORM, form).otherwise("")}
    return F.filter(F.array(*[F.struct(F.lit(k).alias("side"), v.alias("word")) for k, v in sides.items()]), lambda p: p["word"] != "")


def _seed(kind: str, n: int):
    def of(x: Column, i: Column) -> Column:
        start = F.element_at(f"{kind}_p", i + 1)
        left, right = _context(kind, i)
        return F.struct(start.alias("start"), F.lit(n).alias("n"), (start + F.length(x)).alias("end"), x.alias("inst"), left.alias("left"), right.alias("right"), _valid(kind, x).alias("ok"))

    return of


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: base ``spans``, their contexts ``seeds``, and what looks like an identifier outside them, ``mentions``."""
    d = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("t")).withColumn("key", F.xxhash64("t"))
    digit = F.col("t").rlike("[0-9]")
    gates = {"email": F.col("t").contains("@"), "ip": digit, "card": digit, "phone": F.col("t").contains("+")}
    d = d.withColumn("any", digit | F.col("t").contains("@"))
    for kind in KINDS:
        d = _located(d, kind, PATTERNS[kind], F.col("any") & gates[kind])
    seeds = []
    for n, kind in enumerate(KINDS):
        seeds.append(F.filter(F.transform(f"{kind}_m", _seed(kind, n)), lambda x: x["ok"]))
    d = d.withColumn("found", F.sort_array(F.concat(*seeds)))
    d = d.drop(*[f"{k}_{x}" for k in KINDS for x in "msp"])
    d = _located(d, "mention", _MENTION, F.col("t").rlike(r"[0-9@_()\[\]{}=:\\]"))

    def core(x: Column, i: Column) -> Column:
        lead = F.length(F.regexp_extract(x, f"^{_EDGE}*", 0))
        word = F.regexp_replace(F.regexp_replace(x, f"^{_EDGE}+", ""), f"(?<!{_EDGE}){_EDGE}++$", "")
        start = F.element_at("mention_p", i + 1) + lead
        left, right = _context("mention", i)
        return F.struct(start.alias("start"), (start + F.length(word)).alias("end"), word.alias("inst"), left.alias("left"), right.alias("right"))

    # A dotted quad that the base refused, for a part above 255, is no address.
    like = lambda x: (F.length(x["inst"]) >= 6) & ~x["inst"].rlike(_QUAD)
    d = d.withColumn("mentions", F.filter(F.transform("mention_m", core), like))
    apart = lambda x: ~F.exists("found", lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"]))
    return d.select("doc_id", "key", F.transform("found", lambda x: F.struct(x["start"], x["n"], x["end"])).alias("spans"), F.transform("found", lambda x: F.struct(x["n"], x["inst"], x["left"], x["right"])).alias("seeds"), F.filter("mentions", apart).alias("mentions"))


def bootstrap(scanned: DataFrame, rounds: int = 3, support: int = 5, least: float = 0.8) -> DataFrame:
    """``inst, n, conf``: identifiers that the patterns of seeds vouch for, with their kind's number.

    A context's score for a kind is the confidence of its instances of that kind over all its distinct instances: one not known
    speaks against it.  A spelling is strict in itself, so only instances known for another kind speak against it, and contexts and
    spellings vouch for each other's instances: a number that a checksum refused counts as a card if enough checked
    cards are spelt like it.  Patterns with ``support`` instances, discovered ones counted by their confidence, and a score of ``least``
    stay, and an instance's confidence is one less the product of its patterns' doubts.  Each round is two aggregates over narrow rows.
    """
    sides = _patterns(F.col("x.inst"), F.col("x.left"), F.col("x.right"))
    seeds = scanned.select(F.explode("seeds").alias("x")).select(F.col("x.inst").alias("inst"), F.col("x.n").alias("n"), F.explode(sides).alias("p"))
    others = scanned.select(F.explode("mentions").alias("x")).select(F.col("x.inst").alias("inst"), F.lit(None).cast("int").alias("n"), F.explode(sides).alias("p"))
    edges = materialise(seeds.unionByName(others).select("inst", "n", "p.side", "p.word").distinct(), "pii-edges")
    pairs = edges.select("inst", "side", "word").distinct()
    known = edges.where("n is not null").select("inst", "n").distinct().withColumn("conf", F.lit(1.0))
    totals = pairs.groupBy("side", "word").agg(F.count("*").alias("total"))
    conf = known
    for _ in range(rounds):
        score = pairs.join(conf, "inst").groupBy("side", "word", "n").agg(F.sum("conf").alias("mass"))
        known_mass = F.sum("mass").over(Window.partitionBy("side", "word"))  # of four kinds at most
        score = score.withColumn("known", known_mass).where(F.col("mass") >= support).join(totals, ["side", "word"])
        score = score.withColumn("score", F.col("mass") / F.when(F.col("side") == "F", F.col("known")).otherwise(F.col("total"))).where(F.col("score") >= least)
        doubt = F.sum(F.log(1.0 - 0.999 * F.col("score")))
        found = pairs.join(score.select("side", "word", "n", "score"), ["side", "word"]).groupBy("inst", "n").agg((1.0 - F.exp(doubt)).alias("conf"))
        conf = materialise(known.unionByName(found.join(known, ["inst"], "left_anti")), "pii-conf")
    best = conf.join(known.select("inst").distinct(), "inst", "left_anti").groupBy("inst").agg(F.max(F.struct("conf", "n")).alias("b"))
    return best.select("inst", "b.n", "b.conf").where(F.col("conf") >= least)


def personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id``, and ``base`` and ``spans``, arrays of (start, n, end), n counting ``KINDS``.

    ``base`` has the base patterns' valid matches, ``spans`` those and what the contexts discover.  Null and empty texts
    have none.  Rows that repeat an id and its text get equal results.  Offsets are code points, ends exclusive.
    """
    scanned = materialise(scan(docs, id_col, text_col), "pii-scan")
    found = bootstrap(scanned)
    mentions = scanned.where(F.size("mentions") > 0).select("doc_id", "key", F.explode("mentions").alias("x")).select("doc_id", "key", F.col("x.start").alias("start"), F.col("x.end").alias("end"), F.col("x.inst").alias("inst")).distinct()
    new = mentions.join(found, "inst").groupBy("doc_id", "key").agg(F.collect_list(F.struct("start", "n", "end")).alias("new"))
    new = new.select(F.col("doc_id").alias("__id"), F.col("key").alias("__key"), "new")
    out = scanned.join(new, scanned["doc_id"].eqNullSafe(new["__id"]) & (scanned["key"] == new["__key"]), "left")
    return out.select("doc_id", F.col("spans").alias("base"), F.when(F.col("new").isNull(), F.col("spans")).otherwise(F.sort_array(F.concat("spans", "new"))).alias("spans"))


def spell(spans: Column) -> Column:
    """``kind:start:end`` of every span, comma-joined, by start and then kind."""
    name = lambda n: F.element_at(F.array(*[F.lit(k) for k in KINDS]), n + 1)
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", name(x["n"]), x["start"], x["end"])), ",")


def digest(docs: DataFrame) -> DataFrame:
    """The query's columns."""
    d = personal_data(docs)
    kinds = F.transform("base", lambda x: x["n"])
    counts = [(F.size("base") - F.size(F.array_remove(kinds, n))).cast("long").alias(f"n_{k}") for n, k in enumerate(KINDS)]
    return d.select("doc_id", *counts, F.sha2(spell(F.col("base")), 256).alias("base_sha256"), spell(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))
