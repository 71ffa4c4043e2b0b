"""Repeated passages: recurring phrases are confirmed, compiled to sharded Aho-Corasick automata, and located in every document."""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Callable, Iterator
from itertools import accumulate

import ahocorasick
import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geocensus.llm.shared import WordHasher, hot_join, materialise, mixed, release, runs, text_or_empty

WINDOW = 20
#: Words of an anchor.  Each window selects the anchor with the smallest hash in it, the last of equal ones: equal windows select
#: equal anchors at equal places, so a window can only recur if its anchor does.
ANCHOR = 6
_SPAN = WINDOW - ANCHOR + 1
#: Bytes of documents that a shard is planned to hold, and that a task hashes at a time.
SHARD_BYTES, SLICE_BYTES = 2_000_000, 1_000_000
#: Documents without an id share this place, after all others.
_LAST = 9223372036854775807
#: A segment's first word and its number of windows, at most 15, are one number.
_PACK = 16
_K = np.uint64(0x9E3779B97F4A7C15)
_B = np.uint64(0xD6E8FEB86659FD93)
_INVERSE = np.uint64(pow(int(_B), -1, 2**64))


def _joined(x: np.ndarray, y: np.ndarray, k: int) -> np.ndarray:
    """Hashes of runs, each of one in ``x`` and, ``k`` words on, one in ``y``."""
    n = max(0, min(len(x), len(y) - k))
    z = x[:n] * _K + y[k : k + n]
    return (z ^ (z >> np.uint64(32))) * _B


def _least(v: np.ndarray, p: np.ndarray, w: np.ndarray, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The smaller of two minima ``k`` places apart, with its place; the later of equal ones."""
    n = max(0, min(len(v), len(w) - k))
    later = w[k : k + n] <= v[:n]
    return np.where(later, w[k : k + n], v[:n]), np.where(later, q[k : k + n], p[:n])


class Stretch:
    """Words of several documents in one row of hashes, in arrays from end to end: no Python object per word."""

    def __init__(self, hasher: WordHasher, texts: list[bytes]):
        words, start = hasher.words_of(b"\n".join(texts))
        edges = np.cumsum([0] + [len(t) + 1 for t in texts])
        self.owner = np.searchsorted(edges, start, "right") - 1
        #: Where each document's words begin.
        self.base = np.searchsorted(self.owner, np.arange(len(texts)))
        two = _joined(words, words, 1)
        self.four = _joined(two, two, 2)
        self.grams = mixed(_joined(self.four, two, 4))
        n = len(words) - WINDOW + 1
        self.whole = self.owner[: max(n, 0)] == self.owner[WINDOW - 1 :] if n > 0 else np.zeros(0, bool)
        p = np.cumprod(np.concatenate([[np.uint64(1)], np.full(len(words), _B, np.uint64)]), dtype=np.uint64)
        self.total = np.concatenate([[np.uint64(0)], np.cumsum(words * p[:-1], dtype=np.uint64)])
        self.back = np.cumprod(np.concatenate([[np.uint64(1)], np.full(len(words), _INVERSE, np.uint64)]), dtype=np.uint64)

    def segments(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Runs of windows that select one anchor: the first window, the number of windows, the anchor's place."""
        v, p = self.grams, np.arange(len(self.grams))
        for k in (1, 2, 4):
            v, p = _least(v, p, v, p, k)
        place = _least(v, p, v, p, _SPAN - 8)[1]
        at = np.flatnonzero(self.whole)
        if not len(at):
            return at, at, at
        cut = np.flatnonzero(np.concatenate([[True], (np.diff(place[at]) != 0) | (np.diff(at) != 1) | (np.diff(self.owner[at]) != 0)]))
        return at[cut], np.diff(np.append(cut, len(at))), place[at[cut]]

    def hashes(self, first: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Hashes of all words of runs of ``n`` windows."""
        end = first + n + (WINDOW - 1)
        return mixed((self.total[end] - self.total[first]) * self.back[first] + n.astype(np.uint64) * _K)

    def windows(self) -> np.ndarray:
        eight = _joined(self.four, self.four, 4)
        return mixed(_joined(_joined(eight, eight, 8), self.four, 16))


def _slices(b: pd.DataFrame) -> Iterator[pd.DataFrame]:
    """Parts of a batch of about ``SLICE_BYTES`` each; a longer text is a part of its own."""
    place = np.cumsum([len(t) for t in b["t"]]) // SLICE_BYTES
    for lo, hi in zip(*(lambda c: (c, [*c[1:], len(b)]))(np.flatnonzero(np.diff(place, prepend=-1)).tolist()), strict=True):
        yield b.iloc[lo:hi]


def _selected(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    h = WordHasher()
    for b in batches:
        for part in _slices(b):
            s = Stretch(h, part["t"].tolist())
            first, n, place = s.segments()
            own = s.owner[first]
            yield pd.DataFrame({"key": s.grams[place].view(np.int64), "seg": s.hashes(first, n).view(np.int64), "doc_id": part["doc_id"].to_numpy()[own], "xn": (first - s.base[own]) * _PACK + n})


def _cut_out(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """The words of each listed segment, and its windows' hashes if its anchor has other segments too."""
    h = WordHasher()
    for b in batches:
        for part in _slices(b):
            texts = part["t"].tolist()
            s = Stretch(h, texts)
            row = np.repeat(np.arange(len(part)), part["xn"].map(len).to_numpy())
            xn, key, seg, copies, several = (np.concatenate(part[c].tolist()) for c in ("xn", "key", "seg", "copies", "several"))
            x, n = xn // _PACK, xn % _PACK
            at, size = s.base[row] + x, np.diff(np.append(s.base, len(s.owner)))
            # A row that repeats another's id may be shorter, or have other words there.
            same = x + n + (WINDOW - 1) <= size[row]
            same[same] = s.hashes(at[same], n[same]).view(np.int64) == seg[same]
            windows, out = s.windows().view(np.int64), []
            words, last = [], -1
            for k in np.flatnonzero(same).tolist():
                if row[k] != last:
                    last = row[k]
                    words = texts[last].split()
                out.append((b" ".join(words[x[k] : x[k] + n[k] + WINDOW - 1]).decode("utf-8", "replace"), windows[at[k] : at[k] + n[k]] if several[k] else None))
            found = pd.DataFrame(out, columns=["words", "windows"])
            yield pd.DataFrame({"key": key[same], "seg": seg[same], "copies": copies[same], "doc_id": part["doc_id"].to_numpy()[row[same]], "x": x[same].astype(np.int32), "words": found["words"], "windows": found["windows"]})


class Phrases:
    """The automaton of a shard's phrases.

    It finds children by search along a list, so a word is spelt by two or three digits, each place with an alphabet of its own, and
    no state has more children than an alphabet has digits.
    """

    def __init__(self, phrases: list[bytes], places: list[tuple[int, int]]):
        told = dict(zip(zip(places, map(len, phrases), strict=True), phrases, strict=True))  # segments may share phrases
        phrases, places = list(told.values()), [p for p, _ in told]
        rows = [t.split() for t in phrases]
        words = dict.fromkeys([w for r in rows for w in r])
        self.digits = max(2, math.ceil(math.log(len(words) + 1, 256)))
        base = math.ceil((len(words) + 1) ** (1 / self.digits))
        self.spelt = {w: "".join([chr(1 + d * base + n // base**d % base) for d in range(self.digits)]) for n, w in enumerate(words)}
        #: Other words are zeros; only between them is there room for a phrase.
        self.known = re.compile(f"[^\0]{{{WINDOW * self.digits},}}")
        self.machine = ahocorasick.Automaton()
        for r, place in zip(rows, places, strict=True):
            self.machine.add_word("".join([self.spelt[w] for w in r]), (len(r), *place))
        if rows:
            self.machine.make_automaton()

    def repeated(self, doc_id: int, words: list[bytes]) -> Iterator[tuple[int, int]]:
        """Where in a document each phrase begins and ends, but for its first place."""
        if not len(self.machine):
            return
        spelt, other = self.spelt, "\0" * self.digits
        text = "".join([spelt.get(w, other) for w in words])
        for known in self.known.finditer(text):
            for last, (size, first, x) in self.machine.iter(text, *known.span()):
                end = (last + 1) // self.digits
                if end - size != x or doc_id != first:
                    yield end - size, end


def _located(digest: bool) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """Per shard: its automaton is compiled, and its whole documents are read through it."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for g in runs(batches, ["block", "part"]):
            document = g["document"].to_numpy(bool)
            told = g[~document]
            phrases = Phrases(told["t"].tolist(), list(zip(told["doc_id"].tolist(), told["x"].tolist(), strict=True)))
            out = []
            for i, t in zip(g["doc_id"][document].tolist(), g["t"][document], strict=True):
                words = t.split()
                n = len(words)
                spans = list(phrases.repeated(i, words))
                if spans:
                    edge = [0] * (n + 1)
                    for lo, hi in spans:
                        edge[lo] += 1
                        edge[hi] -= 1
                    words = [w for w, c in zip(words, accumulate(edge), strict=False) if not c]
                kept = b" ".join(words)
                out.append((None if i == _LAST else i, n, n - len(words), hashlib.sha256(kept).hexdigest() if digest else kept.decode("utf-8", "replace")))
            names = ["doc_id", "n_words", "n_removed", "kept_sha256" if digest else "kept"]
            yield pd.DataFrame(out, columns=names).astype({"doc_id": "Int64"})

    return run


def _phrases(segments: DataFrame) -> DataFrame:
    """``key, seg, words, first_doc, first_x``: the recurring phrases of each distinct segment, with their first place.

    An anchor's only segment recurs whole.  Of an anchor's several segments, windows recur; those whose first places lie side by
    side make one phrase.
    """
    alone = segments.where("windows is null").select("key", "seg", "words", F.col("doc_id").alias("first_doc"), F.col("x").alias("first_x"))
    w = segments.where("windows is not null").select("key", "seg", "copies", "doc_id", "x", F.posexplode("windows").alias("o", "window"))
    firsts = w.groupBy("key", "window").agg(F.min(F.struct("doc_id", (F.col("x") + F.col("o")).alias("x"))).alias("first"), F.sum("copies").alias("n")).where("n > 1").drop("n")
    # Reading along a segment, a window's first place less its own offset stays the same while one text is followed.
    told = w.join(firsts, ["key", "window"]).groupBy("key", "seg", F.col("first.doc_id").alias("first_doc"), (F.col("first.x") - F.col("o")).alias("line"))
    told = told.agg(F.min("o").alias("lo"), F.max("o").alias("hi")).withColumnRenamed("key", "__key").withColumnRenamed("seg", "__seg")
    told = told.join(segments.where("windows is not null").select("key", "seg", "words"), (F.col("__key") == F.col("key")) & (F.col("__seg") == F.col("seg")))
    part = F.array_join(F.slice(F.split("words", " "), F.col("lo") + 1, F.col("hi") - F.col("lo") + WINDOW), " ")
    return alone.unionByName(told.select("key", "seg", part.alias("words"), "first_doc", (F.col("line") + F.col("lo")).cast("int").alias("first_x")))


def _sharded(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``block, part, document, doc_id, x, t``: each shard's phrases, then its documents."""
    d = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(_LAST)).alias("doc_id"), text_or_empty(text_col).cast("binary").alias("t"))
    rows = materialise(d.mapInPandas(_selected, "key long, seg long, doc_id long, xn long"), "repeat-anchors")
    counts = materialise(rows.groupBy("key").agg(F.count("*").alias("c")).where("c > 1"), "repeat-counts")
    seen = materialise(hot_join(rows, counts, "key", "c", "doc_id").drop("c"), "repeat-seen")
    release(rows, counts)
    firsts = seen.groupBy("key", "seg").agg(F.min(F.struct("doc_id", "xn")).alias("f"), F.count("*").alias("copies"))
    firsts = materialise(firsts.select("key", "seg", "f.doc_id", "f.xn", "copies"), "repeat-firsts")
    several = firsts.groupBy("key").agg(F.count("*").alias("c")).select("key", (F.col("c") > 1).alias("several"), "c")
    sources = hot_join(firsts, several, "key", "c", "doc_id").groupBy("doc_id").agg(F.collect_list(F.struct("xn", "key", "seg", "copies", "several")).alias("s"))
    sources = sources.select("doc_id", *[F.col(f"s.{c}").alias(c) for c in ("xn", "key", "seg", "copies", "several")])

    # Documents that share their smallest recurring anchor, as near copies mostly do, share a block, so that its phrases are few; a
    # block is dealt in parts of a bounded size.
    lead = seen.groupBy("doc_id").agg(F.min("key").alias("lead"))
    sizes = d.groupBy("doc_id").agg(F.sum(F.octet_length("t")).alias("size")).join(lead, "doc_id", "left")
    sizes = materialise(sizes.select("doc_id", "size", F.xxhash64(F.coalesce("lead", "doc_id")).alias("lead")), "repeat-sizes")
    blocks = int(sizes.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("n")).first()["n"]) // SHARD_BYTES + 1
    dealt = sizes.withColumn("block", F.pmod("lead", F.lit(blocks)))
    parts = dealt.groupBy("block").agg(F.ceil(F.sum("size") / SHARD_BYTES).alias("parts"))
    info = materialise(dealt.join(parts, "block").select("doc_id", "block", F.pmod(F.xxhash64("doc_id"), F.greatest("parts", F.lit(1))).alias("part")), "repeat-places")
    placed = materialise(d.join(info, "doc_id").join(sources, "doc_id", "left"), "repeat-documents")
    release(sizes, firsts)

    cut = placed.where("xn is not null").mapInPandas(_cut_out, "key long, seg long, copies long, doc_id long, x int, words string, windows array<long>")
    once = d.count() == info.count()  # else rows that repeat an id may give a segment twice
    segments = materialise(cut if once else cut.dropDuplicates(["key", "seg"]), "repeat-segments")
    phrases = materialise(_phrases(segments), "repeat-phrases")
    wanted = seen.select("doc_id", "key", "seg").join(info, "doc_id").select("block", "part", "key", "seg").distinct()
    routed = wanted.join(phrases, ["key", "seg"]).select("block", "part", F.lit(False).alias("document"), F.col("first_doc").alias("doc_id"), F.col("first_x").alias("x"), F.col("words").cast("binary").alias("t"))
    routed = materialise(routed, "repeat-routed")
    release(seen, info, segments, phrases)
    whole = placed.select("block", "part", F.lit(True).alias("document"), "doc_id", F.lit(0).alias("x"), "t")
    return routed.unionByName(whole).repartition(min(blocks, 20_000), "block", "part").sortWithinPartitions("block", "part", "document")


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_words, n_removed, kept``: every text without its repeated passages, the words that stay joined by blanks.

    A word goes if a window of 20 words covers it whose words also start earlier: under a smaller id, or in the same document.
    Null and empty texts have no words, and an empty table gives no rows; other columns are ignored.  Rows that repeat an id
    are one document read twice (a window starts earlier if it does so by id and place), and null ids count as one id after all
    others.

    Counts of anchors and of distinct segments confirm what recurs and where it comes first; only there is its text cut out.  Each
    document belongs to one shard; a shard's automaton holds the phrases of the segments seen in its documents, and reads all of
    them whole.  A phrase that is in very many documents is one row per shard, and no stage compares occurrences with
    each other.
    """
    return _sharded(docs, id_col, text_col).mapInPandas(_located(False), "doc_id long, n_words long, n_removed long, kept string")


def remove_repeats_digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``remove_repeats`` with the SHA-256 of the kept text in place of it."""
    return _sharded(docs, id_col, text_col).mapInPandas(_located(True), "doc_id long, n_words long, n_removed long, kept_sha256 string")


SQL = r"""
with d as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
p as (select doc_id, unnest(range(1, len(w) - 18)) as lo, w from d where len(w) >= 20),
g as (select doc_id, lo, array_to_string(w[lo:lo + 19], ' ') as phrase from p),
r as (select doc_id, lo from (select *, row_number() over (partition by phrase order by doc_id, lo) as nth from g) where nth > 1),
x as (select distinct doc_id, lo + unnest(range(0, 20)) as k from r),
gone as (select doc_id, count(*) as n, list(k) as ks from x group by doc_id)
select d.doc_id, len(w)::bigint as n_words, coalesce(n, 0)::bigint as n_removed,
       sha256(array_to_string(case when n is null then w else list_filter(w, lambda v, k: not list_contains(ks, k)) end, ' ')) as kept_sha256
from d left join gone using (doc_id)
"""
