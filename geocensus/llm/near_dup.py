"""N-gram Jaccard join with Bayesian candidate pruning."""

from __future__ import annotations

import hashlib
import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geocensus.llm.shared import Forest, WordHasher, connected_components, gram_hashes, materialise, mixed, runs, text_or_empty, words_py

GRAM, THRESHOLD = 5, 0.8
BANDS, ROWS = 25, 4
HASHES = BANDS * ROWS
#: Pairs are dropped when the posterior probability of reaching the threshold falls below this.
TOLERANCE = 1e-6
#: Rows and code points that one block of a unit holds; larger units are compared block by block.
BLOCK_ROWS, BLOCK_CHARS = 512, 8_000_000


def least_matches(step: int = 10) -> dict[int, int]:
    """For each number of hashes seen, the fewest matches at which a pair still may reach the threshold.

    With a uniform prior the posterior of the similarity is a beta law, and its upper tail at the threshold t after m matches of k
    is P(Bin(k + 1, t) <= m).
    """
    out = {}
    for k in range(step, HASHES + 1, step):
        tail, m = 0.0, 0
        while m <= k:
            tail += math.comb(k + 1, m) * THRESHOLD**m * (1 - THRESHOLD) ** (k + 1 - m)
            if tail >= TOLERANCE:
                break
            m += 1
        out[k] = m
    return out


class Signer:
    """MinHash signatures of 100 places of 16 bits; a band is four of them, packed in a long."""

    def __init__(self) -> None:
        r = np.random.default_rng(11)
        self.hasher = WordHasher()
        self.a = (r.integers(0, 2**32, HASHES, np.uint64) | np.uint64(1)).astype(np.uint32)
        self.b = r.integers(0, 2**32, HASHES, np.uint64).astype(np.uint32)

    def __call__(self, text: str) -> list[int] | None:
        words = self.hasher.words(text)
        if not len(words):
            return None
        grams = np.unique(gram_hashes(words, min(GRAM, len(words))))
        low = np.full(HASHES, 2**32 - 1, np.uint32)
        h = (grams >> np.uint64(32)).astype(np.uint32)
        for k in range(0, len(h), 1024):
            low = np.minimum(low, (h[k : k + 1024, None] * self.a + self.b).min(0))
        short = (mixed(low.astype(np.uint64)) >> np.uint64(48)).reshape(BANDS, ROWS)
        packed = short[:, 0] | short[:, 1] << np.uint64(16) | short[:, 2] << np.uint64(32) | short[:, 3] << np.uint64(48)
        return packed.view(np.int64).tolist()


def _sign(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    sign = Signer()
    for b in batches:
        words = [" ".join(words_py(t)) for t in b["t"]]
        yield pd.DataFrame({"doc_id": b["doc_id"], "digest": [hashlib.sha256(w.encode("utf-8", "surrogatepass")).digest() for w in words], "n": [len(w) for w in words], "bands": [sign(t) for t in b["t"]]})


def surviving(left: np.ndarray, right: np.ndarray, near: np.ndarray, need: dict[int, int]) -> np.ndarray:
    """Pairs (row, column) of ``near`` that Bayesian pruning keeps: matches are counted ten hashes at a time, and a pair is
    dropped at the first count that leaves it too little chance."""
    rows, cols = np.nonzero(near)
    matches, done = np.zeros(len(rows), np.int32), 0
    for k, m in need.items():
        matches += (left[rows, done:k] == right[cols, done:k]).sum(1)
        ok = matches >= m
        rows, cols, matches, done = rows[ok], cols[ok], matches[ok], k
    return np.stack([rows, cols], 1)


def _places(bands: pd.Series) -> tuple[np.ndarray, np.ndarray]:
    b = np.array(bands.tolist(), np.int64)
    return b, b.view(np.uint16).reshape(len(b), HASHES)


def _together(b1: np.ndarray, b2: np.ndarray) -> np.ndarray:
    near = np.zeros((len(b1), len(b2)), bool)
    for k in range(BANDS):
        near |= b1[:, k][:, None] == b2[:, k][None, :]
    return near


def _bucket_edges(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Per bucket, or pair of its blocks: a spanning forest of the pairs that pruning keeps."""
    need = least_matches()
    out: list[tuple[int, int]] = []
    for g in runs(batches, ["band", "key", "i", "j"]):
        if len(g) < 2:
            continue
        ids = g["rep"].to_numpy()
        b, places = _places(g["bands"])
        side = g["side"].to_numpy()
        near = np.triu(np.ones((len(g), len(g)), bool), 1) if (side == 2).all() else (side[:, None] == 0) & (side[None, :] == 1)
        forest = Forest(len(g))
        for x, y in surviving(places, places, near, need):
            forest.join(int(x), int(y))
        out += [(int(ids[k]), int(ids[forest.find(k)])) for k in range(len(g)) if forest.find(k) != k]
        if len(out) > 10_000:
            yield pd.DataFrame(out, columns=["a", "b"])
            out = []
    yield pd.DataFrame(out, columns=["a", "b"]).astype("int64")


def grams_of(text: str) -> set[str]:
    w = words_py(text)
    n = min(GRAM, len(w))
    return {" ".join(w[k : k + n]) for k in range(len(w) - n + 1)} if w else set()


def _exact(sets: list[np.ndarray], pairs: np.ndarray) -> np.ndarray:
    """Which pairs of sorted arrays reach the threshold; 9 |A n B| >= 4 (|A| + |B|) at 0.8."""
    sizes = np.array([len(s) for s in sets])
    keep = np.zeros(len(pairs), bool)
    if len(pairs) > 4 * len(sets):  # many pairs of few texts: products of incidence matrices, some shared shingles at a time
        values, where = np.unique(np.concatenate(sets), return_inverse=True)
        owner = np.repeat(np.arange(len(sets)), sizes)
        shared = np.bincount(where, minlength=len(values)) > 1
        column = np.cumsum(shared) - 1
        ok = shared[where]
        rows, cols = owner[ok], column[where[ok]]
        order = np.argsort(cols, kind="stable")
        rows, cols = rows[order], cols[order]
        common = np.zeros((len(sets), len(sets)), np.float32)
        for lo in range(0, int(shared.sum()), 4096):
            x, y = np.searchsorted(cols, [lo, lo + 4096])
            m = np.zeros((len(sets), 4096), np.float32)
            m[rows[x:y], cols[x:y] - lo] = 1
            common += m @ m.T
        both = common[pairs[:, 0], pairs[:, 1]]
    else:
        both = np.array([len(np.intersect1d(sets[x], sets[y], assume_unique=True)) for x, y in pairs])
    if len(pairs):
        total = sizes[pairs[:, 0]] + sizes[pairs[:, 1]]
        keep = both * (1 + THRESHOLD) >= THRESHOLD * total - 1e-6
    return keep


def _verified(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Per unit, or pair of its blocks: pruning again over whole signatures, then exact similarity of shingle sets.

    Gives each text's number of linked documents, and a spanning forest of the links.
    """
    need = least_matches()
    out: list[tuple[int, int, int]] = []
    for g in runs(batches, ["unit", "i", "j"]):
        ids, weight, side = g["rep"].to_numpy(), g["copies"].to_numpy(), g["side"].to_numpy()
        b, places = _places(g["bands"])
        near = _together(b, b)
        near &= np.triu(np.ones_like(near), 1) if (side == 2).all() else (side[:, None] == 0) & (side[None, :] == 1)
        pairs = surviving(places, places, near, need)
        number: dict[str, int] = {}
        used = np.unique(pairs)
        sets: list[np.ndarray] = [np.zeros(0, np.int64)] * len(g)
        texts = g["t"].tolist()
        for k in used:
            sets[k] = np.unique(np.array([number.setdefault(s, len(number)) for s in grams_of(texts[k])], np.int64))
        if len(pairs):
            pairs = pairs[_exact([sets[k] for k in used], np.searchsorted(used, pairs))]
        links, forest = Counter(), Forest(len(g))
        for x, y in pairs.tolist():
            links[x] += int(weight[y])
            links[y] += int(weight[x])
            forest.join(x, y)
        out += [(int(ids[k]), n, int(ids[forest.find(k)])) for k, n in links.items()]
        if len(out) > 10_000:
            yield pd.DataFrame(out, columns=["rep", "links", "root"])
            out = []
    yield pd.DataFrame(out, columns=["rep", "links", "root"]).astype("int64")


def _cells(d: DataFrame, blocks: str) -> DataFrame:
    """Rows with ``i, j, side``: one cell (side 2) where there is one block, else a row for each pair of blocks of which its own is
    one; the pair of a block with itself is a cell of side 2."""
    own = F.pmod(F.xxhash64("rep"), F.col(blocks)).cast("int")
    d = d.withColumn("own", own)
    d = d.withColumn("other", F.explode(F.sequence(F.lit(0), (F.col(blocks) - 1).cast("int"))))
    d = d.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
    return d.withColumn("side", F.when(F.col("i") == F.col("j"), 2).when(F.col("own") == F.col("i"), 0).otherwise(1)).drop("own", "other", blocks)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id, rep_id, class_id, n_links, n_copies``.

    Shingles are five words (all of them in a shorter text); two documents are linked at a Jaccard similarity of 0.8 or more.
    Documents with equal words share ``rep_id``, the smallest id of them; ``class_id`` is the smallest id that links reach;
    ``n_links`` counts all other documents at 0.8 or more, copies included.  Texts without a word, null ones too, have no links and
    are classes of their own; so are rows without an id, which link to none; an empty table gives no rows; rows that repeat an id
    count as copies.

    One pass signs every text.  Equal words collapse first.  Signatures meet in 25 bands of four hashes (a pair at 0.8 is missed with
    probability 2e-6); in each bucket pruning keeps likely pairs, of which only a spanning forest is kept; its components are the units
    in which texts are compared exactly.  Buckets and units beyond a block are split, and only counts and forests leave a
    task, so no stage emits the pairs of a group.
    """
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("t"))
    nameless, d = d.where("doc_id is null"), d.where("doc_id is not null")
    signed = materialise(d.mapInPandas(_sign, "doc_id long, digest binary, n long, bands array<long>"), "near-signed")
    some = signed.where("bands is not null")
    groups = materialise(some.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies")), "near-groups")
    texts = some.join(groups.select(F.col("rep").alias("doc_id"), "rep", "copies", F.col("digest").alias("g")), "doc_id").where("digest = g").dropDuplicates(["rep"]).select("rep", "copies", "n", "bands")
    texts = materialise(texts, "near-texts")

    keyed = texts.select("rep", F.posexplode("bands").alias("band", "key"))
    full = keyed.groupBy("band", "key").agg(F.count("*").alias("c")).where("c > 1").select("band", "key", F.ceil(F.col("c") / BLOCK_ROWS).alias("blocks"))
    met = _cells(keyed.join(full, ["band", "key"]), "blocks").join(texts.select("rep", "bands"), "rep")
    met = met.repartition("band", "key", "i", "j").sortWithinPartitions("band", "key", "i", "j")
    edges = materialise(met.mapInPandas(_bucket_edges, "a long, b long").distinct(), "near-edges")
    units = materialise(connected_components(edges, "near-units"), "near-unit")

    member = texts.join(units.withColumnRenamed("id", "rep").withColumnRenamed("root", "unit"), "rep")
    sizes = member.groupBy("unit").agg(F.greatest(F.ceil(F.count("*") / BLOCK_ROWS), F.ceil(F.sum("n") / BLOCK_CHARS)).alias("blocks"))
    member = member.join(sizes, "unit").select("unit", "rep", "copies", "bands", "blocks")
    body = d.join(member, d["doc_id"] == member["rep"]).dropDuplicates(["rep"]).drop("doc_id")
    cells = _cells(body, "blocks").repartition("unit", "i", "j").sortWithinPartitions("unit", "i", "j")
    cells = cells.select("unit", "i", "j", "side", "rep", "copies", "bands", "t")
    links = materialise(cells.mapInPandas(_verified, "rep long, links long, root long"), "near-links")

    degree = links.groupBy("rep").agg(F.sum("links").alias("links"))
    classes = connected_components(links.select(F.col("rep").alias("a"), F.col("root").alias("b")), "near-classes")
    reps = groups.select("digest", "rep", "copies").join(degree, "rep", "left").join(classes.withColumnRenamed("id", "rep"), "rep", "left")
    reps = reps.select("digest", "rep", "copies", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("root", "rep").alias("root"))
    out = signed.select("doc_id", "digest", F.col("bands").isNotNull().alias("words")).join(reps, "digest", "left")
    one, none = F.lit(1).cast("long"), F.lit(0).cast("long")
    out = out.select(
        "doc_id", F.when(F.col("words"), F.col("rep")).otherwise(F.col("doc_id")).alias("rep_id"), F.when(F.col("words"), F.col("root")).otherwise(F.col("doc_id")).alias("class_id"),
        F.when(F.col("words"), F.col("links") + F.col("copies") - 1).otherwise(F.lit(0)).cast("long").alias("n_links"), F.when(F.col("words"), F.col("copies")).otherwise(one).alias("n_copies"),
    )
    return out.unionByName(nameless.select("doc_id", F.col("doc_id").alias("rep_id"), F.col("doc_id").alias("class_id"), none.alias("n_links"), one.alias("n_copies")))


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one document of each class, that with the smallest id, all its columns kept.

    Where an id repeats or is null, rows are numbered first and stay or go by number, so that each is a document of its own.
    """
    ids = docs.select(F.count("*").alias("n"), F.count_distinct(id_col).alias("ids")).first()
    if ids["n"] != ids["ids"]:
        docs, id_col = materialise(docs.withColumn("__row", F.monotonically_increasing_id()), "near-rows"), "__row"
    found = near_duplicates(docs, id_col, text_col)
    gone = materialise(found.where("doc_id <> class_id").select(F.col("doc_id").alias("__gone")).distinct(), "near-gone")
    return docs.join(gone, docs[id_col].cast("long") == gone["__gone"], "left_anti").drop("__row")
