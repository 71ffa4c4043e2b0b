"""Toxicity: a support vector machine on a subsequence string kernel with Nystroem landmarks."""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geocensus.llm.byte_convnet import held_out, training_rows
from geocensus.llm.shared import collect_garbage, map_texts

#: Subsequences of SHORTEST to ORDER characters; each step inside one, matched or skipped, costs DECAY.
#: Subsequences that reach over more than SPAN characters count as none.
SHORTEST, ORDER, DECAY, SPAN = 3, 4, 0.6, 6
#: The kernel is the Gaussian of the distance in subsequence space: exp((k - 1) / SPREAD).
SPREAD = 0.16
#: Landmarks: insults, up to three fifths, and clean words that come near them.  Words whose kernels are all below LIVE count as far from all.
LANDMARKS, LIVE = 96, 0.03
#: An insult's rate in clean texts is at most this share of its rate in toxic ones.
RARE = 0.01
#: Fits, each with the worst sentences of the last; weight of the loss; of that, weight of clean sentences against toxic ones.
ROUNDS, COST, CAUTION = 5, 3000.0, 1.5
#: Share of held-back clean texts that may lie beyond the score's middle.
ALLOWED = 0.004
#: Weights of all bent insults that many toxic texts hold, and of all others, that of all toxic sentences being one.
BENT = (0.7, 0.03)
#: Bounds of the training sample: labelled rows with the smallest seeded hash, and their longest text in bytes.
SAMPLE_ROWS, SAMPLE_BYTES = 4000, 12_000
#: Words longer than this are read in overlapping pieces.
PIECE = 24
#: Distinct words whose margin a Python worker keeps.
TABLE_ROWS = 300_000
_DROP = {ord(c): None for c in "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~­​‌‍⁠﻿"}
_SPELT = re.compile(r"(?<!\S)\S(?:\s\S){2,}(?!\S)")


_SENTENCE = re.compile(r"(?:(?<=[.!?])[\s]|\n)")


def sentences(text: str) -> list[str]:
    """Parts that end at a full stop, question or exclamation mark before white space, or at a line's end."""
    return [x for x in _SENTENCE.split(text) if x]


def words_in(text: str) -> set[str]:
    """The distinct words of a text, without case and punctuation; letters spelt one by one also as one word."""
    t = text.lower().translate(_DROP)
    out = set(t.split())
    for m in _SPELT.finditer(t):
        out.add("".join(m[0].split()))
    return out


def _pieces(word: str) -> list[str]:
    return [word] if len(word) <= PIECE else [word[i : i + PIECE] for i in range(0, len(word) - PIECE // 2, PIECE // 2)]


def _codes(words: list[str]) -> np.ndarray:
    """Code points, a start mark before each word, padded with zeros."""
    width = max(map(len, words)) + 1
    out = np.zeros((len(words), width), np.uint32)
    for i, w in enumerate(words):
        out[i, 1 : len(w) + 1] = np.frombuffer(w.encode("utf-32-le", "surrogatepass"), np.uint32)
    out[:, 0] = 94
    return out


def diagonal(codes: np.ndarray) -> np.ndarray:
    """Each row's kernel with itself, by the usual recursion over both positions for all rows at once."""
    n, rows = codes.shape[1], codes.shape[0]
    d2 = DECAY * DECAY
    out = np.zeros(rows, np.float32)
    prev = [np.ones((n + 1, rows), np.float32)] + [np.zeros((n + 1, rows), np.float32) for _ in range(ORDER - 1)]
    for i in range(n):
        same = ((codes[:, i : i + 1] == codes) & (codes != 0)).astype(np.float32).T
        new = [prev[0]]
        for k in range(1, ORDER + 1):
            hit = d2 * same * prev[k - 1][:n]
            if k >= SHORTEST:
                out += hit.sum(0)
            if k < ORDER:
                nxt = DECAY * prev[k]
                run = np.zeros(rows, np.float32)
                for j in range(n):
                    run = DECAY * run + hit[j]
                    nxt[j + 1] += run
                new.append(nxt)
        prev = new
    return out


def _patterns() -> list[tuple[int, ...]]:
    out = [(0,)]
    done = []
    for _ in range(ORDER - 1):
        out = [(*o, d) for o in out for d in range(o[-1] + 1, SPAN)]
        done += [o for o in out if len(o) >= SHORTEST]
    return done


_PATTERNS = _patterns()


def subsequences(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All gapped subsequences of all rows: row, key of the characters, weight; one vector operation per pattern of gaps."""
    n = codes.shape[1]
    rows, keys, weights = [], [], []
    for o in _PATTERNS:
        if o[-1] >= n:
            continue
        key = np.full((len(codes), n - o[-1]), len(o), np.uint64)
        for d in o:
            key = (key ^ codes[:, d : n - o[-1] + d]) * np.uint64(0x9E3779B97F4A7C15)
            key ^= key >> np.uint64(29)
        r, c = np.nonzero(codes[:, o[-1] :])
        rows.append(r)
        keys.append(key[r, c])
        weights.append(np.full(len(r), DECAY ** (o[-1] + 1), np.float32))
    if not rows:
        return np.zeros(0, int), np.zeros(0, np.uint64), np.zeros(0, np.float32)
    return np.concatenate(rows), np.concatenate(keys), np.concatenate(weights)


class Landmarks:
    """The landmarks' subsequences, ready for kernels with many words."""

    def __init__(self, words: list[str]):
        self.words = words
        codes = _codes(words)
        rows, keys, weights = subsequences(codes)
        self.keys, at = np.unique(keys, return_inverse=True)
        self.table = np.zeros((len(self.keys) + 1, len(words)), np.float32)
        np.add.at(self.table, (at, rows), weights)
        self.slots = np.full(1 << 18, len(self.keys), np.int32)
        self.slots[(self.keys >> np.uint64(46)).astype(np.int64)] = np.arange(len(self.keys))
        self.own = np.sqrt(np.maximum(diagonal(codes), 1e-9))

    def kernel(self, words: list[str]) -> np.ndarray:
        codes = _codes(words)
        rows, keys, weights = subsequences(codes)
        at = self.slots[(keys >> np.uint64(46)).astype(np.int64)]
        hit = np.flatnonzero(np.append(self.keys, np.uint64(0))[at] == keys)
        out = np.zeros((len(words), len(self.words)), np.float32)
        if len(hit):
            hit = hit[np.argsort(rows[hit], kind="stable")]
            r = rows[hit]
            first = np.flatnonzero(np.append(True, r[1:] != r[:-1]))
            out[r[first]] = np.add.reduceat(self.table[at[hit]] * weights[hit][:, None], first)
        return _gauss(out / np.outer(np.sqrt(np.maximum(diagonal(codes), 1e-9)), self.own))


def _gauss(k: np.ndarray) -> np.ndarray:
    return np.exp((k - 1) / SPREAD)


class InsultKernelSVM:
    """A linear machine on Nystroem coordinates of sentences: a sentence is as near to a landmark as its nearest word."""

    def __init__(self, landmarks: list[str]):
        self.landmarks = landmarks
        self.base = Landmarks(landmarks)
        values, vectors = np.linalg.eigh(self.base.kernel(landmarks).astype(np.float64))
        self.project = vectors / np.sqrt(np.maximum(values, 1e-3))
        self.direction, self.bias, self.slope, self.shift = np.zeros(len(landmarks), np.float32), -1.0, 3.0, 0.0
        self.memo: dict[str, np.ndarray | None] = {}

    def learn(self, words: set[str]) -> None:
        """Puts the kernels of new words into the memo; none for words that are far from every landmark."""
        new = sorted((w for w in words if w not in self.memo), key=len)
        for lo in range(0, len(new), 1024):
            own = new[lo : lo + 1024]
            counts = [len(_pieces(w)) for w in own]
            k = self.base.kernel([p for w in own for p in _pieces(w)])
            k = np.maximum.reduceat(k, np.cumsum([0, *counts[:-1]]))
            for w, row, near in zip(own, k, k.max(1) > LIVE, strict=True):
                self.memo[w] = row.copy() if near else None

    def pooled(self, words: Iterable[str]) -> np.ndarray | None:
        """A sentence's kernels with the landmarks, if any of its words is near one."""
        rows = [k for w in words if (k := self.memo[w]) is not None]
        return None if not rows else rows[0] if len(rows) == 1 else np.max(rows, 0)

    def fit(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray, rounds: int = 30) -> None:
        """Squared hinge loss by Newton steps on the rows inside the margin; y is +1 or -1."""
        z = np.ones((len(x), x.shape[1] + 1), np.float32)
        z[:, :-1] = x @ self.project.astype(np.float32)
        keep = np.eye(z.shape[1])
        keep[-1, -1] = 1e-6
        w, near = np.zeros(z.shape[1]), np.ones(len(z), bool)
        for _ in range(rounds):
            left, right = keep.copy(), np.zeros(len(w))
            for lo in range(0, len(z), 4096):  # some rows at a time, so that the driver holds no copies
                own = lo + np.flatnonzero(near[lo : lo + 4096])
                v, k = z[own].astype(np.float64), weight[own]
                left += 2 * (v * k[:, None]).T @ v
                right += 2 * v.T @ (k * y[own])
            new = np.linalg.solve(left, right)
            w = w + 0.8 * (new - w) if w.any() else new
            again = y * (z @ w.astype(np.float32)) < 1
            if (again == near).all():
                break
            near = again
        self.direction, self.bias = (self.project @ w[:-1]).astype(np.float32), float(w[-1])

    def margins(self, texts: list[str]) -> np.ndarray:
        """Per text the margin of its worst sentence."""
        sets = [words_in(t) for t in texts]
        if len(self.memo) > TABLE_ROWS:
            self.memo.clear()
        self.learn(set().union(*sets))
        out = np.full(len(texts), self.bias)
        for i, (t, words) in enumerate(zip(texts, sets, strict=True)):
            if any(self.memo[w] is not None for w in words):
                parts = [words_in(x) for x in sentences(t)]
                self.learn(set().union(*parts) - words)
                rows = [k for p in parts if (k := self.pooled(p)) is not None]
                if rows:
                    out[i] = max(self.bias, float((np.array(rows) @ self.direction).max()) + self.bias)
        return out

    def score(self, texts: list[str]) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.slope * self.margins(texts) + self.shift).clip(-30, 30)))


def _bent(word: str, r: np.random.Generator) -> list[str]:
    """The word with one character doubled, inserted, and left out."""
    i, j, k = r.integers(1, len(word), 3)
    return [word[:i] + word[i - 1] + word[i:], word[:j] + "x1y0z3q"[r.integers(7)] + word[j:], word[:k] + word[k + 1 :]] if len(word) > 4 else []


def _landmarks(sets: list[tuple[str, ...]], y: np.ndarray) -> tuple[list[str], list[str]]:
    """Words of toxic texts and the words of clean texts that come near them."""
    pos, neg = Counter(), Counter()
    for s, v in zip(sets, y, strict=True):
        (pos if v else neg).update(s)
    n1, n0 = max(1, int(y.sum())), max(1, int((1 - y).sum()))
    # So frequent in toxic texts, and so rare elsewhere, that chance explains no word of the sample.
    enough = max(3.0, math.log(2 * len(pos) + 2) / -math.log(n1 / (n1 + n0)))
    lead = sorted((w for w, c in pos.items() if 3 <= len(w) <= PIECE and c >= enough and neg[w] / n0 <= RARE * c / n1), key=lambda w: (-pos[w], w))
    if not lead:
        lead = sorted((w for w in pos if 3 <= len(w) <= PIECE), key=lambda w: (-pos[w] / (neg[w] + 0.5), w))[:20]
    if not lead:
        return [], []
    pick, near = lead[:1], Landmarks(lead[:1])
    for w in lead[1:]:  # unlike each other
        if len(pick) < LANDMARKS * 3 // 5 and near.kernel([w]).max() < 0.4:
            pick.append(w)
            near = Landmarks(pick)
    common = sorted((w for w, c in neg.items() if c > 1 and 3 <= len(w) <= PIECE and w not in pick), key=lambda w: (-neg[w], w))
    close = [w for lo in range(0, len(common), 1024) for w, k in zip(common[lo : lo + 1024], near.kernel(common[lo : lo + 1024]).max(1), strict=True) if k > 0.1 and neg[w] / n0 > RARE * pos[w] / n1]
    return pick, close[: LANDMARKS - len(pick)]


def _machine(sets: list[tuple[str, ...]], parts: list[list[tuple[str, ...]]], y: np.ndarray, seed: int) -> InsultKernelSVM | None:
    """The machine of labelled texts, given as their words and as their sentences' words; none if toxic texts have no words."""
    insults, confusers = _landmarks(sets, y)
    if not insults:
        return None
    svm = InsultKernelSVM(insults + confusers)
    svm.learn(set().union(*sets, *[p for ps in parts for p in ps]))
    rows, owner = [np.zeros(len(svm.landmarks), np.float32)], [-1]
    for i, ps in enumerate(parts):
        own = {k.tobytes(): k for p in ps if (k := svm.pooled(p)) is not None}
        rows += own.values()
        owner += [i] * len(own)
    x, owner = np.array(rows), np.array(owner)
    clean = np.flatnonzero(np.append(y, 0)[owner] != 1)
    known = set().union(*[s for s, v in zip(sets, y, strict=True) if not v])
    r = np.random.default_rng(seed)
    often = Counter(w for s, v in zip(sets, y, strict=True) if v for w in s)
    variants, heavy = [], []
    for common in (True, False):
        bent = sorted({v for w in insults if bool(often[w] > 0.1 * y.sum()) == common for _ in range(4 if common else 1) for v in _bent(w, r)} - known)
        svm.learn(set(bent))
        rows = [svm.memo[w] for w in bent if svm.memo[w] is not None]
        variants += rows
        heavy += [BENT[not common] / max(1, len(rows))] * len(rows)
    seen = x[:, : len(insults)].max(1)  # at first, the nearest to any insult
    for turn in range(ROUNDS):
        worst = [(at := np.flatnonzero(owner == i))[seen[at].argmax()] for i in np.flatnonzero(y == 1) if (owner == i).any()]
        worst = [k for k in worst if seen[k] > (0.5 if not turn else -0.5)]
        data = np.concatenate([x[worst], np.array(variants).reshape(-1, x.shape[1]), x[clean]])
        side = np.concatenate([np.ones(len(worst) + len(variants)), -np.ones(len(clean))])
        weight = np.concatenate([np.full(len(worst), 1 / max(1, len(worst))), np.array(heavy), np.full(len(clean), CAUTION / (1 - y).sum())])
        svm.fit(data, side, COST * weight)
        seen = x @ svm.direction + svm.bias
    svm.memo.clear()
    return svm


def train(texts: list[str], y: np.ndarray, seed: int = 5) -> InsultKernelSVM | None:
    """Landmarks, machine and calibration from the sentences of labelled texts.

    Without a word in the toxic texts, or labels of both classes, there is no machine.  Every sentence of a clean text is a clean one, and a toxic text has a toxic sentence somewhere: the one that the machine so far finds
    worst teaches the positive class, unless none looks toxic, when the text teaches nothing.  The insults among the landmarks
    teach it too with a character doubled, inserted or left out, those above all that more than a tenth of the toxic texts hold.  A logistic curve of
    a text's worst margin is its probability.  The curve's middle lies at zero or, if that is higher, where the margins that a machine of
    either half of the texts gives the others leave ``ALLOWED`` of the clean ones beyond.
    """
    if len(set(y.tolist())) < 2:
        return None
    own: dict[str, str] = {}
    shared = lambda words: tuple([own.setdefault(w, w) for w in sorted(words)])  # noqa: E731  one string for each word, however often
    sets, parts = [shared(words_in(t)) for t in texts], [[shared(words_in(x)) for x in sentences(t)] for t in texts]
    svm = _machine(sets, parts, y, seed)
    if svm is None:
        return None
    half, z = np.zeros(len(texts), int), np.zeros(len(texts))
    for v in (0, 1):
        half[y == v] = np.arange((y == v).sum()) % 2
    for side in (0, 1):
        some, other = np.flatnonzero(half == side), np.flatnonzero(half != side)
        judge = _machine([sets[i] for i in some], [parts[i] for i in some], y[some], seed) if len(set(y[some].tolist())) == 2 else None
        z[other] = (judge or svm).margins([texts[i] for i in other])
    clean = np.sort(z[y == 0])[::-1]
    svm.shift = -svm.slope * max(0.0, float(clean[int(ALLOWED * len(clean))]))
    return svm


_loaded: dict[int, InsultKernelSVM] = {}


def _kept_model(svm: InsultKernelSVM) -> InsultKernelSVM:
    """The worker's model, kept over tasks with its table of words; another model takes its place."""
    mark = hash((svm.shift, svm.bias, svm.direction.tobytes(), tuple(svm.landmarks)))
    if mark not in _loaded:
        _loaded.clear()
        _loaded[mark] = svm
    return _loaded[mark]


def score(docs: DataFrame, svm: InsultKernelSVM | None, id_col: str = "doc_id", text_col: str = "text", cut: float = 0.5) -> DataFrame:
    """``doc_id, score, predicted`` of every whole text.  Null and empty texts have no words and score lowest; without labels
    of both classes all score 0; rows are independent, so repeated and null ids pass through; an empty table gives no rows."""

    def make() -> Callable[[list[str]], tuple[np.ndarray, np.ndarray]]:
        model = _kept_model(svm) if svm else None

        def run(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
            p = model.score(texts) if model else np.zeros(len(texts))
            return p, (p >= cut).astype(np.int32)

        return run

    return map_texts(docs, id_col, text_col, "score double, predicted int", make)


def fitted(docs: DataFrame, labels: DataFrame) -> InsultKernelSVM | None:
    texts, y = training_rows(docs, labels, "toxic", SAMPLE_ROWS, SAMPLE_BYTES)
    collect_garbage(docs.sparkSession)  # the driver's two processes don't both hold what either has freed
    svm = train(texts, y)
    collect_garbage(docs.sparkSession)
    return svm


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id, held_out, score, predicted``: a machine fitted on the training side's sample, applied to every text."""
    out = score(docs, fitted(docs, labels))
    return out.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", "predicted")


def drop_toxic(docs: DataFrame, labels: DataFrame, text_col: str = "text", cut: float = 0.5) -> DataFrame:
    """``docs`` without the rows that the machine rejects, all columns kept whatever their names and types; one pass, no join.

    Null and empty texts stay, and without labels of both classes every row does.
    """
    svm = fitted(docs, labels)
    if svm is None:
        return docs
    at = docs.columns.index(text_col)
    d = docs.toDF(*[f"c{i}" for i in range(len(docs.columns))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _kept_model(svm)
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                yield part.filter(pa.array(model.score([t or "" for t in part.column(at).to_pylist()]) < cut))

    return d.mapInArrow(run, d.schema).toDF(*docs.columns)
