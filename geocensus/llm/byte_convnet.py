"""Quality classifier: a convolutional network over bytes, trained and run in numpy."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geocensus.llm.shared import map_texts, text_or_empty

WIDTH, STRIDE, FILTERS = 8, 4, 16
#: Windows of a chunk and of its step: chunks of 1,024 bytes overlap by half and cover the whole text.
CHUNK, STEP = 256, 128
#: Bound of the training sample: labelled rows, those with the smallest seeded hash.
SAMPLE_ROWS = 3000
#: Longest labelled text, in bytes, that is used for training; scoring has no bound.
SAMPLE_BYTES = 12_000
_BLOCK = 1 << 20


def _bytes_of(texts: list[str]) -> tuple[np.ndarray, list[int]]:
    """All texts as bytes in windows of ``STRIDE``, each padded with zeros to whole windows and one more; windows per text."""
    parts, counts = [], []
    for t in texts:
        b = t.encode("utf-8", "surrogatepass")
        n = max(1, -(-len(b) // STRIDE))
        parts.append(b + bytes((n + 1) * STRIDE - len(b)))
        counts.append(n + 1)
    return np.frombuffer(b"".join(parts), np.uint8).reshape(-1, STRIDE), counts


def _chunks(counts: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all chunks, in windows, and the number of each text's chunks."""
    lo, hi, per, at = [], [], [], 0
    for n in counts:
        n -= 1
        starts = list(range(0, max(1, n - (CHUNK - STEP)), STEP))
        lo += [at + s for s in starts]
        hi += [at + min(s + CHUNK, n) for s in starts]
        per.append(len(starts))
        at += n + 1
    return np.array(lo), np.array(hi), np.array(per)


class ByteConvNet:
    """Filters are tables: the weight of each byte at each place of a window.  ReLU, maxima per chunk, then the mean and the
    maximum of a text's chunks, and one logistic unit."""

    def __init__(self, seed: int = 7):
        r = np.random.default_rng(seed)
        self.table = (r.standard_normal((WIDTH, 256, FILTERS)) * 0.15).astype(np.float32)
        self.bias = np.zeros(FILTERS, np.float32)
        self.out = (r.standard_normal(2 * FILTERS) * 0.1).astype(np.float32)
        self.out_bias = np.float32(0)

    def _maps(self, w: np.ndarray) -> np.ndarray:
        near = self.table[0][w[:, 0]]
        far = self.table[STRIDE][w[:, 0]]
        for p in range(1, STRIDE):
            near += self.table[p][w[:, p]]
            far += self.table[STRIDE + p][w[:, p]]
        near[:-1] += far[1:]
        return near

    def features(self, texts: list[str]) -> np.ndarray:
        w, counts = _bytes_of(texts)
        lo, hi, per = _chunks(counts)
        maps = self._maps(w)
        best = np.maximum.reduceat(maps, np.stack([lo, hi], 1).ravel())[::2]
        best = np.maximum(best + self.bias, 0)
        first = np.concatenate([[0], np.cumsum(per)[:-1]])
        return np.concatenate([np.add.reduceat(best, first) / per[:, None], np.maximum.reduceat(best, first)], 1)

    def score(self, texts: list[str]) -> np.ndarray:
        """Probabilities of label 1.  Texts go through in blocks of about a megabyte; a longer one is a block of its own."""
        done, held, size = [], [], 0
        for t in [*texts, None]:
            if held and (t is None or size + len(t) > _BLOCK):
                z = self.features(held) @ self.out + self.out_bias
                done.append(1 / (1 + np.exp(-z.astype(np.float64).clip(-30, 30))))
                held, size = [], 0
            if t is not None:
                held.append(t)
                size += len(t)
        return np.concatenate(done) if done else np.zeros(0)

    def fit(self, texts: list[str], labels: np.ndarray, epochs: int = 14, batch: int = 32, rate: float = 0.01, decay: float = 1e-4, seed: int = 7) -> ByteConvNet:
        """Adam on the logistic loss, classes weighted alike; gradients reach the windows at which a chunk has its maxima."""
        r = np.random.default_rng(seed)
        share = np.clip(np.mean(labels), 0.02, 0.98)
        weight = np.where(labels == 1, 0.5 / share, 0.5 / (1 - share)).astype(np.float32)
        params = [self.table, self.bias, self.out]
        moments = [(np.zeros_like(p), np.zeros_like(p)) for p in [*params, np.zeros(1, np.float32)]]
        step = 0
        for epoch in range(epochs):
            order = r.permutation(len(texts))
            for k in range(0, len(order), batch):
                take = order[k : k + batch]
                w, counts = _bytes_of([texts[i] for i in take])
                lo, hi, per = _chunks(counts)
                maps = self._maps(w)
                arg = np.stack([a + maps[a:b].argmax(0) for a, b in zip(lo, hi, strict=True)])
                raw = np.take_along_axis(maps, arg, 0) + self.bias
                best = np.maximum(raw, 0)
                first = np.concatenate([[0], np.cumsum(per)[:-1]])
                owner = np.repeat(np.arange(len(per)), per)
                mean, top = np.add.reduceat(best, first) / per[:, None], np.maximum.reduceat(best, first)
                x = np.concatenate([mean, top], 1)
                g = ((1 / (1 + np.exp(-(x @ self.out + self.out_bias).clip(-30, 30))) - labels[take]) * weight[take] / len(take)).astype(np.float32)
                d_out, d_bias = x.T @ g, g.sum()
                d_best = (g[:, None] * self.out[:FILTERS] / per[:, None])[owner] + np.where(best == top[owner], (g[:, None] * self.out[FILTERS:])[owner], 0)
                d_best = np.where(raw > 0, d_best, 0).astype(np.float32)
                d_table = np.zeros_like(self.table)
                f = np.broadcast_to(np.arange(FILTERS), arg.shape)
                for p in range(WIDTH):
                    np.add.at(d_table[p], (w[np.minimum(arg + p // STRIDE, len(w) - 1), p % STRIDE], f), d_best)
                step += 1
                lr = rate * (1 - epoch / epochs)
                for p, d, (m, v) in zip([*params, None], [d_table, d_best.sum(0), d_out, np.array([d_bias], np.float32)], moments, strict=True):
                    m += 0.1 * (d - m)
                    v += 0.001 * (d * d - v)
                    change = lr * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
                    if p is None:
                        self.out_bias -= change[0]
                    else:
                        p -= change + lr * decay * p
        return self


def training_rows(docs: DataFrame, labels: DataFrame, label: str, rows: int = SAMPLE_ROWS, longest: int = SAMPLE_BYTES, id_col: str = "doc_id", text_col: str = "text") -> tuple[list[str], np.ndarray]:
    """At most ``rows`` labelled texts of the training side (crc32 of the id, mod 5, is not 0), up to half of each class.

    Texts beyond ``longest`` bytes teach nothing.  An id that is labelled more than once has its largest label.
    """
    known = labels.where(F.col(label).isin(0, 1)).groupBy(F.col("doc_id").alias("__id")).agg(F.max(label).cast("int").alias("y"))
    known = known.where(~held_out(F.col("__id"))).withColumn("r", F.md5(F.concat(F.lit("train|"), F.col("__id").cast("string"))))
    ids = known.where("y = 1").orderBy("r").limit(2 * rows).unionByName(known.where("y = 0").orderBy("r").limit(2 * rows))  # a bound, documented
    d = docs.select(F.col(id_col).alias("__id"), text_or_empty(text_col).alias("t")).where(F.octet_length("t") <= longest)
    d = d.join(F.broadcast(ids), "__id")
    half = [d.where(F.col("y") == y).orderBy("r").limit(rows // 2) for y in (0, 1)]
    got = half[0].unionByName(half[1]).select("t", "y", "r").orderBy("r").collect()
    return [g["t"] for g in got], np.array([g["y"] for g in got], np.float32)


def held_out(id_col: Column) -> Column:
    return F.crc32(id_col.cast("string").cast("binary")) % 5 == 0


def score(docs: DataFrame, model: ByteConvNet | None, id_col: str = "doc_id", text_col: str = "text", cut: float = 0.3) -> DataFrame:
    """``doc_id, score, predicted`` of every whole text; null counts as empty, which is scored as a window of zeros.  Without a
    model each text scores 0.5.  Rows are independent, so repeated and null ids pass through; an empty table gives no rows."""

    def make() -> Callable[[list[str]], tuple[np.ndarray, np.ndarray]]:
        def run(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
            p = model.score(texts) if model else np.full(len(texts), 0.5)
            return p, (p >= cut).astype(np.int32)

        return run

    return map_texts(docs, id_col, text_col, "score double, predicted int", make)


def quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id, held_out, score, predicted``: a network fitted on the training side's sample, applied to every text.

    Without labelled rows of both classes there is nothing to learn, and each text scores 0.5.
    """
    texts, y = training_rows(docs, labels, "quality")
    model = ByteConvNet().fit(texts, y) if len(set(y.tolist())) == 2 else None
    out = score(docs, model)
    return out.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", "predicted")
