"""Helpers that several training-data operators use."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import os
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: The white space of every word and text rule here: blank, and U+0009 to U+000D.
WHITE = " \t\n\x0b\x0c\r"
#: One word.
WORD = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, ``spark.checkpoint.dir``; in local mode one of its own where that is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir names no folder that all executors share")
    return folder or os.path.join(tempfile.gettempdir(), "geocensus-checkpoints")


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it again: cuts lineage, and survives a lost executor."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    collect_garbage(spark)
    df.write.option("compression", "zstd").parquet(path)
    collect_garbage(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path
    return out


def collect_garbage(spark: SparkSession) -> None:
    """Collects plans that nothing uses any more, on both sides; Spark then removes their shuffle files.  What the driver's processes
    have freed goes back to the system."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)
    with contextlib.suppress(Py4JError):  # nor have other virtual machines
        _trim(spark)


def _trim(spark: SparkSession) -> str:
    """Gives back what the driver's virtual machine has freed outside its heap, by its diagnostic command; what that says."""
    jvm = spark.sparkContext._jvm
    call = next(m for m in jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
    args = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)
    args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
    return call.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), args)


def release(*frames: DataFrame) -> None:
    """Removes the files of materialised tables; only for tables whose every dependant is itself written."""
    for f in frames:
        context = f.sparkSession.sparkContext
        path = context._jvm.org.apache.hadoop.fs.Path(f.written_at)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def text_or_empty(text: Column | str) -> Column:
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def strip_white(text: Column) -> Column:
    """``text`` without its white-space characters."""
    for c in WHITE:  # byte searches; faster than translate() or a pattern
        text = F.replace(text, F.lit(c), F.lit(""))
    return text


def words_of(text: Column) -> Column:
    """The words of ``text``, in order, as an array."""
    return F.filter(F.split(text, r"[\x20\x09-\x0D]+", -1), lambda w: w != "")


def split_words(text: str) -> list[str]:
    """The words of a Python string; ``str.split`` alone would also cut at other Unicode spaces."""
    return text.translate(_TO_BLANK).split(" ") if text else []


_TO_BLANK = {ord(c): " " for c in WHITE}
_ODD = np.uint64(0x9E3779B97F4A7C15)


def mixed(x: np.ndarray) -> np.ndarray:
    """A finaliser for 64-bit hashes."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class WordHasher:
    """64-bit hashes of all words of a text, by prefix sums over its bytes: no Python object per word."""

    def __init__(self) -> None:
        r = np.random.default_rng(20)
        self.table = r.integers(0, 2**64, 256, np.uint64)
        self.white = np.zeros(256, bool)
        self.white[[32, *range(9, 14)]] = True
        self._grow(1 << 16)

    def _grow(self, n: int) -> None:
        base, back = np.uint64(0xD6E8FEB86659FD93), np.uint64(pow(0xD6E8FEB86659FD93, -1, 2**64))
        self.power = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, base, np.uint64)]), dtype=np.uint64)
        self.inverse = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, back, np.uint64)]), dtype=np.uint64)

    def words(self, text: str) -> np.ndarray:
        return self.words_of(text.encode("utf-8", "surrogatepass"))[0]

    def words_of(self, text: bytes) -> tuple[np.ndarray, np.ndarray]:
        """The words' hashes and the bytes at which they start."""
        b = np.frombuffer(text, np.uint8)
        if not len(b):
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        if len(b) >= len(self.power):
            self._grow(2 * len(b))
        inside = np.concatenate([[False], ~self.white[b], [False]])
        edge = np.flatnonzero(inside[1:] != inside[:-1])
        start, end = edge[::2], edge[1::2]
        total = np.concatenate([[np.uint64(0)], np.cumsum(self.table[b] * self.power[: len(b)], dtype=np.uint64)])
        return mixed((total[end] - total[start]) * self.inverse[start] + (end - start).astype(np.uint64) * _ODD), start


def gram_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hashes of all runs of ``n`` words."""
    if len(words) < n:
        return np.zeros(0, np.uint64)
    out = np.zeros(len(words) - n + 1, np.uint64)
    for k in range(n):
        out = (out + words[k : len(words) - n + 1 + k]) * _ODD
        out ^= out >> np.uint64(32)
    return mixed(out)


def words_py(text: str | None) -> list[str]:
    return [w for w in split_words(text or "") if w]


def runs(batches: Iterator[pd.DataFrame], keys: list[str]) -> Iterator[pd.DataFrame]:
    """Groups of a sorted stream of batches: one frame per run of equal ``keys``, carried over batch ends.

    A run is held whole, so callers bound its size when they make the keys.
    """
    held: list[pd.DataFrame] = []
    for batch in batches:
        if not len(batch):
            continue
        values = [batch[k].to_numpy() for k in keys]
        change = np.zeros(len(batch), bool)
        for v in values:
            change[1:] |= v[1:] != v[:-1]
        cuts = [0, *np.flatnonzero(change).tolist(), len(batch)]
        for lo, hi in zip(cuts, cuts[1:], strict=False):
            part = batch.iloc[lo:hi]
            if lo == 0 and held and any(held[-1][k].iloc[-1] != part[k].iloc[0] for k in keys):
                yield pd.concat(held) if len(held) > 1 else held[0]
                held = []
            elif lo:
                yield pd.concat(held) if len(held) > 1 else held[0]
                held = []
            held.append(part)
    if held:
        yield pd.concat(held) if len(held) > 1 else held[0]


class Forest:
    """Union-find over 0..n-1; roots are the smallest members."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def join(self, x: int, y: int) -> None:
        x, y = self.find(x), self.find(y)
        if x != y:
            self.up[max(x, y)] = min(x, y)


def connected_components(edges: DataFrame, label: str, rounds: int = 60) -> DataFrame:
    """``edges``(a, b: long) to (id, root): root is the smallest id of the component.

    Alternates large-star and small-star steps, each a partial aggregate and a join, until only stars are left; every round
    is a written table.  A hub's neighbours are never gathered in one task: only their minimum is.  No join is broadcast: the
    driver would hold a table of every round.
    """
    e = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), label)
    for _ in range(rounds):
        if _are_stars(e):
            break
        both = e.select("a", "b").unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low.hint("merge"), "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.unionByName(low.where("m < a").select("a", F.col("m").alias("b"))).distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least.hint("merge"), "a").select(F.col("b").alias("x"), "m", "a")
        out = small.select(F.col("x").alias("a"), F.col("m").alias("b")).unionByName(small.select("a", F.col("m").alias("b"))).where("a <> b").distinct()
        e = materialise(out, label)
    else:
        raise RuntimeError("components did not settle")
    found = e.groupBy("a").agg(F.min("b").alias("root")).select(F.col("a").alias("id"), "root")
    return found.unionByName(found.select(F.col("root").alias("id"), "root").distinct())


def _are_stars(e: DataFrame) -> bool:
    """Whether each end of the distinct ``e``(a > b) is either a root or has one edge to a root, which then is the smallest of its component."""
    ends = e.select("a", F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(e.select(F.col("b").alias("a"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    return ends.groupBy("a").agg(F.sum("up").alias("up"), F.max("down").alias("down")).where("up + down > 1").isEmpty()


def small_enough(df: DataFrame, rows: int) -> bool:
    """Whether ``df`` has at most ``rows`` rows: the check before a broadcast."""
    return df.limit(rows + 1).count() <= rows


def join_checked(left: DataFrame, right: DataFrame, on: str | list[str], how: str = "left", rows: int = 50_000) -> DataFrame:
    """Join with ``right`` broadcast if it has at most ``rows`` rows, else by shuffle."""
    return left.join(F.broadcast(right) if small_enough(right, rows) else right, on, how)


def hot_join(left: DataFrame, right: DataFrame, on: str, count: str, spread: str, share: int = 1000, salts: int = 32) -> DataFrame:
    """Inner join of ``left`` with ``right``, which has one row per ``on`` and, in ``count``, how many rows of ``left`` it meets.

    Keys with more than 1/``share`` of the rows, of which there are fewer than ``share``, are dealt over ``salts`` by ``spread``.
    """
    total = right.agg(F.coalesce(F.sum(count), F.lit(0)).alias("n")).first()["n"]
    if right.where(F.col(count) > total / share).isEmpty():
        return left.join(right, on)
    hot = F.broadcast(right.where(F.col(count) > total / share).select(on, F.lit(True).alias("__hot")))
    left = left.join(hot, on, "left").withColumn("__salt", F.when(F.col("__hot"), F.pmod(F.xxhash64(spread), F.lit(salts))).otherwise(0).cast("int")).drop("__hot")
    salt = F.explode(F.when(F.col(count) > total / share, F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))
    return left.join(right.drop("__salt").withColumn("__salt", salt), [on, "__salt"]).drop("__salt")


def map_texts(docs: DataFrame, id_col: str, text_col: str, columns: str, make: Callable[[], Callable[[list[str]], Iterable]], step: int = 256) -> DataFrame:
    """``doc_id`` and ``columns`` of every text, some texts at a time.

    ``make`` is called once per task and gives a function from texts to one list per column.  Null texts count as empty.  Ids
    stay in Arrow, so long ids beside null ones keep all their digits.
    """
    d = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("t"))
    schema = T.StructType([T.StructField("doc_id", d.schema["doc_id"].dataType), *T.StructType.fromDDL(columns)])
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = make()
        for b in batches:
            for lo in range(0, b.num_rows, step):
                part = b.slice(lo, step)
                made = f(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), *[pa.array(c, k.type) for c, k in zip(made, list(arrow)[1:], strict=True)]], names=arrow.names)

    return d.mapInArrow(run, schema)
