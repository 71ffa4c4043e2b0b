"""The crawl index, derived from ``pages``, and reads of single records by byte range."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from geocensus.functions.columns import GEO_MIMES, OTHER_MIMES, RELEASES, bucket, tld

PARTS = 5


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; in local mode a folder of its own where that is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir names no folder that all executors share")
    return folder or os.path.join(tempfile.gettempdir(), "geocensus-checkpoints")


def scratch(spark: SparkSession, label: str) -> str:
    """A new path in the folder that driver and executors share."""
    return f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """``df`` written to the shared folder and read again: later steps read its rows and not its expressions."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def local(path: str) -> str:
    """``path`` as a task opens it: the shared folder is mounted everywhere."""
    return "/" + path[5:].lstrip("/") if path.startswith("file:") else path


def release_of(id_col: str) -> Column:
    return F.element_at(F.array(*[F.lit(r) for r in RELEASES]), (F.pmod(F.col(id_col), F.lit(3)) + 1).cast("int"))


def planted_mime(id_col: str) -> Column:
    """A type per id: a fifth of the ids geospatial, so that counts are not zero at small sizes."""
    b = bucket("mime", id_col)
    geo = F.element_at(F.array(*[F.lit(m) for m in GEO_MIMES]), (b % len(GEO_MIMES) + 1).cast("int"))
    return F.when(b < 200, geo).when(b < 900, OTHER_MIMES[0]).when(b < 950, OTHER_MIMES[1]).otherwise(OTHER_MIMES[2])


MIME_SQL = "(('0x' || substr(md5('mime|' || page_id), 1, 8))::bigint % 1000)"
INDEX_SQL = f"""
select page_id, ['R2019', 'R2021', 'R2024'][(page_id % 3 + 1)::int] as release, ((page_id // 3) % {PARTS})::int as part, url,
  string_split(regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1), '.')[-1] as tld,
  case when {MIME_SQL} < 200 then [{", ".join(f"'{m}'" for m in GEO_MIMES)}][({MIME_SQL} % {len(GEO_MIMES)} + 1)::int] when {MIME_SQL} < 900 then '{OTHER_MIMES[0]}' when {MIME_SQL} < 950 then '{OTHER_MIMES[1]}' else '{OTHER_MIMES[2]}' end as mime,
  octet_length(encode(html))::bigint as length from pages"""


def crawl_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``page_id, release, part, url, tld, mime, length``; without ``length`` a consumer never reads the html."""
    p = table(spark, sf_dir, "pages")
    part = F.pmod(F.floor(F.col("page_id") / 3), F.lit(PARTS)).cast("int")
    return p.select("page_id", release_of("page_id").alias("release"), part.alias("part"), "url", tld(F.col("url")).alias("tld"), planted_mime("page_id").alias("mime"), F.octet_length("html").cast("long").alias("length"))


def with_offsets(index: DataFrame) -> DataFrame:
    """Adds ``offset`` in the archive file of (release, part): the lengths before it, by id."""
    w = Window.partitionBy("release", "part").orderBy("page_id").rowsBetween(Window.unboundedPreceding, -1)
    return index.withColumns({"offset": F.coalesce(F.sum("length").over(w), F.lit(0)), "warc_file": F.concat_ws("/", "release", "part")})


def coalesce_ranges(ranges: DataFrame, gap: int) -> DataFrame:
    """``warc_file, lo, hi, records``: ranges of a file that lie within ``gap`` bytes become one read.  One shuffle, by file."""
    w = Window.partitionBy("warc_file").orderBy("offset")
    end = F.max(F.col("offset") + F.col("length")).over(w.rowsBetween(Window.unboundedPreceding, -1))
    d = ranges.withColumn("new", F.when(end.isNull() | (F.col("offset") > end + gap), 1).otherwise(0))
    d = d.withColumn("island", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return d.groupBy("warc_file", "island").agg(F.min("offset").alias("lo"), F.max(F.col("offset") + F.col("length")).alias("hi"), F.count("*").alias("records")).drop("island")


def archive_name() -> Column:
    return F.concat_ws("-", "release", "part")


def write_archives(pages: DataFrame, path: str) -> None:
    """The bodies of each (release, part), by id, as the bytes of one file ``release-part.arc``; null bodies have no bytes.

    A file takes its name when it is whole, so a repeated task replaces it.
    """
    folder = local(path)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        os.makedirs(folder, exist_ok=True)
        name, part, f, n = None, "", None, 0
        for b in batches:
            for to, html in zip(b["name"], b["html"], strict=True):
                if to != name:
                    if f:
                        f.close()
                        os.replace(part, f"{folder}/{name}.arc")
                    name, part, n = to, f"{folder}/{to}.{uuid.uuid4().hex}", n + 1
                    f = open(part, "wb")  # noqa: SIM115
                f.write((html or "").encode())
        if f:
            f.close()
            os.replace(part, f"{folder}/{name}.arc")
        yield pd.DataFrame({"files": [n]})

    part = F.pmod(F.floor(F.col("page_id") / 3), F.lit(PARTS)).cast("int")
    p = pages.select("page_id", "html", release_of("page_id").alias("release"), part.alias("part")).select("page_id", "html", archive_name().alias("name"))
    p.repartition("name").sortWithinPartitions("name", "page_id").mapInPandas(run, "files long").write.format("noop").mode("overwrite").save()


class _Range(InputPartition):
    def __init__(self, path: str, items: list[tuple[int, int, int]] | None):
        super().__init__(path)
        self.path, self.items = path, items


class RangeSource(DataSource):
    """``id, bytes``: records of archive files, read by (path, offset, length).

    Option ``ranges`` has ``path|id|offset|length`` lines, as a stated request; each file is one partition, read in order.
    Option ``lists`` names a folder of text files of such lines, for requests of any size; each list is one partition, read by its task.
    """

    @classmethod
    def name(cls) -> str:
        return "byte_ranges"

    def schema(self) -> str:
        return "id long, bytes binary"

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        return _ListReader(self.options["lists"]) if "lists" in self.options else _RangeReader(self.options["ranges"])


class _RangeReader(DataSourceReader):
    def __init__(self, ranges: str):
        by: dict[str, list[tuple[int, int, int]]] = {}
        for line in ranges.splitlines():
            path, i, offset, length = line.rsplit("|", 3)
            by.setdefault(path, []).append((int(offset), int(length), int(i)))
        self.by = by

    def partitions(self) -> list[InputPartition]:
        return [_Range(p, sorted(x)) for p, x in sorted(self.by.items())]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, bytes]]:
        with open(partition.path, "rb") as f:
            for offset, length, i in partition.items:
                f.seek(offset)
                yield i, f.read(length)


class _ListReader(DataSourceReader):
    def __init__(self, folder: str):
        self.folder = folder

    def partitions(self) -> list[InputPartition]:
        return [_Range(f"{self.folder}/{n}", None) for n in sorted(os.listdir(self.folder)) if n.startswith("part-")]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, bytes]]:
        path, f = None, None
        with open(partition.path) as lines:
            for line in lines:
                to, i, offset, length = line.rstrip("\n").rsplit("|", 3)
                if to != path:
                    if f:
                        f.close()
                    path, f = to, open(to, "rb")  # noqa: SIM115
                f.seek(int(offset))
                yield int(i), f.read(int(length))
        if f:
            f.close()


def fetch_by_scan(docs: DataFrame, ids: DataFrame, id_col: str) -> DataFrame:
    """The baseline: all bodies are scanned, the sampled ids kept.  Ids are broadcast up to 200,000, a sample's size."""
    few = ids.select(id_col).limit(200_001).count() <= 200_000
    return docs.join(F.broadcast(ids.select(id_col)) if few else ids.select(id_col), id_col, "left_semi")
