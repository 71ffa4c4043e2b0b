"""Sample sizes and reproducible samples."""

from __future__ import annotations

import math
from decimal import ROUND_CEILING, Decimal
from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from geocensus.functions.columns import order_key


def sample_size(e: float, p: float = 0.5, z: float = 1.96, population: int | None = None) -> int:
    """Rows that estimate a proportion within ``e``; decimal arithmetic, rounded up; smaller for a finite population."""
    de, dp, dz = (Decimal(str(x)) for x in (e, p, z))
    n = dz * dz * dp * (1 - dp) / (de * de)
    if population is not None:
        n = n / (1 + (n - 1) / population)
    return int(n.to_integral_value(ROUND_CEILING))


def margin(n: int, p: float = 0.5, z: float = 1.96, population: int | None = None) -> float:
    fpc = 1.0 if population is None or population <= 1 else math.sqrt((population - n) / (population - 1))
    return z * math.sqrt(p * (1 - p) / n) * fpc


def wilson(x: int, n: int, z: float = 1.96) -> tuple[float, float]:
    p, d = x / n, 1 + z * z / n
    half = z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / d
    mid = (p + z * z / (2 * n)) / d
    return mid - half, mid + half


def allocate(n: int, parts: int, headroom: int = 0) -> int:
    """Rows per part that give ``n`` and ``headroom`` over."""
    return -(-(n + headroom) // parts)


def sample_sizes(frame: DataFrame, stratum: str, part: str, e: float, headroom: int = 0) -> DataFrame:
    """For each stratum its rows and parts, the sizes that estimate a proportion within ``e`` (plain, with more digits of z, and for
    a population of the stratum's size), and the rows per part that give the plain size and ``headroom`` over."""
    a, b = (Fraction("1.96") ** 2 / 4 / Fraction(str(e)) ** 2).as_integer_ratio()
    n, more = sample_size(e), sample_size(e, z=1.959964)
    g = frame.groupBy(stratum, part).agg(F.count("*").alias("n")).groupBy(stratum).agg(F.sum("n").alias("population"), F.count("*").alias("parts"))
    finite = f"({a}L * population + {b}L * population + {a - b - 1}L) div ({b}L * population + {a - b}L)"  # rounded up, in whole numbers
    return g.select(stratum, "population", "parts", F.lit(n).cast("long").alias("plain"), F.lit(more).cast("long").alias("z_1959964"), F.expr(finite).alias("finite"), F.expr(f"({n + headroom - 1}L + parts) div parts").alias("per_part"))


def zero_error_bound(n: int, conf: float = 0.95, sides: int = 1) -> float:
    """The largest error rate under which no error among ``n`` still has probability 1 - ``conf`` (exact binomial)."""
    return 1 - ((1 - conf) / sides) ** (1 / n)


def zero_error_bounds(audited: DataFrame, by: str, conf: float = 0.95) -> DataFrame:
    """``zero_error_bound`` for the audited rows of each ``by``, one- and two-sided."""
    n = audited.groupBy(by).agg(F.count("*").alias("n")).withColumn("sides", F.explode(F.array(F.lit(1), F.lit(2))))
    return n.select(by, "sides", "n", F.round(1 - F.pow(F.lit(1 - conf) / F.col("sides"), 1 / F.col("n")), 6).alias("bound"))


def adjusted_prevalence(p: float, sensitivity: float, specificity: float) -> float:
    return (p + specificity - 1) / (sensitivity + specificity - 1)


def stratified_sample(df: DataFrame, strata: list[str], k: int, seed: str, id_cols: list[str], ties: list[str] | None = None) -> DataFrame:
    """``k`` rows per stratum, the same for any partitioning.  Spark limits each map task to ``k`` rows per stratum before the
    shuffle; strata with fewer rows give all of theirs."""
    w = Window.partitionBy(*strata).orderBy(order_key(seed, *id_cols), *id_cols, *(ties or []))
    return df.withColumn("__n", F.row_number().over(w)).where(F.col("__n") <= k).drop("__n")


def proportional_sample(df: DataFrame, strata: list[str], n: int, seed: str, id_cols: list[str]) -> DataFrame:
    """About ``n`` rows, each stratum by its share, rounded up; strata sizes come from one aggregate."""
    sizes = df.groupBy(*strata).agg(F.count("*").alias("__size"))
    total = sizes.agg(F.sum("__size")).first()[0] or 1
    w = Window.partitionBy(*strata).orderBy(order_key(seed, *id_cols), *id_cols)
    ranked = df.join(sizes, strata).withColumn("__n", F.row_number().over(w))
    return ranked.where(F.col("__n") <= F.ceil(F.col("__size") * F.lit(n) / F.lit(total))).drop("__n", "__size")


def bernoulli_sample(df: DataFrame, fraction: float, seed: str, id_cols: list[str]) -> DataFrame:
    """Each row with probability ``fraction``, by its hash; map-only."""
    h = F.conv(F.substring(order_key(seed, *id_cols), 1, 8), 16, 10).cast("long")
    return df.where(h < int(fraction * 2**32))


def fixed_sample(df: DataFrame, n: int, seed: str, id_cols: list[str]) -> DataFrame:
    return df.orderBy(order_key(seed, *id_cols), *id_cols).limit(n)


def coverage(df: DataFrame, strata: list[str], k: int) -> DataFrame:
    """Strata with fewer rows than the quota."""
    return df.groupBy(*strata).agg(F.count("*").alias("n")).where(F.col("n") < k)


def interval_coverage(df: DataFrame, stratum: str, id_col: str, hit: str, k: int, seeds: int, z: float = 1.96) -> DataFrame:
    """``seeds, covered, covered_fpc, covered_stratified, mean_margin, mean_margin_fpc``: how often intervals hold the known share.

    ``k`` rows per stratum are drawn for each seed.  Intervals are the plain normal one, with the finite-population correction, and
    of the stratified estimate (strata weighted by size, corrected in each).  One shuffle of at most ``k`` rows per stratum, seed and task.
    """
    sizes = df.groupBy(stratum).agg(F.count("*").alias("__all"), F.count_if(hit).alias("__hits"))
    total = sizes.agg(F.sum("__all").alias("__n"), (F.sum("__hits") / F.sum("__all")).alias("__p"))
    d = df.select(stratum, id_col, F.col(hit).alias("__hit")).withColumn("__seed", F.explode(F.sequence(F.lit(0), F.lit(seeds - 1))))
    order = F.md5(F.concat_ws("|", F.concat(F.lit("cover"), F.col("__seed").cast("string")), F.col(id_col).cast("string")))
    d = d.withColumn("__nth", F.row_number().over(Window.partitionBy("__seed", stratum).orderBy(order, id_col))).where(F.col("__nth") <= k)
    cells = d.groupBy("__seed", stratum).agg(F.count("*").alias("m"), F.count_if("__hit").alias("x")).join(F.broadcast(sizes), stratum)  # as many rows as strata
    cells = cells.crossJoin(F.broadcast(total))
    w, p = F.col("__all") / F.col("__n"), F.col("x") / F.col("m")
    spread = F.when(F.col("m") > 1, w * w * p * (1.0 - p) / (F.col("m") - 1) * (1.0 - F.col("m") / F.col("__all"))).otherwise(0.0)
    s = cells.groupBy("__seed", "__n", "__p").agg(F.sum("m").alias("m"), F.sum("x").alias("x"), F.sum(w * p).alias("ps"), F.sum(spread).alias("vs"))
    share = F.col("x") / F.col("m")
    plain = F.lit(z) * F.sqrt(share * (1.0 - share) / F.col("m"))
    fpc = plain * F.sqrt((F.col("__n") - F.col("m")) / F.greatest(F.col("__n") - 1, F.lit(1)))
    inside = lambda mid, half: F.count_if(F.abs(mid - F.col("__p")) <= half + 1e-12)
    return s.agg(
        F.count("*").alias("seeds"), inside(share, plain).alias("covered"), inside(share, fpc).alias("covered_fpc"), inside(F.col("ps"), F.lit(z) * F.sqrt("vs")).alias("covered_stratified"),
        F.round(F.avg(plain), 6).alias("mean_margin"), F.round(F.avg(fpc), 6).alias("mean_margin_fpc"),
    )


def sample_then_fetch(index: DataFrame, docs: DataFrame, strata: list[str], k: int, seed: str, id_col: str, rows: int = 200_000) -> DataFrame:
    """Bodies of a sample drawn from the narrow index; ids are broadcast while they are few."""
    ids = stratified_sample(index, strata, k, seed, [id_col]).select(id_col)
    few = ids.limit(rows + 1).count() <= rows
    return docs.join(F.broadcast(ids) if few else ids, id_col, "left_semi")


def cluster_profile(embeddings: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """Sizes of k-means clusters: the fast grouping that other studies used."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = embeddings.select("vec_id", array_to_vector(F.col("embedding").cast("array<double>")).alias("features"))
    return KMeans(k=k, seed=seed, maxIter=10).fit(v).transform(v).groupBy(F.col("prediction").alias("cluster")).agg(F.count("*").alias("n"))
