"""Relational operators over rows that crowd together: right results, and work in proportion."""

import numpy as np
from geocensus.plans import relational
from geocensus.sources import index as I


def joined(df):
    """Rows that the joins of an executed plan put out."""

    def walk(p):
        kind = p.nodeName()
        if kind == "AdaptiveSparkPlan":
            return walk(p.executedPlan())
        if kind.endswith("QueryStage"):
            return walk(p.plan())
        own = p.metrics().apply("numOutputRows").value() if "Join" in kind else 0
        return own + sum(walk(p.children().apply(k)) for k in range(p.children().size()))

    return walk(df._jdf.queryExecution().executedPlan())


def test_nearest_in_a_crowd(spark, monkeypatch):
    rng = np.random.default_rng(1)
    crowd = rng.integers(0, 150, (2500, 2)) + [500, 500]
    ids = rng.permutation(2507)
    at = np.vstack([crowd, [[500, 3000], [1900, 3010], [2100, 3990], [-8990, -17990], [-8000, -14001], [8999, 17999], [0, 0]]])
    rows = [(int(k), float(y) / 100, float(x) / 100) for k, (y, x) in zip(ids, at, strict=True)]
    monkeypatch.setattr(relational, "points", lambda s, d: s.createDataFrame([*rows, rows[0], (None, None, None)], "doc_id long, lat double, lon double"))
    ran, stored = [], I.stored
    monkeypatch.setattr(I, "stored", lambda df, label: (ran.append(df), df.collect(), stored(df, label))[-1])
    df = relational._nearest(spark, "")
    got = {r["doc_id"]: r["other"] for r in df.collect()}

    doc, lat, lon = (np.array(c) for c in zip(*rows, strict=True))
    y, x, want = np.floor(lat / 20), np.floor(lon / 20), {}
    for k in range(len(doc)):
        near = (np.abs(y - y[k]) <= 1) & (np.abs(x - x[k]) <= 1) & (doc != doc[k])
        if near.any():
            sq = np.round((lat - lat[k]) ** 2 + (lon - lon[k]) ** 2, 6)[near]
            want[int(doc[k])] = int(doc[near][sq == sq.min()].min())
    assert got == want and len(want) < len(rows)
    assert sum(joined(x) for x in [*ran, df]) < 100 * len(rows)


def test_salted_copies_are_not_broadcast(spark, sf):
    plan = relational._salted(spark, sf)._jdf.queryExecution().toString()
    assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def test_band_compares_within_buckets(spark):
    top = 2.0**53
    prices = [k / 10 for k in range(1000)] + [-7.5, -5.0, -2.5, -0.0, 999.9, 1004.9, 1004.8999999999999, top - 5, top - 1, top, float("inf"), float("nan"), None]
    part = spark.createDataFrame([(k, k % 2 if k < 1000 else 0, p) for k, p in enumerate(prices)] + [(-1, None, 1.0)], "p_partkey long, p_size int, p_retailprice double")
    df = relational._band(part, 5)
    got = [tuple(r) for r in df.collect()]
    rows = [tuple(r) for r in part.collect() if r["p_size"] is not None and r["p_retailprice"] is not None]
    assert sorted(got) == sorted((a, b) for a, x, p in rows for b, y, q in rows if x == y and p < q < p + 5)
    part.createOrReplaceTempView("part")
    sql = spark.sql(relational.oracle_sql()["join_theta"])
    assert sorted(map(tuple, sql.collect())) == sorted(got)


def test_band_plan(spark, sf):
    assert "bucket" in relational.queries()["join_theta"](spark, sf)._jdf.queryExecution().toString()
