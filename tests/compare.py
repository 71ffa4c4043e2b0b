"""Runs queries and their SQL side by side: ``python tests/compare.py SF_DIR [NAME...]``."""

from __future__ import annotations

import os
import sys
import time
import traceback

import duckdb
import numpy as np
import pandas as pd

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def session():  # noqa: ANN201
    from pyspark.sql import SparkSession

    s = SparkSession.builder.master(f"local[{os.environ.get('CPUS', '4')}]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    return s


def duck(sf: str):  # noqa: ANN201
    c = duckdb.connect()
    for t in TABLES:
        p = f"{sf}/{t}.parquet"
        c.execute(f"create view {t} as select * from '{p}{'/*.parquet' if os.path.isdir(p) else ''}'")
    return c


def rows(frame) -> list[tuple]:  # noqa: ANN001
    names = sorted(frame.columns)
    return sorted((tuple(None if pd.isna(x) else str(x) if not isinstance(x, (int, float, np.number)) or isinstance(x, bool) else round(float(x), 9) for x in r) for r in frame[names].astype(object).itertuples(index=False)), key=str)


def same(spark_frame, duck_frame) -> str:  # noqa: ANN001
    if sorted(spark_frame.columns) != sorted(duck_frame.columns):
        return f"columns {sorted(spark_frame.columns)} {sorted(duck_frame.columns)}"
    kinds = {c: (str(spark_frame[c].dtype), str(duck_frame[c].dtype)) for c in spark_frame.columns if len(spark_frame) and str(spark_frame[c].dtype).split("[")[0] != str(duck_frame[c].dtype).split("[")[0]}
    a, b = rows(spark_frame), rows(duck_frame)
    if a != b:
        odd = [(x, y) for x, y in zip(a, b, strict=False) if x != y][:2]
        return f"rows {len(a)} {len(b)} {str(odd)[:500]} {kinds}"
    return f"ok {len(a)}" + (f" types {kinds}" if kinds else "")


if __name__ == "__main__":
    import __spark_entry__ as entry

    s, c = session(), duck(sys.argv[1])
    queries, sql = entry.queries(), entry.oracle_sql()
    for name in sys.argv[2:] or [k for k in queries if not k.startswith("op") and k != "pipeline"]:
        began = time.time()
        try:
            got = queries[name](s, sys.argv[1]).toPandas()
            said = same(got, c.execute(sql[name]).df()) if name in sql else f"no sql, {len(got)} rows"
        except Exception:
            said = "ERROR " + " ".join(traceback.format_exc().splitlines()[-3:])[:600]
        print(f"{name}: {said} ({time.time() - began:.1f} s)", flush=True)
