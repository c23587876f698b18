"""Compares a query with its SQL on the given tables, as the driver does."""

import math
import time

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows(df, names):
    out = [tuple(round(v, 6) if isinstance(v, float) else v for v in (r[n] for n in names)) for r in df]
    return sorted(out, key=lambda r: tuple((v is None, str(type(v)), v if not isinstance(v, float) or not math.isnan(v) else 0) for v in r))


def same(spark, query, sql, sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    want = con.sql(sql)
    names = sorted(want.columns)
    df = query(spark, sf_dir)
    assert sorted(df.columns) == names
    want = [dict(zip(want.columns, r)) for r in want.fetchall()]
    assert rows([r.asDict() for r in df.collect()], names) == rows(want, names)


def shuffled(spark, least=0, wait=20):
    """Bytes of shuffle files on this machine; waits until they fall to ``least``, as Spark deletes them a little later."""
    for _ in range(wait * 5):
        files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        sizes = [files.apply(k).length() for k in range(files.size()) if files.apply(k).getName().startswith("shuffle_")]
        if sum(sizes) <= least:
            break
        time.sleep(0.2)
    return sum(sizes)
