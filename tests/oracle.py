"""Runs a registered query and its SQL side by side on the given tables."""

import math
import os
import shutil
import tempfile

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    import duckdb

    c = duckdb.connect()
    for t in TABLES:
        if os.path.exists(f"{sf_dir}/{t}.parquet"):
            glob = f"{sf_dir}/{t}.parquet" + ("/*.parquet" if os.path.isdir(f"{sf_dir}/{t}.parquet") else "")
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{glob}')")
    return c


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else float(f"{v:.9g}") + 0.0
    if hasattr(v, "asDict"):
        return tuple(plain(x) for x in v)
    if isinstance(v, dict):
        return tuple(plain(x) for x in v.values())
    if isinstance(v, (list, tuple)):
        return tuple(plain(x) for x in v)
    if hasattr(v, "is_finite"):
        return plain(float(v))
    return v.isoformat() if hasattr(v, "isoformat") else v


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return [columns[i] for i in order], sorted((tuple(plain(r[i]) for i in order) for r in rows), key=repr)


def stored(spark, df):
    """The frame written as Parquet and read back, as its users would; names may not clash whatever their case."""
    names = [c.lower() for c in df.columns]
    assert len(set(names)) == len(names), f"columns clash: {df.columns}"
    path = tempfile.mkdtemp(prefix="query-")
    try:
        df.write.mode("overwrite").parquet(path)
        read = spark.read.schema(df.schema).parquet(path)
        return read.columns, read.collect()
    finally:
        shutil.rmtree(path)


def differences(spark, sf_dir, query, sql):
    """None if equal, else a short description."""
    got_cols, got = rows_of(*stored(spark, query(spark, sf_dir)))
    cur = connect(sf_dir).execute(sql)
    want_cols, want = rows_of([d[0] for d in cur.description], cur.fetchall())
    if got_cols != want_cols:
        return f"columns {got_cols} but {want_cols}"
    if len(got) != len(want):
        return f"{len(got)} rows but {len(want)}: {got[:3]} {want[:3]}"
    bad = [(g, w) for g, w in zip(got, want) if g != w]
    return f"{len(bad)} of {len(got)} rows differ, e.g. {bad[0]}" if bad else None
