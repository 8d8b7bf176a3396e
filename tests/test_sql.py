"""Every query with SQL against DuckDB, on the smallest tables."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry
from comotion import queries as movement

NAMES = sorted(movement.SQL)


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for f in glob.glob(f"{small}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return con


def plain(v):
    return int(v) if isinstance(v, bool) else round(v, 3) if isinstance(v, float) else v


@pytest.mark.parametrize("name", NAMES)
def test_same_rows(spark, small, duck, name):
    df = movement.QUERIES[name](spark, small)
    cols = sorted(df.columns)
    got = sorted((tuple(map(plain, (r[c] for c in cols))) for r in df.collect()), key=repr)
    r = duck.execute(movement.SQL[name])
    names = [c[0] for c in r.description]
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    assert sorted((tuple(plain(x[i]) for i in at) for x in r.fetchall()), key=repr) == got


def test_entry(spark, small):
    assert entry.entry(spark).count() == 5


def test_streamed_convoys_equal_batch(spark, small):
    from pyspark.sql import functions as F

    from comotion.operators.local import local_convoys
    from comotion.sources import trajectories as T
    from comotion.sources.files import scratch
    from comotion.streaming import stream

    p = movement.PARAMS["planted"]
    samples = T.planted(spark, small)
    path = scratch(spark)
    rows = samples.withColumn("ts", F.timestamp_seconds(F.col("t") * 3600))
    rows.repartition(1).write.parquet(path)
    late = rows.limit(1).select(F.lit(-1).cast("long").alias("oid"), F.lit(200_000).cast("long").alias("t"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"), F.timestamp_seconds(F.lit(200_000 * 3600)).alias("ts"))
    late.coalesce(1).write.mode("append").parquet(path)  # a last sample moves the watermark past all others
    source = lambda s, d: s.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)
    got = stream.convoys(source, p, lambda: F.when(F.col("oid") < 0, 1).otherwise(0))(spark, small)
    want = {(",".join(map(str, v)), a, z) for v, a, z in local_convoys([tuple(r) for r in samples.collect()], p)}
    assert {tuple(r) for r in got.collect()} == want


def test_lifetime_union(spark):
    from comotion.functions.sql import lifetime_union

    rows = [(1, 0, 3), (1, 4, 5), (1, 8, 9), (1, 2, 2), (1, 8, 8), (1, None, 4), (2, None, None), (3, 0, 10), (3, 2, 3), (3, 11, 11), (3, 13, 13)]
    got = spark.createDataFrame(rows, "g int, a long, z long").groupBy("g").agg(lifetime_union("a", "z").alias("u")).collect()
    assert {r.g: [tuple(x) for x in r.u] for r in got} == {1: [(0, 5), (8, 9)], 2: [], 3: [(0, 11), (13, 13)]}


@pytest.mark.parametrize("timed", (False, True))
def test_polyline_omega(spark, timed):
    import numpy as np
    from pyspark.sql import functions as F

    from comotion.functions import geometry as G
    from comotion.functions.sql import polyline_omega

    rng = np.random.default_rng(3)
    seg = "array<struct<t0:long,x0:double,y0:double,t1:long,x1:double,y1:double>>"

    def line(n, t):
        x = rng.normal(0, 5, (n + 1, 2)).tolist()
        return [(t + 2 * i, *x[i], t + 2 * i + 2, *x[i + 1]) for i in range(n)]

    rows = [(i, line(rng.integers(1, 6), int(rng.integers(0, 6))), line(rng.integers(1, 6), int(rng.integers(0, 6)))) for i in range(40)]
    rows += [(90, None, line(2, 0)), (91, [], line(2, 0)), (92, line(2, 0), line(2, 50)), (93, line(2, 0), None)]
    df = spark.createDataFrame(rows, f"i int, a {seg}, b {seg}")
    got = {r.i: r.w for r in df.select("i", polyline_omega(F.col("a"), F.col("b"), timed).alias("w")).collect()}
    one = df.select("i", F.explode("a").alias("p"), "b").select("i", "p", F.explode("b").alias("q")).filter("p.t0 <= q.t1 and q.t0 <= p.t1")
    names = ("t0", "x0", "y0", "t1", "x1", "y1")
    p, q = (tuple(F.col(f"{v}.{c}") for c in names) for v in "pq")
    pick = lambda v: tuple(v[k] for k in (1, 2, 4, 5))
    gap = G.dist_cpa(p, q) if timed else G.dist_ss(pick(p), pick(q))
    want = {r.i: r.w for r in one.groupBy("i").agg(F.min(gap).alias("w")).collect()}
    assert set(got) == {r[0] for r in rows} and all(got[i] is None for i in (90, 91, 92, 93))
    assert {i: round(w, 9) for i, w in got.items() if w is not None} == {i: round(w, 9) for i, w in want.items()}
