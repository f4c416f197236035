"""Every catalogued query with an SQL twin matches it; streams, splits, edge tables."""

import math
from collections import Counter

import numpy as np
import pyarrow.compute as pc
import pytest
from pyspark.sql import functions as F

from padgrad.operators import moments
from padgrad.operators.training import CodedTables, train_coded_spark
from padgrad.plans import catalog
from padgrad.sources.devices import split_sorted

SF = "/root/testdata/sf0.01"


def plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    if hasattr(v, "isoformat"):
        return str(v)
    return round(float(v), 6) if isinstance(v, float) or type(v).__name__ == "Decimal" else v


@pytest.mark.parametrize("name", sorted(catalog.SQL))
def test_query_matches_sql(spark, duck, name):
    df = catalog.QUERIES[name](spark, SF)
    want = duck.execute(catalog.SQL[name])
    cols = [c[0] for c in want.description]
    assert sorted(cols) == sorted(df.columns)
    got = Counter(tuple(plain(r[c]) for c in cols) for r in df.collect())
    assert got == Counter(tuple(plain(v) for v in r) for r in want.fetchall())


def test_split_of_empty_and_small_tables(spark):
    empty = spark.createDataFrame([], "label int, id long")
    assert split_sorted(empty, "label", "id", 5).count() == 0
    few = spark.createDataFrame([(i % 2, i) for i in range(7)], "label int, id long")
    sizes = Counter(r.device for r in split_sorted(few, "label", "id", 5).collect())
    assert sorted(sizes.values(), reverse=True) == [2, 2, 1, 1, 1]


def test_moment_engines_agree(spark):
    rng = np.random.default_rng(0)
    rows = [(int(i % 3), rng.integers(-5, 5, 4).astype(float).tolist(), [float(i % 2)]) for i in range(50)]
    ex = spark.createDataFrame(rows, "device int, x array<double>, y array<double>").repartition(3)
    a = moments.collect_moments(moments.device_moments(ex, 4, 1), 4, 4, 1)
    b = moments.collect_moments(moments.device_moments(ex, 4, 1, "sql"), 4, 4, 1)
    assert np.array_equal(a[0], b[0]) and np.array_equal(a[1], b[1]) and not a[0][3].any()


def test_epochs_on_tables_equal_local_ones(spark):
    """Any straggler order, a device without rows, every alpha; folders are left to nobody."""
    rng = np.random.default_rng(1)
    D, d, c, m = 5, 3, 2, 100
    g, h = np.stack([(x := rng.normal(size=(20, d))).T @ x for _ in range(D)]), rng.normal(size=(D, d, c))
    g[3], h[3] = 0, 0
    rows = [(i, k, g[i, k].tolist(), h[i, k].tolist()) for i in range(D) if i != 3 for k in range(d)]
    table = spark.createDataFrame(rows, moments.MOMENTS)
    theta = np.zeros((d, c))
    for _ in range(2):
        theta = theta - 0.1 * ((g @ theta - h).sum(axis=0) / m + 0.01 * theta)
    for alpha, orders in ((1, [[0, 1, 2, 3, 4]] * 2), (3, [[0, 3, 4, 1, 2], [2, 1, 0, 4, 3]]), (5, [[3, 0, 1, 2, 4], [4, 3, 2, 1, 0]])):
        got = train_coded_spark(table, D, alpha, m, (d, c), orders, 0.01, lambda e: 0.1).theta
        assert np.abs(got - theta).max() < 1e-6
    with pytest.raises(ValueError, match="answers"):
        CodedTables(table, D, 3, (d, c)).gradient_cells(theta, [0, 1])


def test_moment_pass_at_published_width(spark):
    """2000 features, ten classes, 25 devices whose rows are mixed in every partition: sums are exact and a task holds one matrix."""
    d, c, n = 2000, 10, 100
    rng = np.random.default_rng(2)
    x, y = rng.integers(-3, 4, (n, d)).astype(float), rng.integers(0, 2, (n, c)).astype(float)
    rows = [(k % 25, x[k].tolist(), y[k].tolist()) for k in range(n)]
    ex = spark.createDataFrame(rows, "device int, x array<double>, y array<double>").repartition(2)
    got = moments.device_moments(ex, d, c).where("device in (0, 24)").toArrow()
    for dev in (0, 24):
        own = np.arange(n) % 25 == dev
        part = got.filter(pc.equal(got["device"], dev)).sort_by("i").combine_chunks()
        assert np.array_equal(np.asarray(part["g"].combine_chunks().flatten()).reshape(d, d), x[own].T @ x[own])
        assert np.array_equal(np.asarray(part["h"].combine_chunks().flatten()).reshape(d, c), x[own].T @ y[own])


def test_sorted_split_keeps_every_row(spark):
    rows = [(None, 1), (None, None), (1, 2**62), (1, -(2**62)), (0, None), (0, 5), (1, 5), (1, 5), (1, 5), (None, -1)]
    got = split_sorted(spark.createDataFrame(rows, "label int, id long").repartition(3), "label", "id", 3).collect()
    assert Counter((r.label, r.id) for r in got) == Counter(rows)
    assert sorted(Counter(r.device for r in got).values()) == [3, 3, 4]
    order = [(r.device, r.label is not None, r.label or 0, r.id is not None, r.id or 0) for r in got]
    assert all(a[1:] <= b[1:] for a in order for b in order if a[0] < b[0])


def test_parity_moments_are_unbiased(spark):
    from padgrad.operators.baselines import parity_moments

    rng = np.random.default_rng(4)
    x = rng.normal(size=(600, 4))
    ex = spark.createDataFrame([(k, k % 5, x[k].tolist(), [float(x[k].sum())]) for k in range(600)], "row_id long, device int, x array<double>, y array<double>").repartition(3)
    miss = np.array([0.0, 0.2, 0.4, 0.6, 0.8])
    z = x * np.sqrt(miss[np.arange(600) % 5])[:, None]
    want = z.T @ z
    runs = [parity_moments(ex, 4, 1, 0.8, miss, seed) for seed in range(6)]
    assert np.abs(np.mean([r[0] for r in runs], axis=0) - want).max() < 0.15 * want.max()
    assert np.allclose(runs[0][1], runs[0][0].sum(axis=1, keepdims=True))


def test_shapes_of_the_trade_off(spark):
    rows = catalog.w9_split_contrast(spark, SF).groupBy("scheme").agg(F.max("accuracy").alias("best"), F.max_by("accuracy", "epoch").alias("last")).collect()
    last = {r.scheme: r.last for r in rows}
    assert last["coded_sorted"] >= last["drop_slowest_sorted"] + 0.02
    assert abs(last["coded_hash"] - last["drop_slowest_hash"]) <= abs(last["coded_sorted"] - last["drop_slowest_sorted"])


def test_entry(spark):
    import __spark_entry__

    out = __spark_entry__.entry(spark)
    assert out.count() > 0 and "accuracy" in out.columns


def test_measures_of_the_trade_off(spark):
    """Offsets rise with alpha, epochs get shorter, and all coded schemes walk the same path."""
    t = catalog.planted_descent(spark, SF).where("scheme = 'coded'").groupBy("epoch").agg(F.max("loss_r5").alias("a"), F.min("loss_r5").alias("b")).collect()
    assert all(abs(r.a - r.b) <= 2e-5 for r in t)
    clock = {(r.alpha, r.epoch): r.elapsed_r5 for r in catalog.elapsed_time(spark, SF).where("scheme = 'coded'").collect()}
    first, last = [clock[a, 1] for a in catalog.ALPHAS], [clock[a, catalog.TRACE_EPOCHS] - clock[a, 1] for a in catalog.ALPHAS]
    assert first == sorted(first) and last == sorted(last, reverse=True)


def test_engine_measures_count_shuffles(spark):
    from padgrad.operators.measures import engine_measures

    got = engine_measures(spark, "sum", lambda: spark.range(1000).repartition(3).groupBy((F.col("id") % 7).alias("k")).count().collect())
    assert got["tasks"] >= 3 and got["shuffle_mb"] > 0 and got["wall_s"] > 0


def test_shared_folder_is_asked_for_on_clusters(spark):
    from types import SimpleNamespace

    from padgrad.shared import shared_root

    unset = SimpleNamespace(get=lambda *a: None)
    cluster = SimpleNamespace(conf=unset, sparkContext=SimpleNamespace(getConf=lambda: unset, master="spark://host:7077"))
    with pytest.raises(ValueError, match="checkpoint"):
        shared_root(cluster)
    assert shared_root(spark).startswith("file:") or spark.conf.get("spark.checkpoint.dir", None)


def test_readers_of_other_formats(spark, tmp_path):
    from padgrad.sources.tables import read_examples

    rows = [(0, [1.0, -2.5], 3), (1, [0.0, 4.0], 5)]
    df = spark.createDataFrame(rows, "device int, x array<double>, n long")
    for fmt in ("json", "orc", "parquet"):
        df.write.format(fmt).save(str(tmp_path / fmt))
        got = read_examples(spark, str(tmp_path / fmt), fmt, "device INT, x ARRAY<DOUBLE>, n BIGINT")
        assert sorted(map(tuple, got.collect())) == rows
    df.withColumn("x", F.to_json("x")).write.option("header", True).option("escape", '"').csv(str(tmp_path / "csv"))
    got = read_examples(spark, str(tmp_path / "csv"), "csv", "device INT, x ARRAY<DOUBLE>, n BIGINT")
    assert sorted(map(tuple, got.collect())) == rows


def test_clean_up_deletes_what_the_session_wrote(spark):
    import os

    from padgrad import shared

    given, shared._given = shared._given, []
    try:
        shared.written(spark.range(3).toDF("id"), "gone")
        (_, path) = shared._given[0]
        place = path.removeprefix("file://")
        assert os.path.isdir(place) and shared.clean_up(spark) == 1 and not os.path.isdir(place)
    finally:
        shared._given = given


def test_costs_follow_the_table(spark, tmp_path):
    rows = [([0.0] * 8, k % 3) for k in range(500)]
    spark.createDataFrame(rows, "embedding array<float>, label int").write.parquet(str(tmp_path / "embeddings.parquet"))
    got = {(r.scheme, r.d, r.alpha): r.macs for r in catalog.cost_table(spark, str(tmp_path)).collect()}
    assert got["coded", 8, 1] == 8 * 8 * 3 and got["minibatch", 8, 1] == 2 * 4 * 8 * 3 and got["encode", 8, 6] == 6 * 8 * 11
