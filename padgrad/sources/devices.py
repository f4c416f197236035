"""Splits of examples over devices, and the simulated fleet."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from padgrad.shared import written

#: MAC rates of the four device classes and of the server, link rates, failure chance, header share.
CLASS_RATES = (25e6, 5e6, 2.5e6, 1.25e6)
SERVER_RATE, DOWN_RATE, UP_RATE, FAILURE, HEADER = 8.24e12, 10e6, 5e6, 0.1, 0.1


def ranked(df: DataFrame, label: str, key: str) -> tuple[DataFrame, int]:
    """``df`` with ``place`` (0-based in the order of ``label``, ``key``; nulls first), and the number of rows.

    Rows are range-partitioned and sorted once and written with their place in their
    partition; the counts before each partition (a row for each) are added. Ranges come from a sample,
    so outliers and wide keys do no harm, and every row stays, whatever is null. Rows that are alike in
    label and key are told apart by their hash.
    """
    kept = df.columns
    cut = df.withColumn("__h", F.xxhash64(*kept)).repartitionByRange(label, key, "__h").sortWithinPartitions(label, key, "__h")
    # the id counts rows from 0 in each partition and has the partition above its lowest 33 bits
    cut = written(cut.drop("__h").withColumn("__at", F.monotonically_increasing_id()), "ranked")
    part, inner = F.shiftright("__at", 33), F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    counts = cut.groupBy(part.alias("__p")).agg(F.count("*").alias("__n"))
    n = counts.agg(F.sum("__n")).first()[0] or 0
    before = F.sum("__n").over(Window.partitionBy().orderBy("__p").rowsBetween(Window.unboundedPreceding, -1))
    counts = counts.withColumn("__before", F.coalesce(before, F.lit(0))).drop("__n")  # a row for each partition
    out = cut.withColumn("__p", part).join(F.broadcast(counts), "__p")
    return out.withColumn("place", F.col("__before") + inner).select(*kept, "place"), n


def split_sorted(df: DataFrame, label: str, key: str, devices: int) -> DataFrame:
    """Non-iid split: sorted by label, cut into equal parts (the first ones hold one row more)."""
    out, n = ranked(df, label, key)
    size, more = divmod(n, devices)
    edge = more * (size + 1)
    place = F.col("place")
    device = F.when(place < edge, F.expr(f"place div {size + 1}")).otherwise(F.lit(more) + F.expr(f"(place - {edge}) div {max(1, size)}"))
    return out.withColumn("device", device.cast("int")).drop("place")


def split_hash(df: DataFrame, key: str, devices: int) -> DataFrame:
    """iid split."""
    return df.withColumn("device", F.pmod(F.xxhash64(key), F.lit(devices)).cast("int"))


def split_by_column(df: DataFrame, owner: str) -> DataFrame:
    """Natural split: the owner is the device."""
    return df.withColumn("device", F.col(owner).cast("int"))


def class_of_region(region: Column) -> Column:
    return F.greatest(region - 1, F.lit(0)).cast("int")


def fleet(nation: DataFrame) -> DataFrame:
    """25 devices in four classes (10, 5, 5, 5) from nations and their regions."""
    kind = class_of_region(F.col("n_regionkey"))
    tau = F.element_at(F.array(*[F.lit(x) for x in CLASS_RATES]), kind + 1)
    return nation.select(
        F.col("n_nationkey").cast("int").alias("device"), kind.alias("class"), tau.alias("tau"),
        F.lit(FAILURE).alias("p_fail"), F.lit(UP_RATE).alias("gamma_u"), F.lit(DOWN_RATE).alias("gamma_d"),
    )
