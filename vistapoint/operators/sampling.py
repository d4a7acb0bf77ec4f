"""Samples of fields of view, all decided by hashes of their ids, so that recomputation cannot change them."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.noise import u01

#: Parts that one counting pass splits an interval of hashes into, and rows of the last part that may be ordered in one task.
PARTS, CUT_ROWS = 4096, 100_000


def by_fraction(fovs: DataFrame, fraction: float, salt: str = "s0") -> DataFrame:
    """About that share, without a shuffle."""
    return fovs.where(u01(salt, "fov_id") < fraction)


def exact_size(fovs: DataFrame, fraction: float, salt: str = "s0") -> DataFrame:
    """Exactly ceil(fraction * n) rows, uniform and without repetition: those with the smallest hashes.

    The last hash that counts is found by counting in ever finer parts of [0, 1), so no task gathers the sample and the
    result is a plain filter. Of a cut part, no more than CUT_ROWS rows are ordered.
    """
    noise = u01(salt, "fov_id")
    hashes = fovs.select(noise.alias("u"), "fov_id")
    n = hashes.count()
    wanted = math.ceil(round(fraction * n, 9))
    if wanted >= n:
        return fovs
    if wanted <= 0:
        return fovs.where("false")
    low, width, part, before = 0.0, 1.0, n, 0
    while part > CUT_ROWS and width > 2**-40:
        inside = hashes.where((F.col("u") >= low) & (F.col("u") < low + width))
        counts = {r.i: r["count"] for r in inside.groupBy(F.floor((F.col("u") - low) / (width / PARTS)).alias("i")).count().collect()}  # at most PARTS rows
        for i in sorted(counts):
            if before + counts[i] >= wanted:
                low, width, part = low + i * (width / PARTS), width / PARTS, counts[i]
                break
            before += counts[i]
    last = hashes.where((F.col("u") >= low) & (F.col("u") < low + width)).orderBy("u", "fov_id").offset(wanted - before - 1).limit(1).first()
    return fovs.where((noise < last.u) | ((noise == last.u) & (F.col("fov_id") <= last.fov_id)))


def batches(fovs: DataFrame, count: int, by: str = "cluster_id", salt: str = "s0", mode: str = "exact", parts: int = 1) -> DataFrame:
    """A column batch from 1 to count: disjoint parts that cover each group. exact: sizes differ by one at most; hash: no sort.

    parts: how many sorts an exact deal of one group is split into. The deal is the same for every number of parts.
    """
    noise = u01(salt, "fov_id")
    if mode != "exact":
        return SAMPLERS[mode](fovs, count, by, noise)
    if parts <= 1:
        return fovs.withColumn("batch", F.ntile(count).over(Window.partitionBy(by).orderBy(noise, "fov_id")))
    cut = fovs.withColumn("_u", noise).withColumn("_part", F.floor(F.col("_u") * parts))
    sizes = cut.groupBy(by, "_part").agg(F.count("*").alias("_n"))
    upto = Window.partitionBy(by).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select(by, "_part", F.coalesce(F.sum("_n").over(upto), F.lit(0)).alias("_before"), F.sum("_n").over(Window.partitionBy(by)).alias("_all"))
    placed = cut.withColumn("_row", F.row_number().over(Window.partitionBy(by, "_part").orderBy("_u", "fov_id"))).join(sizes, [by, "_part"])
    row, least, longer = F.col("_before") + F.col("_row"), F.expr(f"_all div {count}"), F.col("_all") % count
    first = longer * (least + 1)
    dealt = F.when(row <= first, F.ceil(row / (least + 1))).otherwise(longer + F.ceil((row - first) / F.greatest(least, F.lit(1))))
    return placed.withColumn("batch", dealt.cast("int")).select(*fovs.columns, "batch")


def _by_hash(fovs: DataFrame, count: int, by: str, noise: Column) -> DataFrame:
    return fovs.withColumn("batch", (F.floor(noise * count) + 1).cast("int"))


def _by_video(fovs: DataFrame, count: int, by: str, noise: Column) -> DataFrame:
    """Each video's fields of view are spread over the batches one by one, so that every batch sees every long video."""
    turn = F.row_number().over(Window.partitionBy(by, "video_id").orderBy(noise, "fov_id")) + F.floor(u01("turn", "video_id") * count)
    return fovs.withColumn("batch", (F.pmod(turn, F.lit(count)) + 1).cast("int"))


#: Further ways to deal batches: (fields of view, number of batches, group column, noise) -> with a column batch.
SAMPLERS: dict[str, Callable[[DataFrame, int, str, Column], DataFrame]] = {"hash": _by_hash, "by_video": _by_video}


def add_sampler(name: str, deal: Callable[[DataFrame, int, str, Column], DataFrame]) -> None:
    """A sampler of the caller's own, to be named in the options."""
    SAMPLERS[name] = deal


def remaining(fovs: DataFrame, done: int) -> DataFrame:
    """What batches up to ``done`` have not used."""
    return fovs.where(F.col("batch") > done)
