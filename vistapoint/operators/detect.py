"""The front door: top-k places by the method that suits the query."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.query import ClusterOptions, Query
from ..session import kept
from . import matrix, sampler, sampling

#: Grids of more cells than this are answered from clustered samples, unless an exact method is asked for.
EXACT_CELLS = 500_000
SAMPLED = ("single_sample", "clustered")


def choose(fovs: DataFrame, query: Query, method: str = "auto") -> str:
    """The method behind auto (by the size of the grid) and exact (by the number of pairs)."""
    if method == "auto":
        method = "exact" if query.grid.cells <= EXACT_CELLS else "clustered"
    return matrix.plan(fovs, query) if method == "exact" else method


def detect(fovs: DataFrame, query: Query, method: str = "auto", options: ClusterOptions | None = None, fraction: float = 0.3, salt: str = "s0") -> DataFrame:
    """rank, cell_x, cell_y, ci. method: auto, exact, naive, optimized, tiled, single_sample or clustered.

    auto may answer from samples, so its result also says how: method, and sampled, whether ci is an estimate. Tiled is a
    physical form of optimized with the same sums, picked by the number of pairs, so auto names both optimized.
    """
    used = choose(fovs, query, method)
    if used == "clustered":
        top = sampler.run(fovs, query, options or ClusterOptions())[0]
    elif used == "single_sample":
        sample = kept(sampling.exact_size(matrix.candidates(fovs, query), fraction, salt))  # several passes follow; hashes are slow
        top = matrix.best_cells(sample, query, matrix.plan(sample, query))
    else:
        top = matrix.best_cells(fovs, query, used)
    named = "optimized" if used == "tiled" else used
    return top.withColumns({"method": F.lit(named), "sampled": F.lit(used in SAMPLED)}) if method == "auto" else top


class ResultCache:
    """Answers of equal queries, kept as Parquet in a folder that driver and executors share.

    An answer is named by the caller's name for the state of the data, the query and all that decides the method, so a
    changed table, model or grid is another answer. Two sessions may compute the same answer; either file will do.
    """

    def __init__(self, folder: str) -> None:
        self.folder = folder

    def path(self, version: str, query: Query, method: str, options: ClusterOptions | None = None) -> str:
        return f"{self.folder}/{hashlib.sha256(repr((version, query, method, options)).encode()).hexdigest()}"

    def detect(self, fovs: DataFrame, version: str, query: Query, method: str = "auto", options: ClusterOptions | None = None) -> DataFrame:
        """As ``detect``; ``version`` names the state of the table behind ``fovs``."""
        spark, where = fovs.sparkSession, self.path(version, query, method, options)
        done = spark._jvm.org.apache.hadoop.fs.Path(f"{where}/_SUCCESS")
        if not done.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(done):
            detect(fovs, query, method, options).write.mode("overwrite").parquet(where)
        return spark.read.parquet(where).orderBy("rank")
