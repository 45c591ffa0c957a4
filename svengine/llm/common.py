"""What several operators share: the shared folder, exact ranks without one-task windows, range buckets."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder below spark.checkpoint.dir, which driver and executors share; where it is unset, a local one on a local master only."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = tempfile.mkdtemp(prefix="svengine-")
        spark.sparkContext.setCheckpointDir(root)
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows of df written as Parquet in the shared folder and read again: cuts lineage, survives lost executors.

    Uncompressed: most columns are hashes, and the codecs' direct buffers stay in an executor's native memory until a collection of its heap.
    """
    path = shared_folder(df.sparkSession, name)
    df.write.option("compression", "uncompressed").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.shared_path = path
    return out


def drop(df: DataFrame) -> None:
    """Delete what written() made, once nothing reads it any more."""
    jvm, path = df.sparkSession._jvm, df.shared_path
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(target, True)


#: Bytes of one Arrow batch, but for a row that is larger.
BATCH_BYTES = 4_000_000


def bounded_batches(spark: SparkSession) -> None:
    """From now on the session's Arrow batches have BATCH_BYTES, unless it has a limit of its own. No result depends on batches.

    Spark's limits, 10,000 rows and 64 MB, leave a task's whole split of texts in one batch. Each is there four times or more (native buffers of the
    executor, where growing doubles them, both ways, and in the Python worker), and what the allocators keep of that stays with the executor.
    """
    if spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None) is None:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows that one window group of ranked() holds on average.
RANK_ROWS = 4000


def ranked(df: DataFrame, group: list[str], order: list[str], out: str = "rank") -> DataFrame:
    """df with a gapless rank from 0 in each group, whatever a group's size.

    Rows of a group are dealt to hash buckets of their order columns; a window ranks within a bucket, and a
    window over the much smaller table of bucket counts gives each bucket's start. No task gets a whole group.
    df must be stable (a written table). Ties are ranked one after another.
    """
    buckets = df.count() // RANK_ROWS + 1
    dealt = df.withColumn("_bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)))
    local = Window.partitionBy(*group, "_bucket").orderBy(*order)
    starts = (
        dealt.groupBy(*group, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
        .withColumn("_start", F.coalesce(F.sum("_n").over(Window.partitionBy(*group).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .drop("_n")
    )
    return (
        dealt.withColumn("_local", F.row_number().over(local) - 1)
        .join(starts, [*group, "_bucket"])
        .withColumn(out, (F.col("_start") + F.col("_local")).cast("long"))
        .drop("_bucket", "_start", "_local")
    )


#: A key with more than this share of all rows is hot; there are at most HOT_SHARE such keys.
HOT_SHARE = 1024


def looked_up(rows: DataFrame, found: DataFrame, key: str, n: str, total: int | None = None) -> DataFrame:
    """rows joined with found, which has a row for each value of key, with the number n of its rows.

    Rows of hot keys get their row of found by broadcast (of at most HOT_SHARE rows), wherever they lie; the others are
    shuffled by key. So no task gets all rows of a hot key. Both must be stable (written) tables; n is kept as a column.
    """
    total = rows.count() if total is None else total
    hot = F.broadcast(found.where(F.col(n) * HOT_SHARE > total))
    cold = rows.join(F.broadcast(hot.select(key)), key, "left_anti")
    return rows.join(hot, key).unionByName(cold.join(found.where(F.col(n) * HOT_SHARE <= total), key))


#: Ranges that in_ranges() finds by quantiles; they are cut further by arithmetic.
COARSE = 256


def in_ranges(rows: DataFrame, key: str, size: Column, most: int, out: str = "part") -> DataFrame:
    """rows with the range of their key (long, not null): a number that rises with the key, for ranges of about `most` of size each.

    At most COARSE ranges of about equal rows come from quantiles; each is cut into pieces of equal width in the key, as many as its
    size asks for. So driver and plan hold COARSE bounds at any input size. Ranges are even as far as keys are evenly spread inside each.
    """
    shares = [i / COARSE for i in range(1, COARSE)]
    bounds, sum_ = rows.select(F.percentile_approx(key, shares, 20 * COARSE), F.sum(size)).first()
    bounds = np.array(sorted(set((bounds or [])[:: max(1, COARSE * most // max(1, sum_ or 0))])), np.int64)  # fewer where fewer ranges are asked for
    dealt = rows.withColumn("_coarse", _place(key, bounds))
    got = dealt.groupBy("_coarse").agg(F.min(key).alias("lo"), F.max(key).alias("hi"), F.sum(size).alias("size")).orderBy("_coarse").collect()  # COARSE rows at most
    n = len(bounds) + 1
    lo, width, first, sum_ = np.zeros(n, np.int64), np.ones(n), np.zeros(n, np.int64), 0
    for c, least, greatest, total in got:
        pieces = max(1, min(-(-(total or 0) // most), greatest - least + 1))
        lo[c], width[c], first[c], sum_ = least, (greatest - least + 1) / pieces, sum_, sum_ + pieces
    at = lambda values: F.get(F.lit(values), F.col("_coarse"))
    return dealt.withColumn(out, (at(first) + F.floor((F.col(key) - at(lo)) / at(width))).cast("long")).drop("_coarse")


def _place(key: str, bounds: np.ndarray) -> Column:
    """How many of the ascending bounds are <= key; looked up in two steps, so that a row costs the root of the number of bounds."""
    if not len(bounds):
        return F.lit(0)
    width = max(1, int(len(bounds) ** 0.5))
    part = F.size(F.filter(F.lit(bounds[::width]), lambda x: x <= F.col(key)))
    inside = F.slice(F.lit(bounds), F.greatest(part - 1, F.lit(0)) * width + 1, F.lit(width))
    return F.greatest(part - 1, F.lit(0)) * width + F.size(F.filter(inside, lambda x: x <= F.col(key)))
