"""Lineage cuts and global positions."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def shared_dir(spark) -> str:
    """The folder that driver and executors share. Without one a local session (as in tests) gets a folder of its own; a cluster's raises."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not sc.master.startswith("local["):
                raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
            folder = tempfile.mkdtemp(prefix="skyweave-")
        sc.setCheckpointDir(folder)
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a table written to the shared folder: computed once, where a checkpoint computes its rows twice."""
    path = f"{shared_dir(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def global_index(df: DataFrame, order: list, name: str = "t") -> DataFrame:
    """0-based position in the total order ``order`` without a single-task window: a range-partitioned sort is written
    once, then each row adds its partition's offset (one row per partition) to its place in the partition."""
    at = F.monotonically_increasing_id()
    placed = cut(df.orderBy(*order).withColumn("_m", at)).withColumn("_part", F.shiftright("_m", 33)).withColumn("_row", F.col("_m").bitwiseAND(F.lit((1 << 33) - 1)))
    sizes = placed.groupBy("_part").agg(F.count("*").alias("_n")).orderBy("_part").collect()  # one row per partition
    total, offsets = 0, []
    for r in sizes:
        offsets += [F.lit(r["_part"]), F.lit(total)]
        total += r["_n"]
    shift = F.create_map(*offsets)[F.col("_part")] if offsets else F.lit(0)
    return placed.withColumn(name, (F.col("_row") + shift).cast("long")).drop("_m", "_part", "_row")
