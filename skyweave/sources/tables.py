"""Tables, schema contracts, map files and solver state."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

TOD = T.StructType([T.StructField("interval_id", T.LongType()), T.StructField("t", T.LongType()), T.StructField("pix", T.LongType()), T.StructField("phi", T.DoubleType()), T.StructField("d", T.DoubleType())])
MAP = T.StructType([T.StructField("pix", T.LongType()), T.StructField("stokes", T.ByteType()), T.StructField("v", T.DoubleType())])
BLOCKS = "block_id long, interval_id long, t0 long, core_lo int, core_hi int, noise_id int, upix array<long>, lpix array<int>, phi array<double>, d array<double>"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def require_columns(df: DataFrame, *names: str) -> DataFrame:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing; there are {df.columns}")
    return df


def write_map(m: DataFrame, path: str, fmt: str = "parquet", mode: str = "error") -> None:
    require_columns(m, "pix", "stokes", "v").write.format(fmt).mode(mode).save(path)


def read_map(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.schema(MAP).format(fmt).load(path)


def save_state(spark: SparkSession, path: str, iteration: int, **vectors) -> None:
    """Solver vectors (name -> numpy array) of one iteration, restartable by load_state."""
    rows = [(k, i, float(x)) for k, v in vectors.items() for i, x in enumerate(v.ravel())]
    spark.createDataFrame(rows, "name string, k long, v double").write.mode("overwrite").parquet(f"{path}/iteration={iteration}")


def load_state(spark: SparkSession, path: str) -> tuple[int, dict]:
    import numpy as np

    rows = spark.read.parquet(path)
    last = rows.agg({"iteration": "max"}).first()[0]
    out: dict = {}
    for r in rows.where(f"iteration = {last}").orderBy("name", "k").collect():
        out.setdefault(r["name"], []).append(r["v"])
    return int(last), {k: np.array(v) for k, v in out.items()}
