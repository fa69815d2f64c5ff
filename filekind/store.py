"""Durable intermediate tables in the session's shared folder."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. A session that names none gets a temporary one if it runs on this machine alone, else an error."""
    sc = spark.sparkContext
    if named := sc.getConf().get("spark.checkpoint.dir"):
        return named
    current = sc._jsc.sc().getCheckpointDir()
    if not current.isDefined():
        if not re.match(r"local(\[|$)", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(made := tempfile.mkdtemp(prefix="filekind-"))
        atexit.register(shutil.rmtree, made, ignore_errors=True)
        current = sc._jsc.sc().getCheckpointDir()
    return current.get()


#: Bytes up to which a measured table is broadcast, and what a row and a value take besides their characters.
BROADCAST_BYTES, ROW_BYTES, VALUE_BYTES = 32 << 20, 64, 16


def measured(df: DataFrame) -> int:
    """Bytes that a table of numbers and strings takes when it is broadcast, about: one aggregate over it."""
    size = F.lit(ROW_BYTES + VALUE_BYTES * len(df.columns)).cast("long")
    for c, kind in df.dtypes:
        if kind == "string":
            size = size + F.coalesce(F.octet_length(c), F.lit(0))
    return df.agg(F.coalesce(F.sum(size), F.lit(0))).first()[0]


def offered(df: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """A kept table for a join: broadcast where its measured bytes are within the limit, else left to a shuffle."""
    return F.broadcast(df) if measured(df) <= limit else df


def keep(df: DataFrame) -> DataFrame:
    """Write df once and read it back, so that later jobs neither recompute it nor depend on executors' disks."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/kept-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


_MADE: dict[tuple, DataFrame] = {}


def once(spark: SparkSession, key: tuple, make) -> DataFrame:
    """A kept table for each key and application: several queries over the same data share it."""
    full = (spark.sparkContext.applicationId, *key)
    if full not in _MADE:
        _MADE[full] = keep(make())
    return _MADE[full]
