"""What several training-data operators share: durable cuts of lineage and bounded prefix sums."""

from __future__ import annotations

import atexit
import contextlib
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: ASCII white space of the operator contracts.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. A session that names none gets a temporary one if it runs on this machine alone, else an error."""
    sc = spark.sparkContext
    if (named := sc.getConf().get("spark.checkpoint.dir")) is None:
        current = sc._jsc.sc().getCheckpointDir()
        if current.isDefined():
            named = current.get()
        elif re.match(r"local(\[|$)", sc.master):
            named = tempfile.mkdtemp(prefix="filekind-")
            atexit.register(shutil.rmtree, named, ignore_errors=True)
        else:
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(named)
    return named


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Paths of the stashes that stand, in the order of their writing.
_STANDING: list[str] = []


def stash(df: DataFrame) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: a cut of the lineage that any executor can read again."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stash-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _STANDING.append(path)
    return spark.read.schema(df.schema).parquet(path)


def _remove(spark: SparkSession, place: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(place)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def discard(df: DataFrame) -> None:
    """Remove a stash that no later plan reads."""
    for place in {f.rpartition("/")[0] for f in df.inputFiles()}:
        if "/stash-" in place:
            _remove(df.sparkSession, place)
            _STANDING[:] = [p for p in _STANDING if p.rpartition("/")[2] != place.rpartition("/")[2]]


def stash_alone(make: Callable[[], DataFrame]) -> DataFrame:
    """stash(make()), after which the stashes that make() wrote on its way are removed."""
    first = len(_STANDING)
    out = stash(make())
    for path in _STANDING[first:-1]:
        _remove(out.sparkSession, path)
    del _STANDING[first:-1]
    return out


@atexit.register
def _sweep() -> None:
    """Remove what still stands when the driver ends in good order."""
    if _STANDING and (spark := SparkSession.getActiveSession()) is not None:
        with contextlib.suppress(Exception):  # the session's other half may be gone already
            for path in _STANDING:
                _remove(spark, path)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


#: Rows and bytes of texts that go to a Python task in one batch.
BATCH = {"spark.sql.execution.arrow.maxRecordsPerBatch": 1024, "spark.sql.execution.arrow.maxBytesPerBatch": 4 << 20}


def small_batches(spark: SparkSession) -> None:
    """Bound what an executor and its Python workers hold of texts at once. Smaller bounds of the session stay; results do not depend on them.

    The session keeps the bounds, as a plan that is returned is made when its rows are written.
    """
    for name, most in BATCH.items():
        now = spark.conf.get(name)
        now = int(now) if re.fullmatch(r"-?\d+", now) else spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(now)
        spark.conf.set(name, str(min(now, most) if now > 0 else most))


def clean_text(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


#: Rows of numbers and short names up to which a counted table is broadcast, and measured bytes up to which any table is.
BROADCAST_ROWS, BROADCAST_BYTES = 200_000, 32 << 20
#: What a row and a value take in a hashed table besides their characters.
ROW_BYTES, VALUE_BYTES = 64, 16


def measured(df: DataFrame) -> int:
    """Bytes that a (stashed) table takes when it is broadcast, about: one aggregate over it. Strings and arrays of strings count in full."""
    size = F.lit(ROW_BYTES + VALUE_BYTES * len(df.columns)).cast("long")
    for c, kind in df.dtypes:
        if kind in ("string", "binary"):
            size = size + F.coalesce(F.octet_length(c), F.lit(0))
        elif kind == "array<string>":
            size = size + F.coalesce(F.aggregate(c, F.lit(0).cast("long"), lambda n, x: n + VALUE_BYTES + F.octet_length(x)), F.lit(0))
        elif kind.startswith("array"):
            size = size + F.coalesce(F.size(c), F.lit(0)) * VALUE_BYTES
    return df.agg(F.coalesce(F.sum(size), F.lit(0))).first()[0]


def offered(df: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """A stashed table for a join: broadcast where its measured bytes are within the limit, else left to a shuffle."""
    return F.broadcast(df) if measured(df) <= limit else df


def sized(df: DataFrame, rows: int) -> DataFrame:
    """df for a join: broadcast where its counted (or bounded) rows are few, else left to a shuffle."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def running_before(df: DataFrame, group: list[str], slice_: str, order: list[Column], sums: dict[str, str], slices: int = 0) -> DataFrame:
    """Add, for each (new name: column) of sums, the total of the column over the rows that come earlier in the group.

    Rows of a group are ordered by the slice number first and by `order` within a slice. Only slice totals meet
    across tasks: a window runs over the slice totals of each group, and another over the rows of each slice, so no
    task holds a whole group. `slices` is the caller's bound on the number of slices of all groups, which decides how the totals travel.
    """
    keys = [*group, slice_]
    totals = df.groupBy(*keys).agg(*(F.sum(c).alias(f"__t_{n}") for n, c in sums.items()))
    earlier = Window.partitionBy(*group).orderBy(slice_).rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(*keys, *(F.coalesce(F.sum(f"__t_{n}").over(earlier), F.lit(0)).alias(f"__o_{n}") for n in sums))
    within = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    out = df.join(sized(offsets, slices), keys)
    for n, c in sums.items():
        out = out.withColumn(n, F.coalesce(F.sum(c).over(within), F.lit(0)) + F.col(f"__o_{n}"))
    return out.drop(*(f"__o_{n}" for n in sums))


def one_row_each(df: DataFrame, keys: dict[str, Column], chosen: DataFrame) -> DataFrame:
    """The rows of df whose keys (null-safe) are in `chosen`, one row for each key, with the columns of df as they are.

    Texts move once, to meet their keys; rows of one key are copies, so which of them stays makes no difference.
    """
    own = df.columns
    named = df.withColumns({f"__k_{n}": c for n, c in keys.items()})
    # Null keys become empty, with a flag, so that the join stays an equi-join.
    parts = [f"__k_{n}" for n in keys]
    flat = F.concat_ws("\x1f", *(F.coalesce(F.col(p).cast("string"), F.lit("\x00")) for p in parts))
    wanted = chosen.select(*(F.col(n).alias(f"__k_{n}") for n in keys)).select(flat.alias("__key")).distinct()
    met = named.withColumn("__key", flat).join(wanted, "__key", "left_semi")
    first = Window.partitionBy("__key").orderBy("__key")
    return met.withColumn("__nth", F.row_number().over(first)).where("__nth = 1").select(*own)
