"""Work with the session as given: ship this package to the executors, name a checkpoint folder."""

from __future__ import annotations

import gc
import itertools
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: Tables after which the driver is made to let go of what the rounds before have left.
LET_GO_EVERY = 8
_TABLES = itertools.count(1)
_SHIPPED: set[str] = set()
_STAYING, _STAY = [0, None], threading.Lock()  # how many want it at present, and the session's own setting


def ship(spark: SparkSession) -> None:
    """Executors import the package from an archive that the driver serves, once for each application."""
    context = spark.sparkContext
    if context.applicationId not in _SHIPPED:
        home = Path(__file__).resolve().parent
        archive = shutil.make_archive(str(Path(tempfile.mkdtemp(prefix="package-")) / home.name), "zip", home.parent, home.name)
        context.addPyFile(archive)
        _SHIPPED.add(context.applicationId)


def checkpoint_dir(spark: SparkSession) -> None:
    """Make sure a checkpoint folder is set: the one that spark.checkpoint.dir names; without one, a temporary folder, but only where
    driver and executors are one machine."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))


def checkpointed(df: DataFrame) -> DataFrame:
    """Write df to the shared checkpoint folder and go on from there; a lost executor then costs no recomputation."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def cut(df: DataFrame) -> DataFrame:
    """The same as a table of Parquet files: its size is known to the planner afterwards.

    For loops: a checkpoint keeps the estimates of the plan that made it, which multiply in each round until they are numbers of
    millions of digits, and no join after it would know that a side is small.
    """
    spark = df.sparkSession
    checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if next(_TABLES) % LET_GO_EVERY == 0:
        let_go(spark)
    return spark.read.schema(df.schema).parquet(path)


def cut_counted(df: DataFrame) -> tuple[DataFrame, int]:
    """The table and its rows, counted as they are written."""
    seen = Observation()
    table = cut(df.observe(seen, F.count(F.lit(1)).alias("rows")))
    return table, seen.get["rows"]


def let_go(spark: SparkSession) -> None:
    """Frees what is not used any more on the driver. Loops of many small jobs leave plans, broadcasts and records of shuffles in its heap,
    which grows to its limit before it is collected; and Spark removes broadcasts and shuffle files elsewhere only once the driver's side of
    them is collected."""
    gc.collect()  # data frames in Python hold the plans of those in the JVM
    spark.sparkContext._jvm.System.gc()


@contextmanager
def staying(spark: SparkSession, wanted: bool = True) -> Iterator[None]:
    """Meanwhile tables that were put in one partition each are joined where they are. The planner takes a join for the product of its sides,
    and would exchange what it thinks is too much for a task. For tables of a checked size; threads may overlap."""
    if not wanted:
        yield
        return
    key = "spark.sql.maxSinglePartitionBytes"
    with _STAY:
        if not _STAYING[0]:
            _STAYING[1] = spark.conf.get(key)
            spark.conf.set(key, str((1 << 63) - 1))
        _STAYING[0] += 1
    try:
        yield
    finally:
        with _STAY:
            _STAYING[0] -= 1
            if not _STAYING[0]:
                spark.conf.set(key, _STAYING[1])
