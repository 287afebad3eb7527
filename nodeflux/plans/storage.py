"""Tables written to the folder that the whole cluster shares, to cut lineage.

A written table survives lost executors and gives the optimizer real sizes; both
`checkpoint()` and these tables live under ``spark.checkpoint.dir``.
"""

from __future__ import annotations

import gc
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's shared folder; a folder of our own only where none is set."""
    set_dir = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if set_dir:
        return set_dir.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return "file:///tmp/checkpoints/nodeflux"


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._shared_path = path
    return back


def release(spark: SparkSession) -> None:
    """Collect the driver's garbage; its heap shrinks to what is alive and a margin.

    Planning leaves hundreds of MB of garbage and little that stays, but a heap that is not collected as a whole keeps every
    page it has touched. Spark's cleaner then also drops the broadcasts and shuffle files of plans that are gone.
    """
    gc.collect()  # Python's handles hold plans in the JVM
    spark._jvm.System.gc()


def cut_counted(df: DataFrame, name: str, metrics: list[Column]) -> tuple[DataFrame, dict]:
    """`cut`, and aggregates of the table that are gathered while it is written, without a job of their own.

    The rows are observed in the tasks that write, of which each one counts once, retries or not.
    """
    seen = Observation()
    held = cut(df.observe(seen, *metrics), name)
    return held, seen.get or held.agg(*metrics).first().asDict()


def discard(df: DataFrame) -> None:
    """Delete a table that `cut` wrote, once nothing reads it any more."""
    path = getattr(df, "_shared_path", None)
    if path:
        jvm = df.sparkSession._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(p, True)
