"""Tables in, graphs in and out."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from ..shipping import ship

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Registers tables as temporary views, for spark.sql."""
    for name in names or TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, a fresh local one, in local mode only."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not path:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        path = tempfile.mkdtemp(prefix="shared-")
        spark.conf.set("spark.checkpoint.dir", path)
    return path.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that no other run uses."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def checkpointed(df: DataFrame) -> DataFrame:
    """df with its lineage cut by a reliable checkpoint. Its partitioning, and what the optimizer knows of its columns, stay known."""
    ship(df.sparkSession)
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint()


def cut(df: DataFrame) -> DataFrame:
    """df with its lineage cut by a reliable checkpoint, as a plan of one scan: for loops. What the optimizer infers of columns (which are equal,
    which are not null) is kept with a checkpoint and grows to twice as much from one round of a loop to the next; here it is dropped."""
    done, spark = checkpointed(df)._jdf, df.sparkSession
    return type(df)(spark._jsparkSession.internalCreateDataFrame(done.queryExecution().toRdd(), done.schema(), False), spark)


def landed(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """df written to the shared folder and read back, and its path: for loops, as nothing of the plan before remains, on disk or in memory."""
    spark = df.sparkSession
    ship(spark)
    path = fresh_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def remove(spark: SparkSession, path: str) -> None:
    """Removes what landed at path."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def forget(spark: SparkSession, path: str) -> None:
    """Removes what landed at path, and lets Spark remove shuffles that nothing refers to any more."""
    remove(spark, path)
    gc.collect()
    spark._jvm.System.gc()


def write_graph(fg, path: str) -> None:
    """A graph as Parquet tables below path."""
    for name in ("variables", "edges", "potentials"):
        getattr(fg, name).write.mode("overwrite").parquet(f"{path}/{name}")


def read_graph(spark: SparkSession, path: str):
    from ..operators.model import FactorGraph

    ship(spark)
    return FactorGraph(*(spark.read.parquet(f"{path}/{name}") for name in ("variables", "edges", "potentials")))


def append_rounds(rounds: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Adds per-round metrics to a table (Parquet, or CSV with a header)."""
    rounds.write.mode("append").format(fmt).option("header", True).save(path)
