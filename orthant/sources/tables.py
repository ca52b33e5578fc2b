"""Tables by name, and the engine's own folder for intermediate data."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
import warnings

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder shared by all nodes that the session names (spark.checkpoint.dir).

    A session of one machine that names none gets a temporary one, with a warning; one of several machines is refused.
    """
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", sc.master):
            raise ValueError(f"spark.checkpoint.dir must name a folder that all nodes of {sc.master} share")
        found = tempfile.mkdtemp(prefix="orthant-")
        warnings.warn(f"spark.checkpoint.dir is not set: intermediate data go to {found}, which only this machine sees", stacklevel=2)
        atexit.register(shutil.rmtree, found, ignore_errors=True)
        sc.setCheckpointDir(found)
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/orthant/{uuid.uuid4().hex}/{name}"
    top = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path.rsplit("/", 1)[0])
    top.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(top)
    return path


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write df to the shared folder and read it back."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
