"""Cutting lineage: tables in the folder that the cluster names; frames of rows that come from the driver."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

ANNOTATIONS = "column_id string, label string, phase string, source string, threshold double"
CALLS = "role string, phase string, target string, source string, prompt string, response string, in_tokens long, out_tokens long"


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; only where that is unset and all runs on one machine (tests) a folder of this machine."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or _OWN.get(spark.sparkContext.applicationId)
    if not folder:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = _OWN[spark.sparkContext.applicationId] = tempfile.mkdtemp(prefix="coltypes-")
    return folder.rstrip("/")


_OWN: dict[str, str] = {}


def keep(df: DataFrame) -> DataFrame:
    """The frame as Parquet in the shared folder: compressed, read by column, and of a size that plans know."""
    path = f"{shared_dir(df.sparkSession)}/kept-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def frame(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def none(spark: SparkSession, schema: str) -> DataFrame:
    return spark.createDataFrame([], schema)
