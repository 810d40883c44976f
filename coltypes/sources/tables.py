"""Base tables by name, other formats, and Parquet sinks."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Base tables with their scalar columns (fixed values: the given schemas). n: number, s: text, t: timestamp.
SCHEMAS = {
    "region": "r_regionkey:n r_name:s",
    "nation": "n_nationkey:n n_name:s n_regionkey:n",
    "customer": "c_custkey:n c_name:s c_nationkey:n c_acctbal:n c_mktsegment:s",
    "supplier": "s_suppkey:n s_name:s s_nationkey:n s_acctbal:n",
    "part": "p_partkey:n p_name:s p_brand:s p_type:s p_size:n p_retailprice:n",
    "orders": "o_orderkey:n o_custkey:n o_orderstatus:s o_totalprice:n o_orderdate:t o_orderpriority:s",
    "lineitem": "l_orderkey:n l_partkey:n l_suppkey:n l_linenumber:n l_quantity:n l_extendedprice:n l_discount:n l_tax:n l_returnflag:s l_linestatus:s l_shipdate:t",
    "events": "event_id:n ts:t user_id:n event_type:s value:n props:s",
    "documents": "doc_id:n text:s lang:s source:s n_chars:n",
    "embeddings": "vec_id:n label:n",
    "pages": "page_id:n url:s html:s",
    "benchmark": "item_id:n text:s",
    "labels": "doc_id:n quality:n toxic:n",
    "conversations": "conv_id:n turn:n role:s text:s",
}


def columns_of(table: str) -> list[tuple[str, str]]:
    """(column, kind letter) of a base table."""
    return [tuple(c.split(":")) for c in SCHEMAS[table].split()]


def kind_of(letter: str) -> str:
    return "num" if letter == "n" else "text"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """A table in fewer pieces than there are cores is dealt out, as one task would turn all of it to long form; larger ones stay."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def read_any(spark: SparkSession, path: str) -> DataFrame:
    """A foreign table by its suffix: csv and json with inferred schema, orc, else parquet."""
    suffix = path.rstrip("/").rsplit(".", 1)[-1].lower()
    if suffix == "csv":
        return spark.read.csv(path, header=True, inferSchema=True)
    if suffix in ("json", "jsonl"):
        return spark.read.json(path)
    return spark.read.orc(path) if suffix == "orc" else spark.read.parquet(path)


def list_tables(spark: SparkSession, folder: str, glob: str = "*.parquet") -> DataFrame:
    """(path, bytes) of the files of a folder, without reading them."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", glob).option("recursiveFileLookup", "true").load(folder)
    return files.select("path", F.col("length").alias("bytes"))


def column_kind(kind: T.DataType) -> str | None:
    """num, text, or None for what is no column of values (binary and nested data)."""
    if isinstance(kind, T.NumericType):
        return "num"
    return None if isinstance(kind, (T.BinaryType, T.ArrayType, T.MapType, T.StructType)) else "text"


def flat(df: DataFrame, explode_arrays: bool = False) -> DataFrame:
    """Struct fields and known map keys as columns ``parent.child``; arrays of scalars as text if asked for."""
    out = []
    for f in df.schema.fields:
        if isinstance(f.dataType, T.StructType):
            out += [F.col(f"`{f.name}`").getField(c).alias(f"{f.name}.{c}") for c in f.dataType.names]
        elif isinstance(f.dataType, T.ArrayType):
            if explode_arrays:
                out.append(F.array_join(F.col(f"`{f.name}`").cast("array<string>"), "|").alias(f.name))
        elif not isinstance(f.dataType, (T.BinaryType, T.MapType)):
            out.append(F.col(f"`{f.name}`"))
    return df.select(*out)


def as_text(column: str, kind: str) -> F.Column:
    """A cell as text; timestamps in a form that any engine writes alike."""
    return F.date_format(column, "yyyy-MM-dd HH:mm:ss") if kind == "t" else F.col(column).cast("string")


@dataclass(frozen=True)
class Store:
    """Results as Parquet under one folder; the value index bucketed by value hash if a table name is given."""

    folder: str

    def write(self, df: DataFrame, name: str, *partition: str) -> str:
        path = f"{self.folder}/{name}"
        df.write.mode("overwrite").partitionBy(*partition).parquet(path)
        return path

    def read(self, spark: SparkSession, name: str) -> DataFrame:
        return spark.read.parquet(f"{self.folder}/{name}")

    @staticmethod
    def write_index(index: DataFrame, table_name: str, buckets: int = 64) -> None:
        """Bucketed and sorted by value hash: joins with values bucketed alike need no exchange."""
        index.write.mode("overwrite").bucketBy(buckets, "value_hash").sortBy("value_hash").saveAsTable(table_name)

    def export_json(self, df: DataFrame, name: str) -> str:
        path = f"{self.folder}/{name}.json"
        df.write.mode("overwrite").json(path)
        return path
