"""What stands beside a column: headers that share its tables, and rows of its table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def cooccurring(membership: DataFrame, columns: DataFrame, n: int = 5, cluster: str = "seed_cluster") -> DataFrame:
    """(cluster, header, n_tables, of_tables, rank): headers most often in the cluster's source tables, its own columns left out."""
    member = membership.where(F.col(cluster).isNotNull()).select(cluster, "column_id").join(columns.select("column_id", "table_id"), "column_id")
    source = member.select(cluster, "table_id").distinct()
    total = source.groupBy(cluster).agg(F.count("*").alias("of_tables"))
    beside = source.join(columns.select("table_id", "column_id", "header"), "table_id").join(member.select(cluster, "column_id"), [cluster, "column_id"], "left_anti")
    counted = beside.groupBy(cluster, "header").agg(F.countDistinct("table_id").alias("n_tables"))
    order = W.partitionBy(cluster).orderBy(F.desc("n_tables"), "header")
    return counted.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n).join(total, cluster).select(cluster, "header", "n_tables", "of_tables", "rank")


def table_rows(columns: DataFrame, rows: DataFrame | None, n: int = 3) -> DataFrame:
    """(table_id, width, heads): the columns of each table in order, each with its values in the same first ``n`` sampled rows.

    ``rows``: (table_id, place, base_column, value). The k-th values of a table's columns stand in one
    row; a null is shown as an empty string. Without rows, or for a table without any, headers alone.
    """
    described = columns.select("table_id", "ordinal", "column_id", "header", "kind", "base_column")
    empty = F.array().cast("array<string>")
    if rows is None or not n:
        described = described.withColumn("values", empty)
    else:
        cells = rows.where(F.col("place") <= n).groupBy("table_id", "base_column").agg(F.array_sort(F.collect_list(F.struct("place", F.coalesce("value", F.lit("")).alias("value")))).alias("v"))
        described = described.join(cells, ["table_id", "base_column"], "left").withColumn("values", F.coalesce(F.transform("v", lambda x: x["value"]), empty))
    heads = F.array_sort(F.collect_list(F.struct("ordinal", "column_id", "header", "kind", "values")))
    return described.groupBy("table_id").agg(F.count("*").alias("width"), heads.alias("heads"))


def shown(heads: Column) -> Column:
    """Headers and rows as text: a line of headers, then a line for each row."""
    line = F.array_join(F.transform(heads, lambda c: c["header"]), " | ")
    depth = F.array_max(F.transform(heads, lambda c: F.size(c["values"])))
    rows = F.transform(F.sequence(F.lit(1), depth), lambda k: F.array_join(F.transform(heads, lambda c: F.try_element_at(c["values"], k)), " | ", ""))
    return F.when(depth > 0, F.concat_ws("\n", line, F.array_join(rows, "\n"))).otherwise(line)
