"""Derived collections OPS, TXT and MIXED: the base tables cut into many small tables with varied headers.

A collection is two frames: ``columns`` (catalog: column_id, table_id, header, ordinal, kind,
base_table, base_column) and ``cells`` (column_id, kind, value, num). Each base table is read and
turned to long form once, with its slice as an expression, so the plan does not grow with the number
of tables. The catalog is metadata; truth labels are inherited from base columns.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coltypes.operators.sampling import dense_rows
from coltypes.sources import tables as T

#: Semantic types of the base columns (fixed values), as ``type: columns``.
TRUTH = {
    "World Region Key": "region.r_regionkey nation.n_regionkey",
    "World Region Name": "region.r_name",
    "Nation Key": "nation.n_nationkey customer.c_nationkey supplier.s_nationkey",
    "Nation Code Name": "nation.n_name",
    "Customer Key": "customer.c_custkey orders.o_custkey",
    "Customer Account Name": "customer.c_name",
    "Account Balance": "customer.c_acctbal supplier.s_acctbal",
    "Market Segment": "customer.c_mktsegment",
    "Supplier Key": "supplier.s_suppkey lineitem.l_suppkey",
    "Supplier Account Name": "supplier.s_name",
    "Part Key": "part.p_partkey lineitem.l_partkey",
    "Part Name": "part.p_name",
    "Part Brand": "part.p_brand",
    "Part Size Class": "part.p_type",
    "Part Size Number": "part.p_size",
    "Part Retail Price": "part.p_retailprice",
    "Order Key": "orders.o_orderkey lineitem.l_orderkey",
    "Order Status Code": "orders.o_orderstatus",
    "Line Status Code": "lineitem.l_linestatus",
    "Order Total Price": "orders.o_totalprice",
    "Order Date": "orders.o_orderdate",
    "Ship Date": "lineitem.l_shipdate",
    "Order Priority": "orders.o_orderpriority",
    "Order Line Number": "lineitem.l_linenumber",
    "Ordered Quantity": "lineitem.l_quantity",
    "Line Extended Price": "lineitem.l_extendedprice",
    "Discount Rate": "lineitem.l_discount",
    "Tax Rate": "lineitem.l_tax",
    "Return Flag": "lineitem.l_returnflag",
    "Event Key": "events.event_id",
    "Event Timestamp": "events.ts",
    "User Key": "events.user_id",
    "User Event Type": "events.event_type",
    "Event Value": "events.value",
    "Event Properties JSON": "events.props",
    "Document Key": "documents.doc_id labels.doc_id",
    "Natural Language Passage": "documents.text benchmark.text conversations.text",
    "Language Code": "documents.lang",
    "Document Source Code": "documents.source",
    "Character Count": "documents.n_chars",
    "Vector Key": "embeddings.vec_id",
    "Vector Class Label": "embeddings.label",
    "Web Page Key": "pages.page_id",
    "Web Page URL": "pages.url",
    "HTML Markup": "pages.html",
    "Benchmark Item Key": "benchmark.item_id",
    "Quality Flag": "labels.quality",
    "Toxicity Flag": "labels.toxic",
    "Conversation Key": "conversations.conv_id",
    "Conversation Turn Number": "conversations.turn",
    "Conversation Role": "conversations.role",
}
TYPE_OF = {column: label for label, columns in TRUTH.items() for column in columns.split()}

#: Slice keys of the base tables of each collection, as SQL expressions.
SLICES = {
    "OPS": {
        "lineitem": ["l_returnflag", "l_linestatus", "year(l_shipdate)"],
        "orders": ["o_orderstatus", "year(o_orderdate)"],
        "customer": ["c_mktsegment", "c_nationkey % 5"],
        "supplier": ["s_nationkey % 5"],
        "part": ["p_type"],
        "nation": ["n_regionkey"],
    },
    "TXT": {
        "documents": ["lang", "source"],
        "conversations": ["role", "turn"],
        "part": ["p_brand"],
        "pages": ["regexp_extract(url, '^[a-z]+://[^/]*[.]([a-z]+)', 1)"],
        "labels": ["quality", "toxic"],
        "benchmark": ["item_id % 4"],
    },
    "MIXED": {name: [] for name in T.SCHEMAS} | {"events": ["event_type"]},
}

#: Headers that stand in for a base header, taken in turn by slice (fixed values); the base header itself is first.
ALIASES = {
    "custkey": ["custKey", "cust_keys", "customer_key"],
    "nationkey": ["NationKey", "nation_keys", "nation_id"],
    "orderkey": ["orderKey", "ord_key"],
    "orderdate": ["OrderDate", "order_dates", "order_day"],
    "shipdate": ["ShipDate", "ship_dates", "ship_day"],
    "orderpriority": ["OrderPriority", "order_prioritys", "priority", "urgency"],
    "mktsegment": ["MktSegment", "mkt_segments", "industry"],
    "extendedprice": ["ExtendedPrice", "extended_prices"],
    "acctbal": ["AcctBal", "acct_bals", "funds"],
    "brand": ["Brand", "brands", "maker"],
    "quantity": ["Quantity", "quantitys"],
    "source": ["Source", "sources", "origin"],
    "lang": ["Lang", "language"],
}

#: Columns of mixed types: header and the base columns whose distinct values they join (fixed values).
MULTI = [
    ("location", "region.r_name nation.n_name"),
    ("loc", "nation.n_name region.r_name"),
    ("name", "supplier.s_name nation.n_name"),
    ("party", "customer.c_name supplier.s_name"),
    ("owner", "customer.c_name nation.n_name region.r_name"),
    ("product_tag", "part.p_brand part.p_type"),
    ("item", "part.p_name part.p_brand"),
    ("segment_or_priority", "customer.c_mktsegment orders.o_orderpriority"),
    ("status", "orders.o_orderstatus orders.o_orderpriority"),
    ("flag", "lineitem.l_returnflag orders.o_orderpriority"),
    ("actor_action", "conversations.role events.event_type"),
    ("origin", "documents.lang documents.source"),
    ("link", "pages.url documents.source"),
    ("payload", "events.event_type events.props"),
    ("when_state", "lineitem.l_shipdate lineitem.l_linestatus"),
    ("mixed_code", "part.p_type documents.lang part.p_brand"),
]


def alias(column: str, slice_no: int) -> str:
    """The header of a base column in the slice of that number."""
    plain = column.split("_", 1)[1] if column[1:2] == "_" else column
    options = [column, *ALIASES.get(plain, [])]
    return options[slice_no % len(options)]


#: Rows kept of each table for prompts.
ROWS = 10


@dataclass
class Collection:
    """Columns, cells, and ``rows``: (table_id, place, base_column, value), some well filled rows of each table; null values stay."""

    name: str
    columns: DataFrame
    cells: DataFrame
    rows: DataFrame | None = None
    #: (table_id, n_rows)
    sizes: DataFrame | None = None
    #: (column_id, kind, num): the numbers among the cells, without their text
    numbers: DataFrame | None = None

    @property
    def truth(self) -> DataFrame:
        """(column_id, label): one row per true type of a column."""
        return self.columns.select("column_id", F.explode(F.split("truth", "[|]")).alias("label"))


CATALOG = "column_id string, table_id string, header string, ordinal int, kind string, base_table string, base_column string, truth string"


def _slice_id(base: str, keys: list[str]) -> F.Column:
    parts = [F.coalesce(F.expr(k).cast("string"), F.lit("null")) for k in keys]
    return F.concat_ws("_", F.lit(base), *parts)


def _long(df: DataFrame, base: str, keys: list[str], kind: str | None = None) -> DataFrame:
    """(table_id, base_column, kind, value, num) of a base table in one pass; of one kind only if asked for."""
    cells = []
    for column, letter in T.columns_of(base):
        if kind and T.kind_of(letter) != kind:
            continue
        text = T.as_text(column, letter)
        if letter == "s":
            text = F.when(F.trim(text) != "", text)
        number = F.col(column).cast("double") if letter == "n" else F.lit(None).cast("double")
        cells.append(F.struct(F.lit(column).alias("base_column"), F.lit(T.kind_of(letter)).alias("kind"), text.alias("value"), number.alias("num")))
    return df.select(_slice_id(base, keys).alias("table_id"), F.explode(F.array(*cells)).alias("c")).select("table_id", "c.*").where("value is not null and not coalesce(isnan(num), false)")


def _numbers(df: DataFrame, base: str, keys: list[str]) -> DataFrame:
    """(table_id, base_column, kind, num) of the cells of ``_long`` that are numbers."""
    cells = [F.struct(F.lit(column).alias("base_column"), F.col(column).cast("double").alias("num")) for column, letter in T.columns_of(base) if letter == "n"]
    return df.select(_slice_id(base, keys).alias("table_id"), F.explode(F.array(*cells)).alias("c")).select("table_id", "c.base_column", F.lit("num").alias("kind"), "c.num").where("num is not null and not isnan(num)")


def _sampled(df: DataFrame, base: str, keys: list[str]) -> DataFrame:
    """(table_id, place, base_column, value): rows of each table with few empty cells, equals by a hash of the row.

    Only so many rows of a table leave a task.
    """
    text = [T.as_text(column, letter).alias(column) for column, letter in T.columns_of(base)]
    picked = dense_rows(df.select(_slice_id(base, keys).alias("table_id"), *text), ROWS, by=["table_id"], place="place")
    cells = F.array(*[F.struct(F.lit(c).alias("base_column"), F.col(c).alias("value")) for c, _ in T.columns_of(base)])
    return picked.select("table_id", "place", F.explode(cells).alias("c")).select("table_id", "place", "c.*")


def multi_typed(spark: SparkSession, sf_dir: str) -> tuple[list[tuple], DataFrame]:
    """Catalog rows and cells of the columns that mix types."""
    rows, cells = [], None
    for k, (header, sources) in enumerate(MULTI, 1):
        table_id, column_id = f"multi_{k:02d}", f"multi_{k:02d}.{header}"
        rows.append((column_id, table_id, header, 0, "text", "multi", header, "|".join(sorted({TYPE_OF[s] for s in sources.split()}))))
        for source in sources.split():
            base, column = source.split(".")
            letter = dict(T.columns_of(base))[column]
            part = T.table(spark, sf_dir, base).select(T.as_text(column, letter).alias("value")).where("value is not null").distinct()
            part = part.select(F.lit(column_id).alias("column_id"), F.lit("text").alias("kind"), "value", F.lit(None).cast("double").alias("num"))
            cells = part if cells is None else cells.union(part)
    return rows, cells


def build(spark: SparkSession, sf_dir: str, name: str) -> Collection:
    """One of OPS, TXT, MIXED, or MULTI (the mixed columns alone)."""
    rows, parts, samples, sizes, numeric = [], [], [], [], []
    for base, keys in SLICES.get(name, {}).items():
        df = T.table(spark, sf_dir, base)
        dealt = T.spread(df)
        long = _long(dealt, base, keys)
        samples.append(_sampled(dealt, base, keys))
        sizes.append(df.groupBy(_slice_id(base, keys).alias("table_id")).agg(F.count("*").alias("n_rows")))
        if keys:
            found = sorted(r[0] for r in df.select(_slice_id(base, keys)).distinct().collect())
        else:
            found = [base]
        for k, table_id in enumerate(found):
            for ordinal, (column, letter) in enumerate(T.columns_of(base)):
                header = alias(column, k)
                rows.append((f"{table_id}.{header}", table_id, header, ordinal, T.kind_of(letter), base, column, TYPE_OF[f"{base}.{column}"]))
        parts.append(long)
        if any(letter == "n" for _, letter in T.columns_of(base)):
            numeric.append(_numbers(dealt, base, keys))
    mixed_rows, mixed = multi_typed(spark, sf_dir) if name in ("MIXED", "MULTI") else ([], None)
    columns = spark.createDataFrame(rows + mixed_rows, CATALOG)
    cells = numbers = None
    if parts:
        long = parts[0]
        for p in parts[1:]:
            long = long.union(p)
        names = columns.select("table_id", "base_column", "column_id")
        cells = long.join(F.broadcast(names), ["table_id", "base_column"]).select("column_id", "kind", "value", "num")  # names are rows of the driver
        numbers = reduce(DataFrame.union, numeric).join(F.broadcast(names), ["table_id", "base_column"]).select("column_id", "kind", "num")
    if mixed is not None:
        cells = mixed if cells is None else cells.union(mixed)
        split = F.split("column_id", "[.]")
        picked = dense_rows(mixed.select(split[0].alias("table_id"), split[1].alias("base_column"), "value"), ROWS, by=["table_id"], place="place")
        samples.append(picked.select("table_id", "place", "base_column", "value"))
        sizes.append(mixed.groupBy(split[0].alias("table_id")).agg(F.count("*").alias("n_rows")))
    return Collection(name, columns, cells, reduce(DataFrame.union, samples), reduce(DataFrame.union, sizes), numbers)


def base_cells(spark: SparkSession, sf_dir: str, tables=tuple(T.SCHEMAS), kind: str | None = None) -> DataFrame:
    """The cells of some base tables, of one kind if asked for: only these tables and columns are read."""
    parts = [_long(T.table(spark, sf_dir, base), base, [], kind) for base in tables if not kind or any(T.kind_of(letter) == kind for _, letter in T.columns_of(base))]
    return reduce(DataFrame.union, parts).select(F.concat_ws(".", "table_id", "base_column").alias("column_id"), "kind", "value", "num")


def base_columns(spark: SparkSession) -> DataFrame:
    """The catalog of the base tables."""
    rows = [(f"{base}.{c}", base, c, k, T.kind_of(letter), base, c, TYPE_OF[f"{base}.{c}"]) for base in T.SCHEMAS for k, (c, letter) in enumerate(T.columns_of(base))]
    return spark.createDataFrame(rows, CATALOG)


def held_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The catalog of the base columns that hold a value: each table is read once and leaves one row."""
    parts = []
    for base in T.SCHEMAS:
        filled = {c: F.col(c).isNotNull() & (F.trim(c) != "" if letter == "s" else ~F.isnan(F.col(c).cast("double")) if letter == "n" else F.lit(True)) for c, letter in T.columns_of(base)}
        one = T.table(spark, sf_dir, base).agg(*[F.max(x).alias(c) for c, x in filled.items()])
        parts.append(one.select(F.explode(F.array(*[F.struct(F.lit(f"{base}.{c}").alias("column_id"), F.col(c).alias("held")) for c in filled])).alias("c")).select("c.*"))
    return base_columns(spark).join(F.broadcast(reduce(DataFrame.union, parts).where("held")), "column_id", "left_semi")


def base_rows(spark: SparkSession, sf_dir: str, tables=tuple(T.SCHEMAS)) -> DataFrame:
    """Some well filled rows of base tables."""
    return reduce(DataFrame.union, [_sampled(T.table(spark, sf_dir, base), base, []) for base in tables])


def base_collection(spark: SparkSession, sf_dir: str) -> Collection:
    """The base tables as they are, without sampled rows."""
    return Collection("BASE", base_columns(spark), base_cells(spark, sf_dir))
