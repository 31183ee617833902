"""Readers and writers, and the given tables as matrices, tensors and trade graphs.

Values are fixed point where results are compared cell by cell: floor(1000 x) as BIGINT.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.plans.layout import Layout
from relayout.plans.overlay import parcels_from_rows


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, buckets: int | None = None, name: str | None = None) -> None:
    """Files, one folder a value of ``by``; or, with buckets and a name, a bucketed table."""
    out = df.write.format(fmt)
    if by and not buckets:
        out = out.partitionBy(*by)
    if buckets:
        if not name or not by:
            raise ValueError("a bucketed table needs a name and columns")
        out.bucketBy(buckets, *by).sortBy(*by).saveAsTable(name)
    else:
        out.save(path)


def save_layout(spark: SparkSession, layout: Layout, path: str) -> None:
    spark.createDataFrame([(layout.to_json(),)], "descriptor string").coalesce(1).write.text(path)


def load_layout(spark: SparkSession, path: str) -> Layout:
    return Layout.from_json(spark.read.text(path).first()[0])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Tables as sparse matrices: the table, each row's row and column index, and which rows have both. Cells may repeat. The
#: condition names columns, not indices, so dates are taken apart once a row.
POINTS = {
    "customer_months": ("orders", "o_custkey", "month(o_orderdate) - 1", "o_custkey >= 0 AND o_orderdate IS NOT NULL"),
    "supplier_months": ("lineitem", "l_suppkey", "month(l_shipdate) - 1", "l_suppkey >= 0 AND l_shipdate IS NOT NULL"),
    "supplier_parts": ("lineitem", "l_suppkey", "l_partkey", "l_suppkey >= 0 AND l_partkey >= 0"),
    "quantity_lines": ("lineitem", "floor(l_quantity)", "l_linenumber", "l_quantity >= 0 AND l_quantity < 51 AND l_linenumber >= 0"),
    "user_hours": ("events", "user_id", "hour(ts)", "user_id >= 0 AND ts IS NOT NULL"),
    "minute_hours": ("events", "minute(ts)", "hour(ts)", "ts IS NOT NULL"),
}


def points(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(i, j) of every row of a table that has both."""
    of, i, j, where = POINTS[name]
    return table(spark, sf_dir, of).filter(where).select(F.expr(i).cast("long").alias("i"), F.expr(j).cast("long").alias("j"))


def counted(cells: DataFrame) -> DataFrame:
    """(i, j, n_rows): a small matrix's cells and their rows. What follows is done once a cell, not once a row."""
    return cells.groupBy("i", "j").agg(F.count(F.lit(1)).alias("n_rows"))


def shape(cells: DataFrame, n: int | None = None) -> tuple[int, int]:
    """The largest indices + 1, 0 without cells; n: a known number of columns, whether or not cells reach it."""
    last = cells.agg(F.max("i"), F.max("j") if n is None else F.lit(n - 1)).first()
    return tuple(0 if x is None else x + 1 for x in last)


def fixed(x: Column) -> Column:
    return F.floor(x.cast("double") * 1000).cast("long")


def entries_from_vectors(df: DataFrame, row: str, vector: str) -> DataFrame:
    """(i, j, v) of a table of row vectors."""
    return df.select(F.col(row).cast("long").alias("i"), F.posexplode(vector).alias("j", "v")).select("i", F.col("j").cast("long").alias("j"), "v")


def entries_from_table(df: DataFrame, row: Column, col: Column, value: Column, agg: str = "sum") -> DataFrame:
    """(i, j, v): duplicates of a cell are aggregated."""
    fn = {"sum": F.sum, "max": F.max, "min": F.min, "count": F.count}[agg]
    return df.groupBy(row.cast("long").alias("i"), col.cast("long").alias("j")).agg(fn(value).alias("v"))


def emb_shape(spark: SparkSession, sf_dir: str) -> tuple[int, int]:
    """Rows and columns of the embeddings as a matrix: the largest vec_id + 1, and the longest vector."""
    last, width = table(spark, sf_dir, "embeddings").agg(F.max("vec_id"), F.max(F.size("embedding"))).first()
    return (0 if last is None else last + 1), max(width or 0, 0)


def emb_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_from_vectors(table(spark, sf_dir, "embeddings"), "vec_id", "embedding").withColumn("v", fixed(F.col("v")))


def emb_complex(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i, j, v STRUCT<re, im>): even columns are real, odd ones imaginary parts."""
    rows = table(spark, sf_dir, "embeddings").filter(F.size("embedding") > 1)
    value = F.transform(F.sequence(F.lit(0), F.floor(F.size("embedding") / 2).cast("int") - 1), lambda k: F.struct(F.get("embedding", k * 2).cast("double").alias("re"), F.get("embedding", k * 2 + 1).cast("double").alias("im")))
    return rows.select(F.col("vec_id").alias("i"), F.posexplode(value).alias("j", "v")).select("i", F.col("j").cast("long").alias("j"), "v")


def supp_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_from_table(table(spark, sf_dir, "lineitem"), F.col("l_suppkey") - 1, F.col("l_partkey") - 1, F.col("l_quantity"))


def month(date: Column) -> Column:
    return F.month(date) - 1


def cust_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entries_from_table(table(spark, sf_dir, "orders"), F.col("o_custkey") - 1, month(F.col("o_orderdate")), F.lit(1), "count")


def trade(spark: SparkSession, sf_dir: str, level: str) -> DataFrame:
    """Parcels from a supplier's to a customer's nation or region; volume is the quantity. Small sides are broadcast by
    Spark where their size is known to allow it."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    supp = table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").alias("sn"))
    orders, cust = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").alias("cn"))
    rows = line.join(supp, F.col("l_suppkey") == F.col("s_suppkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(cust, F.col("o_custkey") == F.col("c_custkey"))
    if level == "nation":
        return parcels_from_rows(rows, F.col("sn"), F.col("cn"), F.col("l_quantity"))
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    at = rows.groupBy("sn", "cn").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"))
    for key, name in (("sn", "sr"), ("cn", "cr")):
        at = at.join(F.broadcast(nation.select(F.col("n_nationkey").alias(key), F.col("n_regionkey").alias(name))), key)  # 25 rows
    return at.groupBy(F.col("sr").cast("int").alias("src"), F.col("cr").cast("int").alias("dst")).agg(F.sum("n").alias("n_pieces"), F.sum("q").cast("long").alias("vol"))


def square(spark: SparkSession, n: int) -> DataFrame:
    """A synthetic square matrix, v = (31 i + 17 j) mod 1009."""
    return rectangle(spark, n, n)


def rectangle(spark: SparkSession, m: int, n: int) -> DataFrame:
    i = ((F.col("id") - F.pmod("id", F.lit(n))) / n).cast("long")
    return spark.range(m * n).select(i.alias("i"), F.pmod("id", F.lit(n)).alias("j")).select("i", "j", F.pmod(F.col("i") * 31 + F.col("j") * 17, F.lit(1009)).alias("v"))
