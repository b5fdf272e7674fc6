"""Sources and sinks of matrices and vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

ENTRY_SCHEMA = T.StructType([T.StructField("row", T.LongType()), T.StructField("col", T.LongType()), T.StructField("val", T.DoubleType())])


def load_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given Parquet table, cut to the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def as_entries(df: DataFrame) -> DataFrame:
    """df with the columns and types of entries."""
    return df.select(*[F.col(f.name).cast(f.dataType) for f in ENTRY_SCHEMA])


def read_triples_csv(spark: SparkSession, path: str, sep: str = ",", header: bool = False) -> DataFrame:
    return spark.read.schema(ENTRY_SCHEMA).csv(path, sep=sep, header=header)


def read_triples_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(ENTRY_SCHEMA).json(path)


def read_triples_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(ENTRY_SCHEMA).orc(path)


def read_coordinate_text(spark: SparkSession, path: str) -> DataFrame:
    """Coordinate text: comment lines start with %, one line of sizes, then one-based row, column and value (1 where left out).

    The line of sizes is told by the file it is in: it is the first line that is no comment, so a text file may not be
    split for it; sizes are found as the only line whose place is 0 among such lines of its file.
    """
    lines = spark.read.text(path, wholetext=True).select(F.explode(F.slice(F.filter(F.split("value", "\r?\n"), lambda s: ~s.startswith("%") & (F.trim(s) != "")), 2, 1 << 30)).alias("line"))
    part = F.split(F.trim("line"), r"\s+")
    value = F.when(F.size(part) > 2, F.get(part, F.lit(2)).cast("double")).otherwise(1.0)
    return lines.select((F.get(part, F.lit(0)).cast("long") - 1).alias("row"), (F.get(part, F.lit(1)).cast("long") - 1).alias("col"), value.alias("val"))


def read_svm_lines(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(entries, labels) of lines `label index:value ...` with one-based indices; rows are numbered by a running id."""
    lines = spark.read.text(path).where(F.trim("value") != "").withColumn("row", F.monotonically_increasing_id())
    part = F.split(F.trim("value"), r"\s+")
    labels = lines.select("row", F.get(part, F.lit(0)).cast("double").alias("label"))
    item = lines.select("row", F.explode(F.slice(part, 2, 1 << 30)).alias("item"))
    pair = F.split("item", ":")
    return item.select("row", (F.get(pair, F.lit(0)).cast("long") - 1).alias("col"), F.get(pair, F.lit(1)).cast("double").alias("val")), labels


def read_runs(spark: SparkSession, path: str, run_bytes: int) -> DataFrame:
    """Entries read as contiguous file splits of about run_bytes; each task reads its own span."""
    spark.conf.set("spark.sql.files.maxPartitionBytes", str(run_bytes))
    return spark.read.schema(ENTRY_SCHEMA).parquet(path)


def is_column_major(entries: DataFrame) -> bool:
    """Whether the entries come sorted by (col, row), within each partition and from one partition to the next."""
    numbered = entries.withColumn("at", F.monotonically_increasing_id()).withColumn("task", F.spark_partition_id())
    from pyspark.sql import Window

    key = F.struct("col", "row")
    before = F.lag(key).over(Window.partitionBy("task").orderBy("at"))
    wrong = numbered.select("task", key.alias("key"), (before > key).alias("falls")).groupBy("task").agg(F.max(F.coalesce("falls", F.lit(False))).alias("falls"), F.min("key").alias("lo"), F.max("key").alias("hi"))
    rows = wrong.orderBy("task").collect()  # one row for each file split
    return not any(r["falls"] for r in rows) and all(a["hi"] <= b["lo"] for a, b in zip(rows, rows[1:], strict=False))


def write_placed(placed: DataFrame, path: str) -> None:
    """Entries of each part sorted by (col, row), in folders by part."""
    placed.sortWithinPartitions("part", "col", "row").write.partitionBy("part").parquet(path)


def write_blocks(blocks: DataFrame, path: str) -> None:
    blocks.write.parquet(path)


def write_vector(vector: DataFrame, path: str, fmt: str = "parquet") -> None:
    vector.write.format(fmt).save(path)


def drain(df: DataFrame) -> None:
    """Run df to its end and keep nothing, for timing."""
    df.write.format("noop").mode("overwrite").save()
