"""Reading and writing edge tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
EDGE_SCHEMA = "src bigint, dst bigint, label string"


def load_tables(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """The given tables by name, also as temporary views."""
    out = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES}
    for name, df in out.items():
        df.createOrReplaceTempView(name)
    return out


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", schema: str = EDGE_SCHEMA, comment: str = "#") -> DataFrame:
    """Delimited edges with comment lines, as public graph collections publish them."""
    return spark.read.csv(path, sep=sep, schema=schema, comment=comment, ignoreLeadingWhiteSpace=True, ignoreTrailingWhiteSpace=True, mode="DROPMALFORMED")


def read_edges(spark: SparkSession, path: str, format: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Edges in any format that the session can read; text formats need a schema."""
    if format in ("csv", "json") and schema is None:
        raise ValueError(f"{format} needs a schema")
    reader = spark.read.format(format).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, format: str = "parquet", mode: str = "errorifexists", partition_by: tuple[str, ...] = ()) -> None:
    """Write edges or answers; partitioned by label, scans of forbidden labels are pruned."""
    writer = df.write.format(format).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
