"""Reading and writing of tables, rule files and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = (
    "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"
).split()

RULE_FILE_SCHEMA = "lhs array<string>, rhs array<string>, support double, confidence double, lift double"


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def register_views(spark: SparkSession, folder: str, names: list[str] | None = None) -> None:
    """Temp views for SQL users."""
    for name in names or TABLES:
        table(spark, folder, name).createOrReplaceTempView(name)


def read_rules(spark: SparkSession, path: str, fmt: str = "json", schema: str = RULE_FILE_SCHEMA) -> DataFrame:
    """Rules mined elsewhere, elements as ``attr=val``. CSV files hold the sides joined by ``|``."""
    if fmt != "csv":
        return spark.read.format(fmt).schema(schema).load(path)
    flat = spark.read.csv(path, header=True, schema=schema.replace("array<string>", "string"))
    return flat.withColumns({side: F.split(side, r"\|") for side in ("lhs", "rhs")})


def render_rule(lhs: str = "lhs", rhs: str = "rhs"):
    """``(a, v), (b, w) -> (c, u)`` of sides given as arrays of ``attr=val``."""

    def side(c: str):
        pair = lambda e: F.concat(F.lit("("), F.substring_index(e, "=", 1), F.lit(", "), F.regexp_replace(e, "^[^=]*=", ""), F.lit(")"))
        return F.array_join(F.transform(c, pair), ", ")

    return F.concat(side(lhs), F.lit(" -> "), side(rhs))


def write_result(df: DataFrame, path: str, partition_by: list[str] | None = None, fmt: str = "parquet", mode: str = "overwrite") -> None:
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
