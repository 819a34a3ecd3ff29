"""Raw tables in the formats they come in, with the schema given, never guessed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read_table(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | T.StructType | None = None, **options) -> DataFrame:
    """Parquet and ORC know their schema; CSV, JSON and text need one (CSV has a header line unless told otherwise)."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt)
    if schema is not None:
        reader = reader.schema(schema)
    if fmt == "csv":
        options = {"header": "true"} | options
    return reader.options(**options).load(path)


def flattened(df: DataFrame, lists: dict[str, int] | None = None) -> DataFrame:
    """Plain columns out of structs and arrays: ``lists`` names array columns and their length."""
    lists, out = lists or {}, []
    for field in df.schema:
        if isinstance(field.dataType, T.StructType):
            out += [F.col(f"`{field.name}`.`{f.name}`").alias(f"{field.name}_{f.name}") for f in field.dataType]
        elif field.name in lists:
            out += [F.get(F.col(field.name), F.lit(k)).alias(f"{field.name}_{k}") for k in range(lists[field.name])]
        elif not isinstance(field.dataType, (T.ArrayType, T.MapType)):
            out.append(F.col(field.name))
    return df.select(*out)


def json_fields(df: DataFrame, column: str, schema: str) -> DataFrame:
    """A JSON text column's fields as columns of their own, null where they are missing."""
    parsed = df.withColumn("_j", F.from_json(column, schema))
    return parsed.select(*[c for c in df.columns if c != column], *[F.col(f"_j.{f.name}").alias(f"{column}_{f.name}") for f in parsed.schema["_j"].dataType])
