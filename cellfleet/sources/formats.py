"""Readers and writers of position feeds in the usual formats, schemas always given and never inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write(rows: DataFrame, kind: str, path: str) -> None:
    if kind == "text":
        rows.select(F.to_json(F.struct(*rows.columns), {"ignoreNullFields": "false"}).alias("value")).write.text(path)
    else:
        rows.write.format(kind).options(**({"header": "true"} if kind == "csv" else {})).save(path)


def read(spark, kind: str, path: str, schema) -> DataFrame:
    if kind == "text":
        return spark.read.text(path).select(F.from_json("value", schema).alias("r")).select("r.*")
    return spark.read.format(kind).schema(schema).options(**({"header": "true"} if kind == "csv" else {})).load(path)


def round_trip(rows: DataFrame, kind: str, path: str) -> DataFrame:
    write(rows, kind, path)
    return read(rows.sparkSession, kind, path, rows.schema)
