"""Readers, writers and the SQL surface."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import Catalog, ForeignKey, TableSpec


def read_any(spark: SparkSession, path: str, fmt: str, schema=None, **options) -> DataFrame:
    """csv, json, orc or parquet with a declared schema; malformed fields of text formats become null."""
    reader = spark.read.format(fmt)
    if schema is not None:
        reader = reader.schema(schema)
    if fmt in ("csv", "json"):
        options = {"mode": "PERMISSIVE", **({"header": True} if fmt == "csv" else {}), **options}
    return reader.options(**options).load(path)


def write_any(df: DataFrame, path: str, fmt: str, partition_by: list[str] | None = None, **options) -> None:
    w = df.write.format(fmt).mode("overwrite").options(**({"header": True} if fmt == "csv" else {}), **options)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def write_table(df: DataFrame, name: str, bucket_by: str, buckets: int, sort_by: str | None = None) -> None:
    """A bucketed table: joins and groupings by that column need no exchange on its side."""
    df.write.mode("overwrite").bucketBy(buckets, bucket_by).sortBy(sort_by or bucket_by).saveAsTable(name)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, parts: int = 64, **props) -> DataFrame:
    """A table of a database, read in ranges of a numeric column."""
    return spark.read.jdbc(url, table, column=column, lowerBound=low, upperBound=high, numPartitions=parts, properties=props)


def schema_json(catalog: Catalog) -> str:
    return json.dumps({"tables": [s.name for s in catalog.specs.values()], "fks": [[k.src, k.column, k.dst] for k in catalog.fks]})


def join_paths_udtf():
    """Table function (schema_json, target, depth) -> path, length, simple: the walks of a schema for SQL users."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="path string, length int, simple boolean")
    class JoinPaths:
        def eval(self, schema: str, target: str, depth: int):
            spec = json.loads(schema)
            todo = [("", (target,))]
            while todo:
                path, seen = todo.pop(0)
                if len(seen) > 1:
                    yield path, len(seen) - 1, len(set(seen)) == len(seen)
                if len(seen) <= depth:
                    for a, c, b in spec["fks"]:
                        if a == seen[-1]:
                            todo.append((f"{path} {a}.{c}>".strip(), (*seen, b)))
                        if b == seen[-1]:
                            todo.append((f"{path} {a}.{c}<".strip(), (*seen, a)))

    return JoinPaths


def register_sql(spark: SparkSession, catalog: Catalog) -> None:
    """Temporary views of the tables, and the table function ``join_paths``."""
    for name, df in catalog.frames.items():
        df.createOrReplaceTempView(name)
    spark.udtf.register("join_paths", join_paths_udtf())


def spec_from_json(text: str) -> tuple[list[TableSpec], list[ForeignKey]]:
    d = json.loads(text)
    return [TableSpec(t["name"], tuple(t["key"]), tuple(t.get("numeric", ())), tuple(t.get("categorical", ()))) for t in d["tables"]], [ForeignKey(*k) for k in d["fks"]]


def partition_report(df: DataFrame) -> DataFrame:
    """part, n: rows a partition."""
    return df.groupBy(F.spark_partition_id().alias("part")).agg(F.count("*").alias("n"))
