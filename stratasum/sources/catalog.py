"""Sources and sinks: the given tables with declared schemas, other formats, and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

#: Declared columns of the given tables; a table that lacks one, or has it in another type, is refused.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
}


class SchemaDrift(ValueError):
    """A table does not have its declared columns."""


def table(spark: SparkSession, sf_dir: str, name: str, check: bool = False) -> DataFrame:
    """A given table. check: compare its schema with the declared one first."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if check and name in SCHEMAS:
        have = dict(df.dtypes)
        for f in T._parse_datatype_string(SCHEMAS[name]).fields:
            if have.get(f.name) != f.dataType.simpleString():
                raise SchemaDrift(f"{name}.{f.name}: {have.get(f.name)}, not {f.dataType.simpleString()}")
    return df


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Temporary views of the given tables, for SQL."""
    for name in names or SCHEMAS:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def scan(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """parquet, json, csv, orc or text; a schema avoids a pass over the data to infer one."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: tuple[str, ...] = (), **options) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, *columns: str, mode: str = "overwrite") -> DataFrame:
    """A table of the warehouse bucketed by its join key, so that later joins on it need no shuffle."""
    df.write.mode(mode).bucketBy(buckets, *columns).sortBy(*columns).saveAsTable(name)
    return df.sparkSession.table(name)
