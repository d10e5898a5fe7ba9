"""Reading and writing with declared schemas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
    "pages": "page_id long, url string, html string",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}
FORMATS = ("parquet", "json", "csv", "orc", "text")


class SchemaError(ValueError):
    """An input lacks a column, or has it with another type."""


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A known table; labels may come as long or int, so labels are cast after an inferred read of the footer."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    declared = T._parse_datatype_string(SCHEMAS[name])
    require(df, declared.names)
    return df.select(*[F.col(f.name).cast(f.dataType).alias(f.name) if df.schema[f.name].dataType != f.dataType else F.col(f.name) for f in declared])


def require(df: DataFrame, columns: list[str]) -> DataFrame:
    if missing := [c for c in columns if c not in df.columns]:
        raise SchemaError(f"missing columns {missing}; there are {df.columns}")
    return df


def read(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    if fmt not in FORMATS:
        raise SchemaError(f"unknown format {fmt!r}")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: tuple[str, ...] = ()) -> None:
    if fmt not in FORMATS:
        raise SchemaError(f"unknown format {fmt!r}")
    df.write.format(fmt).mode(mode).partitionBy(*partition_by).save(path)


def write_manifest(manifest: DataFrame, path: str, shards: int, mode: str = "errorifexists") -> None:
    """Manifest rows in ``shards`` hash shards per domain folder."""
    manifest.repartition(shards, "doc_id").write.mode(mode).partitionBy("domain").parquet(path)
