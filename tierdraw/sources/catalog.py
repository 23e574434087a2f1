"""Schemas of the given tables, pruned readers and idempotent sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

_L, _I, _D, _S, _N = T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType(), T.TimestampNTZType()


def _schema(**columns: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in columns.items()])


SCHEMAS = {
    "region": _schema(r_regionkey=_L, r_name=_S),
    "embeddings": _schema(vec_id=_L, embedding=T.ArrayType(T.FloatType()), label=_I),
    "documents": _schema(doc_id=_L, text=_S, lang=_S, source=_S, n_chars=_L),
    "labels": _schema(doc_id=_L, quality=_I, toxic=_I),
    "lineitem": _schema(l_orderkey=_L, l_partkey=_L, l_suppkey=_L, l_linenumber=_I, l_quantity=_D, l_extendedprice=_D, l_discount=_D, l_tax=_D, l_returnflag=_S, l_linestatus=_S, l_shipdate=_N),
    "orders": _schema(o_orderkey=_L, o_custkey=_L, o_orderstatus=_S, o_totalprice=_D, o_orderdate=_N, o_orderpriority=_S),
    "events": _schema(event_id=_L, ts=_N, user_id=_L, event_type=_S, value=_D, props=_S),
}
#: Run log of a training method, and a compressed message.
RUN_LOG = _schema(method=_S, seed=_I, m=_I, k_frac=_D, step=_I, bits_cum=_L, loss=_D, acc=_D, grad_norm2=_D)
MESSAGE = _schema(step=_I, worker=_I, kind=_S, level=_I, q=_D, scale=_D, pos=T.ArrayType(_L), val=T.ArrayType(_D), payload=T.BinaryType(), bits=_L)


def load(spark: SparkSession, directory: str, name: str, *columns: str) -> DataFrame:
    """A table, with only the named columns if any; columns of a known schema must have its types."""
    df = spark.read.parquet(f"{directory}/{name}.parquet")
    for field in SCHEMAS.get(name, T.StructType([])):
        if field.name in df.columns and df.schema[field.name].dataType.simpleString() != field.dataType.simpleString():
            raise TypeError(f"{name}.{field.name} is {df.schema[field.name].dataType.simpleString()}, not {field.dataType.simpleString()}")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, path: str, form: str, schema: T.StructType) -> DataFrame:
    """Files of another form (json, csv, orc, parquet) with a stated schema; nothing is inferred."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if form == "csv" else reader).format(form).load(path)


def save(df: DataFrame, path: str, by: list[str] | None = None) -> None:
    """Writes Parquet; with ``by``, only the partitions that ``df`` holds are replaced, so a step that runs again leaves one copy."""
    writer = df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic")
    (writer.partitionBy(*by) if by else writer).parquet(path)
