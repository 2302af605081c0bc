"""Schemas of the tables that operators exchange, and checks at their borders."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T


_TYPES = {"long": T.LongType(), "int": T.IntegerType(), "double": T.DoubleType(), "string": T.StringType(), "timestamp_ntz": T.TimestampNTZType(), "array<float>": T.ArrayType(T.FloatType())}


def _struct(text: str) -> T.StructType:
    """A schema from "name type, …"; needs no running session, so executors can import this module."""
    return T.StructType([T.StructField(name, _TYPES[kind]) for name, kind in (c.split(" ") for c in text.split(", "))])


EDGES = _struct("edge_id long, u long, v long, w double, channel int")
LABELS = _struct("v long, cluster long")
EXCLUSIONS = _struct("a long, b long")
ACTIVE = _struct("edge_id long, u long, v long, w double, active int")
SEEDS = _struct("v long, seed long")


def ddl(schema: T.StructType) -> str:
    return ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in schema.fields)


def require(df: DataFrame, schema: T.StructType, what: str) -> DataFrame:
    """df's columns of the schema, in its order; raises if one is missing or of another type."""
    have = {f.name: f.dataType for f in df.schema.fields}
    wrong = [f"{f.name} {f.dataType.simpleString()}" for f in schema.fields if have.get(f.name) != f.dataType]
    if wrong:
        raise TypeError(f"{what} needs columns {', '.join(wrong)}; it has {df.schema.simpleString()}")
    return df.select(*schema.names)


#: The given tables, read with these schemas, never inferred.
TABLES = {
    "region": _struct("r_regionkey int, r_name string"),
    "nation": _struct("n_nationkey int, n_name string, n_regionkey int"),
    "customer": _struct("c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string"),
    "supplier": _struct("s_suppkey long, s_name string, s_nationkey int, s_acctbal double"),
    "part": _struct("p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double"),
    "orders": _struct("o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string"),
    "lineitem": _struct("l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz"),
    "events": _struct("event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"),
    "documents": _struct("doc_id long, text string, lang string, source string, n_chars long"),
    "labels": _struct("doc_id long, quality int, toxic int"),
    "embeddings": _struct("vec_id long, embedding array<float>, label int"),
    "pages": _struct("page_id long, url string, html string"),
    "benchmark": _struct("item_id long, text string"),
    "conversations": _struct("conv_id long, turn long, role string, text string"),
}
