"""Schemas of the logical tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, BooleanType, DoubleType, IntegerType, LongType, StringType, StructField, StructType


def _table(**fields) -> StructType:
    return StructType([StructField(n, t) for n, t in fields.items()])


NET_REF = _table(net_id=LongType(), weight=DoubleType())
PINS = _table(net_id=LongType(), vertex_id=LongType())
NETS = _table(net_id=LongType(), weight=DoubleType(), size=IntegerType())
VERTICES = _table(vertex_id=LongType(), seq=LongType(), weight=DoubleType())
VERTEX_STREAM = _table(seq=LongType(), vertex_id=LongType(), weight=DoubleType(), nets=ArrayType(NET_REF))
EDGES = _table(src=LongType(), dst=LongType(), weight=DoubleType())
ASSIGNMENT = _table(vertex_id=LongType(), block=IntegerType())
DECISIONS = _table(seq=LongType(), vertex_id=LongType(), block=IntegerType(), affinity=DoubleType(), score=DoubleType(), source=StringType(), touched=IntegerType(), evaluated=IntegerType())
NET_STATE = _table(net_id=LongType(), last_block=IntegerType(), is_cut=BooleanType(), last_seq=LongType())
BLOCKS = _table(block=IntegerType(), load=DoubleType())
RUNS = _table(instance=StringType(), k=IntegerType(), algorithm=StringType(), seed=IntegerType(), pins=LongType(), cut_net=DoubleType(), connectivity=DoubleType(), imbalance=DoubleType(), wall_ns=LongType())


def assert_schema(df: DataFrame, schema: StructType) -> DataFrame:
    """df narrowed to the schema's columns; an error where a column is missing or of another type."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if f.name not in have:
            raise ValueError(f"missing column {f.name}")
        if have[f.name].simpleString() != f.dataType.simpleString():
            raise ValueError(f"{f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df.select(*schema.names)
