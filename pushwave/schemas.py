"""Fixed schemas of the engine's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T


_TYPES = {"long": T.LongType(), "double": T.DoubleType()}


def _schema(text: str) -> T.StructType:
    """From 'name type, ...', without a session."""
    return T.StructType([T.StructField(name, _TYPES[kind]) for name, kind in map(str.split, text.split(", "))])


ARCS = _schema("src long, dst long")
OUT_ARCS = _schema("src long, pos long, dst long, src_deg long, dst_deg long")
NODES = _schema("v long, out_deg long, in_deg long")
STATE = _schema("query_id long, v long, deg long, p double, r double, touched long")
ALLOC = _schema("query_id long, start long, n_walks long, weight double")
INDEX = _schema("start long, walk_no long, endpoint long")
PPR = _schema("query_id long, v long, score double")


def conform(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df with the schema's columns in order, cast; a missing column is an error."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"missing columns {missing}")
    return df.select(*(df[f.name].cast(f.dataType).alias(f.name) for f in schema))
