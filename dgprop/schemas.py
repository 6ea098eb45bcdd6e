"""Schemas of the tables that operators exchange, and a check against them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import _parse_datatype_string

EVENTS = "seq bigint, ts timestamp, kind string, src bigint, dst bigint, w double"
EDGE_DELTAS = "step int, src bigint, dst bigint, dw double"
EDGES = "src bigint, dst bigint, w double"
FEATURES = "node bigint, x array<double>"
REPRESENTATIONS = "step int, node bigint, z array<double>"
LABELS = "node bigint, step int, label int"
PAIRS = "query_id bigint, step int, src bigint, dst bigint, label int"


def check(df: DataFrame, schema: str) -> DataFrame:
    """The frame's columns of the schema, in its order; a missing or differently typed one is an error."""
    have = {f.name: f.dataType for f in df.schema}
    for f in _parse_datatype_string(schema).fields:
        if f.name not in have:
            raise ValueError(f"no column {f.name}")
        if have[f.name].simpleString().replace("timestamp_ntz", "timestamp") != f.dataType.simpleString():
            raise ValueError(f"{f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df.select(*[f.name for f in _parse_datatype_string(schema).fields])
