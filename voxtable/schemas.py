"""Declared schemas of the input tables. Reading never infers: a table that does not fit is refused."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

COLUMNS = {
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "labels": "doc_id bigint, quality int, toxic int",
    "benchmark": "item_id bigint, text string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "pages": "page_id bigint, url string, html string",
}


def require_schema(df: DataFrame, table: str) -> DataFrame:
    """The frame, if it has the table's columns with types that widen to the declared ones."""
    for part in COLUMNS.get(table, "").split(", "):
        if part:
            name, kind = part.split(" ", 1)
            have = dict(df.dtypes).get(name)
            wider = {"int": "bigint", "float": "double", "array<double>": "array<float>", "bigint": "int", "timestamp": "timestamp_ntz"}
            if have != kind and wider.get(have or "") != kind:
                raise TypeError(f"{table}.{name}: {have} where {kind} is declared")
    return df


RESULT_CELLS = T.StructType(
    [
        T.StructField("tbl", T.StringType()),
        T.StructField("model", T.StringType()),
        T.StructField("subset", T.StringType()),
        T.StructField("metric", T.StringType()),
        T.StructField("value", T.DoubleType()),
    ]
)
