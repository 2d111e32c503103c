"""Declared schemas of what stages hand on, and a check at their borders."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

PAGES = "page_id long, url string, html string"
DOCUMENTS = "doc_id long, text string, lang string, source string, n_chars long"
SEGMENTS = "array<struct<pos:int,kind:string,text:string,image_url:string>>"
INTERLEAVED = f"page_id long, url string, segments {SEGMENTS}"
PARALLEL = "doc_id long, texts array<string>, images array<string>"
IMAGE_REFS = "doc_id long, pos long, image_url string"
FETCHED = "image_url string, status string, sha256 string, bytes binary"
SIGNATURES = "doc_id long, sig array<long>"
EDGES = "src long, dst long"
SCORES = "doc_id long, prob double"
LEDGER = "step int, stage string, n_in long, n_out long"


def check(df: DataFrame, schema: str) -> DataFrame:
    """df if it has the schema's columns with their types (others may follow); raises else. Nullability isn't compared."""
    want = T.StructType.fromDDL(schema)
    for field in want:
        if field.name not in df.columns:
            raise ValueError(f"no column {field.name}")
        if df.schema[field.name].dataType.simpleString() != field.dataType.simpleString():
            raise TypeError(f"{field.name} is {df.schema[field.name].dataType.simpleString()}, not {field.dataType.simpleString()}")
    return df
