"""Rows written in one file format and scanned again, with the schema that they had."""

from __future__ import annotations

from pyspark.sql import DataFrame

from slicegrad.sources.store import shared_folder

_MICROS = "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"

#: What keeps nulls, empty texts, blanks, line breaks and microseconds apart in each format.
OPTIONS = {
    "csv": {"header": True, "nullValue": "\\N", "escape": '"', "multiLine": True, "ignoreLeadingWhiteSpace": False, "ignoreTrailingWhiteSpace": False, "timestampNTZFormat": _MICROS},
    "json": {"ignoreNullFields": False, "timestampNTZFormat": _MICROS},
    "orc": {},
    "parquet": {},
    "text": {},
}


def scanned(df: DataFrame, kind: str) -> DataFrame:
    """``df`` by way of files of the ``kind`` in the shared folder. The schema is given to the reader, not inferred
    from another pass. ``text`` takes one string column, a line a row; nulls and line breaks don't survive it."""
    if kind not in OPTIONS:
        raise ValueError(f"kind is one of {sorted(OPTIONS)}")
    folder = shared_folder(df.sparkSession, kind)
    df.write.format(kind).options(**OPTIONS[kind]).save(folder)
    return df.sparkSession.read.format(kind).options(**OPTIONS[kind]).schema(df.schema).load(folder)
