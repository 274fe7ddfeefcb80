"""Schemas of the tables that the store reads and writes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

COLLECTION = "doc_id long, ord long, body binary, n_bytes long, start_off long"
SAMPLES = "k long, start long, bytes binary"
FACTORS = "doc_id long, factors array<struct<pos:long,len:int>>"
ENCODED = "doc_id long, dict_version int, codec string, n_bytes long, n_factors long, pos_stream binary, len_stream binary"
DOCMAP = "doc_id long, segment int, byte_off long, byte_len long"
BLOCKS = "block_id long, first_ord long, n_docs long, raw_bytes long, members array<struct<doc_id:long,off:long,len:long>>, payload binary"
REQUESTS = "req_no long, doc_id long"
MEASURES = "workload string, config map<string,string>, metric string, value double"


def require(df: DataFrame, schema: str) -> DataFrame:
    """df, after a check that it has the columns of a schema with these types."""
    have = {f.name: f.dataType for f in df.schema}
    for f in T._parse_datatype_string(schema):
        if have.get(f.name) is None or have[f.name].simpleString() != f.dataType.simpleString():
            raise TypeError(f"column {f.name}: {f.dataType.simpleString()} wanted, {have.get(f.name) and have[f.name].simpleString()} found")
    return df
