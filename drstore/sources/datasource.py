"""``spark.read.format("drstore")``: documents of an encoded store, with filters on doc_id pushed to the files.

Options: path (a store written by ``write_store``), dictionary (a folder written by ``Dictionary.save``).
"""

from __future__ import annotations

import os
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.dataset as ds
import pyarrow.parquet as pq
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual


class Piece(InputPartition):
    def __init__(self, path: str):
        self.path = path


class StoreReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.dictionary = options["path"], options["dictionary"]
        self.low, self.high, self.ids = None, None, None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        for f in filters:
            name = getattr(f, "attribute", None)
            if name != ("doc_id",):
                yield f
            elif isinstance(f, EqualTo):
                self.ids = {f.value} if self.ids is None else self.ids & {f.value}
            elif isinstance(f, In):
                self.ids = set(f.value) if self.ids is None else self.ids & set(f.value)
            elif isinstance(f, (GreaterThan, GreaterThanOrEqual)):
                v = f.value + isinstance(f, GreaterThan)
                self.low = v if self.low is None else max(self.low, v)
            elif isinstance(f, (LessThan, LessThanOrEqual)):
                v = f.value - isinstance(f, LessThan)
                self.high = v if self.high is None else min(self.high, v)
            else:
                yield f

    def _wanted(self):
        test = None
        for part in (
            pc.field("doc_id") >= self.low if self.low is not None else None,
            pc.field("doc_id") <= self.high if self.high is not None else None,
            pc.field("doc_id").isin(sorted(self.ids)) if self.ids is not None else None,
        ):
            if part is not None:
                test = part if test is None else test & part
        return test

    def partitions(self) -> list[InputPartition]:
        """Files whose range of doc_id can hold a wanted id."""
        out = []
        low = max((x for x in (self.low, min(self.ids) if self.ids else None) if x is not None), default=None)
        high = min((x for x in (self.high, max(self.ids) if self.ids else None) if x is not None), default=None)
        for name in ds.dataset(self.path, format="parquet", partitioning="hive").files:
            meta = pq.ParquetFile(name).metadata
            at = meta.schema.names.index("doc_id")
            stats = [meta.row_group(i).column(at).statistics for i in range(meta.num_row_groups)]
            if any(s is None or ((low is None or s.max >= low) and (high is None or s.min <= high)) for s in stats):
                out.append(Piece(name))
        return out

    def read(self, partition: Piece) -> Iterator[pa.RecordBatch]:
        from ..operators import codecs
        from ..operators.factorize import decode_document

        d = open(os.path.join(self.dictionary, "dict.bin"), "rb").read()  # noqa: SIM115
        for b in ds.dataset(partition.path, format="parquet").to_batches(columns=["doc_id", "codec", "n_bytes", "pos_stream", "len_stream"], filter=self._wanted(), batch_size=512):
            out = []
            for codec, p, k in zip(b["codec"].to_pylist(), b["pos_stream"].to_pylist(), b["len_stream"].to_pylist(), strict=True):
                pos, length = codecs.decode_pairs(p, k, codec)
                out.append(decode_document(pos.tolist(), length.tolist(), d))
            yield pa.RecordBatch.from_arrays([b["doc_id"], b["n_bytes"], pa.array(out, pa.binary())], names=["doc_id", "n_bytes", "body"])


class StoreSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "drstore"

    def schema(self) -> str:
        return "doc_id long, n_bytes long, body binary"

    def reader(self, schema) -> StoreReader:
        return StoreReader(self.options)


def register(spark) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(StoreSource)
