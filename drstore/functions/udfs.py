"""SQL functions of the store: codes, compressors, factors and traces."""

from __future__ import annotations

import lzma
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf

from ..operators import codecs
from ..operators.baselines import zlib_size_agg
from ..operators.dictionary import Dictionary, Shipped
from ..operators.factorize import decode_document, factor_batch, factor_document, factor_lists


def _lists(a: pa.Array) -> list[np.ndarray]:
    return [np.array(x or [], np.int64) for x in a.to_pylist()]


def general() -> tuple[dict, dict]:
    """(functions, table functions) by name, made when a session exists."""

    @arrow_udf("binary")
    def vbyte_encode(a: pa.Array) -> pa.Array:
        return pa.array([codecs.enc_v(x) for x in _lists(a)], pa.binary())

    @arrow_udf("array<bigint>")
    def vbyte_decode(a: pa.Array) -> pa.Array:
        return pa.array([codecs.dec_v(x or b"").tolist() for x in a.to_pylist()], pa.list_(pa.int64()))

    @arrow_udf("binary")
    def u32_pack(a: pa.Array) -> pa.Array:
        return pa.array([codecs.enc_u(x) for x in _lists(a)], pa.binary())

    @arrow_udf("array<bigint>")
    def u32_unpack(a: pa.Array) -> pa.Array:
        return pa.array([codecs.dec_u(x or b"").tolist() for x in a.to_pylist()], pa.list_(pa.int64()))

    @arrow_udf("binary")
    def z_compress(a: pa.Array) -> pa.Array:
        return pa.array([None if x is None else zlib.compress(x, 9) for x in a.to_pylist()], pa.binary())

    @arrow_udf("binary")
    def z_expand(a: pa.Array) -> pa.Array:
        return pa.array([None if x is None else zlib.decompress(x) for x in a.to_pylist()], pa.binary())

    @arrow_udf("binary")
    def lzma_compress(a: pa.Array) -> pa.Array:
        return pa.array([None if x is None else lzma.compress(x) for x in a.to_pylist()], pa.binary())

    @arrow_udf("binary")
    def lzma_expand(a: pa.Array) -> pa.Array:
        return pa.array([None if x is None else lzma.decompress(x) for x in a.to_pylist()], pa.binary())


    @F.udtf(returnType="seq int, value long")
    class VbyteValues:
        """The numbers of a V stream, one a row."""

        def eval(self, stream: bytes):
            for i, v in enumerate(codecs.dec_v(bytes(stream or b"")).tolist()):
                yield i, v

    functions = {f.__name__: f for f in (vbyte_encode, vbyte_decode, u32_pack, u32_unpack, z_compress, z_expand, lzma_compress, lzma_expand)}
    return functions | {"z_size_agg": zlib_size_agg()}, {"vbyte_values": VbyteValues}


def for_dictionary(spark: SparkSession, dictionary: Dictionary) -> dict:
    """Functions bound to a dictionary: drf_factorize(body), drf_decode(factors), and table functions drf_factors(body), refine_trace(x)."""
    ship = Shipped(spark, dictionary)

    @arrow_udf("array<struct<pos:bigint,len:int>>")
    def drf_factorize(a: pa.Array) -> pa.Array:
        return factor_lists(*factor_batch([x or b"" for x in a.to_pylist()], ship.searcher()))

    @arrow_udf("binary")
    def drf_decode(a: pa.Array) -> pa.Array:
        d = ship.data()
        return pa.array([decode_document([f["pos"] for f in x or []], [f["len"] for f in x or []], d) for x in a.to_pylist()], pa.binary())

    @F.udtf(returnType="seq int, pos long, len int")
    class DrfFactors:
        def eval(self, body: bytes):
            p, k = factor_document(bytes(body or b""), ship.searcher())
            yield from zip(range(len(p)), p, k, strict=True)

    @F.udtf(returnType="j int, lb int, rb int")
    class RefineTrace:
        def eval(self, x: bytes):
            for j, got in ship.searcher().trace(bytes(x or b"")):
                yield (j, *(got or (None, None)))

    return {"drf_factorize": drf_factorize, "drf_decode": drf_decode, "drf_factors": DrfFactors, "refine_trace": RefineTrace}


def register(spark: SparkSession, dictionary: Dictionary | None = None) -> None:
    """Register everything for SQL; what is bound to a dictionary only with one."""
    functions, tables = general()
    if dictionary is not None:
        bound = for_dictionary(spark, dictionary)
        functions |= {k: bound[k] for k in ("drf_factorize", "drf_decode")}
        tables |= {k: bound[k] for k in ("drf_factors", "refine_trace")}
    for name, f in functions.items():
        spark.udf.register(name, f)
    for name, f in tables.items():
        spark.udtf.register(name, f)
