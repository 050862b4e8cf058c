"""The names that SQL reaches: views of the fixtures, functions of words and costs, and a table function that traces decoding.

The functions are SQL expressions, which Catalyst puts into the plan of the statement that calls them; only
the trace runs Python.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import codec

_SET_BITS = "filter(sequence(0, 63), b -> getbit(w, b) = 1)"
#: Parameters, type and expression of each function.
FUNCTIONS = {
    "carrier_id_width": ("h BIGINT", "BIGINT", "CAST(IF(h <= 1, 1, length(bin(h - 1))) AS BIGINT)"),
    "carrier_bits_dense": ("h BIGINT", "BIGINT", "h"),
    "carrier_bits_list": ("k BIGINT, h BIGINT", "BIGINT", "k * carrier_id_width(h)"),
    "carrier_bits_hybrid": ("k BIGINT, h BIGINT", "BIGINT", "least(h, k * carrier_id_width(h))"),
    "carrier_row_encoding": ("k BIGINT, h BIGINT", "STRING", "IF(k * carrier_id_width(h) <= h, 'list', 'bitmap')"),
    "carrier_popcount": ("words ARRAY<BIGINT>", "BIGINT", "aggregate(words, 0L, (n, w) -> n + bit_count(w))"),
    "carrier_and": ("x ARRAY<BIGINT>, y ARRAY<BIGINT>", "ARRAY<BIGINT>", "zip_with(x, y, (a, b) -> a & b)"),
    "carrier_or": ("x ARRAY<BIGINT>, y ARRAY<BIGINT>", "ARRAY<BIGINT>", "zip_with(x, y, (a, b) -> a | b)"),
    "carrier_and_not": ("x ARRAY<BIGINT>, y ARRAY<BIGINT>", "ARRAY<BIGINT>", "zip_with(x, y, (a, b) -> a & ~b)"),
    "carrier_contains": ("words ARRAY<BIGINT>, hap BIGINT", "BOOLEAN", "getbit(get(words, CAST(hap DIV 64 AS INT)), CAST(hap % 64 AS INT)) = 1"),
    "carrier_ids": ("words ARRAY<BIGINT>", "ARRAY<BIGINT>", f"flatten(transform(words, (w, i) -> transform({_SET_BITS}, b -> CAST(i AS BIGINT) * 64 + b)))"),
}


def register_functions(spark: SparkSession) -> None:
    for name, (parameters, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {kind} RETURN {body}")


def register_views(views: dict[str, DataFrame]) -> None:
    """Each DataFrame as a temporary view, for any statement of the session."""
    for name, rows in views.items():
        rows.createOrReplaceTempView(name)


def register_trace(spark: SparkSession, codebook: DataFrame, name: str = "trace_decode") -> None:
    """The table function ``name(bits, n_bits)`` -> (step, ctx, code, sym, bit_offset, status) of one codebook, of a checked size, sent to the executors once."""
    sent = codec._decoder(codebook)

    class Trace:
        def __init__(self):
            self.decoder = codec.Decoder(*sent.value)

        def eval(self, bits: bytes, n_bits: int) -> Iterator[tuple]:
            for step, (ctx, code, sym, at) in enumerate(self.decoder.steps(bytes(bits or b""), n_bits or 0)):
                failed = isinstance(sym, str)
                yield step, ctx, code, None if failed else sym, at, sym if failed else "ok"

    made = F.udtf(Trace, returnType="step long, ctx long, code string, sym long, bit_offset long, status string")
    spark.udtf.register(name, made)
