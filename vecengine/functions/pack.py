"""Dense packing of B-bit codes, and the bytes that codecs take."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from vecengine.functions.vectors import col

#: Bits of a stored constant, of an original component, of an edge.
CONST_BITS, FLOAT_BITS, EDGE_BYTES = 16, 32, 4
LINE = 32


def pack(codes, bits: int, pad: int = 1) -> Column:
    """Codes as bytes: 8 and 4 bits inside the JVM (low nibble first), others by an Arrow kernel."""
    codes = col(codes)
    if bits == 8:
        out = F.unhex(F.concat_ws("", F.transform(codes, lambda c: F.lpad(F.hex(c), 2, "0"))))
    elif bits == 4:
        even = F.filter(codes, lambda _, i: i % 2 == 0)
        odd = F.filter(codes, lambda _, i: i % 2 == 1)
        out = F.unhex(F.concat_ws("", F.zip_with(even, odd, lambda lo, hi: F.concat(F.hex(F.coalesce(hi, F.lit(0))), F.hex(lo)))))
    else:
        out = _kernel(bits)(codes)
    if pad <= 1:
        return out
    full = F.ceil(F.octet_length(out) / pad).cast("int") * pad
    return F.unhex(F.rpad(F.hex(out), full * 2, "0"))


def _kernel(bits: int):
    @F.pandas_udf("binary")
    def run(codes: pd.Series) -> pd.Series:
        return codes.map(lambda c: pack_bits(np.asarray(c), bits))

    return run


def pack_bits(codes: np.ndarray, bits: int) -> bytes:
    """Codes one after the other, each with its lowest bit first."""
    planes = (codes.astype(np.int64)[:, None] >> np.arange(bits)) & 1
    return np.packbits(planes.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpack_bits(data: bytes, bits: int, d: int) -> np.ndarray:
    planes = np.unpackbits(np.frombuffer(data, np.uint8), count=bits * d, bitorder="little").reshape(d, bits)
    return (planes.astype(np.int64) << np.arange(bits)).sum(axis=1)


def footprint(d, bits, pad=1, bits2=0, codec: str = "pv") -> Column:
    """Bytes of a stored vector.

    pv keeps two constants with each vector; gl and pd share theirs among all
    rows. The second level is a stream of its own and is not padded. pad 0
    means no padding.
    """
    lit = lambda v: v if isinstance(v, Column) else F.lit(v)
    d, bits, pad, bits2 = map(lit, (d, bits, pad, bits2))
    if codec in ("f32", "f16"):
        return (d * (4 if codec == "f32" else 2)).cast("long")
    own = 2 * CONST_BITS if codec == "pv" else 0
    unit = F.greatest(pad, F.lit(1))
    first = F.ceil((d * bits + own) / (unit * 8)) * unit
    return (first + F.ceil(d * bits2 / 8)).cast("long")


def compression_ratio(d, bytes_) -> Column:
    return (d if isinstance(d, Column) else F.lit(d)) * (FLOAT_BITS / 8) / bytes_


def index_bytes(n, vector_bytes, degree) -> Column:
    """Vectors and a flat adjacency list of ``degree`` four-byte ids each."""
    return n * (vector_bytes + EDGE_BYTES * degree)
