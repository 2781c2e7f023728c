"""52-bit hashes of canonical strings, and what the counters and the gate read from them.

`portable` is md5-based and can be computed in any SQL engine; `fast` is xxhash64. Both run in the JVM. Sketches remember which one they
are made of, since the two must not be merged. Tags keep the draws independent: "c|" counter, "g|" gate, "p|" pair, "r<i>|" row i of a grid.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

HASH_BITS = 52
LOW_BITS = 24  # their remainder by a few thousand is even to a part in thousands
HASHES = ("portable", "fast")


def canonical(column: Column, kind: T.DataType) -> Column:
    """The string that stands for a label or an item. Floating numbers, maps and arrays are refused; structs become JSON."""
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        raise TypeError("a floating-point label or item has no canonical form; round it to a decimal first")
    if isinstance(kind, (T.MapType, T.ArrayType)):
        raise TypeError("a map or an array can't be a label or an item; explode it first")
    if isinstance(kind, T.StructType):
        return F.to_json(column)
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        # the same text in any session time zone
        return F.unix_micros(column).cast("string") if isinstance(kind, T.TimestampType) else F.date_format(column, "yyyy-MM-dd'T'HH:mm:ss.SSSSSS")
    return column.cast("string")


def hash52(column: Column, tag: str, hash: str = "portable", seed: int = 0) -> Column:
    """A hash of a string, 0 to 2**52 - 1."""
    text = F.concat(F.lit(f"{tag}{seed or ''}|"), column)
    if hash == "portable":
        return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("bigint")
    if hash == "fast":
        return F.shiftrightunsigned(F.xxhash64(text), 12)
    raise ValueError(f"hash must be one of {HASHES}")


def bit_length(w: Column) -> Column:
    """Binary digits of a number of at least 0; 0 has none."""
    return F.when(w == 0, 0).otherwise(F.length(F.bin(w)))


def bucket_and_rank(h: Column, m: int) -> tuple[Column, Column]:
    """The register of a hash, and 1 + the leading zeros of other bits. Powers of two take leading bits and the rest; any other m a remainder of the LOW_BITS lowest bits, and the bits above."""
    if m & (m - 1) == 0:
        rest = HASH_BITS - (m.bit_length() - 1)
        return F.shiftright(h, rest).cast("int"), (rest + 1 - bit_length(h.bitwiseAND(F.lit((1 << rest) - 1)))).cast("tinyint")
    low = h.bitwiseAND(F.lit((1 << LOW_BITS) - 1))
    return F.pmod(low, F.lit(m)).cast("int"), (HASH_BITS - LOW_BITS + 1 - bit_length(F.shiftright(h, LOW_BITS))).cast("tinyint")


def draw(h: Column) -> Column:
    """1 / h(x) for a hash x of the open unit interval: above 1, and above a with probability 1 / a."""
    return F.lit(float(1 << HASH_BITS)) / (h + F.lit(0.5))


def gate_pass_probability(a: Column) -> Column:
    """The chance that a draw is above a."""
    return F.when(a <= 1, 1.0).otherwise(1 / a)
