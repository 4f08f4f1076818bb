"""Binary codes: a bit is set where the code is +1. Up to 64 bits are one BIGINT, more are words of 64."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def pack_bits(bits: Column) -> Column:
    """BIGINT of an array of at most 64 zeros and ones; element i is bit i."""
    return F.aggregate(F.transform(bits, lambda x, i: F.call_function("shiftleft", x.cast("long"), i)), F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b))


def unpack_bits(code: Column, n_bits: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(n_bits - 1)), lambda i: F.call_function("shiftrightunsigned", code, i).bitwiseAND(F.lit(1).cast("long")).cast("int"))


def hamming(a: Column, b: Column) -> Column:
    """Differing bits of two BIGINT codes."""
    return F.bit_count(a.bitwiseXOR(b))


def hamming_words(a: Column, b: Column) -> Column:
    """Differing bits of two codes of several words."""
    return F.aggregate(F.zip_with(a, b, hamming), F.lit(0), lambda x, y: x + y)


def code_l1(a: Column, b: Column) -> Column:
    """Distance of the codes as vectors of -1 and +1 in the 1-norm."""
    return 2 * hamming(a, b)


def band_keys(code: Column, n_bits: int, bands: int) -> Column:
    """Array of (band, value) of even cuts of the bits."""
    cuts = [int(x) for x in np.linspace(0, n_bits, bands + 1)]
    return F.array(*[F.struct(F.lit(i).alias("band"), F.call_function("shiftrightunsigned", code, F.lit(lo)).bitwiseAND(F.lit((1 << (hi - lo)) - 1 if hi - lo < 63 else -1).cast("long")).alias("value")) for i, (lo, hi) in enumerate(zip(cuts, cuts[1:]))])


def pack_array(signs: np.ndarray) -> np.ndarray:
    """(n, L) of booleans to int64 codes, L <= 64, or to (n, words)."""
    n, bits = signs.shape
    words = -(-bits // 64)
    padded = np.zeros((n, words * 64), bool)
    padded[:, :bits] = signs
    out = np.packbits(padded, axis=1, bitorder="little").view("<i8").reshape(n, words)
    return out[:, 0] if words == 1 else out


def unpack_array(codes: np.ndarray, n_bits: int) -> np.ndarray:
    """(n, L) of -1.0 and +1.0."""
    words = np.ascontiguousarray(codes.astype("<i8")).reshape(len(codes), -1)
    bits = np.unpackbits(words.view(np.uint8), axis=1, bitorder="little")[:, :n_bits]
    return bits.astype(float) * 2 - 1
