"""Configurations as words of 63 bits: packing, counting, moving.  Lowest orbital is bit 0 of ``w0``."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from detspark.functions.schema import BITS


def _span(m: int, k: int) -> int:
    """Orbitals in word ``k``."""
    return min(BITS, m - k * BITS)


def _one(position: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), position.cast("int"))


def _inside(k: int):
    return lambda p: (p >= k * BITS) & (p < (k + 1) * BITS)


def _gathered(k: int):
    return lambda acc, p: acc.bitwiseOR(_one(p - k * BITS))


def pack(orbitals: Column, m: int) -> list[Column]:
    """Words of an array of occupied orbitals."""
    words = range(max(1, -(-m // BITS)))
    return [F.aggregate(F.filter(orbitals, _inside(k)), F.lit(0).cast("long"), _gathered(k)) for k in words]


def parse(text: Column, m: int) -> list[Column]:
    """Words of a string of 0 and 1, highest orbital first."""
    low = F.reverse(F.lpad(text, m, "0"))
    positions = F.filter(F.sequence(F.lit(0), F.lit(m - 1)), lambda p: F.substr(low, p + 1, F.lit(1)) == "1")
    return pack(positions, m)


def show(words: list[Column], m: int) -> Column:
    """The string of 0 and 1, highest orbital first."""
    parts = [F.lpad(F.bin(w), _span(m, k), "0") for k, w in enumerate(words)]
    return F.concat(*parts[::-1])


def _has(word: Column, bit: int):
    return lambda i: F.getbit(word, i) == bit


def _select(words: list[Column], m: int, bit: int) -> Column:
    parts = [F.filter(F.sequence(F.lit(0), F.lit(_span(m, k) - 1)), _has(w, bit)) for k, w in enumerate(words)]
    parts = [F.transform(x, _shifted(k)) if k else x for k, x in enumerate(parts)]
    return F.concat(*parts) if len(parts) > 1 else parts[0]


def _shifted(k: int):
    return lambda i: i + k * BITS


def occupied(words: list[Column], m: int) -> Column:
    """Occupied orbitals, rising."""
    return _select(words, m, 1)


def virtual(words: list[Column], m: int) -> Column:
    """Empty orbitals, rising."""
    return _select(words, m, 0)


def flip(words: list[Column], masks: list[Column]) -> list[Column]:
    return [w.bitwiseXOR(x) for w, x in zip(words, masks, strict=True)]


def popcount(words: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, [F.bit_count(w) for w in words])


def overlap(words: list[Column], masks: list[Column]) -> Column:
    """Number of common ones."""
    return popcount([w.bitwiseAND(x) for w, x in zip(words, masks, strict=True)])


# --- the same on the driver and in Arrow batches ---


def mask_words(orbitals: list[int], m: int) -> list[int]:
    out = [0] * max(1, -(-m // BITS))
    for p in orbitals:
        out[p // BITS] |= 1 << (p % BITS)
    return out


def between(p: int, a: int, m: int) -> list[int]:
    """Orbitals strictly between two, as words."""
    return mask_words(list(range(min(p, a) + 1, max(p, a))), m)


def to_bits(words: np.ndarray, m: int) -> np.ndarray:
    """Occupation matrix (rows x m) of a word matrix (rows x words)."""
    p = np.arange(m)
    return ((words[:, p // BITS] >> (p % BITS)) & 1).astype(np.int8)


def from_bits(bits: np.ndarray) -> np.ndarray:
    m = bits.shape[1]
    out = np.zeros((len(bits), max(1, -(-m // BITS))), np.int64)
    for p in range(m):
        out[:, p // BITS] |= bits[:, p].astype(np.int64) << (p % BITS)
    return out


def occupied_rows(words: np.ndarray, m: int, n: int) -> np.ndarray:
    """Occupied orbitals of each row (rows x n); every row has ``n``."""
    return np.nonzero(to_bits(words, m))[1].reshape(len(words), n)


def parity(words: np.ndarray) -> np.ndarray:
    return np.bitwise_count(words).sum(axis=-1) & 1
