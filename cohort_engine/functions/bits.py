"""Fixed-width bit packing: as many values as fit go into a 64-bit word, so any one can be read by itself."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def bits_needed(largest: int) -> int:
    """Bits for values from 0 to ``largest``; none if zero is the only one."""
    return int(largest).bit_length()


def pack(values: np.ndarray) -> tuple[int, np.ndarray]:
    """Bits a value and the words, as signed 64-bit integers. Values are not negative."""
    values = np.asarray(values, np.uint64)
    bits = bits_needed(int(values.max())) if len(values) else 0
    if bits == 0:
        return 0, np.zeros(0, np.int64)
    per = 64 // bits
    padded = np.zeros(-(-len(values) // per) * per, np.uint64)
    padded[: len(values)] = values
    shifts = (np.arange(per, dtype=np.uint64) * np.uint64(bits))[None, :]
    return bits, np.bitwise_or.reduce(padded.reshape(-1, per) << shifts, axis=1).view(np.int64)


def unpack(bits: int, words: np.ndarray, n: int) -> np.ndarray:
    if bits == 0:
        return np.zeros(n, np.int64)
    per = 64 // bits
    mask = np.uint64((1 << bits) - 1)
    shifts = (np.arange(per, dtype=np.uint64) * np.uint64(bits))[None, :]
    return ((np.asarray(words, np.int64).view(np.uint64)[:, None] >> shifts) & mask).reshape(-1)[:n].astype(np.int64)


def read_at(bits: int, words: np.ndarray, place: int) -> int:
    """One value, without unpacking the others."""
    if bits == 0:
        return 0
    per = 64 // bits
    return (int(words[place // per]) & 0xFFFFFFFFFFFFFFFF) >> (place % per * bits) & ((1 << bits) - 1)


def read_many(bits: int, words: np.ndarray, places: np.ndarray) -> np.ndarray:
    """The values at some places, as unsigned numbers, without unpacking the others."""
    if bits == 0:
        return np.zeros(len(places), np.uint64)
    per = 64 // bits
    place = np.asarray(places, np.int64)
    shifts = ((place % per) * bits).astype(np.uint64)
    return (np.asarray(words, np.int64).view(np.uint64)[place // per] >> shifts) & np.uint64((1 << bits) - 1)


def read_column(bits: Column, words: Column, place: Column) -> Column:
    """The same read as an expression, for packed columns in a table."""
    per = F.lit(64).cast("int") / bits
    per = F.floor(per).cast("int")
    word = F.get(words, F.floor(place / per).cast("int"))
    shifted = F.call_function("shiftrightunsigned", word, (F.pmod(place, per) * bits).cast("int"))
    mask = F.call_function("shiftleft", F.lit(1).cast("bigint"), bits) - 1
    return F.when(bits == 0, F.lit(0).cast("bigint")).when(bits == 64, word).otherwise(shifted.bitwiseAND(mask))
