"""Arrays of small cells packed into 64-bit words, in numpy and as Spark expressions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def pack(cells: np.ndarray, width: int) -> np.ndarray:
    """Words that hold the cells one after the other, with a spare word at the end."""
    words = np.zeros(len(cells) * width // 64 + 2, np.uint64)
    at = np.arange(len(cells), dtype=np.int64) * width
    w, o = at >> 6, (at & 63).astype(np.uint64)
    v = cells.astype(np.uint64)
    np.bitwise_or.at(words, w, v << o)
    high = np.where(o > 0, (v >> np.uint64(1)) >> (np.uint64(63) - o), np.uint64(0))
    np.bitwise_or.at(words, w + 1, high)
    return words.view(np.int64)


def read_np(words: np.ndarray, cell: np.ndarray, width: int) -> np.ndarray:
    words = words.view(np.uint64)
    at = cell.astype(np.int64) * width
    w, o = at >> 6, (at & 63).astype(np.uint64)
    mask = np.uint64((1 << width) - 1)
    return ((words[w] >> o) | ((words[w + 1] << np.uint64(1)) << (np.uint64(63) - o))) & mask


def read_col(words: Column, cell: Column, width: Column | int) -> Column:
    width = width if isinstance(width, Column) else F.lit(width)
    return read_at(words, cell.cast("long") * width, width)


def read_at(words: Column, at: Column, width: Column) -> Column:
    """The ``width`` bits from bit ``at`` on."""
    w, o = F.call_function("shiftright", at, F.lit(6)).cast("int"), at.bitwiseAND(F.lit(63)).cast("int")
    low = F.call_function("shiftrightunsigned", F.get(words, w), o)
    high = F.call_function("shiftleft", F.shiftleft(F.get(words, w + 1), 1), F.lit(63) - o)
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), width.cast("int")) - 1
    return low.bitwiseOR(high).bitwiseAND(mask)


def bit_col(words: Column, bit: Column) -> Column:
    word = F.get(words, F.shiftright(bit.cast("long"), 6).cast("int"))
    return F.call_function("shiftrightunsigned", word, bit.bitwiseAND(F.lit(63)).cast("int")).bitwiseAND(F.lit(1))
