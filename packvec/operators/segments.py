"""Codes of variable length in shared words of seg_bits bits, and back.

Codes stand one after the other from the highest bit of the first word. The column form makes one compact expression for
each word or dimension, which stays in generated code; the array form packs whole matrices.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def offsets(bits: Sequence[int]) -> list[int]:
    out, at = [], 0
    for b in bits:
        out.append(at)
        at += b
    return out


def words_needed(bits: Sequence[int], seg_bits: int) -> int:
    return -(-sum(bits) // seg_bits)


def pack(codes: Column, bits: Sequence[int], seg_bits: int) -> list[Column]:
    """One long column for each word, its value unsigned below 64 bits. codes: an array of whole numbers."""
    where, out = offsets(bits), []
    mask = (1 << seg_bits) - 1
    for g in range(words_needed(bits, seg_bits)):
        low, high = g * seg_bits, (g + 1) * seg_bits
        word = F.lit(0).cast("long")
        for j, (at, b) in enumerate(zip(where, bits)):
            if b and at < high and at + b > low:
                shift, code = high - (at + b), F.get(codes, j).cast("long")
                part = F.shiftleft(code, shift) if shift >= 0 else F.shiftrightunsigned(code, -shift)
                word = word.bitwiseOR(part.bitwiseAND(F.lit(mask)) if seg_bits < 64 else part)
        out.append(word.alias(f"seg_{g:03d}"))
    return out


def pack_plain(codes: Column, bits: Sequence[int], seg_bits: int) -> list[Column]:
    """One word a dimension: the layout that packing is compared with."""
    kind = {8: "smallint", 16: "int", 32: "long", 64: "long"}[seg_bits]  # unsigned values of that width
    return [F.get(codes, j).cast(kind).alias(f"dim_{j:03d}") for j in range(len(bits))]


def extract(bits: Sequence[int], dim: int, seg_bits: int) -> Column:
    """The code of one dimension from the words it lies in, and no others.

    In each word, bits to the left of the dimension are masked away and bits to the right shifted out; the pieces of a
    dimension over several words are shifted to their places and joined.
    """
    at, b = offsets(bits)[dim], bits[dim]
    out = F.lit(0).cast("long")
    for g in range(at // seg_bits, (at + b - 1) // seg_bits + 1 if b else at // seg_bits):
        low, high = max(at, g * seg_bits), min(at + b, (g + 1) * seg_bits)
        right, left = (g + 1) * seg_bits - high, at + b - high
        piece = F.shiftrightunsigned(F.col(f"seg_{g:03d}"), right)
        piece = piece.bitwiseAND(F.lit((1 << (high - low)) - 1)) if high - low < 64 else piece
        out = out.bitwiseOR(F.shiftleft(piece, left))
    return out


def unpack(bits: Sequence[int], seg_bits: int) -> Column:
    """All codes as an array."""
    return F.array(*[extract(bits, j, seg_bits) for j in range(len(bits))])


def packed(df: DataFrame, codes: str, bits: Sequence[int], seg_bits: int, *keep: str) -> DataFrame:
    return df.select(*keep, *pack(F.col(codes), bits, seg_bits))


def pack_matrix(codes: np.ndarray, bits: Sequence[int], seg_bits: int = 8) -> np.ndarray:
    """Rows of codes as rows of bytes; rows are padded to whole words of seg_bits bits."""
    n, total = len(codes), sum(bits)
    width = words_needed(bits, seg_bits) * seg_bits
    out = np.zeros((n, width), np.uint8)
    at = 0
    for j, b in enumerate(bits):
        if b:
            out[:, at : at + b] = (codes[:, j, None] >> np.arange(b - 1, -1, -1)) & 1
        at += b
    assert at == total
    return np.packbits(out, axis=1)


def unpack_matrix(rows: np.ndarray, bits: Sequence[int]) -> np.ndarray:
    """Codes of all dimensions from rows of bytes. A dimension takes a gather of at most nine bytes and two shifts."""
    n = len(rows)
    out = np.zeros((n, len(bits)), np.int64)
    for j, (at, b) in enumerate(zip(offsets(bits), bits)):
        if not b:
            continue
        first, last = at // 8, (at + b - 1) // 8
        word = np.zeros(n, np.int64)
        for k in range(first, last + 1):
            word = (word << 8) | rows[:, k]
        out[:, j] = (word >> ((last + 1) * 8 - at - b)) & ((1 << b) - 1)
    return out
