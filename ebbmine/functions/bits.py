"""Bit masks of item sets: expressions on LONG word columns and helpers on driver-side integers.

On the driver a mask is one Python integer of any width; in tables it is `words` LONG columns
w0, w1, ... of 64 items each. The sign bit is an ordinary item bit: masks are compared for
equality only and never ordered or shifted with sign.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

WORD_BITS, LOW = 64, (1 << 64) - 1


def n_words(m: int) -> int:
    return max(1, -(-m // WORD_BITS))


def word_names(words: int) -> list[str]:
    return [f"w{j}" for j in range(words)]


def signed(word: int) -> int:
    return word - (1 << 64) if word >> 63 else word


def split_mask(mask: int, words: int) -> list[int]:
    """The signed LONG words of a mask."""
    return [signed((mask >> (WORD_BITS * j)) & LOW) for j in range(words)]


def mask_array(masks: list[int], words: int) -> np.ndarray:
    return np.array([[(x >> (WORD_BITS * j)) & LOW for j in range(words)] for x in masks], np.uint64).reshape(len(masks), words)


def bits_of(mask: int) -> list[int]:
    out = []
    while mask:
        low = mask & -mask
        out.append(low.bit_length() - 1)
        mask ^= low
    return out


def contains(masks: list[Column], sets: list[Column]) -> Column:
    """Whether each word of the set lies in the transaction's word."""
    test = F.lit(True)
    for t, c in zip(masks, sets):
        test = test & (t.bitwiseAND(c) == c)
    return test


def contains_literal(words: int, mask: int) -> Column:
    """The same for a fixed set; only its non-zero words are tested."""
    test = None
    for j, c in enumerate(split_mask(mask, words)):
        if c:
            one = F.col(f"w{j}").bitwiseAND(F.lit(c).cast("bigint")) == F.lit(c).cast("bigint")
            test = one if test is None else test & one
    return F.lit(True) if test is None else test


def overlaps(masks: list[Column], sets: list[Column]) -> Column:
    hit = F.lit(False)
    for t, c in zip(masks, sets):
        hit = hit | (t.bitwiseAND(c) != 0)
    return hit


def cardinality(words: int) -> Column:
    total = F.lit(0)
    for name in word_names(words):
        total = total + F.bit_count(name)
    return total


def item_ids(words: int, of: str = "w") -> Column:
    """The item numbers of a transaction, ascending."""
    parts = [F.filter(F.sequence(F.lit(WORD_BITS * j), F.lit(WORD_BITS * j + WORD_BITS - 1)), _held(f"{of}{j}")) for j in range(words)]
    return F.concat(*parts) if words > 1 else parts[0]


def _held(name: str):
    return lambda i: F.call_function("getbit", F.col(name), (i % WORD_BITS).cast("int")) == 1
