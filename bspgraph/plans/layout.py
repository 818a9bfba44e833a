"""Partition labels that Spark's own shuffle deals one to a partition.

A vertex belongs to partition ``n = pmod(hash(id), P)``.  Were ``n`` itself the
clustering column, the shuffle would hash it once more and some partitions would
get several numbers and others none.  So rows carry a label in its place: the
integer whose hash is exactly ``n``.  The hash of an integer (Murmur3, 32 bits) is
a bijection, so the label follows from ``n`` by running it backwards.
"""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed values of the 32-bit Murmur3 hash and of Spark's seed.
FIRST, SECOND, ADDED, FINAL = 0xCC9E2D51, 0x1B873593, 0xE6546B64, (0x85EBCA6B, 0xC2B2AE35)
SEED, BYTES = 42, 4
WORD = 1 << 32


def label_of(number: int) -> int:
    """The 32-bit integer whose hash is ``number``."""
    undo = lambda x, factor: x * pow(factor, -1, WORD) % WORD
    right = lambda x, bits: x >> bits | (x << 32 - bits) % WORD
    x = number ^ number >> 16
    x = undo(x, FINAL[1])
    x ^= x >> 13 ^ x >> 26
    x = undo(x, FINAL[0])
    x ^= x >> 16 ^ BYTES
    x = right(undo((x - ADDED) % WORD, 5), 13) ^ SEED
    x = undo(right(undo(x, SECOND), 15), FIRST)
    return x - WORD if x >= WORD // 2 else x


@lru_cache(maxsize=16)
def _labels(partitions: int) -> str:
    return ",".join(str(label_of(n)) for n in range(partitions))


def place(column: str | Column, partitions: int) -> Column:
    """The label of the partition that an identifier belongs to.  The list of
    labels is a constant of the plan, a few bytes a partition."""
    labels = F.split(F.lit(_labels(partitions)), ",").cast("array<int>")
    return F.get(labels, F.pmod(F.hash(column), F.lit(partitions)))
