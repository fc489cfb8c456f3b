"""Sizes and rates of Bloom filters, as numbers and as columns."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

LOG2E = math.log2(math.e)

#: Largest filter, in bytes, that is ever collected and broadcast; larger ones stay sharded. Its bits are no more than the hashes' range, 2^31.
MOST_BROADCAST = 256 << 20


def ideal_bits(n: float, fpr: float) -> float:
    """Bits of an ideally filled filter: none for no keys or for a filter that lets everything through."""
    return LOG2E * n * math.log2(1 / fpr) if n > 0 and 0 < fpr < 1 else 0.0


def bloom_size(n: int, fpr: float) -> tuple[int, int]:
    """(bits, hash functions) of a real filter: a whole number of hashes and the bits that then meet the rate."""
    if n <= 0 or fpr >= 1:
        return 1, 1
    k = max(1, round(math.log2(1 / fpr)))
    return max(8, math.ceil(-k * n / math.log1p(-(fpr ** (1 / k))))), k


def bloom_fpr(n: float, m: float, k: int) -> float:
    return (1 - math.exp(-k * n / m)) ** k


def backup_fpr(keys: float, others: float, fpr: float) -> float:
    """Rate of a backup filter by the shares of keys and non-keys that reach it: no key rejects all, no non-key accepts all."""
    if keys <= 0:
        return 0.0
    return 1.0 if others <= 0 else min(1.0, fpr * keys / others)


def ideal_bits_col(n: Column, fpr: Column) -> Column:
    return F.when((n <= 0) | (fpr >= 1) | (fpr <= 0), F.lit(0.0)).otherwise(F.lit(LOG2E) * n * F.log2(1 / fpr))


def hashes_col(fpr: Column) -> Column:
    return F.greatest(F.lit(1), F.round(F.log2(1 / fpr)).cast("int"))


def bloom_bits_col(n: Column, fpr: Column) -> Column:
    k = hashes_col(fpr)
    return F.ceil(-k * n / F.log(1 - F.pow(fpr, 1.0 / k))).cast("bigint")


def backup_fpr_col(keys: Column, others: Column, fpr: Column) -> Column:
    return F.when(keys <= 0, F.lit(0.0)).when(others <= 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), fpr * keys / others))
