"""Element hashes and filter positions, the same in Spark columns, NumPy and plain SQL.

An element's identity is hashed once to 60 bits by md5. Every filter draws its positions
from that by its own seed with multiplication modulo a prime, so filters of different
seeds behave as independent hash families, and nothing exceeds 63 bits on the way.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIME = 2147483647
HALF = 1 << 30
# Fixed multipliers under 2^31; any odd numbers do, both engines must use the same.
FIRST = (1664525013, 1013904223, 69069)
STEP = (1103515245, 1812433253, 22695477)
BLOCK = (1597334677, 747796405, 48271)
BLOCK_BITS = 32768
SECOND = 12345


def element_hash(eid: Column) -> Column:
    return F.conv(F.substring(F.md5(eid.cast("string").cast("binary")), 1, 15), 16, 10).cast("bigint")


def uniform(salt: str, eid: Column) -> Column:
    """A number in [0, 1) that depends on salt and element alone."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), eid.cast("string")).cast("binary")), 1, 8), 16, 10).cast("bigint") / F.lit(float(1 << 32))


def _mix(h, seed, m):
    """A seed changes both multipliers, so hashes of different seeds are not shifts of each other."""
    return (h // HALF * ((m[0] + seed * m[2]) % PRIME) + h % HALF * ((m[1] + seed * (m[2] + SECOND)) % PRIME)) % PRIME


def _mix_col(h: Column, seed: Column, m) -> Column:
    return (F.shiftright(h, 30) * ((m[0] + seed * m[2]) % PRIME) + h.bitwiseAND(HALF - 1) * ((m[1] + seed * (m[2] + SECOND)) % PRIME)) % PRIME


def smallest(rows: DataFrame, n: int) -> DataFrame:
    """The n rows of the smallest hash of h. They are counted first, so that tasks offer few more than n in all, however many tasks there are."""
    by, share = F.xxhash64("h"), (1.1 * n + 1000) / max(1, rows.count())
    if share < 1:
        rows = rows.filter(by <= F.lit(int(-(2**63) + share * 2**64)))
    return rows.orderBy(by).limit(n)


def positions(h: Column, seed: Column | int, k: Column | int, m: Column | int) -> Column:
    """Array of k positions below m. All of seed, k and m may be columns."""
    seed, k, m = (F.lit(x).cast("bigint") if isinstance(x, int) else x.cast("bigint") for x in (seed, k, m))
    first, step = _mix_col(h, seed, FIRST), _mix_col(h, seed, STEP)
    return F.transform(F.sequence(F.lit(0).cast("bigint"), k - 1), lambda i: (first + i * (step % F.greatest(m - 1, F.lit(1).cast("bigint")) + 1)) % m)


def block_of(h: Column, seed: Column | int, blocks: Column | int) -> Column:
    seed, blocks = (F.lit(x).cast("bigint") if isinstance(x, int) else x.cast("bigint") for x in (seed, blocks))
    return _mix_col(h, seed, BLOCK) % blocks


def positions_np(h: np.ndarray, seed: int, k: int, m: int) -> np.ndarray:
    """Rows of k positions."""
    first, step = _mix(h, seed, FIRST), _mix(h, seed, STEP)
    return (first[:, None] + np.arange(k) * (step % max(m - 1, 1) + 1)[:, None]) % m


def block_np(h: np.ndarray, seed: int, blocks: int) -> np.ndarray:
    return _mix(h, seed, BLOCK) % blocks


def hash_sql(eid: str) -> str:
    return f"(('0x' || substr(md5({eid}), 1, 15))::BIGINT)"


def uniform_sql(salt: str, eid: str) -> str:
    return f"((('0x' || substr(md5('{salt}' || {eid}), 1, 8))::BIGINT) / 4294967296.0)"


def _mix_sql(h: str, seed, m) -> str:
    return f"((({h} >> 30) * (({m[0]} + ({seed}) * {m[2]}) % {PRIME}) + ({h} & {HALF - 1}) * (({m[1]} + ({seed}) * {m[2] + SECOND}) % {PRIME})) % {PRIME})"


def position_sql(h: str, seed, i: str, m) -> str:
    return f"(({_mix_sql(h, seed, FIRST)} + ({i}) * ({_mix_sql(h, seed, STEP)} % greatest(({m}) - 1, 1) + 1)) % ({m}))"


def block_sql(h: str, seed, blocks) -> str:
    return f"({_mix_sql(h, seed, BLOCK)} % ({blocks}))"
