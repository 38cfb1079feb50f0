"""Repeatable randomness and universal hashing as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(salt: str, *columns: str | Column) -> Column:
    """A number in [0, 1) that only the salt and the columns decide, so a task that runs again draws the same."""
    text = F.concat_ws("|", F.lit(salt), *[(F.col(c) if isinstance(c, str) else c).cast("string") for c in columns])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def uniform_sql(salt: str, *columns: str) -> str:
    return f"(('0x' || substr(md5(concat_ws('|', '{salt}', {', '.join(columns)})), 1, 8))::BIGINT::DOUBLE / 4294967296.0::DOUBLE)"


def next_prime(n: int) -> int:
    """The least prime at or above n."""
    n = max(2, n)
    while any(n % k == 0 for k in range(2, int(n**0.5) + 1)):
        n += 1
    return n


def universal_hash(key: Column, a: int, b: int, p: int, buckets: int) -> Column:
    """((a * key + b) mod p) mod buckets. The key is reduced first, so with p below 2**31 nothing overflows."""
    if not 0 < a < p < 1 << 31 or not 0 <= b < p:
        raise ValueError("need 0 < a < p < 2**31 and 0 <= b < p")
    return F.pmod(F.pmod(F.pmod(key, F.lit(p)) * F.lit(a) + F.lit(b), F.lit(p)), F.lit(buckets)).cast("long")
