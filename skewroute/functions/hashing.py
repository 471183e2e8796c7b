"""Families of hash functions that map a key to workers.

``xx`` is the production family (one 64-bit hash a choice, JVM code generation); ``md5`` gives the same workers in any
engine and serves comparisons. Choice i uses hash i whatever the number of choices, so more choices only add workers.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

FAMILIES = ("xx", "md5")


def hash_choice(key: Column | str, i: int | Column, n: int, family: str = "md5") -> Column:
    """Worker of the i-th choice (from 1) of a key, of ``n``."""
    key = F.col(key) if isinstance(key, str) else key
    i = F.lit(i) if isinstance(i, int) else i
    if family == "xx":
        return F.pmod(F.xxhash64(i, key), F.lit(n)).cast("int")
    if family != "md5":
        raise ValueError(f"unknown hash family {family}")
    text = F.concat(i.cast("string"), F.lit(":"), F.coalesce(key.cast("string"), F.lit("\0null")))
    return (F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") % n).cast("int")


def candidates(key: Column | str, d: int, n: int, family: str = "md5") -> Column:
    """The first ``d`` choices of a key, collisions kept."""
    return F.array(*(hash_choice(key, i, n, family) for i in range(1, d + 1)))


def md5_choice(key: str | None, i: int, n: int) -> int:
    """The md5 family in Python, for head keys whose further choices the router asks for."""
    return int(hashlib.md5(f"{i}:{chr(0) + 'null' if key is None else key}".encode("utf-8", "surrogatepass")).hexdigest()[:8], 16) % n


def xx_choice(key: str | None, i: int, n: int) -> int:
    """The xx family in Python: Spark hashes columns in turn, each with the hash so far as its seed."""
    import xxhash

    seed = xxhash.xxh64_intdigest(i.to_bytes(4, "little"), 42)
    h = seed if key is None else xxhash.xxh64_intdigest(key.encode("utf-8", "surrogatepass"), seed)
    return (h - (1 << 64) if h >> 63 else h) % n


CHOICES = {"md5": md5_choice, "xx": xx_choice}
