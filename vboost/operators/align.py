"""Private instance intersection."""

from __future__ import annotations

import hashlib
import secrets
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed value: the 768-bit modulus of the first well-known Diffie-Hellman group.
PRIME = int(
    "FFFFFFFFFFFFFFFFC90FDAA22168C234C4C6628B80DC1CD129024E088A67CC74020BBEA63B139B22514A08798E3404DDEF9519B3CD3A431B302B0A6DF25F14374FE1356D6D51C245E485B576625E7EC6F44C42E9A63A3620FFFFFFFFFFFFFFFF",
    16,
)


def draw_exponent() -> int:
    """A secret odd exponent: with a safe prime, powers by it are one to one on the squares that digests are mapped to."""
    return secrets.randbits(255) | 1 << 254 | 1


def intersect_digest(left: DataFrame, right: DataFrame, salt: str | None = None, key: str = "inst_id") -> DataFrame:
    """Ids of both sides, joined on a digest with a salt that both know (drawn anew unless given): each id once."""
    salt = salt or secrets.token_hex(16)
    d = F.sha2(F.concat(F.lit(salt), F.col(key).cast("string")), 256).alias("digest")
    mine = left.select(key, d).where(F.col(key).isNotNull()).distinct()
    return mine.join(right.select(d).distinct(), "digest", "left_semi").select(key)


def _blind(exponent: int, column: str):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            raw = [int.from_bytes(hashlib.sha512(str(x).encode()).digest(), "big") ** 2 % PRIME if column == "raw" else int(x, 16) for x in f["x"]]
            yield f.assign(x=[format(pow(x, exponent, PRIME), "x") for x in raw])

    return run


def intersect_dh(left: DataFrame, right: DataFrame, a: int | None = None, b: int | None = None, key: str = "inst_id") -> DataFrame:
    """The same by commutative exponents: each side blinds its own digests and the other's, and equal twice-blinded
    values are the same id. Only modular powers run in Python, on Arrow batches."""
    a, b = a or draw_exponent(), b or draw_exponent()  # each side's own secret
    one = left.select(key).where(F.col(key).isNotNull()).distinct().select(key, F.col(key).cast("string").alias("x"))
    two = right.select(key).where(F.col(key).isNotNull()).distinct().select(F.col(key).cast("string").alias("x"))
    one = one.mapInPandas(_blind(a, "raw"), f"{key} long, x string").mapInPandas(_blind(b, "blind"), f"{key} long, x string")
    two = two.mapInPandas(_blind(b, "raw"), "x string").mapInPandas(_blind(a, "blind"), "x string")
    return one.join(two, "x", "left_semi").select(key)
