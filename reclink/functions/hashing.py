"""Hashes that any SQL engine can repeat; no random numbers, so retries change nothing."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def portable(key: Column, salt: str, modulus: int) -> Column:
    """First 32 bits of md5('key|salt') modulo `modulus`."""
    text = F.concat(key.cast("string"), F.lit(f"|{salt}"))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") % modulus


def salted(value: Column, secret: str) -> Column:
    """256-bit digest of a signature under a secret, for exchange without raw values."""
    return F.sha2(F.concat(F.lit(secret), value), 256)
