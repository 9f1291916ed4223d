"""Hashes that other SQL engines can compute as well."""

from __future__ import annotations

from pyspark.sql import Column, functions as F

KNUTH = 2654435761


def portable_hash(c: Column | str) -> Column:
    """Multiplicative 32-bit hash of an integer column, as plain arithmetic: ``(id * 2654435761) % 2**32``."""
    c = F.col(c) if isinstance(c, str) else c
    return F.pmod(c * F.lit(KNUTH), F.lit(1 << 32))


def portable_edge_hash(a: Column | str, b: Column | str) -> Column:
    """Hash of an ordered pair."""
    return F.pmod(portable_hash(a) * 31 + portable_hash(b), F.lit(1 << 32))
