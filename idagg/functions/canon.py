"""Identities as canonical strings."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def canonical(*cols: Column | str, lower: bool = False, trim: bool = False) -> Column:
    """One value as text, or several as one text in which each part is led by its length, so ("a", "bc") and ("ab", "c") differ.

    A null part makes the identity null, and a record without identity is no record."""
    parts = []
    for c in cols:
        s = (F.col(c) if isinstance(c, str) else c).cast("string")
        s = F.trim(s) if trim else s
        parts.append(F.lower(s) if lower else s)
    if len(parts) == 1:
        return parts[0]
    return F.concat(*(F.concat(F.length(p).cast("string"), F.lit(":"), p) for p in parts))
