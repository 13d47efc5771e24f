"""DuckDB text for register states and readouts."""

from __future__ import annotations

from idagg.functions.estimate import sql_estimate
from idagg.functions.hashing import sql_hash, sql_index, sql_rank


def _k(keys: str) -> str:
    return f"{keys}, " if keys else ""


def _g(keys: str) -> str:
    return f"GROUP BY {keys}" if keys else ""


def hashed(src: str, keys: str, ident: str, seed: int = 0) -> str:
    return f"SELECT {_k(keys)}{sql_hash(f'CAST({ident} AS VARCHAR)', seed)} AS h FROM {src}"


def regs(name: str, src: str, keys: str, ident: str, p: int = 11, seed: int = 0) -> str:
    """CTE of (keys, j, r). src may end with a WHERE clause."""
    return f"{name} AS (SELECT {_k(keys)}j, max(r) AS r FROM (SELECT {_k(keys)}{sql_index('h', p)} AS j, {sql_rank('h', p)} AS r FROM ({hashed(src, keys, ident, seed)})) GROUP BY {_k(keys)}j)"


def estimate(reg: str, keys: str, p: int = 11, out: str = "estimate", digits: int = 4) -> str:
    """SELECT of (keys, estimate) over register rows."""
    m = 1 << p
    return f"SELECT {_k(keys)}round({sql_estimate(f'sum(pow(2.0::DOUBLE, -r)) + ({m} - count(*))', f'{m} - count(*)', m)}, {digits}) AS {out} FROM {reg} {_g(keys)}"


def merged(name: str, reg: str, keys: str) -> str:
    return f"{name} AS (SELECT {_k(keys)}j, max(r) AS r FROM {reg} GROUP BY {_k(keys)}j)"
