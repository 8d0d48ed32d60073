"""Uniform draws that depend on (seed, tag, keys) only.

A retried or speculative task draws the same values, and SQL engines with ``md5`` can follow.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = 1 << 52


def _col(k) -> Column:
    return F.col(k) if isinstance(k, str) else k if isinstance(k, Column) else F.lit(k)


def bits(seed: int, tag: str, *keys) -> Column:
    """52 uniform bits as a long."""
    text = F.concat_ws("|", F.lit(str(seed)), F.lit(tag), *[_col(k).cast("string") for k in keys])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def u(seed: int, tag: str, *keys) -> Column:
    """A uniform double in [0, 1)."""
    return bits(seed, tag, *keys) / F.lit(float(SCALE))


def below(total, seed: int, tag: str, *keys) -> Column:
    """A uniform long in [0, total)."""
    t = _col(total)
    return F.least(F.floor(u(seed, tag, *keys) * t.cast("double")).cast("long"), t - 1)


def key_id(key) -> Column:
    """A 53-bit identifier of a string key, above all plain integer ids of the tables.

    It needs no dictionary and no global numbering; with a million keys two of them share an id
    with a chance of one in ten thousand, which ``sources.graphs.shared_ids`` reports.
    """
    return F.conv(F.substring(F.md5(_col(key).cast("string")), 1, 13), 16, 10).cast("long") + F.lit(SCALE)


def sql_bits(seed: int, tag: str, *keys: str) -> str:
    """The same bits as a DuckDB expression; ``keys`` are SQL expressions."""
    return f"('0x' || substr(md5(concat_ws('|', '{seed}', '{tag}', {', '.join(f'({k})::VARCHAR' for k in keys)})), 1, 13))::BIGINT"


def sql_below(total: str, seed: int, tag: str, *keys: str) -> str:
    return f"least(floor({sql_bits(seed, tag, *keys)} / {float(SCALE)!r} * ({total})::DOUBLE)::BIGINT, ({total}) - 1)"


def sql_key_id(key: str) -> str:
    return f"(('0x' || substr(md5({key}), 1, 13))::BIGINT + {SCALE})"


def py_bits(seed: int, tag: str, *keys) -> int:
    return int(hashlib.md5("|".join([str(seed), tag, *map(str, keys)]).encode()).hexdigest()[:13], 16)
