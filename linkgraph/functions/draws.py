"""Random draws as functions of their labels: the same on any engine, task order or retry."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

_SCALE = float(1 << 52)


def _text(part) -> Column:
    return part.cast("string") if isinstance(part, Column) else F.lit(str(part))


def u52(seed: int, tag: str, *parts) -> Column:
    """A uniform draw in [0, 1) from 52 bits of the digest of seed, tag and parts."""
    joined = F.concat_ws("|", F.lit(str(seed)), F.lit(tag), *map(_text, parts))
    return F.conv(F.substring(F.md5(joined), 1, 13), 16, 10).cast("long") / F.lit(_SCALE)


def u52_sql(seed: int, tag: str, *parts: str) -> str:
    """The same draw as DuckDB SQL; ``parts`` are SQL expressions."""
    joined = " || '|' || ".join([f"'{seed}'", f"'{tag}'", *(f"CAST({p} AS VARCHAR)" for p in parts)])
    return f"(('0x' || substr(md5({joined}), 1, 13))::BIGINT / {_SCALE!r})"


def u52_py(seed: int, tag: str, *parts) -> float:
    raw = hashlib.md5("|".join([str(seed), tag, *map(str, parts)]).encode()).hexdigest()
    return int(raw[:13], 16) / _SCALE


def node_id(kind: str, key: Column) -> Column:
    """A 60-bit id of a node from its kind and key."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(kind + "|"), key)), 1, 15), 16, 10).cast("long")


def node_id_sql(kind: str, key: str) -> str:
    return f"(('0x' || substr(md5('{kind}|' || {key}), 1, 15))::BIGINT)"
