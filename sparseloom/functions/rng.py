"""Counter-based draws that any engine can reproduce.

A draw is a function of its coordinates (seed, batch, layer, row, counter), so results don't
depend on partitioning, task order or retries. `md5` draws are the first 52 bits of an MD5
digest, which DuckDB computes alike; `fast` draws use xxhash64 and stay inside whole-stage code.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 52


def u52(*parts: Column | int | str, kind: str = "md5") -> Column:
    """An integer below 2^52 from the coordinates."""
    if kind == "fast":
        columns = [p if isinstance(p, Column) else F.lit(p) for p in parts]
        return F.shiftrightunsigned(F.xxhash64(*[c.cast("long") for c in columns]), 64 - BITS)
    if kind != "md5":
        raise ValueError(f"unknown generator {kind!r}")
    return F.conv(h52(*parts), 16, 10).cast("long")


def h52(*parts: Column | int | str) -> Column:
    """The md5 draw as 13 hexadecimal digits: sorts like the number and costs less to make."""
    return digits52(stem(*parts[:-1]), parts[-1])


def stem(*parts: Column | int | str) -> Column:
    """What the md5 draws of one row have in common: their coordinates but for the last."""
    pieces: list[Column] = []
    for p in parts:
        pieces += [p.cast("string") if isinstance(p, Column) else F.lit(str(p)), F.lit("|")]
    return F.concat(*pieces)


def digits52(stem: Column, last: Column | int | str) -> Column:
    """The md5 draw of a stem and a last coordinate, as `h52` gives it."""
    return F.substring(F.md5(F.concat(stem, last.cast("string") if isinstance(last, Column) else F.lit(str(last)))), 1, 13)


def u01(*parts: Column | int | str, kind: str = "md5") -> Column:
    """A double strictly between 0 and 1."""
    return (u52(*parts, kind=kind) + F.lit(0.5)) / F.lit(float(1 << BITS))


def u52_sql(*parts: str) -> str:
    """The same draw as DuckDB SQL; parts are SQL expressions."""
    key = " || '|' || ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"CAST(('0x' || substr(md5({key}), 1, 13)) AS BIGINT)"
