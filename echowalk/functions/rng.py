"""Randomness as data: draws are functions of keys, so retries, speculation and
re-planning cannot change a result, and another engine can replay it."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 32


def draw(seed: int, purpose: str, *keys: Column) -> Column:
    """32 uniform bits of an md5 over seed, purpose and keys."""
    text = F.concat_ws("|", F.lit(str(seed)), F.lit(purpose), *(k.cast("string") for k in keys))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def fast_draw(seed: int, purpose: str, *keys: Column) -> Column:
    """As ``draw``, by xxhash64: cheaper, and only Spark can replay it."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(purpose), *keys), 32)


def uniform(bits: Column) -> Column:
    """In (0, 1)."""
    return (bits + F.lit(0.5)) / F.lit(float(SPAN))


def draw_local(seed: int, purpose: str, *keys) -> int:
    """``draw`` outside Spark."""
    return int(hashlib.md5("|".join([str(seed), purpose, *map(str, keys)]).encode()).hexdigest()[:8], 16)


def draws_local(seed: int, purpose: str, a: np.ndarray, b: np.ndarray, k: int) -> np.ndarray:
    """``draw_local`` for the keys (a, b, k) of each row."""
    return draws_of(f"{seed}|{purpose}|%d|%d|{k}", a, b)


def draws_of(form: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The draws of the texts that ``form`` makes of each row."""
    text, md5 = form.encode(), hashlib.md5
    digests = b"".join([md5(text % key).digest() for key in zip(a.tolist(), b.tolist())])
    return np.frombuffer(digests, ">u4")[::4].astype(np.int64)


def draw_sql(seed: int, purpose: str, *keys: str) -> str:
    """``draw`` as DuckDB SQL."""
    return f"CAST('0x' || substr(md5(concat_ws('|', '{seed}', '{purpose}', {', '.join(keys)})), 1, 8) AS BIGINT)"
