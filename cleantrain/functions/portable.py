"""Uniform numbers and row ids that Spark and any SQL engine with md5 compute alike, from a row's key and a seed."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

HEX_UNIFORM, HEX_ID = 8, 13


def _hex(text: Column, digits: int) -> Column:
    return F.conv(F.substring(F.md5(text), 1, digits), 16, 10).cast("long")


def uniform(key: str | Column, *seed: object) -> Column:
    """In (0, 1), never an end; the seed's parts and the key are joined by |. Ties are broken by row id where order matters."""
    key = F.col(key) if isinstance(key, str) else key
    return (_hex(F.concat_ws("|", *[s.cast("string") if isinstance(s, Column) else F.lit(str(s)) for s in seed], key.cast("string")), HEX_UNIFORM) + 0.5) / 2.0**32


def uniform_number(key: object, *seed: object) -> float:
    """The same number in Python."""
    text = "|".join(str(s) for s in (*seed, key))
    return (int(hashlib.md5(text.encode()).hexdigest()[:HEX_UNIFORM], 16) + 0.5) / 2.0**32


def hashed_id(key: Column) -> Column:
    """A 52-bit id of a row's key: stable over runs and partitionings, without a sort."""
    return _hex(key, HEX_ID)


def noise(key: str | Column, seed: object) -> Column:
    """Zero mean, unit variance, near normal: the sum of four uniforms. Sums keep engines equal to the last bits, logarithms don't."""
    total = uniform(key, seed, "a") + uniform(key, seed, "b") + uniform(key, seed, "c") + uniform(key, seed, "d")
    return (total - 2.0) * 3.0**0.5


def uniform_sql(key: str, *seed: object) -> str:
    text = "||".join([f"'{s}|'" for s in seed] + [f"({key})::varchar"])
    return f"((('0x'||substr(md5({text}),1,{HEX_UNIFORM}))::bigint + 0.5::double) / 4294967296::double)"


def hashed_id_sql(key: str) -> str:
    return f"('0x'||substr(md5({key}),1,{HEX_ID}))::bigint"


def noise_sql(key: str, seed: object) -> str:
    return "(" + "+".join(uniform_sql(key, seed, c) for c in "abcd") + f" - 2::double) * {3.0**0.5!r}::double"
