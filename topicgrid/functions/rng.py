"""Random keys that any engine, cluster size and retry reproduces: 48 bits of an MD5."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def key(seed: int, axis: str, stage: str, trial: Column | int, id_: Column) -> Column:
    """A non-negative BIGINT below 2 ** 48 that is a function of its arguments only."""
    trial = trial if isinstance(trial, Column) else F.lit(trial)
    text = F.concat_ws(":", F.lit(str(seed)), trial.cast("string"), F.lit(axis), F.lit(stage), id_.cast("string"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 12), 16, 10).cast("bigint")


def fast_key(seed: int, axis: str, stage: str, trial: Column | int, id_: Column) -> Column:
    """The same role by xxhash64: several times faster, Spark only."""
    trial = trial if isinstance(trial, Column) else F.lit(trial)
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(f"{axis}:{stage}"), trial.cast("bigint"), id_.cast("bigint")), 16)
