"""Checks before a match runs: columns there, coordinates numeric, keys unique, errors positive."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.match import Participant


class ResolveError(ValueError):
    pass


def _type(df: DataFrame, text: str, what: str) -> T.DataType:
    try:
        return df.select(F.expr(text).alias("v")).schema["v"].dataType
    except Exception as error:
        raise ResolveError(f"{what}: {text!r} can't be resolved") from error


def check(p: Participant) -> Participant:
    """Schema checks alone: free."""
    for k in p.key:
        if isinstance(_type(p.df, k, f"{p.alias} key"), (T.DoubleType, T.FloatType)):
            raise ResolveError(f"{p.alias}: a key of floating numbers is no key")
    for c in p.position:
        if not isinstance(_type(p.df, c, f"{p.alias} position"), T.NumericType):
            raise ResolveError(f"{p.alias}: coordinate {c!r} is not numeric")
    if isinstance(p.error, str) and not isinstance(_type(p.df, p.error, f"{p.alias} error"), T.NumericType):
        raise ResolveError(f"{p.alias}: error {p.error!r} is not numeric")
    if not isinstance(p.error, str) and p.error <= 0:
        raise ResolveError(f"{p.alias}: an error must be positive")
    return p


def validate(p: Participant, strict: bool = True, rate: float = 1.0) -> dict[str, int]:
    """Counts of what the match would leave out; strict: one aggregate for repeated keys, an error if there is one.

    rate below 1 looks at a sample of the keys by hash: all rows of a key are in it or none, so repeats stay visible.
    """
    check(p)
    df = p.rows()
    if rate < 1:
        df = df.filter(F.pmod(F.xxhash64(*p.key), F.lit(1 << 30)) < int(rate * (1 << 30)))
    bad = F.lit(False)
    for c in p.position:
        v = F.expr(c).cast("double")
        bad = bad | v.isNull() | F.isnan(v)
    e = (F.expr(p.error) if isinstance(p.error, str) else F.lit(float(p.error))).cast("double")
    row = df.agg(F.count("*").alias("rows"), F.sum(bad.cast("long")).alias("no_position"), F.sum((e.isNull() | F.isnan(e) | (e <= 0)).cast("long")).alias("no_error")).first()
    out = {k: int(row[k] or 0) for k in ("rows", "no_position", "no_error")}
    if strict:
        twice = df.groupBy(*p.key).agg(F.count("*").alias("n")).filter("n > 1").limit(1).collect()
        if twice:
            raise ResolveError(f"{p.alias}: key {p.key} repeats, for example {tuple(twice[0])[:-1]}")
    return out
