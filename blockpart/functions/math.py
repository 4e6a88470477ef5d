"""Column functions of the model, each a plain expression that stays in generated code."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def phi(x: Column) -> Column:
    """x ln x, 0 at and below 0."""
    return F.when(x > 0, x * F.ln(x)).otherwise(F.lit(0.0))


def h(x: Column) -> Column:
    """(1 + x) ln(1 + x) - x ln x."""
    return phi(F.lit(1.0) + x) - phi(x)


def u01(seed: int, phase: str, it: object, ident: Column, k: object = 0) -> Column:
    """A number in [0, 1) of 52 bits, from its arguments only: the same after retries, in any partitioning and in other engines."""
    text = F.concat_ws("|", F.lit(str(seed)), F.lit(phase), it if isinstance(it, Column) else F.lit(str(it)), ident.cast("string"), k if isinstance(k, Column) else F.lit(str(k)))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("bigint") / F.lit(4503599627370496.0)


def string_id(x: Column, tag: int) -> Column:
    """A node id for a string key: 52 bits of its hash, with a tag for its kind."""
    return F.conv(F.substring(F.md5(x), 1, 13), 16, 10).cast("bigint") * 4 + tag


def sql_u01(seed: int, phase: str, it: object, ident: str, k: object = 0) -> str:
    """The same draw in DuckDB."""
    return f"(('0x' || substr(md5(concat_ws('|', '{seed}', '{phase}', '{it}', ({ident})::varchar, '{k}')), 1, 13))::bigint / 4503599627370496.0)"


def sql_phi(x: str) -> str:
    return f"(case when ({x}) > 0 then ({x}) * ln(({x})::double) else 0.0 end)"
