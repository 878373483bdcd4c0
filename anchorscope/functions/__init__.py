"""Column functions shared by all operators: keyed draws, text forms, vectors."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SEED = 42


def u01(*parts: Column | str | int) -> Column:
    """A draw in [0, 1) from the md5 of the parts joined by `|`; strings name columns, F.lit gives constants."""
    text = F.concat_ws("|", *[(F.lit(str(p)) if isinstance(p, int) else F.col(p) if isinstance(p, str) else p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / 4294967296.0


def r6(c: Column | str) -> Column:
    """Ratios leave the library rounded to six decimals."""
    return F.round(F.col(c) if isinstance(c, str) else c, 6)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def words(text: Column) -> Column:
    """Runs of a-z after lower-casing."""
    return F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != "")
