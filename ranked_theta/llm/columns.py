"""Names for columns that operators add to a caller's rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def prefix(df: DataFrame, word: str) -> str:
    """``word``, behind as many underscores as it takes that no column of ``df`` begins with it (in either case)."""
    names = [c.lower() for c in df.columns]
    while any(c.startswith(word.lower()) for c in names):
        word = f"_{word}"
    return word


def own(df: DataFrame) -> list[Column]:
    """The columns of ``df`` as they are, whatever characters their names hold."""
    return [F.col(quoted(c)) for c in df.columns]


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"
