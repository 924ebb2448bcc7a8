"""Words as the query contracts define them: runs of anything but the six ASCII space characters."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPACES = r"[\x20\x09-\x0D]+"


def split_words(text: Column) -> Column:
    """Array of words; empty for null, empty or all-space text."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACES), lambda w: w != "")


def count_words(text: Column) -> Column:
    """Number of words, long; 0 for null text."""
    return F.size(split_words(text)).cast("long")


def fold_doc_id(doc_id: Column, folds: int) -> Column:
    """crc32 of the id written as text, modulo ``folds``; null ids count as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(folds))


def free_names(df: DataFrame, *names: str) -> list[str]:
    """The names, each with as many underscores behind it as keep it apart from the columns of ``df``."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out
