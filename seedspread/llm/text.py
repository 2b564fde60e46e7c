"""Native column expressions for the two word definitions the operators share."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Runs that separate words once A-Z are folded: every ASCII character but digits and a-z.
NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The same in a text that has not been folded.
RAW_SEPARATORS = r"\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F"
BLANKS = r"[\x20\x09-\x0D]+"


def folded(text: Column) -> Column:
    """ASCII-only lower case; other letters stay as they are. Null becomes empty."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def words(text: Column) -> Column:
    """Array of the lower-cased words of a text; empty for null, empty and all-punctuation texts."""
    return F.array_remove(F.split(folded(text), NOT_WORD, -1), "")


def n_blank_words(text: Column) -> Column:
    """Number of runs of non-blank characters; 0 for null."""
    return F.size(F.array_remove(F.split(F.coalesce(text, F.lit("")), BLANKS, -1), "")).cast("long")


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names like ``names`` that ``df`` has not (names are compared without case, as Spark does)."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


#: The columns of documents that operators read by name.
DOCUMENT = ("doc_id", "text", "lang", "source", "n_chars")
PACK = "others_"


def shielded(operator: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """Any further columns of the input travel in one struct, so their names cannot meet an operator's own.

    They come back untouched and in place; a column that the operator adds takes a free name, by underscores.
    """

    @wraps(operator)
    def run(docs: DataFrame, *args, **settings) -> DataFrame:
        further = [c for c in docs.columns if c not in DOCUMENT]
        if not further:
            return operator(docs, *args, **settings)
        known = [c for c in docs.columns if c in DOCUMENT]
        out = operator(docs.select(*known, F.struct(*[F.col(f"`{c}`") for c in further]).alias(PACK)), *args, **settings)
        added = [c for c in out.columns if c not in known and c != PACK]
        back = [F.col(PACK).getField(c).alias(c) if c in further else F.col(c) for c in docs.columns]
        return out.select(*back, *[F.col(c).alias(n) for c, n in zip(added, fresh(docs, *added), strict=True)])

    return run
