"""Words and lines of a text as built-in expressions: no user function, and one evaluation of each shared value."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: White space between words is U+0020 and U+0009 to U+000D.
OTHER_SPACE = "\t\n\x0b\x0c\r"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once for each row, also where the body uses it inside lambdas."""
    return F.element_at(F.transform(F.array(value), body), 1)


def spaced(text: Column) -> Column:
    """The text with every white-space character as a plain space; null is empty."""
    out = F.coalesce(text, F.lit(""))
    for c in OTHER_SPACE:
        out = F.replace(out, F.lit(c), F.lit(" "))
    return out


def word_array(text: Column) -> Column:
    """Maximal runs of characters other than white space."""
    return F.array_remove(F.split(spaced(text), " "), "")


def word_count(text: Column) -> Column:
    """Length of ``word_array`` without building it: spaces left after runs of them are made one."""
    plain = spaced(text)
    single = F.trim(F.when(F.contains(plain, F.lit("  ")), F.regexp_replace(plain, " {2,}", " ")).otherwise(plain))
    return F.when(single == "", F.lit(0)).otherwise(F.length(single) - F.length(F.replace(single, F.lit(" "), F.lit(""))) + 1).cast("long")
