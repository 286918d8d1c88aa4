"""Distances and items as column expressions; all stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def shared(a, b) -> Column:
    return F.size(F.array_intersect(a, b))


def hamming(a, b) -> Column:
    """Size of the symmetric difference of two item sets."""
    return F.size(a) + F.size(b) - 2 * shared(a, b)


def jaccard(a, b) -> Column:
    """Intersection over union; 1 for two empty sets."""
    both = shared(a, b)
    union = F.size(a) + F.size(b) - both
    return F.when(union == 0, F.lit(1.0)).otherwise(both / union)


def item_of(col, ns: str) -> Column:
    """A value of any primitive type as a namespaced item."""
    return F.concat(F.lit(f"{ns}:"), F.col(col).cast("string") if isinstance(col, str) else col.cast("string"))


def is_word(item) -> Column:
    """A keyword; attribute items hold a colon after their namespace, which no word does."""
    return ~F.contains(item, F.lit(":"))


def words(text, pattern: str = r"[^\p{L}\p{N}]+") -> Column:
    """Lower-cased words, empty ones removed."""
    return F.filter(F.split(F.lower(text), pattern), lambda w: w != "")


def canonical(items) -> Column:
    """Sorted, distinct, without nulls."""
    return F.array_sort(F.array_distinct(F.filter(items, lambda x: x.isNotNull())))


def joined(items, sep: str = "|") -> Column:
    """A set as one comparable string."""
    return F.concat_ws(sep, F.array_sort(items))
