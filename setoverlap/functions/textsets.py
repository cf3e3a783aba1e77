"""Sets of words, shingles, lines and links out of texts; arrays first, exploded by the caller."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def words(text: Column) -> Column:
    return F.split(F.lower(text), r"\s+")


def shingles(text: Column, width: int = 5) -> Column:
    """Distinct runs of `width` words; a shorter text is one run."""
    split = F.split(F.lower(F.trim(text)), r"\s+")

    def runs(w: Column) -> Column:
        return F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - (width - 1), F.lit(1))), lambda i: F.array_join(F.slice(w, i, width), " "))

    # a one-element transform binds the words once; inlined they would be split again for every run
    return F.array_distinct(F.transform(F.array(split), runs)[0])


def lines(text: Column) -> Column:
    return F.array_distinct(F.filter(F.transform(F.split(text, "\n"), lambda x: F.trim(x)), lambda x: x != ""))


def stripped(html: Column) -> Column:
    return F.regexp_replace(html, "<[^>]*>", " ")


def links(html: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(html, F.lit('href="([^"]*)"'), F.lit(1)))


def host(url: Column) -> Column:
    return F.regexp_extract(url, "^[a-z]+://([^/]+)", 1)
