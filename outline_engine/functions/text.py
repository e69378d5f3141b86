"""Canonical words of texts, as the accuracy measures compare them."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Letters with marks and typographic quotes, and what they become (fixed values).
MARKED = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ"
PLAIN = "aaaaaaceeeeiiiinooooouuuuyy"


def normalised(text: Column) -> Column:
    """Small letters without marks; all but letters, digits and blanks goes; blanks are squeezed."""
    small = F.translate(F.lower(F.coalesce(text, F.lit(""))), MARKED, PLAIN)
    kept = F.regexp_replace(small, r"[^\p{L}\p{N}\x20\x09-\x0D]", "")
    return F.trim(F.regexp_replace(kept, r"[\x20\x09-\x0D]+", " "))


def norm_words(text: Column) -> Column:
    return F.array_remove(F.split(normalised(text), " "), "")


def normalised_sql(text: str) -> str:
    """The same in DuckDB."""
    small = f"translate(lower(coalesce({text}, '')), '{MARKED}', '{PLAIN}')"
    return rf"trim(regexp_replace(regexp_replace({small}, '[^\p{{L}}\p{{N}}\x20\x09-\x0D]', '', 'g'), '[\x20\x09-\x0D]+', ' ', 'g'))"
