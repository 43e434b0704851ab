"""Column expressions that stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: What no valid title contains (case matters), besides titles of digits alone.
TITLE_MARKERS = ("Talk", "User", "File", "ISO", "%", "#", ":")
WORD = r"[^\x20\x09-\x0D]+"


def hash8(*parts: Column | str) -> Column:
    """The first 32 bits of the md5 of the parts joined by |, as a number; equal in any engine that has md5."""
    joined = F.concat_ws("|", *(p.cast("string") if isinstance(p, Column) else F.lit(p) for p in parts))
    return F.conv(F.substring(F.md5(joined), 1, 8), 16, 10).cast("long")


def is_valid_title(title: Column, *, mode: str = "substring") -> Column:
    """False for null and empty titles, digits alone, and titles with a marker: anywhere, or as a whole word (mode "word")."""
    words = [m for m in TITLE_MARKERS if m.isalpha()]
    signs = "".join(m for m in TITLE_MARKERS if not m.isalpha())
    inner = "|".join(words)
    marked = title.rlike(rf"\b(?:{inner})\b|[{signs}]" if mode == "word" else rf"{inner}|[{signs}]")
    return F.coalesce(~marked & ~title.rlike("^[0-9]*$"), F.lit(False))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays; 0 if either has no length."""
    norm = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(norm > 0, dot(a, b) / norm).otherwise(F.lit(0.0))


def cosine_sparse(a: Column, b: Column) -> Column:
    """Cosine of two maps from terms to weights."""
    both = F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0.0)) * F.coalesce(y, F.lit(0.0)))
    total = lambda m: F.aggregate(F.map_values(m), F.lit(0.0), lambda s, x: s + x)
    square = lambda m: F.sqrt(F.aggregate(F.map_values(m), F.lit(0.0), lambda s, x: s + x * x))
    norm = square(a) * square(b)
    return F.when(norm > 0, total(both) / norm).otherwise(F.lit(0.0))


def url_host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[A-Za-z]+://([^/?#]*)", 1))


def url_path(url: Column) -> Column:
    return F.regexp_extract(url, r"^[A-Za-z]+://[^/?#]*([^?#]*)", 1)


def url_plain(url: Column) -> Column:
    """Without scheme, query and fragment."""
    return F.regexp_replace(F.regexp_replace(url, r"^[A-Za-z]+://", ""), r"[?#].*$", "")
