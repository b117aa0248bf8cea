"""Vector and text functions as Column expressions: built-ins only, so they stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x)


def dot(a: Column | str, b: Column | str) -> Column:
    return total(F.zip_with(_col(a), _col(b), lambda x, y: x * y))


def l2sq(a: Column | str, b: Column | str) -> Column:
    return total(F.zip_with(_col(a), _col(b), lambda x, y: (x - y) * (x - y)))


def l2(a: Column | str, b: Column | str) -> Column:
    return F.sqrt(l2sq(a, b))


def norm(a: Column | str) -> Column:
    return F.sqrt(total(F.transform(_col(a), lambda x: x * x)))


def cosine(a: Column | str, b: Column | str) -> Column:
    """Cosine similarity; 0 where either vector has no length."""
    both = norm(a) * norm(b)
    return F.when(both == 0, F.lit(0.0)).otherwise(dot(a, b) / both)


def distance(a: Column | str, b: Column | str, metric: str = "l2") -> Column:
    """Smaller is nearer: l2, or the negated inner product, or 1 - cosine."""
    if metric == "l2":
        return l2(a, b)
    if metric == "ip":
        return -dot(a, b)
    if metric == "cosine":
        return F.lit(1.0) - cosine(a, b)
    raise ValueError(f"no such metric: {metric}")


def tokens(text: Column | str) -> Column:
    """Words of letters and digits, in lower case."""
    return F.regexp_extract_all(F.lower(F.coalesce(_col(text), F.lit(""))), F.lit(r"([\p{L}\p{N}]+)"))


def token_count(text: Column | str) -> Column:
    return F.size(tokens(text))


def sentences(text: Column | str) -> Column:
    """Trimmed sentences: cut after . ! ? before white space; a text without such a cut is cut at newlines; blanks go."""
    body = F.coalesce(_col(text), F.lit(""))
    marked = F.regexp_replace(body, r"([.!?])\s+", "$1\u0001")
    parts = F.when(F.contains(marked, F.lit("\u0001")), F.split(marked, "\u0001")).otherwise(F.split(body, "\n"))
    return F.filter(F.transform(parts, lambda s: F.regexp_replace(s, r"^\s+|\s+$", "")), lambda s: s != "")


def bucket(token: Column, dim: int) -> Column:
    """Bucket of a token: its md5's first 8 hex digits modulo dim."""
    return F.pmod(F.conv(F.substring(F.md5(token), 1, 8), 16, 10).cast("long"), F.lit(dim)).cast("int")


def sign(token: Column) -> Column:
    """+1 where the ninth hex digit of the md5 is odd, else -1."""
    return F.when(F.pmod(F.conv(F.substring(F.md5(token), 9, 1), 16, 10).cast("int"), F.lit(2)) == 1, F.lit(1.0)).otherwise(F.lit(-1.0))
