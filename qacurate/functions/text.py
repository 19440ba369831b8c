"""Text columns: tokens, shingles, similarity and repetition measures as built-in expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = "([\\p{L}\\p{N}]+)"
CHUNK_TOKEN = "([ \\t\\n\\r]*[^ \\t\\n\\r]+)"  # a word with the blanks before it, so that slices join to the text


def col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def let(value: Column, fn: Callable[[Column], Column]) -> Column:
    """fn of a value that is worked out once per row, however often fn names it, also inside lambdas."""
    return F.get(F.transform(F.array(value), fn), 0)


def tokens(c: Column | str, kind: str = "word") -> Column:
    """kind: word (letters and digits, lower case), space (split at blanks), chunk (blanks kept), char."""
    text = F.coalesce(col(c), F.lit(""))
    if kind == "word":
        return F.regexp_extract_all(F.lower(text), F.lit(WORD), 1)
    if kind == "space":
        return F.regexp_extract_all(text, F.lit("([^ \\t\\n\\r]+)"), 1)
    if kind == "chunk":
        return F.regexp_extract_all(text, F.lit(CHUNK_TOKEN), 1)
    if kind == "char":
        return F.split(text, "")
    raise ValueError(f"unknown kind of token: {kind}")


def n_tokens(c: Column | str, kind: str = "word") -> Column:
    return F.size(tokens(c, kind))


def normalised(c: Column | str) -> Column:
    """Words in lower case with one blank between."""
    return F.array_join(tokens(c), " ")


def runs(w: Column, n: int) -> Column:
    """All runs of n words, repeats included; a shorter text is one run."""
    return F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - n + 1, F.lit(1))), lambda i: F.array_join(F.slice(w, i, n), " "))


def ngrams(words: Column | str, n: int) -> Column:
    """Distinct runs of n words; a shorter text is one run of all its words, none if it has no word."""
    return let(col(words), lambda w: F.when(F.size(w) > 0, F.array_distinct(runs(w, n))).otherwise(F.array().cast("array<string>")))


def shingles(c: Column | str, n: int = 1) -> Column:
    return F.array_distinct(tokens(c)) if n == 1 else ngrams(tokens(c), n)


def _shared(a: Column | str, b: Column | str, fn: Callable[[Column, Column, Column], Column]) -> Column:
    """fn of the numbers of shared distinct members and of those of each side."""
    # Plain columns, not a lambda: they run compiled, and a projection works out what it names twice only once.
    a, b = F.array_distinct(col(a)), F.array_distinct(col(b))
    return fn(F.size(F.array_intersect(a, b)).cast("double"), F.size(a).cast("double"), F.size(b).cast("double"))


def jaccard(a: Column | str, b: Column | str) -> Column:
    """Of two sets held as arrays; null if both are empty."""
    return _shared(a, b, lambda n, x, y: F.try_divide(n, x + y - n))


def containment(a: Column | str, b: Column | str) -> Column:
    """Shared distinct words over those of the smaller side."""
    return _shared(a, b, lambda n, x, y: F.try_divide(n, F.least(x, y)))


def token_f1(a: Column | str, b: Column | str) -> Column:
    """Harmonic mean of precision and recall over distinct words."""
    return _shared(a, b, lambda n, x, y: F.coalesce(F.try_divide(2.0 * n, x + y), F.lit(0.0)))


def repetition(words: Column | str, n: int = 3) -> Column:
    """Share of word n-grams that are repeats: 1 - distinct / all; 0 for texts below n words."""
    share = let(col(words), lambda w: F.when(F.size(w) >= n, F.size(F.array_distinct(runs(w, n))) / F.size(runs(w, n)).cast("double")))
    return F.coalesce(1 - share, F.lit(0.0))


def n_sentences(c: Column | str) -> Column:
    return F.regexp_count(F.coalesce(col(c), F.lit("")), F.lit("[.!?]( |\\n|$)"))


def md5_int(key: Column | str, digits: int = 8) -> Column:
    """The first hexadecimal digits of md5 as a number: a random value that any engine repeats."""
    return F.conv(F.substring(F.md5(col(key)), 1, digits), 16, 10).cast("long")


def md5_fraction(*parts: Column | str | int) -> Column:
    """In [0, 1), from md5 of the parts joined with colons."""
    key = F.concat_ws(":", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return md5_int(key) / F.lit(4294967296.0)


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(col(a), col(b), lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column | str, b: Column | str) -> Column:
    return F.try_divide(dot(a, b), norm(a) * norm(b))
