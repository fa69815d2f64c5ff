"""Columns of the token pipeline: ASCII mapping, tokens, trimming, n-grams. All are built-in expressions, so they stay in generated code."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Stands for any character that is not ASCII.
SENTINEL = "\x1a"
#: Names of unknown terms by n-gram order. `<` is a token of its own, so no token has these names.
UNKNOWN = {1: "<unk>", 2: "<unk2>", 3: "<unk3>"}
#: One punctuation sign, or a run without punctuation and white space. `_` counts as a letter.
PUNCTUATION = r"!-/:-@\[-^`{-~"
TOKEN = rf"[^ \t\n\r\f\x0b{PUNCTUATION}]+|[{PUNCTUATION}]"
PRINTABLE = r"[\x20-\x7e\t\n\r]"


def to_ascii(text: Column, unit: str = "codepoint") -> Column:
    """Map what is not ASCII to the sentinel: one for each character, or (unit `byte`) one for each of its UTF-8 bytes; unit `none` maps nothing."""
    if unit == "none":
        return text
    if unit == "codepoint":
        return F.regexp_replace(text, r"[^\x00-\x7f]", SENTINEL)
    if unit != "byte":
        raise ValueError(f"unit {unit!r}: codepoint, byte or none")
    for span, size in ((r"[\x{80}-\x{7ff}]", 2), (r"[\x{800}-\x{ffff}]", 3), (r"[\x{10000}-\x{10ffff}]", 4)):
        text = F.regexp_replace(text, span, SENTINEL * size)
    return text


def tokenize(text: Column) -> Column:
    """Tokens in order. Signs are set apart and the text is split at white space, which takes half the time of matching TOKEN."""
    apart = F.regexp_replace(F.coalesce(text, F.lit("")), rf"[{PUNCTUATION}]", " $0 ")
    return F.array_remove(F.split(apart, r"[ \t\n\r\f\x0b]+"), "")


def tokens_of(text: Column, unit: str = "codepoint") -> Column:
    return tokenize(to_ascii(text, unit))


def trim(tokens: Column, head: int = 10, tail: int = 10, fraction: float | None = None) -> Column:
    """Without the first and last tokens: a count of each, or a fraction of the tokens at either end. Short files become empty."""
    if fraction is not None:
        cut = F.floor(F.size(tokens) * fraction).cast("int")
        return F.slice(tokens, cut + 1, F.greatest(F.size(tokens) - 2 * cut, F.lit(0)))
    return F.slice(tokens, head + 1, F.greatest(F.size(tokens) - (head + tail), F.lit(0)))


def ngrams(tokens: Column, n: int) -> Column:
    """Runs of n tokens joined by a space, which no token contains; a file of fewer tokens has none."""
    out = tokens
    for k in range(1, n):
        rest = F.slice(tokens, k + 1, F.greatest(F.size(tokens) - k, F.lit(0)))
        out = F.zip_with(F.slice(out, 1, F.greatest(F.size(tokens) - k, F.lit(0))), rest, lambda a, b: F.concat_ws(" ", a, b))
    return out


def map_unknown(terms: Column, known: Iterable[str], n: int = 1) -> Column:
    """Each term as itself, or as the unknown of its order. The set of known terms is probed by hash."""
    known = list(known)
    if not known:
        return F.transform(terms, lambda t: F.lit(UNKNOWN[n]))
    return F.transform(terms, lambda t: F.when(t.isin(known), t).otherwise(F.lit(UNKNOWN[n])))


def nonprintable_ratio(col: Column, unit: str = "codepoint", binary: bool = False) -> Column:
    """Share of units that are not printable ASCII, tab, line feed or carriage return; null for empty content."""
    if binary:
        text, size = F.decode(col, "ISO-8859-1"), F.octet_length(col)
        odd = F.length(F.regexp_replace(text, PRINTABLE, ""))
    elif unit == "byte":
        size, odd = F.octet_length(col), F.octet_length(F.regexp_replace(col, PRINTABLE, ""))
    else:
        size, odd = F.length(col), F.length(F.regexp_replace(col, PRINTABLE, ""))
    return F.try_divide(odd.cast("double"), F.nullif(size, F.lit(0)))


def extension(filename: Column) -> Column:
    """What follows the last dot, in its own case; null without a dot, for hidden files, and after a final dot."""
    return F.nullif(F.regexp_extract(filename, r"^.*[^/]\.([^./]+)$", 1), F.lit(""))


def token_rows(df: DataFrame, content: str = "content") -> DataFrame:
    return df.select("file_id", F.posexplode(tokens_of(F.col(content))).alias("pos", "token"))


def bucket(key: Column, seed: int | str, modulus: int) -> Column:
    """A seeded bucket of a key, the same in any engine that has md5."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", key, F.lit(str(seed)))), 1, 8), 16, 10).cast("long") % modulus
