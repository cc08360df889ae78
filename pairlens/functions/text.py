"""Text columns: normal forms, tokens, n-grams, sentences, fingerprints. All built-in expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Characters that count as blank: ASCII white space, no-break space, zero-width space, byte-order mark.
BLANK = "[\\s\u00a0\u200b\ufeff]"
WORD, SENTENCE_END = r"[^\s]+", r"([.!?])[ \t]+"


def normalized(c: Column, how: str = "none") -> Column:
    match how:
        case "none":
            return c
        case "strip":
            return F.regexp_replace(F.regexp_replace(c, rf"^{BLANK}+", ""), rf"{BLANK}+$", "")
        case "casefold":
            return F.lower(c)
        case "collapse":
            return F.regexp_replace(normalized(c, "strip"), rf"{BLANK}+", " ")
    raise ValueError(f"unknown normal form {how}")


def fingerprint(c: Column, normalize: str = "none", algo: str = "md5") -> Column:
    """md5 can be compared with other engines; two seeded 64-bit hashes are shorter and faster."""
    c = normalized(c, normalize)
    if algo == "md5":
        return F.md5(c)
    return F.concat_ws("-", F.hex(F.xxhash64(c, F.lit(1))), F.hex(F.xxhash64(c, F.lit(2))))


def words(c: Column) -> Column:
    return F.filter(F.split(c, r"[\x20\x09-\x0D]+"), lambda w: w != "")


def tokens(c: Column, ascii_only: bool = False) -> Column:
    """Lower-case runs of letters and digits; ascii_only splits words at other letters, which shows the sensitivity."""
    return F.regexp_extract_all(F.lower(c), F.lit(r"[a-z0-9]+" if ascii_only else r"[\p{L}\p{N}]+"), F.lit(0))


def ngrams(toks: Column, n: int) -> Column:
    """Overlapping n-grams joined by a blank; none if there are fewer tokens."""
    if n == 1:
        return toks
    grams = lambda t: F.when(F.size(t) >= n, F.transform(F.sequence(F.lit(1), F.size(t) - (n - 1)), lambda i: F.array_join(F.slice(t, i, n), " "))).otherwise(F.array().cast("array<string>"))
    # as the argument of a lambda the tokens are made once, inside one they would be made for every gram
    return F.get(F.transform(F.array(toks), grams), 0)


def sentences(c: Column, abbreviations: tuple[str, ...] = ()) -> Column:
    """A line feed ends a sentence; so does . ! or ? before a blank, unless an abbreviation of the list stands there."""
    guarded = c
    for a in abbreviations:
        guarded = F.regexp_replace(guarded, rf"(?<![\p{{L}}]){a}\.[ \t]+", f"{a}.\u0001")
    cut = F.regexp_replace(guarded, SENTENCE_END, "$1\n")
    parts = F.transform(F.split(cut, "\n"), lambda s: F.regexp_replace(F.regexp_replace(s, "\u0001", " "), r"^[ \t]+|[ \t]+$", ""))
    return F.filter(parts, lambda s: s != "")


def n_units(c: Column, unit: str = "char") -> Column:
    match unit:
        case "char":
            return F.length(c)
        case "token":
            return F.size(words(c))
        case "sentence":
            return F.size(sentences(c))
    raise ValueError(f"unknown unit {unit}")
