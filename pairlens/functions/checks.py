"""Row-level checks of a pair: Boolean columns, true where the pair is faulty."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from pairlens.functions.text import BLANK, n_units, normalized, sentences, tokens

LEVELS = ("missing", "blank", "symbols", "encoding")


def is_missing(ref: Column, summ: Column) -> Column:
    return ref.isNull() | summ.isNull() | (F.length(ref) == 0) | (F.length(summ) == 0)


def is_blank(c: Column) -> Column:
    return F.coalesce(c.rlike(rf"^{BLANK}*$"), F.lit(True))


def is_symbolic(c: Column) -> Column:
    """No letter or digit."""
    return F.coalesce(~c.rlike(r"[\p{L}\p{N}]"), F.lit(True))


def is_misencoded(c: Column, max_share: float = 0.0) -> Column:
    """Replacement characters, control characters and typical traces of double decoding, above a share of the text."""
    bad = F.regexp_count(c, F.lit("\ufffd|[\\x00-\\x08\\x0E-\\x1F\\x7F]|\u00c3[\u0080-\u00bf]"))
    return F.coalesce(bad > F.length(c) * max_share, F.lit(False))


def is_empty(ref: Column, summ: Column, level: str = "missing") -> Column:
    """Levels add up: each has all before it."""
    tests = [is_missing(ref, summ), is_blank(ref) | is_blank(summ), is_symbolic(ref) | is_symbolic(summ), is_misencoded(ref) | is_misencoded(summ)]
    out = tests[0]
    for t in tests[1 : LEVELS.index(level) + 1]:
        out = out | t
    return out


def too_short(c: Column, minimum: Column | int, unit: str = "char") -> Column:
    return F.coalesce(n_units(c, unit) < minimum, F.lit(True))


def too_long(c: Column, maximum: int, unit: str = "char") -> Column:
    return F.coalesce(n_units(c, unit) > maximum, F.lit(False))


def compression_ratio(ref: Column, summ: Column, unit: str = "char") -> Column:
    return F.try_divide(n_units(ref, unit).cast("double"), n_units(summ, unit).cast("double"))


def low_compression(ref: Column, summ: Column, min_cr: float = 1.25, unit: str = "char", allow_expansion: bool = False) -> Column:
    """True below the ratio, which itself passes. A ratio of 1 or less asks for allow_expansion."""
    if min_cr <= 1.0 and not allow_expansion:
        raise ValueError("a ratio of 1 or less admits summaries as long as their references")
    return F.coalesce(n_units(ref, unit).cast("double") < n_units(summ, unit) * F.lit(float(min_cr)), F.lit(False))


def not_compressed(ref: Column, summ: Column, unit: str = "char") -> Column:
    return F.coalesce(n_units(ref, unit) <= n_units(summ, unit), F.lit(False))


def extreme_compression(ref: Column, summ: Column, max_cr: float, unit: str = "char") -> Column:
    return F.coalesce(n_units(ref, unit).cast("double") > n_units(summ, unit) * F.lit(float(max_cr)), F.lit(False))


def identical(ref: Column, summ: Column, normalize: str = "none") -> Column:
    a, b = normalized(ref, normalize), normalized(summ, normalize)
    return (F.length(a) == F.length(b)) & a.eqNullSafe(b)


def fully_extractive(ref: Column, summ: Column, mode: str = "substring") -> Column:
    """The summary is a part of its reference: as characters, tokens in a row, sentences in a row or any sentences."""
    match mode:
        case "substring":
            out = F.contains(ref, summ)
        case "token_run":
            pad = lambda c: F.concat(F.lit(" "), F.array_join(tokens(c), " "), F.lit(" "))
            out = F.contains(pad(ref), pad(summ))
        case "sentence_run":
            pad = lambda c: F.concat(F.lit("\n"), F.array_join(sentences(c), "\n"), F.lit("\n"))
            out = F.contains(pad(ref), pad(summ))
        case "sentence_subset":
            out = F.size(F.array_except(sentences(summ), sentences(ref))) == 0
        case _:
            raise ValueError(f"unknown mode {mode}")
    return F.coalesce(out, F.lit(False))


def copy_position(ref: Column, summ: Column) -> dict[str, Column]:
    """offset from 0 (null if the summary isn't part of the reference), relative offset, and whether it is the start."""
    at = F.instr(ref, summ)
    return {"copy_offset": F.when(at > 0, at - 1), "copy_share": F.when(at > 0, F.round((at - 1) / F.length(ref), 6)), "is_prefix": F.coalesce(at == 1, F.lit(False))}


def jaccard(a: Column, b: Column) -> Column:
    x, y = F.array_distinct(tokens(a)), F.array_distinct(tokens(b))
    return F.try_divide(F.size(F.array_intersect(x, y)).cast("double"), F.size(F.array_union(x, y)).cast("double"))
