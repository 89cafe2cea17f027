"""Normalising, masking and matching cell texts; everything here is a Catalyst expression."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Texts that stand for a missing cell, after trimming and lower-casing.
MISSING = ("", "n/a", "na", "-", "–")
#: Least similarity of a fuzzy match.
TAU = 0.6


def normalize_value(text: Column) -> Column:
    """Canonical form: trimmed, lower case, single blanks, no leading zeros of all-digit texts, decimal point; missing is null."""
    plain = F.lower(F.trim(F.regexp_replace(text, r"\s+", " ")))
    plain = F.when(plain.rlike(r"^\d+,\d+$"), F.replace(plain, F.lit(","), F.lit("."))).otherwise(plain)
    plain = F.when(plain.rlike(r"^0+\d+$"), F.regexp_replace(plain, r"^0+(?=\d)", "")).otherwise(plain)
    return F.when(plain.isin(*MISSING), F.lit(None)).otherwise(plain)


def number_of(text: Column) -> Column:
    """The text's number, or null."""
    return F.expr("cast(null as decimal(38,6))") if text is None else text.try_cast("decimal(38,6)")


def mask_text(text: Column, whitespace: str = "drop", lengths: bool = False) -> Column:
    """Runs of letters become A, of digits D, of anything else N. With `lengths`, letter and digit runs carry theirs."""
    plain = F.regexp_replace(text, r"\s+", "") if whitespace == "drop" else text
    if lengths:
        runs = F.regexp_extract_all(plain, F.lit(r"(\p{L}+|\p{Nd}+|[^\p{L}\p{Nd}]+)"), F.lit(1))
        kind = lambda r: F.when(r.rlike(r"^\p{L}"), F.concat(F.lit("A"), F.length(r))).when(r.rlike(r"^\p{Nd}"), F.concat(F.lit("D"), F.length(r))).otherwise(F.lit("N"))
        return F.array_join(F.transform(runs, kind), "")
    # control characters stand in, so that a letter put in isn't masked again
    plain = F.regexp_replace(plain, r"[\x01\x02\x03]", " ")
    plain = F.regexp_replace(plain, r"\p{L}+", "\x01")
    plain = F.regexp_replace(plain, r"\p{Nd}+", "\x02")
    plain = F.regexp_replace(plain, r"[^\x01\x02]+", "\x03")
    return F.translate(plain, "\x01\x02\x03", "ADN")


def tokens_of(text: Column) -> Column:
    """Distinct lower-case tokens of letters and digits."""
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(r"[\p{L}\p{N}]+"), F.lit(0)))


def qgrams(text: Column, q: int = 2) -> Column:
    """Distinct q-grams of the text with a blank at both ends."""
    padded = F.concat(F.lit(" "), text, F.lit(" "))
    places = F.sequence(F.lit(1), F.greatest(F.length(padded) - (q - 1), F.lit(1)))
    return F.array_distinct(F.transform(places, lambda i: F.substring(padded, i, q)))


def most_edits(length: Column, tau: float) -> Column:
    """How many edits a likeness of tau allows to texts of which the longer has this length."""
    return F.floor(length * F.lit(1 - tau) + F.lit(1e-9)).cast("int")


def match_score(asked: Column, held: Column, mode: str = "edit", tau: float = TAU) -> Column:
    """Likeness of two normalised texts: 1 for equal ones, 0 for no match, between tau and 1 for a fuzzy match.

    Modes: exact; edit (edit distance by length, cut off at what tau allows); token (share of asked tokens held);
    prefix (share of the held text that the asked one begins).
    """
    if not 0 < tau <= 1:
        raise ValueError("tau lies above 0, so that a fuzzy match beats none")
    same = asked == held
    if mode == "exact":
        fuzzy = F.lit(0.0)
    elif mode == "edit":
        longest = F.greatest(F.length(asked), F.length(held))
        # no more of the distance is computed than tau allows; beyond it the function gives -1
        distance = F.call_function("levenshtein", asked, held, most_edits(longest, tau))
        share = 1 - distance / F.greatest(longest, F.lit(1))
        fuzzy = F.when((distance >= 0) & (share >= tau) & (share < 1), share).otherwise(0.0)
    elif mode == "token":
        wanted = tokens_of(asked)
        share = F.size(F.array_intersect(wanted, tokens_of(held))) / F.greatest(F.size(wanted), F.lit(1))
        fuzzy = F.when(share >= tau, F.least(share, F.lit(0.99))).otherwise(0.0)
    elif mode == "prefix":
        fuzzy = F.when(F.startswith(held, asked) & (F.length(asked) > 0), tau + (1 - tau) * F.length(asked) / F.greatest(F.length(held), F.lit(1)) * 0.99).otherwise(0.0)
    else:
        raise ValueError(f"no such mode: {mode}")
    return F.coalesce(F.when(same, F.lit(1.0)).otherwise(fuzzy), F.lit(0.0))
