"""Column functions over sequences; all of them stay in the JVM."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from .scoring import Scoring

GAP = "_"
#: The 26 letters, dealt to four symbols in turn.
LETTERS, FOLDED = "abcdefghijklmnopqrstuvwxyz", "ACGTACGTACGTACGTACGTACGTAC"


def fold_letters(text: Column) -> Column:
    """Letters a to z of a text in lower case, dealt to A, C, G and T; all else is left out."""
    return F.translate(F.regexp_replace(F.lower(text), "[^a-z]", ""), LETTERS, FOLDED)


def strip_gaps(seq: Column) -> Column:
    return F.regexp_replace(seq, "[_-]", "")


def reverse_complement(seq: Column) -> Column:
    return F.reverse(F.translate(seq, "ACGTacgt", "TGCAtgca"))


def clean(seq: Column, alphabet: str = "ACGT", on_unknown: str = "keep") -> Column:
    """Letters outside the alphabet are kept, dropped, or make the row's value null ("error" raises)."""
    unknown = f"[^{alphabet}]"
    if on_unknown == "drop":
        return F.regexp_replace(seq, unknown, "")
    if on_unknown == "null":
        return F.when(~seq.rlike(unknown), seq)
    if on_unknown == "error":
        return F.when(seq.rlike(unknown), F.raise_error(F.concat(F.lit("letter outside the alphabet: "), seq))).otherwise(seq)
    return seq


def kmers(seq: Column, k: int = 3) -> Column:
    n = F.length(seq) - (k - 1)
    return F.when(n >= 1, F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(seq, i, F.lit(k)))).otherwise(F.array().cast("array<string>"))


def letter_count(seq: Column, letter: str) -> Column:
    return F.length(seq) - F.length(F.translate(seq, letter, ""))


def score_upper_bound(a: Column, b: Column, s: Scoring, alphabet: str = "ACGT") -> Column:
    """No alignment of a and b scores more: from the letters they share and their lengths."""
    shared = reduce(lambda x, y: x + y, [F.least(letter_count(a, c), letter_count(b, c)) for c in alphabet])
    short = F.least(F.length(a), F.length(b))
    hits = F.least(short, shared)
    return s.match * hits + max(s.mismatch, 0) * (short - hits) + s.gap * F.abs(F.length(a) - F.length(b))


def global_score_sql(a: Column, b: Column, s: Scoring) -> Column:
    """Optimal score by nested higher-order functions. For short strings and for checks: it is interpreted row by row."""
    m, x, g = (F.lit(int(v)).cast("long") for v in (s.match, s.mismatch, s.gap))
    zero = F.lit(0).cast("long")
    letters = lambda c: F.when(c == "", F.array().cast("array<string>")).otherwise(F.split(c, ""))
    start = F.transform(F.sequence(zero, F.length(b).cast("long")), lambda j: j * g)

    def row(prev: Column, letter: Column) -> Column:
        cell = lambda acc, j: F.greatest(
            F.element_at(prev, j) + F.when(F.substring(b, j, F.lit(1)) == letter, m).otherwise(x), F.element_at(prev, j + 1) + g, F.element_at(acc, -1) + g
        )
        first = F.array(F.element_at(prev, 1) + g)
        steps = F.when(F.length(b) > 0, F.sequence(F.lit(1), F.length(b))).otherwise(F.array().cast("array<int>"))
        return F.aggregate(steps, first, lambda acc, j: F.concat(acc, F.array(cell(acc, j))))

    return F.element_at(F.aggregate(letters(a), start, row), -1)
