"""Answer measures: exact match, normalised edit similarity, lexical judgement."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from doccurate.functions.text import edit_ratio, norm, token_f1


def exact_match(prediction: Column, references: Column) -> Column:
    """Whether the normal form of the prediction is that of a reference (array)."""
    return F.exists(references, lambda r: norm(r) == norm(prediction))


def anls(prediction: Column, references: Column, tau: float = 0.5) -> Column:
    """Best over references of 1 - normalised edit distance, 0 where that distance is tau or more."""
    best = F.array_max(F.transform(references, lambda r: edit_ratio(norm(prediction), norm(r))))
    return F.when(1 - best < tau, best).otherwise(0.0)


def lexical_judge(prediction: Column, reference: Column, tau: float = 0.8) -> Column:
    """Stand-in for a judging model: equal, the reference contained as whole words, or token F1 of at least tau."""
    p, r = norm(prediction), norm(reference)
    inside = F.concat(F.lit(" "), p, F.lit(" ")).contains(F.concat(F.lit(" "), r, F.lit(" ")))
    return (p == r) | ((r != "") & inside) | (token_f1(prediction, reference) >= tau)
