"""The four similarity measures and the bounds that filters derive from them.

With I the summed smaller weights of shared tokens (for the cosine: summed products of
unit weights) and W the summed weights, similarities are I / (Wa + Wb - I), I,
2 I / (Wa + Wb) and I. ``power`` tells which sums prefixes and suffixes are made of.
Fixed values of the method: the bounds below.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

SLACK = 1e-9


@dataclass(frozen=True)
class Measure:
    name: str
    power: int = 1
    bounded: bool = True

    def shared(self, wa: Column, wb: Column) -> Column:
        """What one shared token adds to I."""
        return wa * wb if self.name == "cosine" else F.least(wa, wb)

    def value(self, i: Column, wa: Column, wb: Column) -> Column:
        if self.name == "jaccard":
            return i / (wa + wb - i)
        if self.name == "dice":
            return F.lit(2.0) * i / (wa + wb)
        return i

    def number(self, i, wa, wb):
        """``value`` of numbers and arrays."""
        return i / (wa + wb - i) if self.name == "jaccard" else 2 * i / (wa + wb) if self.name == "dice" else i

    def sigma(self, total: Column, tau: Column) -> Column:
        """Least suffix of a token that belongs to the prefix."""
        return {
            "jaccard": lambda: tau * total,
            "cosine": lambda: tau * tau,
            "dice": lambda: tau / (2 - tau) * total,
            "overlap": lambda: tau,
        }[self.name]() - SLACK

    def suffix_low(self, tau: Column, total_a: Column, s_a: Column, p_b: Column) -> Column:
        """Least suffix of b at the first shared token, given b's passed prefix."""
        return {
            "jaccard": lambda: tau * (total_a + p_b),
            "cosine": lambda: tau * tau / F.greatest(s_a, F.lit(1e-300)),
            "dice": lambda: tau / (2 - tau) * (total_a + p_b),
            "overlap": lambda: tau,
        }[self.name]() - SLACK

    def suffix_high(self, tau: Column, s_a: Column, p_a: Column, p_b: Column) -> Column | None:
        """Largest suffix of b; None where the measure sets no upper bound."""
        safe = F.greatest(tau, F.lit(1e-300))
        if self.name == "jaccard":
            return s_a / safe - p_a - p_b + SLACK
        if self.name == "dice":
            return (2 - tau) / safe * s_a - p_a - p_b + SLACK
        return None

    def size_low(self, tau: Column, total_a: Column) -> Column:
        return {"jaccard": lambda: tau * total_a, "dice": lambda: tau / (2 - tau) * total_a, "overlap": lambda: tau, "cosine": lambda: tau * 0}[self.name]() - SLACK

    def size_high(self, tau: Column, total_a: Column) -> Column | None:
        safe = F.greatest(tau, F.lit(1e-300))
        if self.name == "jaccard":
            return total_a / safe + SLACK
        if self.name == "dice":
            return (2 - tau) / safe * total_a + SLACK
        return None

    def attainable(self, tau: Column, s_a: Column, s_b: Column, total_a: Column, total_b: Column) -> Column:
        """Positional test: whether the two suffixes can still reach the threshold."""
        if self.name == "cosine":
            return s_a * s_b >= tau * tau - SLACK
        need = {"jaccard": lambda: tau / (1 + tau) * (total_a + total_b), "dice": lambda: tau / 2 * (total_a + total_b), "overlap": lambda: tau}[self.name]()
        return F.least(s_a, s_b) >= need - SLACK

    def attainable_exact(self, tau: Column, s_a: Column, s_b: Column, total_a: Column, total_b: Column, w_a: Column, w_b: Column) -> Column:
        """The positional test with what the token itself adds, apart from what may follow it."""
        if self.name == "cosine":
            left = F.greatest(s_a - w_a * w_a, F.lit(0.0)) * F.greatest(s_b - w_b * w_b, F.lit(0.0))
            return w_a * w_b + F.sqrt(left) >= tau - SLACK
        need = {"jaccard": lambda: tau / (1 + tau) * (total_a + total_b), "dice": lambda: tau / 2 * (total_a + total_b), "overlap": lambda: tau}[self.name]()
        return F.least(w_a, w_b) + F.least(s_a - w_a, s_b - w_b) >= need - SLACK


MEASURES = {
    "jaccard": Measure("jaccard"),
    "cosine": Measure("cosine", power=2),
    "dice": Measure("dice"),
    "overlap": Measure("overlap", bounded=False),
}


def binary_similarity(a: Column, b: Column, measure: str) -> Column:
    """Similarity of two token arrays without weights."""
    a, b = F.array_distinct(a), F.array_distinct(b)
    i, na, nb = F.size(F.array_intersect(a, b)).cast("double"), F.size(a).cast("double"), F.size(b).cast("double")
    if measure == "cosine":
        return F.when((na == 0) | (nb == 0), 0.0).otherwise(i / F.sqrt(na * nb))
    if measure == "overlap":
        return i
    m = MEASURES[measure]
    return F.when(na + nb == 0, 0.0).otherwise(m.value(i, na, nb))
