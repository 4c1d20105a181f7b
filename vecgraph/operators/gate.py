"""The routing gate and the edge screen, as columns.

With a = length of the edge, b = distance of the target from the pivot and r =
distance of the target from the rim, a neighbour is nearer to the target than the
rim exactly if the cosine between edge and way is at least
(a^2 + b^2 - r^2) / (2ab); it is nearer than the pivot if the cosine exceeds
a / (2b). Both are compared with the same estimate, so one scan serves both.
"""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def estimate_cosine(cos_target: Column, cos_own: Column) -> Column:
    return cos_target / cos_own


def gate_threshold(a: Column, b: Column, r: Column) -> Column:
    """Cosine needed to come within r of the target."""
    return (a * a + b * b - r * r) / (2 * a * b)


def screen_threshold(a: Column, b: Column) -> Column:
    """Cosine needed to be nearer to the target than the pivot is."""
    return a / (2 * b)


def gate_stat(cos_target: Column, cos_own: Column, tau: Column) -> Column:
    """The gate passes a neighbour if this is not negative; without a threshold it is open."""
    return F.coalesce(estimate_cosine(cos_target, cos_own) - tau, F.lit(float("inf")))


def gate_and_screen(a: Column, b: Column, r: Column, cos_target: Column, cos_own: Column) -> Column:
    """struct(gate, screen) of one scan: the screen is the gate moved left by (r^2 - b^2) / (2ab)."""
    gate = gate_stat(cos_target, cos_own, gate_threshold(a, b, r))
    return F.struct(gate.alias("gate"), (gate - (r * r - b * b) / (2 * a * b)).alias("screen"))


def screen_stat(term: Column) -> Column:
    """Aggregate of a pivot's screen terms; the edge survives if it is negative."""
    return F.max(term)
