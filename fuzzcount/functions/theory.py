"""Closed forms: filter load, flips, and the chance that a noisy copy stays within a radius."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from fuzzcount.functions.noise import flip_rate


def fpr(hashes: Column, items: Column, ell: Column) -> Column:
    """False-positive rate of a filter with so many items."""
    return F.pow(1 - F.exp(-hashes * items / ell), hashes)


def optimal_hashes(ell: float, items: float) -> float:
    return ell / items * math.log(2)


def eta(epsilon: Column) -> Column:
    return 1 / (1 + F.exp(epsilon))


def erf(x: Column) -> Column:
    """Error function by a published rational approximation (absolute error below 1.5e-7)."""
    #: Fixed values of the approximation.
    p, a = 0.3275911, (0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429)
    t = 1 / (1 + p * F.abs(x))
    series = t * (a[0] + t * (a[1] + t * (a[2] + t * (a[3] + t * a[4]))))
    return F.signum(x) * (1 - series * F.exp(-x * x))


def same_cluster_prob(radius: Column, epsilon: Column, ell: int) -> Column:
    """Chance that a filter and its noisy copy lie within a Euclidean radius (its square in bits), by the normal law."""
    rate = eta(epsilon)
    mean, spread = ell * rate, F.sqrt(2 * ell * rate * (1 - rate))
    return 0.5 * (1 + erf((radius * radius - mean) / spread))


def same_cluster_prob_exact(radius: int, epsilon: float, ell: int) -> float:
    """The same by the binomial law."""
    q = flip_rate(epsilon)
    return math.fsum(math.comb(ell, i) * q**i * (1 - q) ** (ell - i) for i in range(min(ell, radius * radius) + 1))


def same_cluster_prob_value(radius: float, epsilon: float, ell: int) -> float:
    q = flip_rate(epsilon)
    mean, spread = ell * q, math.sqrt(2 * ell * q * (1 - q))
    return 0.5 * (1 + math.erf((radius * radius - mean) / spread))


def min_eps(radius: float, probability: float, ell: int) -> float:
    """The least budget at which a noisy copy stays within the radius with the given probability."""
    low, high = 0.0, 30.0
    for _ in range(80):
        middle = (low + high) / 2
        low, high = (low, middle) if same_cluster_prob_value(radius, middle, ell) >= probability else (middle, high)
    return high


def debias_hamming(distance: Column, epsilon: float, ell: int) -> Column:
    """The distance before both filters were perturbed, in expectation."""
    q = 2 * flip_rate(epsilon) * (1 - flip_rate(epsilon))
    return (distance - ell * q) / (1 - 2 * q)


def debias_popcount(ones: Column, epsilon: float, ell: int) -> Column:
    rate = flip_rate(epsilon)
    return (ones - ell * rate) / (1 - 2 * rate)
