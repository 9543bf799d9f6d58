"""Closed forms: bounds, exact probabilities, sizes. log is to base 2, ln is natural."""

from __future__ import annotations

from math import ceil, e, exp, log, log2, prod, sqrt

from pyspark.sql import Column
from pyspark.sql import functions as F


def independence_bound(k: int, c: int) -> float:
    """Lower bound of the chance that n random equations in n + c variables over GF(2^k) are independent. Vacuous for k=1, c=0."""
    return 1 - 1 / (2 ** (k * c) * (2**k - 1))


def independence_exact(k: int, n: int, c: int = 0) -> float:
    q = 2.0**k
    return prod(1 - q ** (i - n - c) for i in range(n))


def expected_tries(k: int, n: int, c: int = 0) -> float:
    return 1 / independence_exact(k, n, c)


def vars_lower_bound(n: int, t: int, eps: float = 0.0) -> float:
    """With fewer variables t-sparse equations are dependent with high probability. Necessary, not sufficient."""
    return n * (1 + exp(-t - eps))


def vars_asserted(n: int, t: int) -> float:
    """The number said to be enough. Over GF(2) with t distinct places it is not; see SLACK."""
    return n * (1 + exp(-t))


#: Measured shares of variables to equations at which t-sparse binary systems of a thousand equations or more are solved.
SLACK = {3: 1.125, 4: 1.05, 5: 1.02}


def slack_for(t: int) -> float:
    if t < 3:
        raise ValueError("rows of fewer than 3 places need twice as many variables; give slack")
    return SLACK.get(t, 1.02)


def bits_for_error(eps: float) -> int:
    """Fingerprint bits for a false-positive rate of at most eps."""
    if not 0 < eps < 1:
        raise ValueError("the error must be between 0 and 1")
    return max(1, ceil(-log2(eps) - 1e-12))


def bits_for_error_col(eps: Column) -> Column:
    """The same as a column of errors between 0 and 1."""
    return F.greatest(F.lit(1), F.ceil(-F.log2(eps) - 1e-12)).cast("int")


class PaperParams:
    """Sizes by the formulas, for cost tables. At real n the cells are too small to be of use."""

    def __init__(self, n: int, k: int):
        if n < 4 or k < 1:
            raise ValueError("n must be at least 4 and k at least 1")
        lg = log2(n)
        self.n, self.k = n, k
        self.buckets = n / lg**2
        self.bucket_mean = lg**2
        self.bucket_cap = 2 * lg**4
        self.bad_keys_limit = n / lg**2
        self.cell_mean = 0.5 * sqrt(lg / k)
        self.cell_cap = sqrt(lg / (2 * k))
        self.matrices = sqrt(n)
        self.matrix_list_bits = sqrt(n) * lg
        self.table_len = lg**8
        self.table_funcs = ceil(2 * lg)


def bloom_bits(n: int, k: int = 1) -> float:
    """k one-probe filters of n log2 e bits each."""
    return n * k * log2(e)


def bloom_single_error(n: int, bits: int) -> float:
    return 1 - (1 - 1 / bits) ** n


def no_collision(s: int, positions: int) -> float:
    """Chance that s keys fall on different ones of so many positions."""
    return prod(1 - i / positions for i in range(s))


def comparison_table(n: int, k: int) -> list[dict]:
    """Bits, probes, build and the hashing that each structure asks for. Lower-order terms of the two-level one are measured, not here."""
    lg = log2(n)
    rows = [
        ("exact hash table", None, 1.0, "O(n)", "universal", 0.0),
        ("one-probe Bloom", bloom_bits(n), 1.0, "O(n)", "uniform", 0.5),
        ("k-fold Bloom", bloom_bits(n, k), float(k), "O(nk)", "uniform", 2.0**-k),
        ("fingerprint set", float(n * (k + 2)), 2.0, "O(n)", "uniform", 2.0**-k),
        ("dense system", float(n * k), float(n), "O(n^3)", "uniform", 2.0**-k),
        ("sparse system", vars_asserted(n, 5) * k, 5.0, "O(t n^2)", "uniform", 2.0**-k),
        ("one level", float(n * k), lg**2, "O(n s^2)", "uniform", 2.0**-k),
        ("two levels", float(n * k), 3.0 + k, "O(n)", "pairwise", 2.0**-k),
        ("global sparse", float(n * k), float(ceil(log(n))), "O(n^2)", "uniform", 2.0**-k),
    ]
    return [dict(zip(("method", "bits", "probes", "build", "hashing", "error"), r, strict=True)) for r in rows]
