"""Description lengths in bits, as column expressions that stay inside generated code.

All logarithms are to base 2. The logarithm of a binomial coefficient is computed in a
form that keeps its digits for very large N: differences of log-gamma would lose them.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Natural log of k! for k below this comes from a table, Stirling's series above.
_TABLE = 64


def _ln_factorial(k: Column) -> Column:
    table = F.array(*[F.lit(math.lgamma(i + 1)) for i in range(_TABLE)])
    x = k.cast("double")
    series = (x + 0.5) * F.log(x) - x + 0.5 * math.log(2 * math.pi) + 1 / (12 * x) - 1 / (360 * x * x * x)
    return F.when(x < _TABLE, F.element_at(table, F.least(x, F.lit(_TABLE - 1.0)).cast("int") + 1)).otherwise(series)


def log2_choose(n: Column | str, k: Column | str) -> Column:
    """log2 of n over k; 0 for k = 0 and k = n, null where k > n or k < 0."""
    n = (F.col(n) if isinstance(n, str) else n).cast("double")
    k = (F.col(k) if isinstance(k, str) else k).cast("double")
    j = F.least(k, n - k)
    safe = F.greatest(j, F.lit(1.0))
    # ln of n (n-1) ... (n-j+1) by Stirling's series for both ends, arranged so that no large terms cancel
    wide = safe * F.log(n) - safe - (n - safe + 0.5) * F.log1p(-safe / n) + (1 / n - 1 / (n - safe)) / 12
    value = (wide - _ln_factorial(safe)) / math.log(2)
    return F.when((k < 0) | (k > n), None).when((k == 0) | (k == n), 0.0).when(j == 1, F.log2(n)).otherwise(value)


def log2_choose_array(n: np.ndarray, k: np.ndarray) -> np.ndarray:
    """:func:`log2_choose` over arrays with 0 <= k <= n."""
    n, k = n.astype(float), k.astype(float)
    j = np.minimum(k, n - k)
    safe = np.maximum(j, 1.0)
    table = np.array([math.lgamma(i + 1) for i in range(_TABLE)])
    with np.errstate(all="ignore"):  # both forms are computed everywhere
        series = (safe + 0.5) * np.log(safe) - safe + 0.5 * math.log(2 * math.pi) + 1 / (12 * safe) - 1 / (360 * safe * safe * safe)
        factorial = np.where(safe < _TABLE, table[np.minimum(safe, _TABLE - 1).astype(int)], series)
        wide = safe * np.log(n) - safe - (n - safe + 0.5) * np.log1p(-safe / n) + (1 / n - 1 / (n - safe)) / 12
        return np.where(j == 0, 0.0, np.where(j == 1, np.log2(n), (wide - factorial) / math.log(2)))


def log2_choose_exact(n: int, k: int) -> float:
    """The same for the driver, from exact integers where they are small."""
    if k < 0 or k > n:
        raise ValueError("k lies outside 0..n")
    k = min(k, n - k)
    if k == 0:
        return 0.0
    if k <= 2000 or n < 1 << 20:
        return math.log2(math.comb(n, k))
    n, k = float(n), float(k)
    return (k * math.log(n) - k - (n - k + 0.5) * math.log1p(-k / n) + (1 / n - 1 / (n - k)) / 12 - math.lgamma(k + 1)) / math.log(2)


def code_bits(count: Column | str, total: Column | str) -> Column:
    """Length of an optimal prefix code for something that occurs count times in total."""
    count = F.col(count) if isinstance(count, str) else count
    total = F.col(total) if isinstance(total, str) else total
    return -F.log2(count / total)


def n_log_n(n: Column | str) -> Column:
    n = (F.col(n) if isinstance(n, str) else n).cast("double")
    return F.when(n > 0, n * F.log2(n)).otherwise(0.0)


def error_bits(cells: float, explained: Column | str, unexplained: Column | str) -> Column:
    """Bits to tell which free cells of one tick hold the unexplained facts."""
    m = F.col(explained) if isinstance(explained, str) else explained
    return log2_choose(F.lit(float(cells)) - m, unexplained)


def header_bits(categories: int, relations: int) -> float:
    """The two upper bounds at the head of a model: constants of the category and relation counts."""
    space = 2 * categories * categories * relations
    return math.log2(space) + log2_choose_exact(space, 3) if space >= 3 else 0.0


def f_beta(tp: Column, fp: Column, fn: Column, beta: float = 0.5) -> Column:
    b = beta * beta
    return F.try_divide((1 + b) * tp, (1 + b) * tp + b * fn + fp)
