"""The inverse of Ackermann's function, and the published bounds as numbers."""

from __future__ import annotations

import math
from functools import lru_cache

from pyspark.sql import Column
from pyspark.sql import functions as F

CAP = 1 << 62


@lru_cache(maxsize=4096)
def ackermann(i: int, j: int) -> int:
    """A(1, j) = 2^j, A(i, 1) = A(i - 1, 2), A(i, j) = A(i - 1, A(i, j - 1)); cut at 2^62."""
    if i == 1:
        return 1 << min(j, 62)
    value = ackermann(i - 1, 2)
    for _ in range(j - 1):
        if value >= 62:
            return CAP
        value = ackermann(i - 1, value)
    return min(value, CAP)


def inv_ackermann(m: int, n: int) -> int:
    """The least i with A(i, m div n) > log2 n; m div n counts as 1 at least."""
    ratio, goal, i = max(1, m // max(n, 1)), math.log2(n) if n > 1 else 0.0, 1
    while ackermann(i, ratio) <= goal:
        i += 1
    return i


def inv_ackermann_column(m: Column, n: Column) -> Column:
    """The same for n up to 2^16 at ratio 1 (2^62 else), as a built-in expression."""
    ratio, goal = F.greatest(F.lit(1), F.floor(m / F.greatest(n, F.lit(1)))), F.when(n > 1, F.log2(n.cast("double"))).otherwise(F.lit(0.0))
    first = F.pow(F.lit(2.0), F.least(ratio, F.lit(62)))
    second = F.when(ratio == 1, F.lit(4.0)).when(ratio == 2, F.lit(16.0)).when(ratio == 3, F.lit(65536.0)).otherwise(F.lit(float(CAP)))
    third = F.when(ratio == 1, F.lit(16.0)).otherwise(F.lit(float(CAP)))
    return F.when(first > goal, 1).when(second > goal, 2).when(third > goal, 3).otherwise(4).cast("int")


#: The rows of the table of bounds, as problem, old bound, new bound.
BOUNDS = (
    ("connected components", "a", "1"),
    ("bipartition", "a", "1"),
    ("2,3-vertex connectivity", "a", "1"),
    ("4-vertex connectivity", "log n", "1"),
    ("k-vertex connectivity", "k^2 n", "1"),
    ("2,3-edge connectivity", "a", "1"),
    ("4-edge connectivity", "n a", "1"),
    ("k-edge connectivity", "n log n", "1"),
    ("minimum spanning forest", "log n", "1"),
)


def bound_value(form: Column, n: Column, k: Column) -> Column:
    """A bound's leading term at n and k, constants left out; a is the inverse at m = n."""
    x = n.cast("double")
    a = inv_ackermann_column(n, n).cast("double")
    log = F.log2(x)
    return F.when(form == "a", a).when(form == "log n", log).when(form == "k^2 n", k * k * x).when(form == "n a", x * a).when(form == "n log n", x * log).otherwise(F.lit(1.0))
