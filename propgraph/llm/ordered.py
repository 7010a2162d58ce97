"""Global order without one task that sees all rows: buckets that are ranges of the id."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LEAST, PER_BUCKET, MOST_BUCKETS = -(1 << 63), 2000, 20000


def range_bucket(df: DataFrame, key: str, rows_per_bucket: int = PER_BUCKET, max_buckets: int = MOST_BUCKETS, cuts: int = 64) -> Column:
    """The bucket of a row: consecutive ranges of a LONG key, in order.

    Approximate quantiles give `cuts` coarse ranges, each split evenly, so that uneven ids stay
    balanced. The driver holds `cuts` numbers; there are at most about max_buckets buckets."""
    n = df.count()
    want = max(1, min(max_buckets, -(-n // rows_per_bucket)))
    q = min(cuts, want)
    marks = [int(x) for x in df.where(F.col(key) != LEAST).approxQuantile(key, [i / q for i in range(q + 1)], 0.2 / q)] if n else []
    lows = sorted({*marks[:-1]})
    if not lows:
        return F.lit(0).cast("long")
    per = -(-want // len(lows))
    highs = [*lows[1:], max(marks[-1] + 1, lows[-1] + 1)]

    def coarse(a: int, b: int) -> Column:
        if a == b:
            width = max(1, -(-(highs[a] - lows[a]) // per))
            # in doubles: monotonous, and no difference of two ids is too large for them
            inside = F.least(F.greatest(F.floor((F.col(key).cast("double") - float(lows[a])) / float(width)), F.lit(0)), F.lit(per - 1))
            return (F.lit(a * per) + inside).cast("long")
        m = (a + b + 1) // 2
        return F.when(F.col(key) < lows[m], coarse(a, m - 1)).otherwise(coarse(m, b))

    return coarse(0, len(lows) - 1)
