"""Column functions: set similarity, canonical sets, reproducible draws; all of them built-in expressions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: Draws are whole numbers below this prime; three quadratic rounds mix them, and every engine does them exactly.
PRIME = 2147483647


def canonical(a: Column) -> Column:
    """Sorted distinct members; null counts as the empty set."""
    return F.array_sort(F.array_distinct(F.coalesce(a, F.array().cast("array<string>"))))


def jaccard(a: Column, b: Column) -> Column:
    """Shared over all members of two sets; 0 if both are empty."""
    both = F.size(F.array_union(a, b))
    return F.when(both > 0, F.size(F.array_intersect(a, b)) / both).otherwise(F.lit(0.0))


def draw(*keys, salt: int = 42) -> Column:
    """A whole number in 0..PRIME-1 that depends on the keys and the salt only."""
    x = F.lit(salt % PRIME).cast("long")
    for k in keys:
        k = F.lit(k) if isinstance(k, int) else (F.col(k) if isinstance(k, str) else k)
        x = F.pmod(x * F.lit(48271) + F.pmod(k.cast("long"), F.lit(PRIME)), F.lit(PRIME))
        # A fold evaluates each round once; spelled out, every round would repeat the one before three times.
        x = F.aggregate(F.array(*[F.lit(c).cast("long") for c in (12345, 67891, 424243)]), x, lambda a, c: F.pmod(a * a + a * F.lit(65537) + c, F.lit(PRIME)))
    return x


def draw_sql(*keys: str, salt: int = 42) -> str:
    """The same as SQL text for an engine with 64-bit whole numbers."""
    x = f"{salt % PRIME}::BIGINT"
    for k in keys:
        x = f"mixed3(({x} * 48271 + ({k})::BIGINT % {PRIME}) % {PRIME})"
    # mixed3 is spelled out as a list reduction, so that each round is evaluated once.
    while "mixed3(" in x:
        at = x.rindex("mixed3(")
        depth, end = 0, at + 6
        for end in range(at + 6, len(x)):
            depth += {"(": 1, ")": -1}.get(x[end], 0)
            if not depth:
                break
        inner = x[at + 7 : end]
        x = x[:at] + f"list_reduce([{inner}, 12345, 67891, 424243], lambda a, c: (a * a + a * 65537 + c) % {PRIME})" + x[end + 1 :]
    return x


def register_sql(spark: SparkSession) -> None:
    """jaccard_sets(a, b) for SQL users."""
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION jaccard_sets(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN "
        "CASE WHEN size(array_union(a, b)) = 0 THEN 0D ELSE CAST(size(array_intersect(a, b)) AS DOUBLE) / size(array_union(a, b)) END"
    )
