"""A bounded sample of rows by a threshold on their hash, found without sorting or collecting rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

HASH_BITS, STEP_BITS, STEPS = 60, 12, 3


def least_hashed(rows: DataFrame, key: Column, bound: int) -> DataFrame:
    """At most `bound` rows, those of the least hash of key; all rows if there are no more.

    Counts by the leading 12 bits show the bucket in which the bound is passed, which alone is
    counted again by the next bits: the driver sees 4096 counts a step. Rows of one key are taken
    together or not at all, so the sample falls short of the bound by less than a last bucket.
    """
    hashed = F.shiftrightunsigned(F.xxhash64(key), 64 - HASH_BITS)
    taken, prefix, shift = 0, None, HASH_BITS
    for _ in range(STEPS):
        inside = rows if prefix is None else rows.where(F.shiftright(hashed, shift) == prefix)
        shift -= STEP_BITS
        counts = inside.groupBy(F.shiftright(hashed, shift).alias("bucket")).count().collect()  # at most 2^12 rows
        for bucket, n in sorted(map(tuple, counts)):
            if taken + n > bound:
                prefix = bucket
                break
            taken += n
        else:
            return rows if prefix is None else rows.where(F.shiftright(hashed, shift + STEP_BITS) <= prefix)
    return rows.where(hashed < prefix << shift)
