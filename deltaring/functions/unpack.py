"""A table function that spreads a packed block of moments over rows."""

from __future__ import annotations

from pyspark.sql.functions import udtf


@udtf(returnType="i int, j int, v double")
class UnpackEntries:
    """Entries of an upper triangle stored row by row, with their indices."""

    def eval(self, block: list, m: int):
        at = 0
        for i in range(m):
            for j in range(i, m):
                yield i, j, float(block[at])
                at += 1
