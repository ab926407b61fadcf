"""Table functions."""

from __future__ import annotations

from pyspark.sql.functions import udtf


@udtf(returnType="l int, k bigint")
class DyadicCover:
    """The fewest dyadic blocks (level l, number k) that make up [lo, hi) within [0, 2^bits), from left to right."""

    def eval(self, lo: int, hi: int, bits: int):
        at = lo
        while at < hi:
            level = bits if at == 0 else min(bits, (at & -at).bit_length() - 1)
            while at + (1 << level) > hi:
                level -= 1
            yield level, at >> level
            at += 1 << level
