"""Box queries through ranges of a curve index."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def decompose_box(lo: list[int], hi: list[int], bits: int, max_ranges: int = 64) -> list[tuple[int, int]]:
    """Index ranges that cover a grid box (bounds inclusive), at most ``max_ranges``.

    The box is cut along the curve's own halving; once there would be too many pieces, the remaining cells are
    taken whole, so the cover stays a superset.
    """
    n = len(lo)
    ranges: list[tuple[int, int]] = []
    queue = [(0, n * bits, [0] * n, [(1 << bits) - 1] * n)]
    while queue:
        queue.sort(key=lambda c: -c[1])
        code, left, a, b = queue.pop(0)
        if any(y < l or x > h for x, y, l, h in zip(a, b, lo, hi)):
            continue
        inside = all(x >= l and y <= h for x, y, l, h in zip(a, b, lo, hi))
        if inside or left == 0 or len(queue) + len(ranges) + 2 > max_ranges:
            ranges.append((code, code + (1 << left) - 1))
            continue
        d = (n * bits - left) % n
        mid = (a[d] + b[d]) // 2
        queue.append((code, left - 1, a, [mid if i == d else v for i, v in enumerate(b)]))
        queue.append((code + (1 << (left - 1)), left - 1, [mid + 1 if i == d else v for i, v in enumerate(a)], b))
    merged: list[list[int]] = []
    for x, y in sorted(ranges):
        if merged and x <= merged[-1][1] + 1:
            merged[-1][1] = max(merged[-1][1], y)
        else:
            merged.append([x, y])
    return [(x, y) for x, y in merged]


def box_filter(df: DataFrame, cols: list[str], lo: list[int], hi: list[int]) -> DataFrame:
    """Plain filter on the grid coordinates."""
    return df.where(reduce(lambda a, b: a & b, (F.col(c).between(l, h) for c, l, h in zip(cols, lo, hi))))


def index_box_filter(df: DataFrame, index: str, cols: list[str], lo: list[int], hi: list[int], bits: int, max_ranges: int = 64) -> DataFrame:
    """The same rows through index ranges, which reach the scan as pushed filters, and the plain filter behind them."""
    ranges = decompose_box(lo, hi, bits, max_ranges)
    return box_filter(df.where(reduce(lambda a, b: a | b, (F.col(index).between(x, y) for x, y in ranges))), cols, lo, hi)
