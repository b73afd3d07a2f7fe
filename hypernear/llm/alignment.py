"""Banded alignment of word sequences with bit-parallel rows."""

from __future__ import annotations

from collections import Counter


def banded_distance(a: list, b: list, limit: int) -> int | None:
    """Least number of insertions, deletions and substitutions that turn a into b, or None above limit.

    Common ends are cut off. Length and bag differences, which bound the distance from below, rule most pairs out. Then a
    narrow band is tried before the whole one.
    """
    if abs(len(a) - len(b)) > limit:
        return None
    start, shorter = 0, min(len(a), len(b))
    while start < shorter and a[start] == b[start]:
        start += 1
    end = 0
    while end < shorter - start and a[-1 - end] == b[-1 - end]:
        end += 1
    a, b = a[start : len(a) - end], b[start : len(b) - end]
    if len(a) > len(b):
        a, b = b, a
    if not a:
        return len(b) if len(b) <= limit else None
    bag = Counter(b)
    bag.subtract(a)
    if max(sum(c for c in bag.values() if c > 0), -sum(c for c in bag.values() if c < 0)) > limit:
        return None
    for width in sorted({min(16, limit), min(128, limit), limit}):
        if len(b) - len(a) <= width:
            found = in_band(a, b, width) if width < len(a) else whole(a, b)
            if found is not None and found <= width:
                return found
    return None


def places(a: list, shift: int = 0) -> dict:
    at: dict = {}
    for i, x in enumerate(a):
        at[x] = at.get(x, 0) | 1 << (i + shift)
    return at


def whole(a: list, b: list) -> int:
    """Distance without a band: one bit a row of the table of vertical differences."""
    at, full, top = places(a), (1 << len(a)) - 1, 1 << (len(a) - 1)
    up, down, score = full, 0, len(a)
    for x in b:
        same = at.get(x, 0)
        across = (((same & up) + up) ^ up) | same
        more, less = down | (full & ~(across | up)), up & across
        score += bool(more & top) - bool(less & top)
        more, less, vertical = more << 1 | 1, less << 1, same | down
        up, down = full & (less | ~(vertical | more)), more & vertical & full
    return score


def in_band(a: list, b: list, width: int) -> int | None:
    """Distance if it is at most width, which is under len(a); the window of rows slides down the diagonal.

    The score follows the window's last row until that is the last of a, then that row to the end of b.
    """
    size = 2 * width + 1
    full, last = (1 << size) - 1, 1 << (size - 1)
    at = places(a, width)
    up, down, score = full & ~((1 << width) - 1), 0, width
    turn, row = len(a) - width, last >> 1
    for j, x in enumerate(b):
        same = at.get(x, 0) >> j & full
        diagonal = (((same & up) + up) ^ up) & full | same | down
        more, less = down | (full & ~(diagonal | up)), diagonal & up
        if j < turn:
            score += not diagonal & last
            if score > 2 * width + len(b) - len(a) + width:
                return None
        else:
            score += bool(more & row) - bool(less & row)
            row >>= 1
        slid = diagonal >> 1
        up, down = full & (less | ~(slid | more)), slid & more
    return score if score <= width else None
