"""Sliding windows for backends that answer many lists at once: the calls of ``generators.slide_window``, one and all, without a request each.

A pass follows the one before it at a distance: its next window waits only for windows that share a place with it. So in each step every
pass under way has one window, all of them apart from one another, and these are one wave of lists. A key travels as a number, its code.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np
from numpy.lib.stride_tricks import as_strided

from semrank.plans.spec import PathConfig

#: Fewer items are not worth arrays.
LEAST = 64


class Lists(Protocol):
    """Answers lists of codes. ``steady``: whether all lists follow one total order."""

    codes: np.ndarray
    steady: bool

    def sort(self, lists: np.ndarray) -> np.ndarray:
        """Each column's codes in order, in place; the tokens that asking for each column takes."""

    def places(self, codes: np.ndarray) -> np.ndarray: ...
    def out_tok(self, calls: int, items: int) -> int: ...


def n_passes(n: int, m: int, want: int, rescan: bool) -> int:
    """Passes over n items that a window of m makes unless the order is stable before."""
    h, p = max(m // 2, 1), 0
    while p * h < want and n - p * h > 1:
        p += 1
        if n - (0 if rescan else (p - 1) * h) <= m:
            break
    return p


def slide_all(path: PathConfig, k: int | None, lists: Lists) -> tuple[np.ndarray, int, int, int]:
    """The places best first, at most ``k``; calls, items shown and tokens in of all calls."""
    order, m, h = lists.codes.copy(), path.m, max(path.m // 2, 1)
    n = len(order)
    want = n if k is None else max(min(k, n), 0)
    passes = n_passes(n, m, want, path.rescan)
    # windows of the first pass but one, and by how many each pass has fewer; the last window of a pass may lie closer to the one before
    full, fewer = max(-(-(n - m) // h), 0), int(not path.rescan)
    odd = n < m or (n - m) % h > 0
    lag = -(-m // h) + odd
    tokens, moved = np.zeros(passes, dtype=np.int64), np.zeros(passes, dtype=bool)
    buffer, step = np.empty((m, max(-(-n // (lag * h)), 1) + 3), dtype=np.int64), order.itemsize
    ended, t = 0, 0
    while ended < passes:
        # passes under way: pass p is at its window t - lag * p
        first, last = max(-(-(t - full + odd) // (lag - fewer)), 0), min(t // lag, passes - 1)
        count = max(last - first + 1, 0)
        ends, rest = divmod(t - full, lag - fewer)
        if rest or not 0 <= ends < passes:
            ends = None
        # a pass whose last window lies closer to the one before has it in a column of its own, or, if it is short, asks it alone
        head = 0 if path.rescan or not odd or ends is None else ends * h
        alone, close = (order[head : min(head + m, n)], 1) if odd and ends is not None else (order[:0], 0)
        if 0 < len(alone) < m:
            shown, close = alone.reshape(-1, 1).copy(), 0
            moved[ends] |= bool((shown[1:] < shown[:-1]).any())
            tokens[ends] += int(lists.sort(shown)[0])
            alone[:] = shown[:, 0]
        if count + close:
            shown = buffer[:, : count + close]
            if count:
                here = as_strided(order[n - m - (t - lag * first) * h :], (m, count), (step, lag * h * step))
                np.copyto(shown[:, :count], here)
            if close:
                shown[:, count] = alone
            if path.stop_when_stable:
                change = (shown[1:] < shown[:-1]).any(axis=0)
                moved[first : last + 1] |= change[:count]
                if close:
                    moved[ends] |= change[count]
            spent = lists.sort(shown)
            if count:
                tokens[first : last + 1] += spent[:count]
                np.copyto(here, shown[:, :count])
            if close:
                tokens[ends] += spent[count]
                alone[:] = shown[:, count]
        if ends is not None:
            ended = ends + 1
            if path.stop_when_stable and not moved[ends]:
                # all is in order: the windows of later passes, begun ahead, have changed nothing and are not counted
                break
        t += 1
    windows = [full + 1 - fewer * p for p in range(ended)]
    calls = sum(windows)
    short = m - (n - (ended - 1) * h * fewer) if ended and full - fewer * (ended - 1) == 0 else 0
    return lists.places(order[:want]), calls, calls * m - max(short, 0), int(tokens[:ended].sum())
