"""External merges for backends that answer many lists at once: the calls of ``generators.run_merge``, one and all, without a request each.

Such a backend's lists follow one total order (see ``ModelBackend``), so what is shown of a run is always its next unread items. Items are places in
arrays; the merges of a round keep in step, a wave of lists for all of them, and where few are left each goes its own way.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np

#: So many merges in step are worth arrays.
WIDE = 128


class Orders(Protocol):
    """Answers lists of places and keeps count of ``calls``, ``in_tok`` and ``out_tok``."""

    def one(self, places: list[int]) -> list[int]: ...
    def many(self, places: np.ndarray) -> np.ndarray:
        """The order of each row's slots; -1 is an empty slot, which comes last."""


def merge_all(n: int, m: int, k: int | None, orders: Orders) -> np.ndarray:
    """The places 0 to n - 1 best first, at most ``k``: runs of m, then rounds of merges of neighbours."""
    cut = n if k is None else k
    if n < 1 or cut < 1:
        return np.zeros(0, dtype=np.int64)
    grid = np.full(-(-n // m) * m, -1, dtype=np.int64)
    grid[:n] = np.arange(n)
    grid = grid.reshape(-1, m)
    grid = np.take_along_axis(grid, orders.many(grid), 1)[:, :cut]
    size, items = np.count_nonzero(grid >= 0, axis=1), grid[grid >= 0]
    while len(size) > 1:
        items, size = _round(items, size, max(m // 2, 1), cut, orders)
    return items


def _round(items: np.ndarray, size: np.ndarray, h: int, cut: int, orders: Orders) -> tuple[np.ndarray, np.ndarray]:
    """Neighbouring runs merged pair by pair; a last one without a neighbour stays."""
    begin, two = np.cumsum(size) - size, len(size) // 2 * 2
    b, n = begin[:two].reshape(-1, 2), size[:two].reshape(-1, 2)
    want = np.minimum(n.sum(axis=1), cut)
    if len(b) >= WIDE:
        merged = _in_step(items, b, n, want, h, orders)
    else:
        merged = np.concatenate([merge_pair(items[x : x + c].tolist(), items[y : y + d].tolist(), int(w), h, orders) for (x, y), (c, d), w in zip(b.tolist(), n.tolist(), want, strict=True)])
    alone = items[begin[two] :] if two < len(size) else items[:0]
    return np.concatenate([merged, alone]), np.concatenate([want, size[two:]])


def merge_pair(a: list[int], b: list[int], want: int, h: int, orders: Orders) -> list[int]:
    """One merge: up to h unread places of each run are shown, and emitted in the order of the reply until one run's share is used up."""
    out, i, j, one = [], 0, 0, orders.one
    while len(out) < want and i < len(a) and j < len(b):
        x, y = a[i : i + h], b[j : j + h]
        got = one(x + y)
        p, q = got.index(x[-1]) + 1, got.index(y[-1]) + 1
        if p < q:
            out += got[:p]
            i, j = i + len(x), j + p - len(x)
        else:
            out += got[:q]
            i, j = i + q - len(y), j + len(y)
    return [*out, *a[i:], *b[j:]][:want]


def _in_step(items: np.ndarray, begin: np.ndarray, n: np.ndarray, want: np.ndarray, h: int, orders: Orders) -> np.ndarray:
    out = np.empty(int(want.sum()), dtype=np.int64)
    first, slots = np.cumsum(want) - want, np.arange(h)
    at, made = np.zeros_like(n), np.zeros_like(want)
    while True:
        done = (made >= want) | (at >= n).any(axis=1)
        if done.any():
            # of what is left one run at most has a share
            rest = np.minimum((n - at)[done].sum(axis=1), np.maximum((want - made)[done], 0))
            s = np.argmax((n - at)[done], axis=1)
            r = np.arange(len(s))
            step = np.arange(rest.sum()) - np.repeat(np.cumsum(rest) - rest, rest)
            out[np.repeat((first + made)[done], rest) + step] = items[np.repeat((begin + at)[done][r, s], rest) + step]
            live = ~done
            begin, n, want, first, at, made = (x[live] for x in (begin, n, want, first, at, made))
        if not len(want):
            return out
        left = n - at
        place = np.minimum((begin + at)[:, :, None] + slots, len(items) - 1)
        shown = np.where(slots < left[:, :, None], items[place], -1).reshape(len(want), 2 * h)
        order = orders.many(shown)
        rank = np.empty_like(order)
        np.put_along_axis(rank, order, np.broadcast_to(np.arange(2 * h), order.shape), 1)
        # the last of a run's share is emitted last of it
        last = np.minimum(left, h) - 1 + np.array([0, h])
        used = np.take_along_axis(rank, last, 1).min(axis=1) + 1
        got = np.take_along_axis(shown, order, 1)
        for c in range(2 * h):
            here = (c < used) & (made + c < want)
            out[(first + made + c)[here]] = got[here, c]
        of_a = np.count_nonzero((rank[:, :h] < used[:, None]) & (shown[:, :h] >= 0), axis=1)
        at = at + np.stack([of_a, used - of_a], axis=1)
        made = made + used
