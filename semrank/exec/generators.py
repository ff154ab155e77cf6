"""The access paths as generators over one task: each ``yield`` is a wave of calls that may run at once.

A request is (op, keys...) and is answered in place; every generator returns the ids best first, at most
``k`` of them. The same generators run packed (a task in one worker) and inside wave jobs (a merge of two runs).
"""

from __future__ import annotations

import hashlib
import random
from collections.abc import Generator, Sequence
from functools import cached_property

import numpy as np

from semrank.plans.spec import PathConfig
from semrank.sources.model import Key

Wave = list[tuple]
Steps = Generator[Wave, list, list[int]]


class Columns:
    """A task's keys, and their numbers as arrays for backends that answer a wave at once."""

    def __init__(self, keys: Sequence[Key]):
        self.keys = keys

    @classmethod
    def of(cls, ids: np.ndarray, latent: np.ndarray, chars: np.ndarray) -> Columns:
        """Numbers alone."""
        out = cls(())
        out.numbers = (ids, latent, chars)
        return out

    @cached_property
    def numbers(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, latent values and lengths."""
        return tuple(np.array([getattr(x, c) for x in self.keys], dtype=np.int64) for c in ("item_id", "latent", "chars"))


class Pairs(Sequence):
    """A wave of comparisons, of the keys at places ``a`` with those at ``b``: requests one by one, or arrays for who answers them at once."""

    def __init__(self, shown: Columns, a: np.ndarray, b: np.ndarray):
        self.shown, self.a, self.b = shown, a, b

    def __len__(self) -> int:
        return len(self.a)

    def __getitem__(self, i: int) -> tuple:
        return "compare", self.shown.keys[self.a[i]], self.shown.keys[self.b[i]]

    def __iter__(self):
        keys = self.shown.keys
        return (("compare", keys[x], keys[y]) for x, y in zip(self.a.tolist(), self.b.tolist(), strict=True))


def _seeded(*parts) -> random.Random:
    return random.Random(int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:15], 16))


def score_each(keys: Sequence[Key], path: PathConfig, k: int | None) -> Steps:
    scores = yield [("score", key) for key in keys]
    # an unknown score sorts last; equal ones go by id
    order = sorted(range(len(keys)), key=lambda i: (scores[i] is None, -(scores[i] or 0), keys[i].item_id))
    return [keys[i].item_id for i in order][:k]


def score_batch(keys: Sequence[Key], path: PathConfig, k: int | None) -> Steps:
    batches = [keys[i : i + path.m] for i in range(0, len(keys), path.m)]
    replies = yield [("score_many", n, *b) for n, b in enumerate(batches)]
    scored = [(s is None, -(s or 0), key.item_id) for b, r in zip(batches, replies, strict=True) for key, s in zip(b, r, strict=True)]
    return [i for _, _, i in sorted(scored)][:k]


def vote(first: int, peers: Sequence[tuple[int, int]], side: dict[int, int]) -> int:
    """1.5 votes for the pivot's verdict; one for each settled peer whose own side bears its verdict out."""
    less = 1.5 if first < 0 else 0.0
    more = 1.5 if first > 0 else 0.0
    for peer, verdict in peers:
        settled = side.get(peer, 0)
        less += settled < 0 and verdict < 0
        more += settled > 0 and verdict > 0
    return -1 if less > more else 1


def peer_slots(seed: int, pivot: int, x: int, n: int, count: int) -> list[int]:
    """Which of n items of the other side, by input order, are drawn as peers of x: hashed places, the next free one if taken."""
    out: list[int] = []
    for j in range(min(count, n)):
        slot = int(hashlib.md5(f"{seed}|{pivot}|{x}|{j}".encode()).hexdigest()[:15], 16) % n
        while slot in out:
            slot = (slot + 1) % n
        out.append(slot)
    return out


def settle(members: Sequence[int], first: dict[int, int], peers: dict[int, list[tuple[int, int]]], peer_override: bool = True, known: dict[int, int] | None = None) -> dict[int, int]:
    """Side (-1 less, 1 greater) of each member, in input order; ``known`` are sides settled before.

    Unanimous peers decide at once. Others wait for their peers and then vote; all that are ready vote in the same
    round, which gives what one at a time would, as a ready vote depends on settled sides alone. If nobody is ready, the first in
    input order votes with what is known.
    """
    side: dict[int, int] = dict(known or {})
    for x in members if known is None else ():
        got = {r for _, r in peers[x]}
        if not got:
            side[x] = first[x]
        elif len(got) == 1 and (peer_override or got == {first[x]}):
            side[x] = got.pop()
    waiting = [x for x in members if x not in side]
    while waiting:
        ready = [x for x in waiting if all(p in side for p, _ in peers[x])] or waiting[:1]
        side |= {x: vote(first[x], peers[x], side) for x in ready}
        waiting = [x for x in waiting if x not in side]
    return side


def pivot_split(keys: Sequence[Key], path: PathConfig, k: int | None, seed: int = 7) -> Steps:
    """Quick sort, with v - 1 peers of the other provisional side to check each verdict. All segments of a level share its waves.

    Items are places in ``keys``, a level is one array of them, segment by segment in input order: equal items in id order make as many levels as items.
    """
    shown, ids, n = Columns(keys), [x.item_id for x in keys], len(keys)
    want = n if k is None else min(k, n)
    if want <= 0:
        return []
    out = np.zeros(n, dtype=np.int64)
    # of each segment: its size, the rank of its best, how many of its best are wanted
    items, size, at, need = np.arange(n), np.array([n]), np.array([0]), np.array([want])
    while len(size):
        alone = size == 1
        if alone.any():
            out[at[alone]] = items[(np.cumsum(size) - size)[alone]]
            items = items[np.repeat(~alone, size)]
            size, at, need = size[~alone], at[~alone], need[~alone]
            if not len(size):
                break
        if len(size) == 1 and path.pivot == "first":
            # one segment, and perhaps all of it on one side of its pivot: the plain way for long chains of levels
            side = np.asarray((yield Pairs(shown, items[1:], np.broadcast_to(items[:1], len(items) - 1))))
            greater = int(np.count_nonzero(side > 0))
            if greater in (0, len(side)):
                if need[0] > greater:
                    out[at[0] + greater] = items[0]
                if not greater:
                    at, need = at + 1, need - 1
                items, size = items[1:], size - 1
                need = np.minimum(need, size)
                if not need[0]:
                    break
                continue
        else:
            side = None
        begin = np.cumsum(size) - size
        pivot = items[begin]
        if path.pivot == "random":
            pivot = np.array([_seeded(seed, *[ids[x] for x in own[:8]], len(own)).choice(own) for own in (items[b : b + c].tolist() for b, c in zip(begin, size, strict=True))])
        elif path.pivot == "median3" and (three := np.flatnonzero(size > 2)).size:
            x = np.stack([items[begin[three]], items[begin[three] + size[three] // 2], items[begin[three] + size[three] - 1]])
            got = np.asarray((yield Pairs(shown, x[[0, 0, 1]].T.ravel(), x[[1, 2, 2]].T.ravel()))).reshape(-1, 3).T > 0
            wins = np.stack([got[0].astype(int) + got[1], (~got[0]).astype(int) + got[2], (~got[1]).astype(int) + ~got[2]])
            pivot[three] = x[np.argmax(wins == 1, axis=0), np.arange(len(three))]
        seg = np.repeat(np.arange(len(size)), size)
        rest = items != pivot[seg]
        items, seg = items[rest], seg[rest]
        if side is None:
            side = np.asarray((yield Pairs(shown, items, pivot[seg])))
        greater = np.bincount(seg[side > 0], minlength=len(size))
        # an item has peers where both sides have any
        both = np.flatnonzero((greater > 0) & (greater < size - 1)) if path.v > 1 else ()
        if len(both):
            end, first, asked = np.cumsum(size - 1), {}, []
            for s in both:
                verdict = first[s] = dict(zip(items[end[s] - size[s] + 1 : end[s]].tolist(), side[end[s] - size[s] + 1 : end[s]].tolist(), strict=True))
                sides = {r: [x for x, y in verdict.items() if y == r] for r in (-1, 1)}
                for x, r in verdict.items():
                    other = sides[-r]
                    asked += [(s, x, other[i]) for i in peer_slots(seed, ids[pivot[s]], ids[x], len(other), path.v - 1)]
            got = yield Pairs(shown, np.array([x for _, x, _ in asked]), np.array([y for _, _, y in asked]))
            peers: dict[int, dict[int, list[tuple[int, int]]]] = {s: {x: [] for x in first[s]} for s in both}
            for (s, x, y), r in zip(asked, got, strict=True):
                peers[s][x].append((y, int(r)))
            side = side.copy()
            for s in both:
                settled = settle(list(first[s]), first[s], peers[s], path.peer_override)
                side[end[s] - size[s] + 1 : end[s]] = [settled[x] for x in first[s]]
            greater = np.bincount(seg[side > 0], minlength=len(size))
        less, placed = size - 1 - greater, need > greater
        out[(at + greater)[placed]] = pivot[placed]
        down = (less > 0) & (need > greater + 1)
        keep = (side > 0) | down[seg]
        items, part = items[keep], 2 * seg[keep] + (side[keep] < 0)
        items = items[np.argsort(part, kind="stable")]
        pairs = lambda up, low: np.stack([up, low], axis=1).ravel()[pairs_kept]
        pairs_kept = np.stack([greater > 0, down], axis=1).ravel()
        size, at, need = pairs(greater, less), pairs(at, at + greater + 1), pairs(np.minimum(need, greater), need - greater - 1)
    return [ids[x] for x in out[:want].tolist()]


def slide_window(keys: Sequence[Key], path: PathConfig, k: int | None) -> Steps:
    """Windows of m from the tail to the head in steps of m/2; the best half rides along, each pass fixes m/2 places."""
    by_id = {x.item_id: x for x in keys}
    order, h = list(keys), max(path.m // 2, 1)
    want, done = len(order) if k is None else min(k, len(order)), 0
    while done < want and len(order) - done > 1:
        head, before = (0 if path.rescan else done), list(order) if path.stop_when_stable else None
        end = len(order)
        while True:
            start = max(head, end - path.m)
            (got,) = yield [("order", *order[start:end])]
            order[start:end] = [by_id[i] for i in got]
            if start == head:
                break
            end = max(end - h, head + min(path.m, len(order) - head))
        if len(order) - head <= path.m:
            break
        done += h
        if path.stop_when_stable and order == before:
            break
    return [x.item_id for x in order[:want]]


def merge_two(a: Sequence[int], b: Sequence[int], m: int, k: int | None) -> Generator[list[int], list[int], list[int]]:
    """Merge two runs of ids, best first: yields buffers, is sent their order, returns the merged run (at most k).

    A buffer holds up to m/2 unread ids of each run; its order is emitted until one run's share is used up. A reply may
    contradict a run's own order: ids that were passed over then stay at the head of their run, so none is lost or doubled.
    """
    h, out = max(m // 2, 1), []
    # read positions, and ids that were shown but not emitted
    at, held, runs = [0, 0], [[], []], (a, b)
    want = len(a) + len(b) if k is None else min(k, len(a) + len(b))
    while True:
        for s in (0, 1):
            more = runs[s][at[s] : at[s] + h - len(held[s])]
            held[s], at[s] = [*held[s], *more], at[s] + len(more)
        if len(out) >= want or not held[0] or not held[1]:
            return [*out, *held[0], *a[at[0] :], *held[1], *b[at[1] :]][:want]
        left = {**dict.fromkeys(held[0], 0), **dict.fromkeys(held[1], 1)}
        for x in (yield [*held[0], *held[1]]):
            out.append(x)
            s = left.pop(x)
            if s not in left.values():
                break
        held = [[x for x in held[s] if x in left] for s in (0, 1)]


def merge_round(runs: list[list[int]], by_id: dict[int, Key], m: int, k: int | None) -> Generator[Wave, list, list[list[int]]]:
    """Neighbouring runs merged pair by pair, all pairs in step."""
    pairs = [merge_two(runs[i], runs[i + 1], m, k) for i in range(0, len(runs) - 1, 2)]
    done: dict[int, list[int]] = {}
    asked: dict[int, list[int]] = {}
    for n, g in enumerate(pairs):
        try:
            asked[n] = next(g)
        except StopIteration as end:
            done[n] = end.value
    while asked:
        live = sorted(asked)
        got = yield [("order", *[by_id[x] for x in asked[n]]) for n in live]
        for n, r in zip(live, got, strict=True):
            try:
                asked[n] = pairs[n].send(r)
            except StopIteration as end:
                done[n] = end.value
                del asked[n]
    return [done[n] for n in range(len(pairs))] + ([runs[-1]] if len(runs) % 2 else [])


def run_merge(keys: Sequence[Key], path: PathConfig, k: int | None) -> Steps:
    """Runs of m, each ordered by one call, then rounds of pairwise merges through a buffer of m."""
    by_id = {x.item_id: x for x in keys}
    runs = [keys[i : i + path.m] for i in range(0, len(keys), path.m)]
    if not runs or k == 0:
        return []
    if len(keys) == 1:
        return [keys[0].item_id]
    runs = yield [("order", *r) for r in runs]
    runs = [list(r)[:k] for r in runs]
    while len(runs) > 1:
        runs = yield from merge_round(runs, by_id, path.m, k)
    return runs[0][:k]


PATHS = {"score_each": score_each, "score_batch": score_batch, "pivot_split": pivot_split, "slide_window": slide_window, "run_merge": run_merge}
