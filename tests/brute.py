"""The access paths again, recursively and in the plainest way; nothing is imported from the package but the simulator."""

import hashlib


def noise(key, a):
    return int(hashlib.md5(key.encode()).hexdigest()[:8], 16) % (2 * a + 1) - a


class Model:
    """lat: id -> latent; a: amplitude."""

    def __init__(self, lat, compare=0, order=0, task="t", seed=7):
        self.lat, self.c, self.o, self.task, self.seed, self.calls = lat, compare, order, task, seed, 0

    def less(self, x, y):
        """x ranks behind y."""
        self.calls += 1
        lo, hi = min(x, y), max(x, y)
        lo_better = self.lat[lo] - self.lat[hi] + noise(f"{self.seed}|c|{self.task}|{lo}|{hi}", self.c) >= 0
        return (x == hi) if lo_better else (x == lo)

    def order(self, ids):
        self.calls += 1
        sign = "-".join(map(str, sorted(ids)))
        return sorted(ids, key=lambda i: (-(self.lat[i] + noise(f"{self.seed}|o|{self.task}|{sign}|{i}", self.o)), i))


def quick(m, ids, v, k=None):
    if k is not None and k <= 0:
        return []
    if len(ids) <= 1:
        return list(ids)
    p, rest = ids[0], ids[1:]
    first = {x: "l" if m.less(x, p) else "g" for x in rest}
    L0, G0 = [x for x in rest if first[x] == "l"], [x for x in rest if first[x] == "g"]
    peers = {}
    for x in rest:
        other = G0 if first[x] == "l" else L0
        free, drawn = list(range(len(other))), []
        for j in range(min(v - 1, len(other))):
            at = int(hashlib.md5(f"7|{p}|{x}|{j}".encode()).hexdigest()[:15], 16) % len(other)
            at = min(free, key=lambda f: (f - at) % len(other))
            free.remove(at)
            drawn.append(other[at])
        peers[x] = [(y, "l" if m.less(x, y) else "g") for y in drawn]
    side = {}
    for x in rest:
        said = [r for _, r in peers[x]]
        if not said:
            side[x] = first[x]
        elif all(r == said[0] for r in said):
            side[x] = said[0]

    def vote(x):
        less, more = (1.5, 0) if first[x] == "l" else (0, 1.5)
        for y, r in peers[x]:
            less += side.get(y) == "l" and r == "l"
            more += side.get(y) == "g" and r == "g"
        return "l" if less > more else "g"

    while len(side) < len(rest):
        moved = False
        for x in rest:  # one at a time
            if x not in side and all(y in side for y, _ in peers[x]):
                side[x] = vote(x)
                moved = True
        if not moved:
            x = next(x for x in rest if x not in side)
            side[x] = vote(x)
    L, G = [x for x in rest if side[x] == "l"], [x for x in rest if side[x] == "g"]
    if k is None:
        return quick(m, G, v) + [p] + quick(m, L, v)
    out = quick(m, G, v, min(k, len(G)))
    if k > len(G):
        out += [p] + quick(m, L, v, k - len(G) - 1)
    return out[:k]


def bubble(m, ids, size, k=None):
    ids, h, done = list(ids), max(size // 2, 1), 0
    want = len(ids) if k is None else min(k, len(ids))
    while done < want and len(ids) - done > 1:
        end = len(ids)
        while end > done:
            start = max(done, end - size)
            ids[start:end] = m.order(ids[start:end])
            if start == done:
                break
            end = max(end - h, min(done + size, len(ids)))
        if len(ids) - done <= size:
            break
        done += h
    return ids[:want]


def merge(m, ids, size, k=None):
    runs = [m.order(ids[i : i + size])[:k] for i in range(0, len(ids), size)] if len(ids) > 1 else [list(ids)]
    while len(runs) > 1:
        new = []
        for i in range(0, len(runs), 2):
            if i + 1 == len(runs):
                new.append(runs[i])
                continue
            a, b, out = list(runs[i]), list(runs[i + 1]), []
            h = max(size // 2, 1)
            while a and b and (k is None or len(out) < k):
                x, y = a[:h], b[:h]
                for item in m.order(x + y):
                    out.append(item)
                    (a if item in a else b).remove(item)
                    if not set(x) & set(a) or not set(y) & set(b):
                        break
            new.append((out + a + b)[:k] if not (a and b) else out[:k])
        runs = new
    return runs[0][:k]
