"""Model access: one protocol of six operations, a seeded simulator, an adapter for hosted models.

A backend is bound to a criterion and a direction by ``about``; its ``identity`` names everything beside the keys that
decides a reply. The simulator stands in for a hosted model; its answers say nothing about real ones. All of
it is integer arithmetic on MD5, so that SQL can repeat it:

* an item has a latent value 0..10000 (10000 is best); for an ascending order it is 10000 less that;
* noise(x, a) is the first 8 hex digits of md5(x), modulo 2a+1, less a; x holds the criterion if there is one;
* a score is latent + noise, clipped to 0..10000 and cut into 0..max_point buckets (coarse buckets make ties);
* a comparison is the sign of the difference of latents + the pair's noise: symmetric, not always transitive;
* a list is sorted by latent + noise of (batch, item);
* the judge is shown the sample and the candidates' rankings of it, orders the sample by latent + noise, and picks the candidate closest
  to that (Kendall tau; equal ones by a seeded numbering);
* an inquiry is shown the first keys of a sample and returns the task's kind, flipped when md5(seed|task) mod 1000 is below the tier's error.
"""

from __future__ import annotations

import hashlib
import json
import threading
import time
import urllib.error
import urllib.request
from collections.abc import Callable, Mapping, Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace
from functools import cached_property
from typing import TYPE_CHECKING, NamedTuple, Protocol

import numpy as np

from semrank.sources.noise import ListNoise

if TYPE_CHECKING:
    from semrank.exec.generators import Pairs

TOP = 10000
#: Characters of an instruction, tokens of a reply, tokens per returned item, by operation.
TEMPLATE = {"score": 160, "score_many": 200, "compare": 150, "order": 190, "inquiry": 400, "judge": 500}
REPLY = {"score": 6, "score_many": 6, "compare": 6, "order": 6, "inquiry": 5, "judge": 8}
PER_ITEM = {"score_many": 3, "order": 3}
REASONING = 120


@dataclass(frozen=True)
class Profile:
    """Noise amplitudes by operation, an inquiry error per mille, seconds per call (a + b * output tokens)."""

    name: str
    score: int
    score_many: int
    compare: int
    order: int
    inquiry: int = 100
    judge: int = 1500
    base_ms: int = 800
    ms_per_token: int = 20


#: One published configuration; never tuned to flatter a policy.
PROFILES = {
    "clean": Profile("clean", 0, 0, 0, 0, 0, 0),
    "factual": Profile("factual", 300, 600, 2500, 2000),
    "reasoning": Profile("reasoning", 3500, 4000, 1500, 1200),
}
#: Tiers scale a profile's noise, in percent.
TIERS = {"small": 130, "medium": 100, "large": 70}
#: Micro-dollars per 1,000 tokens in and out, and per lookup.
PRICES = {"small": (720, 720, 5000), "medium": (250, 2000, 5000), "large": (1000, 5000, 5000)}


class Usage(NamedTuple):
    in_tok: int
    out_tok: int
    lookups: int = 0


def noise(key: str, amplitude: int) -> int:
    # whatever the digits are, there is one number within 0
    return int.from_bytes(hashlib.md5(key.encode()).digest()[:4], "big") % (2 * amplitude + 1) - amplitude if amplitude else 0


def count_tokens(chars: int) -> int:
    return -(-chars // 4)


def nano_usd(in_tok: int, out_tok: int, lookups: int, tier: str) -> int:
    """Micro-dollars per 1,000 tokens are nano-dollars per token; money stays whole."""
    a, b, fee = PRICES[tier]
    return in_tok * a + out_tok * b + lookups * fee * 1000


@dataclass(frozen=True, slots=True)
class Key:
    """What is shown to the model (the key) and what only the simulator knows."""

    item_id: int
    chars: int
    latent: int = 0
    fact: int | None = None
    text: str = ""


class ModelBackend(Protocol):
    """Operations a path or the optimizer may ask for. Replies may be malformed: ``repair_order`` and ``repair_scores`` deal with that.

    ``reads_text``: whether keys must carry their text, which then travels with them. ``threads``: calls that one worker keeps in flight.
    A backend may have ``compare_many(task, pairs)`` too, which answers a wave of comparisons as ``compare`` would, with the tokens of all of them. It may
    have ``orders(task, ids, latent, chars)``: what answers lists of places as ``order`` would, one or many at once (``semrank.exec.merges.Orders``), if all lists
    follow one total order, and None if they do not. It may have ``lists(task, ids, latent, chars, m)``: what answers lists of up to m codes, many at once
    (``semrank.exec.slides.Lists``), or None.
    """

    tier: str
    reads_text: bool
    threads: int

    def about(self, criterion: str, descending: bool = True) -> ModelBackend: ...
    def identity(self) -> str: ...
    def score(self, task: str, key: Key, max_point: int, lookup: bool = False) -> tuple[int, Usage]: ...
    def score_many(self, task: str, batch: int, keys: Sequence[Key], max_point: int, lookup: bool = False) -> tuple[list[int], Usage]: ...
    def compare(self, task: str, a: Key, b: Key) -> tuple[int, Usage]: ...
    def order(self, task: str, keys: Sequence[Key]) -> tuple[list[int], Usage]: ...
    def inquire(self, task: str, keys: Sequence[Key], kind: str) -> tuple[str, Usage]: ...
    def judge(self, task: str, keys: Sequence[Key], rankings: Mapping[str, Sequence[int]]) -> tuple[str, Usage]: ...


def numbered(seed: int, task: str, path_ids: Sequence[str]) -> list[str]:
    """Candidates in the seeded order in which a judge is shown them, so that no path is always first."""
    return sorted(path_ids, key=lambda p: (int(hashlib.md5(f"{seed}|{task}|{p}".encode()).hexdigest()[:8], 16), p))


def concordance(ranking: Sequence[int], value: Mapping[int, int]) -> float:
    """Kendall tau of a ranking of ids with their values (higher is better); 0 for fewer than two."""
    ids = [i for i in ranking if i in value]
    pairs = [(value[a] > value[b]) - (value[a] < value[b]) for n, a in enumerate(ids) for b in ids[n + 1 :]]
    return sum(pairs) / len(pairs) if pairs else 0.0


class SimOrders:
    """Lists of a simulator without noise, by latent value and id, and what they cost."""

    def __init__(self, ids: np.ndarray, behind: np.ndarray, chars: np.ndarray, asked: int, reply: int):
        self.ids, self.behind, self.chars, self.asked, self.reply = ids, behind, chars, asked + 3, reply
        self.calls, self.items, self.in_tok = 0, 0, 0

    @cached_property
    def _lists(self) -> tuple[Callable[[int], int], list[int]]:
        # numbers that compare as (behind, id)
        return [(x << 64) + i for x, i in zip(self.behind.tolist(), self.ids.tolist(), strict=True)].__getitem__, self.chars.tolist()

    def one(self, places: list[int]) -> list[int]:
        standing, chars = self._lists
        n = self.asked
        for x in places:
            n += chars[x]
        self.calls += 1
        self.items += len(places)
        self.in_tok += n >> 2
        return sorted(places, key=standing)

    def many(self, places: np.ndarray) -> np.ndarray:
        full = places >= 0
        self.calls += len(places)
        self.items += int(np.count_nonzero(full))
        self.in_tok += int(((np.where(full, self.chars[places], 0).sum(axis=1) + self.asked) >> 2).sum())
        return np.lexsort((self.ids[places], self.behind[places], ~full), axis=-1)

    @property
    def out_tok(self) -> int:
        return self.calls * self.reply + self.items * PER_ITEM["order"]


class SimLists:
    """Lists of a simulator without noise: a code holds a key's standing and, below it, its length."""

    steady = True

    def __init__(self, ids: np.ndarray, behind: np.ndarray, chars: np.ndarray, asked: int, reply: int, m: int):
        self.reply = reply
        self.bits, self.asked = int(chars.max(initial=0) * m).bit_length(), asked + 3
        self.best = np.lexsort((ids, behind))
        self.codes = np.empty(len(ids), dtype=np.int64)
        self.codes[self.best] = np.arange(len(ids)) << self.bits
        self.codes += chars

    def sort(self, lists: np.ndarray) -> np.ndarray:
        # the sum of the lengths has room below the standings
        tokens = lists.sum(axis=0)
        tokens &= (1 << self.bits) - 1
        tokens += self.asked
        tokens >>= 2
        sort_columns(lists)
        return tokens

    def places(self, codes: np.ndarray) -> np.ndarray:
        return self.best[codes >> self.bits]

    def out_tok(self, calls: int, items: int) -> int:
        return calls * self.reply + items * PER_ITEM["order"]


class NoisyLists:
    """Lists of a simulator with noise, which depends on the list: a code is a key's rank by id."""

    steady = False

    def __init__(self, ids: np.ndarray, behind: np.ndarray, chars: np.ndarray, asked: int, reply: int, noises: ListNoise, by_id: np.ndarray):
        self.by_id, self.behind, self.chars, self.asked, self.reply, self.noises = by_id, behind[by_id], chars[by_id], asked + 3, reply, noises
        self.bits = len(ids).bit_length()
        self.codes = np.empty(len(ids), dtype=np.int64)
        self.codes[by_id] = np.arange(len(ids))

    def sort(self, lists: np.ndarray) -> np.ndarray:
        sort_columns(lists)
        tokens = (self.chars[lists].sum(axis=0) + self.asked) >> 2
        standing = self.behind[lists]
        standing -= self.noises.of(lists)
        # equal ones by id
        standing <<= self.bits
        lists |= standing
        sort_columns(lists)
        lists &= (1 << self.bits) - 1
        return tokens

    def places(self, codes: np.ndarray) -> np.ndarray:
        return self.by_id[codes]

    def out_tok(self, calls: int, items: int) -> int:
        return calls * self.reply + items * PER_ITEM["order"]


def sort_columns(x: np.ndarray) -> None:
    """Each column in order, in place."""
    if len(x) != 4:
        x.sort(axis=0)
        return
    a, b, c, d = x
    low, high, low2, high2 = np.minimum(a, b), np.maximum(a, b), np.minimum(c, d), np.maximum(c, d)
    np.minimum(low, low2, out=a)
    np.maximum(high, high2, out=d)
    np.maximum(low, low2, out=low)
    np.minimum(high, high2, out=high)
    np.minimum(low, high, out=b)
    np.maximum(low, high, out=c)


@dataclass(frozen=True)
class SimBackend:
    """The seeded simulator. Best is the highest latent; equal latents go by id, the lower first."""

    profile: str = "clean"
    tier: str = "medium"
    seed: int = 7
    reasoning: bool = False
    scale: bool = True
    criterion: str = ""
    descending: bool = True
    reads_text: bool = False
    threads: int = 1

    def about(self, criterion: str, descending: bool = True) -> SimBackend:
        return replace(self, criterion=criterion, descending=descending)

    def identity(self) -> str:
        return json.dumps(["sim", self.profile, self.tier, self.seed, self.reasoning, self.scale, self.criterion, self.descending])

    def amplitude(self, op: str) -> int:
        a = getattr(PROFILES[self.profile], op)
        return a * TIERS[self.tier] // 100 if self.scale else a

    def usage(self, op: str, keys: Sequence[Key], lookups: int = 0, more: int = 0) -> Usage:
        out = REPLY[op] + PER_ITEM.get(op, 0) * len(keys) + (REASONING if self.reasoning else 0)
        return Usage(-(-(TEMPLATE[op] + len(self.criterion) + more + sum([k.chars for k in keys])) // 4), out, lookups)

    def _task(self, task: str) -> str:
        return f"{task}|{self.criterion}" if self.criterion else task

    def _value(self, value: int) -> int:
        return value if self.descending else TOP - value

    def _bucket(self, value: int, max_point: int) -> int:
        return min(max(value, 0), TOP) * max_point // TOP

    def _scored(self, key: Key, seen: str, a: int, max_point: int, lookup: bool) -> int:
        if lookup and key.fact is not None:
            return self._bucket(self._value(key.fact), max_point)
        return self._bucket(self._value(key.latent) + noise(f"{self.seed}|{seen}|{key.item_id}", a), max_point)

    def score(self, task: str, key: Key, max_point: int, lookup: bool = False) -> tuple[int, Usage]:
        return self._scored(key, f"s|{self._task(task)}", self.amplitude("score"), max_point, lookup), self.usage("score", [key], int(lookup))

    def score_many(self, task: str, batch: int, keys: Sequence[Key], max_point: int, lookup: bool = False) -> tuple[list[int], Usage]:
        a, seen = self.amplitude("score_many"), f"b|{self._task(task)}|{batch}"
        return [self._scored(k, seen, a, max_point, lookup) for k in keys], self.usage("score_many", keys, len(keys) * lookup)

    def compare(self, task: str, a: Key, b: Key) -> tuple[int, Usage]:
        """-1 if a is less (ranks behind b), else 1."""
        lo, hi = (a, b) if a.item_id < b.item_id else (b, a)
        a_c = self.amplitude("compare")
        d = self._value(lo.latent) - self._value(hi.latent) + (noise(f"{self.seed}|c|{self._task(task)}|{lo.item_id}|{hi.item_id}", a_c) if a_c else 0)
        lo_is_better = d >= 0
        return (1 if (lo is a) == lo_is_better else -1), self.usage("compare", [a, b])

    def compare_many(self, task: str, pairs: Pairs) -> tuple[np.ndarray, int, int]:
        """The verdicts of ``compare`` on every pair, tokens in and out of all these calls."""
        a, b, a_c = pairs.a, pairs.b, self.amplitude("compare")
        if b.strides == (0,):
            # one key against all
            b = b[:1]
        ids, latent, chars = pairs.shown.numbers
        ahead = ids[a] < ids[b]
        d = latent[a] - latent[b] if self.descending else latent[b] - latent[a]
        if a_c:
            name, first, second = f"{self.seed}|c|{self._task(task)}", np.minimum(ids[a], ids[b]).tolist(), np.maximum(ids[a], ids[b]).tolist()
            n = np.array([noise(f"{name}|{x}|{y}", a_c) for x, y in zip(first, second, strict=True)], dtype=np.int64)
            d = d + np.where(ahead, n, -n)
        # of two that are equal the lower id is better
        verdicts = np.where((d > 0) | ((d == 0) & ahead), 1, -1)
        tokens = (chars[a] + (chars[b] + TEMPLATE["compare"] + len(self.criterion) + 3)) >> 2
        return verdicts, int(tokens.sum()), len(a) * self.usage("compare", ()).out_tok

    def order(self, task: str, keys: Sequence[Key]) -> tuple[list[int], Usage]:
        """Ids, best first."""
        a = self.amplitude("order")
        if a:
            shown = f"{self.seed}|o|{self._task(task)}|{'-'.join(map(str, sorted([k.item_id for k in keys])))}|"
            placed = [(-self._value(k.latent) - noise(f"{shown}{k.item_id}", a), k.item_id) for k in keys]
        else:
            placed = [(-k.latent if self.descending else k.latent - TOP, k.item_id) for k in keys]
        placed.sort()
        return [i for _, i in placed], self.usage("order", keys)

    def orders(self, task: str, ids: np.ndarray, latent: np.ndarray, chars: np.ndarray) -> SimOrders | None:
        if self.amplitude("order"):
            return None
        return SimOrders(ids, -latent if self.descending else latent - TOP, chars, TEMPLATE["order"] + len(self.criterion), self.usage("order", ()).out_tok)

    def lists(self, task: str, ids: np.ndarray, latent: np.ndarray, chars: np.ndarray, m: int) -> SimLists | NoisyLists | None:
        asked, reply, a = TEMPLATE["order"] + len(self.criterion), self.usage("order", ()).out_tok, self.amplitude("order")
        behind = -latent if self.descending else latent - TOP
        if a:
            prefix, by_id = f"{self.seed}|o|{self._task(task)}|".encode(), np.argsort(ids)
            # longer messages are hashed one by one
            fits = ListNoise.fits(prefix, ids, m) and np.abs(behind).max(initial=0) < 1 << 31
            return NoisyLists(ids, behind, chars, asked, reply, ListNoise(prefix, ids[by_id], a), by_id) if fits else None
        # standing and lengths must fit a code, sums of m codes too
        if int(chars.max(initial=0) * m).bit_length() + (len(ids) * m).bit_length() > 62:
            return None
        return SimLists(ids, behind, chars, asked, reply, m)

    def inquire(self, task: str, keys: Sequence[Key], kind: str) -> tuple[str, Usage]:
        """'factual' or 'reasoning'; ``kind`` is the truth, which only the simulator is told."""
        flipped = int(hashlib.md5(f"{self.seed}|{task}".encode()).hexdigest()[:8], 16) % 1000 < self.amplitude("inquiry")
        other = "reasoning" if kind == "factual" else "factual"
        return (other if flipped else kind), self.usage("inquiry", keys)

    def judge(self, task: str, keys: Sequence[Key], rankings: Mapping[str, Sequence[int]]) -> tuple[str, Usage]:
        a = self.amplitude("judge")
        value = {k.item_id: self._value(k.latent) + noise(f"{self.seed}|j|{self._task(task)}|{k.item_id}", a) for k in keys}
        shown = numbered(self.seed, task, list(rankings))
        # the first of equals, as they are numbered
        best = max(shown, key=lambda p: concordance(rankings[p], value))
        return best, self.usage("judge", keys, more=sum(4 * len(r) for r in rankings.values()))


class Throttle:
    """At most so many calls a minute from this worker: what travels to a worker starts anew there."""

    def __init__(self):
        self.lock, self.free_at = threading.Lock(), {}

    def __reduce__(self):
        return Throttle, ()

    def wait(self, name: str, per_minute: float) -> None:
        with self.lock:
            at = max(time.monotonic(), self.free_at.get(name, 0.0))
            self.free_at[name] = at + 60.0 / per_minute
        time.sleep(max(0.0, at - time.monotonic()))


THROTTLE = Throttle()


class BadReply(ValueError):
    """A reply that does not follow the schema."""


@dataclass(frozen=True)
class HttpBackend:
    """A hosted model behind a JSON endpoint: {model, temperature, prompt, schema} -> {reply, in_tok, out_tok}.

    ``reply`` is an object or JSON text. A call is tried again, with rising pauses, when the service is busy or the reply breaks the schema. An
    ascending order asks the same questions and turns the answers round. ``per_minute`` is this worker's share of a provider's limit.
    """

    endpoint: str
    model: str
    tier: str = "medium"
    criterion: str = ""
    descending: bool = True
    timeout: float = 60.0
    attempts: int = 4
    pause: float = 0.5
    threads: int = 8
    per_minute: float | None = None
    reasoning: bool = False
    seed: int = 7
    reads_text: bool = True

    def about(self, criterion: str, descending: bool = True) -> HttpBackend:
        return replace(self, criterion=criterion, descending=descending)

    def identity(self) -> str:
        return json.dumps(["http", self.endpoint, self.model, self.reasoning, self.criterion, self.descending])

    def _ask(self, prompt: str, schema: dict, read: Callable[[dict], object], lookups: int = 0):
        """What ``read`` makes of the reply, and the usage of all attempts."""
        body = json.dumps({"model": self.model, "temperature": 0, "reasoning": "medium" if self.reasoning else "minimal", "tools": ["search"] if lookups else [], "prompt": prompt, "schema": schema}).encode()
        used = Usage(0, 0, 0)
        for n in range(self.attempts):
            if self.per_minute:
                THROTTLE.wait(self.endpoint, self.per_minute)
            try:
                with urllib.request.urlopen(urllib.request.Request(self.endpoint, body, {"Content-Type": "application/json"}), timeout=self.timeout) as r:
                    got = json.load(r)
                used = Usage(used.in_tok + int(got.get("in_tok", 0)), used.out_tok + int(got.get("out_tok", 0)), used.lookups + lookups)
                reply = got["reply"]
                return read(json.loads(reply) if isinstance(reply, str) else reply), used
            except urllib.error.HTTPError as e:
                if e.code not in (408, 429, 500, 502, 503, 504) or n + 1 == self.attempts:
                    raise
            except (urllib.error.URLError, TimeoutError, BadReply, KeyError, TypeError, ValueError):
                if n + 1 == self.attempts:
                    raise
            time.sleep(self.pause * 2**n)

    def _facts(self, keys: Sequence[Key], lookup: bool) -> str:
        known = [f"[{i}] {k.fact}" for i, k in enumerate(keys, 1) if lookup and k.fact is not None]
        return "\nValues found in reference sources:\n" + "\n".join(known) if known else ""

    @staticmethod
    def _shown(keys: Sequence[Key]) -> str:
        return "\n".join(f"[{i}] {k.text}" for i, k in enumerate(keys, 1))

    def _point(self, value, max_point: int) -> int:
        if isinstance(value, bool) or not isinstance(value, int):
            raise BadReply("not a whole number")
        value = min(max(value, 0), max_point)
        return value if self.descending else max_point - value

    def score(self, task: str, key: Key, max_point: int, lookup: bool = False) -> tuple[int, Usage]:
        text = f"Criterion: {self.criterion}\nHow far does this entry meet it? Give a whole number, 0 for not at all, {max_point} for fully.\n{self._shown([key])}{self._facts([key], lookup)}"
        return self._ask(text, {"value": "integer"}, lambda r: self._point(r["value"], max_point), int(lookup))

    def score_many(self, task: str, batch: int, keys: Sequence[Key], max_point: int, lookup: bool = False) -> tuple[list[int], Usage]:
        """A list of another length is the caller's to deal with (``repair_scores``)."""
        text = f"Criterion: {self.criterion}\nHow far does each entry meet it? Give one whole number per entry, in the order shown, 0 for not at all, {max_point} for fully.\n{self._shown(keys)}{self._facts(keys, lookup)}"
        return self._ask(text, {"values": ["integer"]}, lambda r: [self._point(v, max_point) for v in r["values"]], len(keys) * lookup)

    def compare(self, task: str, a: Key, b: Key) -> tuple[int, Usage]:
        def read(r: dict) -> int:
            if r["better"] not in (1, 2):
                raise BadReply("neither entry")
            return 1 if (r["better"] == 1) == self.descending else -1

        return self._ask(f"Criterion: {self.criterion}\nOf these two entries, which meets it better, 1 or 2?\n{self._shown([a, b])}", {"better": "integer"}, read)

    def order(self, task: str, keys: Sequence[Key]) -> tuple[list[int], Usage]:
        """Ids; what the reply leaves out or repeats is the caller's to deal with (``repair_order``)."""

        def read(r: dict) -> list[int]:
            ids = [keys[i - 1].item_id for i in r["order"] if isinstance(i, int) and 1 <= i <= len(keys)]
            return ids if self.descending else ids[::-1]

        return self._ask(f"Criterion: {self.criterion}\nPut the numbers of these entries in order, the one that meets it best first.\n{self._shown(keys)}", {"order": ["integer"]}, read)

    def inquire(self, task: str, keys: Sequence[Key], kind: str = "") -> tuple[str, Usage]:
        text = f"Somebody wants entries sorted by this criterion: {self.criterion}\nSome of the entries:\n{self._shown(keys)}\nDoes public knowledge about the world settle the order, so that no judgement is needed?"
        return self._ask(text, {"world_fact": "boolean"}, lambda r: "factual" if r["world_fact"] is True else "reasoning")

    def judge(self, task: str, keys: Sequence[Key], rankings: Mapping[str, Sequence[int]]) -> tuple[str, Usage]:
        shown, place = numbered(self.seed, task, list(rankings)), {k.item_id: i for i, k in enumerate(keys, 1)}
        lists = "\n".join(f"Result {n}: " + ", ".join(str(place[i]) for i in rankings[p] if i in place) for n, p in enumerate(shown, 1))
        way = "best first" if self.descending else "worst first"

        def read(r: dict) -> str:
            if not isinstance(r["choice"], int) or not 1 <= r["choice"] <= len(shown):
                raise BadReply("no such result")
            return shown[r["choice"] - 1]

        text = f"You compare sorted results. The entries:\n{self._shown(keys)}\nThey were to be sorted, {way}, by this criterion: {self.criterion}\n{lists}\nReason about the order step by step, then give the number of the result that is sorted best."
        return self._ask(text, {"reasoning": "string", "choice": "integer"}, read)


def each(backend: ModelBackend, ask: Callable, requests: Sequence) -> list:
    """Answers to requests that may run at once, in order, with as many threads as the backend says."""
    if backend.threads <= 1 or len(requests) <= 1:
        return [ask(r) for r in requests]
    with ThreadPoolExecutor(min(backend.threads, len(requests))) as pool:
        return list(pool.map(ask, requests))


def repair_order(reply: Sequence[int], keys: Sequence[Key]) -> tuple[list[int], int]:
    """A permutation whatever the reply: unknown and repeated ids go, missing ones follow in input order."""
    known, out = {k.item_id for k in keys}, []
    if len(reply) == len(keys) and known == {*reply} and len(known) == len(keys):
        return list(reply), 0
    for i in reply:
        if i in known and i not in out:
            out.append(i)
    missing = [k.item_id for k in keys if k.item_id not in out]
    return out + missing, len(missing) + (len(reply) - len(out) if len(reply) > len(out) else 0)


def repair_scores(ask, keys: Sequence[Key]) -> tuple[list[int | None], Usage, int]:
    """A list of the right length is taken; a wrong one is asked for again once, then nothing is known of the batch."""
    reply, used = ask()
    if len(reply) == len(keys):
        return list(reply), used, 0
    again, more = ask()
    used = Usage(used.in_tok + more.in_tok, used.out_tok + more.out_tok, used.lookups + more.lookups)
    return (list(again) if len(again) == len(keys) else [None] * len(keys)), used, 1


