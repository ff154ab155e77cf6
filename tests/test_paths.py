import random

import pytest
from brute import Model, bubble, merge, quick
from hypothesis import given, settings
from hypothesis import strategies as st

from semrank.exec.generators import merge_two, settle, vote
from semrank.exec.packed import run_path
from semrank.plans.complexity import calls, exact_calls, extrapolate
from semrank.plans.spec import EXT_BUBBLE, EXT_MERGE, EXT_POINT, POINT, QUICK, QUICK_3, PathConfig, RankSpec, candidate_grid
from semrank.sources.model import Key, SimBackend, Usage, repair_order, repair_scores

FINE = [PathConfig("score_each", max_point=10000), PathConfig("score_batch", max_point=10000), QUICK, QUICK_3, PathConfig("pivot_split", v=2), PathConfig("pivot_split", v=5), EXT_BUBBLE, EXT_MERGE, PathConfig("slide_window", m=5), PathConfig("run_merge", m=7), PathConfig("run_merge", m=2), PathConfig("pivot_split", pivot="random"), PathConfig("pivot_split", pivot="median3", v=3), PathConfig("slide_window", rescan=True), PathConfig("slide_window", stop_when_stable=True)]


def keys(lats):
    return [Key(i, 10, x) for i, x in enumerate(lats)]


def n_calls(usage):
    return sum(u[0] for u in usage.values())


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 40), max_size=45), st.sampled_from(FINE), st.one_of(st.none(), st.integers(0, 50)))
def test_a_perfect_comparator_gives_the_order(lats, path, k):
    got, _ = run_path(keys([x * 100 for x in lats]), path, k, SimBackend("clean"), "t")
    assert got == sorted(range(len(lats)), key=lambda i: (-lats[i], i))[:k]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 10000), max_size=40), st.sampled_from(FINE), st.one_of(st.none(), st.integers(0, 12)))
def test_noise_loses_no_item(lats, path, k):
    got, _ = run_path(keys(lats), path, k, SimBackend("reasoning"), "t")
    assert len(got) == len(set(got)) == (len(lats) if k is None else min(k, len(lats)))
    assert set(got) <= set(range(len(lats)))


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(0, 10000), min_size=1, max_size=40), st.integers(1, 5), st.one_of(st.none(), st.integers(1, 12)))
def test_noisy_quick_sort_against_brute_force(lats, v, k):
    m = Model(dict(enumerate(lats)), compare=2500)
    got, usage = run_path(keys(lats), PathConfig("pivot_split", v=v), k, SimBackend("factual"), "t")
    assert got == quick(m, list(range(len(lats))), v, k)
    assert n_calls(usage) == m.calls


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 10000), min_size=1, max_size=40), st.integers(2, 7), st.one_of(st.none(), st.integers(1, 12)))
def test_noisy_list_paths_against_brute_force(lats, size, k):
    for kind, plain in (("slide_window", bubble), ("run_merge", merge)):
        m = Model(dict(enumerate(lats)), order=2000)
        got, usage = run_path(keys(lats), PathConfig(kind, m=size), k, SimBackend("factual"), "t")
        assert got == plain(m, list(range(len(lats))), size, k), kind
        assert n_calls(usage) == m.calls, kind


def test_worked_merge():
    asked, g = [], merge_two([8, 5, 4, 1], [7, 6, 3, 2], 4, None)
    try:
        ask = next(g)
        while True:
            asked.append(sorted(ask))
            ask = g.send(sorted(ask, reverse=True))
    except StopIteration as end:
        out = end.value
    assert out == [8, 7, 6, 5, 4, 3, 2, 1] and len(asked) == 3
    _, usage = run_path([Key(i, 1, -x) for i, x in enumerate([1, 4, 5, 8, 2, 3, 6, 7])], EXT_MERGE, None, SimBackend(), "t")
    assert n_calls(usage) == 5


@pytest.mark.parametrize(("n", "k", "want"), [(8, None, 6), (8, 2, 3), (8, 3, 5), (8, 4, 5), (100, 10, 235), (100, None, 1225)])
def test_bubble_calls(n, k, want):
    _, usage = run_path(keys(random.Random(1).sample(range(10000), n)), EXT_BUBBLE, k, SimBackend(), "t")
    assert n_calls(usage) == want == exact_calls(EXT_BUBBLE, n, k)


def test_quick_calls():
    lats = [3, 1, 4, 2, 5]
    assert n_calls(run_path(keys(lats), QUICK, None, SimBackend(), "t")[1]) == 6
    assert n_calls(run_path(keys(lats), QUICK_3, None, SimBackend(), "t")[1]) == 14
    got, usage = run_path(keys(lats), QUICK, 2, SimBackend(), "t")
    assert got == [4, 2] and n_calls(usage) == 5
    n = 12
    assert n_calls(run_path(keys(range(n)), QUICK, None, SimBackend(), "t")[1]) == n * (n - 1) // 2


def test_vote():
    assert vote(-1, [(1, -1), (2, 1)], {1: -1, 2: 1}) == -1
    assert vote(-1, [(1, -1), (2, 1), (3, 1), (4, 1)], {1: 1, 2: 1, 3: 1, 4: 1}) == 1
    assert vote(1, [(1, -1), (2, -1)], {1: 1, 2: -1}) == 1  # 1.5 against 1


def test_settle_corner_cases():
    # nobody to ask: the pivot decides; unanimous peers overrule it, or not
    assert settle([1], {1: -1}, {1: []}) == {1: -1}
    assert settle([1, 2], {1: -1, 2: 1}, {1: [(2, 1)], 2: []}) == {1: 1, 2: 1}
    assert settle([1, 2], {1: -1, 2: 1}, {1: [(2, 1)], 2: []}, peer_override=False)[1] in (-1, 1)
    # a deadlock: a, b provisionally less, c, d greater; a < c, a > d, b > c, b < d
    a, b, c, d = range(4)
    side = settle([a, b, c, d], {a: -1, b: -1, c: 1, d: 1}, {a: [(c, -1), (d, 1)], b: [(c, 1), (d, -1)], c: [(a, 1), (b, -1)], d: [(a, -1), (b, 1)]})
    assert side == {a: -1, b: -1, c: 1, d: 1}


def test_depths():
    """Sequential waves at N = 100, K = 10, m = 4: 1, about 8, about 22, 235."""
    def depth(path, seed):
        rng = random.Random(seed)
        _, usage = run_path(keys(rng.sample(range(10000), 100)), path, 10, SimBackend(), "t")
        return len({w for _, w in usage})

    assert depth(POINT, 0) == 1 and depth(EXT_BUBBLE, 0) == 235
    assert 6.5 < sum(depth(QUICK, s) for s in range(60)) / 60 < 9.7
    assert 21 < sum(depth(EXT_MERGE, s) for s in range(60)) / 60 < 24


def test_call_ratios():
    """Votes cost some 2.6 times plain quick sort; a full bubble sort some 6 times a merge."""
    def mean(path, k):
        return sum(n_calls(run_path(keys(random.Random(s).sample(range(10000), 100)), path, k, SimBackend(), "t")[1]) for s in range(20)) / 20

    assert 2.2 < mean(QUICK_3, None) / mean(QUICK, None) < 2.9
    assert 5.4 < mean(EXT_BUBBLE, None) / mean(EXT_MERGE, None) < 6.4
    assert 1.8 < mean(EXT_BUBBLE, 10) / mean(EXT_MERGE, 10) < 2.5


def test_merge_call_bound():
    for s in range(30):
        rng = random.Random(s)
        a, b, m, n = sorted(rng.sample(range(1000), 17)), sorted(rng.sample(range(1000, 2000), 9)), 6, 0
        g = merge_two(a, b, m, None)
        try:
            ask = next(g)
            while True:
                n += 1
                ask = g.send(sorted(ask, key=lambda x: (x * 7919) % 1009))
        except StopIteration:
            pass
        assert n <= -(-len(a) // 3) + -(-len(b) // 3) - 1


def test_extrapolation():
    assert extrapolate(0.02, POINT, 20, 1000) == pytest.approx(1.0)
    assert extrapolate(0.05, EXT_BUBBLE, 20, 1000) == pytest.approx(125.0)
    assert calls(EXT_POINT, 1000) / calls(EXT_POINT, 20) == 50
    assert extrapolate(0.235, EXT_BUBBLE, 20, 100, 10, form="per_call", sample_calls=exact_calls(EXT_BUBBLE, 20, 10)) == pytest.approx(0.235 * 235 / exact_calls(EXT_BUBBLE, 20, 10))
    with pytest.raises(ValueError):
        extrapolate(1, POINT, 20, 100, form="guess")


def test_validation():
    for bad in (dict(kind="bogo"), dict(kind="run_merge", m=1), dict(kind="pivot_split", v=0), dict(kind="run_merge", lookup=True), dict(kind="pivot_split", pivot="last")):
        with pytest.raises(ValueError):
            PathConfig(**bad)
    for bad in (dict(criterion=" "), dict(criterion="x", limit=-1), dict(criterion="x", nulls="somewhere")):
        with pytest.raises(ValueError):
            RankSpec(**bad)
    assert [p.path_id for p in candidate_grid(lookup=True)] == ["point", "ext_point_4", "quick", "quick_3", "ext_bubble_4", "ext_merge_4", "point_search", "ext_point_4_search"]


def test_repair():
    ks = keys([1, 2, 3])
    assert repair_order([2, 9, 2], ks) == ([2, 0, 1], 4)
    assert repair_order([0, 1, 2], ks) == ([0, 1, 2], 0)
    replies = iter([([1, 2], Usage(1, 1)), ([4, 5, 6], Usage(2, 2))])
    assert repair_scores(lambda: next(replies), ks) == ([4, 5, 6], Usage(3, 3), 1)
    replies = iter([([1], Usage(1, 1)), ([1], Usage(1, 1))])
    assert repair_scores(lambda: next(replies), ks)[0] == [None] * 3
