from __future__ import annotations

import random

import pytest

from motifknn.operators.automaton import OnlineIndex, build


def brute(items):
    ends: dict[str, set] = {}
    for i, s in items:
        for e in range(len(s)):
            for b in range(e + 1):
                ends.setdefault(s[b : e + 1], set()).add((i, e))
    classes: dict[frozenset, list[str]] = {}
    for p, v in ends.items():
        classes.setdefault(frozenset(v), []).append(p)
    return ends, classes


def test_banana():
    a = build([(1, "banana")])
    assert len(a.span) == 10 and sum(map(len, a.next)) == 11
    assert a.locate("nana") is not None and a.locate("nab") is None
    assert a.name(a.locate("anan")) == "banan"


def test_three_strings_keep_id_sets_apart():
    a = build([(1, "ac"), (2, "acab"), (3, "acba")])
    assert (len(a.span), sum(map(len, a.next)), sum(map(len, a.ids))) == (8, 10, 15)
    assert a.ids[a.locate("cab")] == {2} and a.ids[a.locate("cba")] == {3} and a.ids[a.locate("ac")] == {1, 2, 3}
    _, held = a.donors()
    assert sum(map(len, held.values())) == 7


@pytest.mark.parametrize("seed", range(60))
def test_against_brute_force(seed):
    r = random.Random(seed)
    alphabet = r.choice(["a", "ab", "abc", "aé𝄞"])
    items = [(i, "".join(r.choice(alphabet) for _ in range(r.randrange(0, 9)))) for i in range(r.randrange(1, 6))]
    a = build(items)
    ends, classes = brute(items)
    assert len(a.span) == len(classes) + 1
    for p, v in ends.items():
        s = a.locate(p)
        assert a.ids[s] == {i for i, _ in v}
        assert a.name(s) == max(classes[frozenset(v)], key=len)
    donor, held = a.donors()
    for s in range(len(a.span)):
        given = held[donor[s]] if s in donor else set()
        assert held[s] | given == a.ids[s] and not held[s] & given
    for s in range(len(a.span)):
        for t in a.next[s].values():
            assert a.ids[t] <= a.ids[s]
    m = sum(len(s) for _, s in items)
    assert len(a.span) <= max(2, 2 * m)


@pytest.mark.parametrize("seed", range(40))
def test_online_lists_stay_an_exact_cover(seed):
    r = random.Random(100 + seed)
    items = [(i, "".join(r.choice("abc"[: 2 + seed % 2]) for _ in range(r.randrange(0, 9)))) for i in range(12)]
    index = OnlineIndex(build(items[:5]))
    for k, (i, s) in enumerate(items[5:], 6):
        index.insert(i, s)
        ends, _ = brute(items[:k])
        for p, v in ends.items():
            assert index.matches(p) == {i for i, _ in v}
        for state in range(len(index.a.span)):
            own, given = index.cover(state)
            assert not own & given and own | given == index.a.ids[state]
    index.rebuild()
    assert not index.fresh and all(index.matches(p) == {i for i, _ in v} for p, v in ends.items())


def test_memory_is_linear_in_a_long_sequence():
    r = random.Random(1)
    seq = "".join(r.choice("abcd") for _ in range(20_000))
    a = build([(1, seq)])
    assert len(a.span) < 2 * len(seq) and sum(map(len, a.seqs.values())) == len(seq) and a.locate(seq[5000:9000]) is not None
