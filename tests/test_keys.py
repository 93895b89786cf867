"""Candidate keys of any size, against all attribute sets."""

from __future__ import annotations

import random
from itertools import combinations

import pytest

from depscope.operators import armstrong


def all_keys(fds, arity):
    found = []
    for n in range(arity + 1):
        for c in map(frozenset, combinations(range(1, arity + 1), n)):
            if not any(k <= c for k in found) and len(armstrong.closure_of(fds, c)) == arity:
                found.append(c)
    return found


def two_way(n):
    """n pairs of attributes that determine each other, as in a product of n relations with two keys."""
    return [(frozenset({a}), b) for k in range(n) for a, b in ((2 * k + 1, 2 * k + 2), (2 * k + 2, 2 * k + 1))]


def test_keys_of_five_attributes():
    found = armstrong.keys_of(two_way(5), 10)
    assert len(found) == 32 and set(found) == set(all_keys(two_way(5), 10))


def test_keys_match_all_sets():
    rnd = random.Random(1)
    for _ in range(150):
        arity = rnd.randint(1, 8)
        fds = [(frozenset(rnd.sample(range(1, arity + 1), rnd.randint(0, min(3, arity)))), rnd.randint(1, arity)) for _ in range(rnd.randint(0, 10))]
        assert armstrong.keys_of(fds, arity) == all_keys(fds, arity)


def test_too_many_keys_are_an_error():
    with pytest.raises(ValueError, match="more than 10"):
        armstrong.keys_of(two_way(5), 10, most=10)
