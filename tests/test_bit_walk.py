"""Masses and draws along the bits of a large domain against the whole conditional, and the passes they take."""

import numpy as np
import pytest

from selweave.operators import dens, ranges

CARDS = [5, 1_041, 16, 1, 23]


def networks(leak="renormalise"):
    for seed in range(3):
        net = dens.MaskedNet(CARDS, dens.attribute_order(list("abcde"), seed=seed), (24, 24), leak=leak, seed=seed)
        for w, m in zip(net.net.weights, net.net.masks):
            w *= 1.5 * m
        yield net


def some_rows(n):
    draw = np.random.default_rng(5)
    codes = draw.integers(0, CARDS, (n, len(CARDS)))
    low, high = np.sort(draw.integers(0, [[c] * 2 for c in CARDS], (n, len(CARDS), 2)), axis=2).transpose(2, 0, 1)
    high[: n // 3] = low[: n // 3]  # single values
    low[-n // 4 :], high[-n // 4 :] = 0, np.array(CARDS) - 1  # whole domains
    return codes, low, high


@pytest.mark.parametrize("leak", ["renormalise", "ignore"])
def test_masses_and_draws_are_those_of_the_conditional(leak):
    codes, low, high = some_rows(120)
    u = np.random.default_rng(6).random(len(codes))
    for net in networks(leak):
        for k, a in enumerate(net.order):
            inside = np.where((np.arange(CARDS[a]) >= low[:, [a]]) & (np.arange(CARDS[a]) <= high[:, [a]]), net.conditional(codes, k), 0)
            mass, x = net.interval(codes, k, low[:, a], high[:, a], u)
            assert mass == pytest.approx(inside.sum(axis=1), rel=1e-4)
            up = np.cumsum(inside, axis=1)
            drawn = np.clip((up < (u * up[:, -1])[:, None]).sum(axis=1), low[:, a], high[:, a])
            assert (x == drawn).mean() > 0.98 and np.abs(x - drawn).max() <= 1  # rounding at an edge
            assert (net.interval(codes, k, low[:, a], high[:, a])[0] == mass).all()


def test_probabilities_are_products_of_the_conditionals():
    codes, _, _ = some_rows(60)
    for net in networks():
        each = [net.conditional(codes, k)[np.arange(len(codes)), codes[:, a]] for k, a in enumerate(net.order)]
        for upto in (0, 2, 5):
            assert net.prob(codes, upto) == pytest.approx(np.prod(each[:upto], axis=0) * np.ones(len(codes)), rel=1e-4)


def test_a_walk_over_a_large_domain_takes_few_passes(monkeypatch):
    _, low, high = some_rows(40)
    net, seen = next(networks()), []
    for name in ("forward", "output"):
        monkeypatch.setattr(type(net.net), name, lambda self, x, *rest, f=getattr(type(net.net), name): (seen.append(len(x)), f(self, x, *rest))[1])
    ranges.progressive_many(net, low, high, 50, list(range(len(low))))
    assert sum(seen) < 40 * 50 * 60  # the conditional of 1,041 codes takes so many for each path
